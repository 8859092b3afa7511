import hashlib
import random
import zlib
from collections import Counter

import brute
import numpy as np
import pandas as pd
import public_tokenizers
import pytest
from helpers import rows
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from fieldseg.llm import decontaminate, language_id, line_dedup, packing, quality_classifier, quality_rules, sharding, simhash, suffix_dedup, textkernel, url_filter
from fieldseg.llm.queries import ORACLES, QUERIES


def plain(df, columns):
    return sorted(str(tuple(r[c] for c in columns)) for r in df.collect())


def expected(tuples):
    return sorted(map(str, tuples))


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_sql(spark, duck, sf, name):
    assert rows(QUERIES[name](spark, sf)) == rows(duck.sql(ORACLES[name]).df())


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_empty_tables(spark, empty, name):
    assert QUERIES[name](spark, empty).count() == 0


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_odd_rows_keep_their_number(spark, odd, odd_rows, name):
    n = QUERIES[name](spark, odd).count()
    if name.startswith("op7"):
        assert n == len(pd.read_parquet(f"{odd}/pages.parquet"))
    elif name.startswith("op10"):
        assert n >= len(odd_rows)
    else:
        assert n == len(odd_rows)


def test_decontamination(spark, odd, odd_rows):
    items = pd.read_parquet(f"{odd}/benchmark.parquet")
    want = brute.decontaminate(odd_rows, [(None if pd.isna(i) else int(i), t) for i, t in zip(items.item_id, items.text)])
    cols = ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"]
    assert plain(decontaminate.op3(spark, odd), cols) == expected(want)
    assert sum(r[5] for r in want) > 2
    docs, bench = (spark.read.parquet(f"{odd}/{t}.parquet") for t in ("documents", "benchmark"))
    assert decontaminate.remove_contaminated(docs, bench).count() == sum(not r[5] for r in want)
    # a benchmark in many blocks gives the same
    one, many = (decontaminate.match_items(docs, bench, keep=["doc_id"], index_bytes=b).selectExpr("doc_id", "match.n_words", "match.n_hit", "to_json(match.spans) s") for b in (1 << 24, 100))
    assert rows(one) == rows(many)


def test_index_blocks_are_bounded(spark):
    """Blocks of the benchmark keep to the bytes they may have, also where words are short, and hold all windows between them."""
    rng = random.Random(3)
    items = [(str(i), " ".join(f"{rng.randrange(36 ** n):x}" for _ in range(60))) for n in (1, 6) for i in range(3000)]
    df = spark.createDataFrame(items, "i string, t string")
    limit = 2 << 20
    indexes = list(decontaminate.index_blocks(df, 10, limit))
    assert len(indexes) > 5 and max(x.n_bytes() for x in indexes) < 1.3 * limit
    assert sum(len(x.ids) for x in indexes) == len(items)
    assert sum(len(p.start) for x in indexes for p in x.parts) == 51 * len({t for _, t in items})


def test_one_window_of_many_items(spark):
    """A window that all items share is searched once and told for each."""
    head = " ".join(f"h{i}" for i in range(12))
    items = spark.createDataFrame([(i, f"{head} own{i}") for i in range(300)] + [(300, "h1 h2"), (301, "h5")], "item_id long, text string")
    docs = spark.createDataFrame([(1, f"x {head} own7"), (2, "h5 h1"), (3, "h1 h2 h1")], "doc_id long, text string")
    got = {r.doc_id: (r.match.n_hit, {(x.item_id, x.doc_word, x.n_words) for x in r.match.spans}) for r in decontaminate.match_items(docs, items).collect()}
    assert got[1] == (13, {(str(i), 1, 13 if i == 7 else 12) for i in range(300)} | {("300", 2, 2), ("301", 6, 1)})
    assert got[2] == (1, {("301", 0, 1)}) and got[3] == (2, {("300", 0, 2)})


def test_spans_are_longest_matches(spark):
    docs = spark.createDataFrame([(1, "zz a b c d e f g h i j k l yy a b c d e f g h i j")], "doc_id long, text string")
    items = spark.createDataFrame([(7, "A, b c d e f g h i j k l m")], "item_id long, text string")
    assert [tuple(s) for s in decontaminate.match_items(docs, items).first().match.spans] == [("7", 1, 12), ("7", 14, 10)]


def test_base_counts(spark, odd, odd_rows):
    got = quality_rules.op5(spark, odd)
    assert plain(got, ["doc_id", *quality_rules.BASE, "base_failed"]) == expected(brute.base_counts(odd_rows))
    assert got.where("base_failed and kept").count() == 0


def test_sketches_merge_and_bound_quantiles(spark):
    rng = random.Random(1)
    values = [rng.randint(0, 100_000) for _ in range(3000)]
    df = spark.createDataFrame([(v, v % 3) for v in values], "v long, g int")
    f = {"x": ("v", 0)}
    fine = quality_rules.sketch(df, ["g"], f)
    assert rows(quality_rules.merge_sketches(fine, [])) == rows(quality_rules.sketch(df, [], f))
    row = quality_rules.fences(quality_rules.merge_sketches(fine, []), [], f).first()
    q1, q3 = sorted(values)[749], sorted(values)[2249]
    top, low = row.high - 3 * (row.high - row.low) // 7, None
    assert low is None and q3 <= top <= q3 * 1.02 + 1 and row.rows == 3000 and q1 > 0


def test_simhash(spark, odd, odd_rows):
    want = brute.simhash(odd_rows)
    assert plain(simhash.op6(spark, odd), ["doc_id", "fingerprint", "component_id"]) == expected(want)


@pytest.mark.parametrize("run", [1, 4, 64])
def test_links_lose_nothing(spark, run, monkeypatch):
    """Random fingerprints with neighbours at 0 to 3 bits, and a large ball around one."""
    rng = random.Random(run)
    fps = set()
    for _ in range(60):
        f = rng.getrandbits(64)
        fps.add(f)
        for _ in range(3):
            g = f
            for b in rng.sample(range(64), rng.randint(1, 3)):
                g ^= 1 << b
            fps.add(g)
    centre = rng.getrandbits(64)
    fps |= {centre ^ (1 << a) for a in range(64)}
    fps = sorted(fps)
    signed = [f - (1 << 64) if f >> 63 else f for f in fps]
    monkeypatch.setattr(simhash, "RUN", run)
    got = simhash.near_components(spark.createDataFrame(list(enumerate(signed)), "doc_id long, fp long"))
    comp = brute.components(len(fps), lambda a, b: (fps[a] ^ fps[b]).bit_count() <= 2)
    first = {}
    for i, c in enumerate(comp):
        first.setdefault(c, i)
    assert {r.doc_id: r.component_id for r in got.collect()} == {i: first[c] for i, c in enumerate(comp)}


def test_golay_code():
    code = simhash.Golay()
    rng = np.random.default_rng(0)
    v = rng.integers(0, 1 << 23, 400)
    words = v ^ code.err[(v & 0x7FF) ^ code.rest[v >> 11]]
    assert (np.bitwise_count(v ^ words) <= 3).all() and len(set(code.err.tolist())) == 2048
    row, idx = code.indices(v)
    keys = [set(idx[row == i]) for i in range(400)]
    assert max(map(len, keys)) <= 6
    for _ in range(3):
        a, b = rng.integers(0, 23, 400), rng.integers(0, 23, 400)
        row2, idx2 = code.indices(v ^ (1 << a) ^ np.where(a == b, 0, 1 << b))
        assert all(keys[i] & set(idx2[row2 == i]) for i in range(400))


def test_repeats(spark, odd, odd_rows):
    got = suffix_dedup.op8(spark, odd)
    want = brute.repeats(odd_rows)
    assert plain(got, ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"]) == expected(want)
    assert sum(r[2] for r in want) > 10_000
    docs = spark.read.parquet(f"{odd}/documents.parquet")
    hot = suffix_dedup.remove_repeats(docs, ["doc_id"], hot=1).drop("kept")
    assert rows(hot) == rows(got)


@settings(max_examples=80, deadline=None)
@given(st.lists(st.integers(1, 4), max_size=120))
def test_suffix_order(symbols):
    t = np.array(symbols, np.int64)
    got = suffix_dedup.suffix_order(t, 1, len(t) + 3)
    assert got.tolist() == sorted(range(len(t)), key=lambda i: symbols[i:])


@settings(max_examples=40, deadline=None)
@given(st.lists(st.integers(1, 2), min_size=5, max_size=200), st.integers(2, 12))
def test_shallow_suffix_order_groups_prefixes(symbols, width):
    t = np.array(symbols, np.int64)
    got = suffix_dedup.suffix_order(t, 1, width + 2)
    prefixes = [tuple(symbols[i : i + width]) for i in got]
    assert sorted(got.tolist()) == list(range(len(t)))
    assert [p for p in prefixes] == sorted(prefixes)


@pytest.mark.parametrize("honest", [True, False])
def test_prefixes_are_compared_by_bytes(monkeypatch, honest):
    """Also where every hash is equal, so that bytes alone tell."""
    if not honest:
        monkeypatch.setattr(suffix_dedup.Block, "hashes", staticmethod(lambda s, a, b: np.zeros(len(a), np.uint64)))
    monkeypatch.setattr(suffix_dedup, "COMPARE_BYTES", 50)
    rng = random.Random(5)
    for _ in range(60):
        text = bytes(rng.choice(b"ab") for _ in range(rng.randint(12, 90)))
        text += text[: rng.randint(5, 40)]
        window = rng.randint(2, 9)
        data = np.frombuffer(text, np.uint8)
        order = np.array(sorted(range(len(text) - window + 1), key=lambda i: (text[i : i + window], rng.random())))
        want = [text[i : i + window] == text[j : j + window] for i, j in zip(order, order[1:])]
        assert suffix_dedup.equal_prefixes(data, order, window).tolist() == want


def test_long_text_in_stretches(spark, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "STRETCH", 3000)
    monkeypatch.setattr(suffix_dedup, "SORT_BYTES", 2000)
    rng = random.Random(9)
    text = "".join(rng.choice("abcdefgh ") for _ in range(20_000))
    text += text[5000:6200] + "".join(rng.choice("abcdefgh ") for _ in range(3000)) + text[100:460]
    data = [(1, text), (2, text[9000:9500])]
    df = spark.createDataFrame(data, "doc_id long, text string").repartition(1)
    got = suffix_dedup.remove_repeats(df, ["doc_id"]).drop("kept")
    assert plain(got, ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"]) == expected(brute.repeats(data))


def test_line_dedup(spark, odd, odd_rows):
    want = brute.line_dedup(odd_rows)
    got = line_dedup.op9(spark, odd)
    assert plain(got, ["doc_id", "n_lines", "n_dropped", "kept_sha256"]) == expected((i, n, d, hashlib.sha256(t.encode()).hexdigest()) for i, n, d, t in want)
    assert sum(r[2] for r in want) == 8 + 11


def test_line_runs(spark):
    store = line_dedup.LineRuns(spark, fan=2)
    batches = [[(i, h, 0) for h in range(i, i + 3)] for i in range(5)]
    seen = set()
    for b in batches:
        df = spark.createDataFrame(b, "id long, h1 long, h2 long")
        assert {r.h1 for r in store.new_lines(df).collect()} == {h for _, h, _ in b} - seen
        store.add(df)
        seen |= {h for _, h, _ in b}
    assert [len(x) for x in store.levels] == [1, 0, 1]
    assert {r.h1: (r.n_docs, r.min_id, r.max_id) for r in store.counts().collect()} == {h: (len(o), min(o), max(o)) for h in seen for o in [[i for i in range(5) if i <= h < i + 3]]}
    store.close()


def test_every_line_is_fresh_in_one_run(spark, sf):
    """Batches are merge-anti-joined with the runs: no line is new twice, and a hot line goes another way with the same result."""
    store = line_dedup.LineRuns(spark, fan=100)
    entries = line_dedup.line_entries(spark.read.parquet(f"{sf}/documents.parquet")).cache()
    for k in range(3):
        store.add(entries.where(f"pmod(id, 3) = {k}"))
    fresh = [{(r.h1, r.h2) for r in t.where("fresh").collect()} for t in store._all()]
    assert sum(map(len, fresh)) == len(set.union(*fresh)) == entries.select("h1", "h2").distinct().count()
    assert store.new_lines(entries).count() == 0
    store.close()
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    one, other = (line_dedup.dropped_lines(docs, hot_lines=n).selectExpr("id", "to_json(array_sort(gone)) g") for n in (1, 1 << 40))
    assert one.count() > 0 and rows(one) == rows(other)


def test_sharding(spark, odd, odd_rows):
    got = sharding.op2(spark, odd).toPandas()
    assert got["shard"].value_counts().reindex(range(16)).between(len(odd_rows) // 16, len(odd_rows) // 16 + 1).all()
    for _, g in got.groupby("shard"):
        assert sorted(g["slot"]) == list(range(len(g)))
    size = lambda t: len((t or "").encode())
    ids = got["doc_id"].astype(object).where(got["doc_id"].notna(), None)
    assert Counter(zip(ids, got["size"], got["text_crc32"])) == Counter((i, size(t) + 1, zlib.crc32((t or "").encode())) for i, t in odd_rows)
    again = sharding.op2(spark, odd)
    assert rows(again.repartition(3)) == rows(again)


def test_shuffle_is_uniform_and_seeded(spark):
    df = spark.range(4000).selectExpr("id", "1L as size")
    a = sharding.external_shuffle(df, "size", 4, seed=1, bucket_bytes=500, min_buckets=1).toPandas()
    b = sharding.external_shuffle(df.repartition(7), "size", 4, seed=1, bucket_bytes=500, min_buckets=1).toPandas()
    c = sharding.external_shuffle(df, "size", 4, seed=2, bucket_bytes=500, min_buckets=1).toPandas()
    place = lambda x: dict(zip(x["id"], zip(x["shard"], x["slot"])))
    assert place(a) == place(b) and sum(place(a)[i] == place(c)[i] for i in range(4000)) < 30
    assert abs(np.corrcoef(a["id"], a["slot"] * 4 + a["shard"])[0, 1]) < 0.06


def test_a_hot_record_fills_no_bucket(spark):
    df = spark.range(3000).selectExpr("0L as id", "1L as size")
    rows_, counts = sharding.scatter(df, 10)
    buckets = rows_.groupBy("_fs_bucket").count().toPandas()["count"]
    assert len(buckets) == 10 and buckets.max() < 400 and sorted(buckets) == sorted(r._fs_rows for r in counts.collect())


@pytest.mark.parametrize("limit", [100_000, 1])
def test_copies_broadcast_or_shuffled(spark, monkeypatch, limit):
    """Repeated records of several kinds, more than one row spreads, next to records that occur once."""
    monkeypatch.setattr(sharding, "BROADCAST_COPIES", limit)
    monkeypatch.setattr(sharding, "COPIES_A_ROW", 7)
    df = spark.range(900).selectExpr("case when id % 3 = 0 then 0 when id % 3 = 1 then id % 12 else id end as id", "if(id % 5 = 0, null, 'x') as t")
    got = sharding.external_shuffle(df, F.lit(1), 7, min_buckets=5).toPandas()
    assert sorted(map(str, zip(got["id"], got["t"]))) == sorted(map(str, zip(*df.toPandas().values.T)))
    for k, g in got.groupby("shard"):
        assert sorted(g["slot"]) == list(range(len(g))) and len(g) in (128, 129)
    assert got["shard"].nunique() == 7


def test_write_shards(spark, odd, odd_rows, tmp_path):
    sharding.write_shards(spark.read.parquet(f"{odd}/documents.parquet"), str(tmp_path / "s"), n_shards=3)
    back = spark.read.parquet(str(tmp_path / "s"))
    assert back.count() == len(odd_rows) and back.select("shard").distinct().count() == 3
    size = lambda t: -1 if t is None else len(t)
    assert sorted((str(r.doc_id), size(r.text)) for r in back.collect()) == sorted((str(i), size(t)) for i, t in odd_rows)


def test_url_rules(spark, odd):
    def verdict(url):
        u = "" if url is None or "://" not in url else url.split("://", 1)[1]
        import re

        host = re.match(r"[^/?#]*", u)[0]
        path = re.match(r"[^?#]*", u[len(host) :])[0]
        host = host.translate(brute.LOWER)
        fits = [(len(h + p), h + p, v) for h, p, v in url_filter.HOST_RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
        if fits:
            return host, path, *max(fits)[1:]
        return host, path, None, "block" if url and any(re.search(p, url) for p, _ in url_filter.PATTERN_RULES) else "allow"

    pages = pd.read_parquet(f"{odd}/pages.parquet")
    want = [(None if pd.isna(i) else int(i), *verdict(None if pd.isna(u) else u)) for i, u in zip(pages.page_id, pages.url)]
    assert plain(url_filter.op7(spark, odd), ["page_id", "host", "path", "rule", "verdict"]) == expected(want)
    rules = url_filter.rule_table(spark)
    index = {r.rule_id: r.token for r in url_filter.rarest_token_index(spark.read.parquet(f"{odd}/pages.parquet"), rules).collect()}
    assert index[1] == "en" and index[0] == "net"


def test_packing(spark, odd, odd_rows):
    path = public_tokenizers.path("word_bpe_49k.json")
    got = packing.op10(spark, odd).toPandas()
    tok = Tokenizer.from_file(path)
    want = Counter()
    for i, t in odd_rows:
        want[i] += len(tok.encode(t or "", add_special_tokens=False).ids) + 1
    have = got.assign(doc_id=got["doc_id"].astype(object).where(got["doc_id"].notna(), None)).groupby("doc_id", dropna=False)["length"].sum()
    assert {None if pd.isna(k) else int(k): v for k, v in have.items()} == want
    for _, g in got.groupby("sequence_id"):
        g = g.sort_values("offset")
        assert (g["offset"] == g["length"].cumsum() - g["length"]).all() and g["length"].sum() <= 4096
    one = got[got["doc_id"] == 5].iloc[0]
    ids = np.array([*tok.encode(odd_rows[5][1], add_special_tokens=False).ids, 2], "<u4")
    assert one["ids_crc32"] == zlib.crc32(ids.tobytes()) and one["doc_tokens"] == len(ids)


def test_differencing():
    rng = np.random.default_rng(2)
    for n, k in ((1, 1), (5, 5), (40, 7), (300, 60)):
        s = rng.integers(1, 4000, n)
        part = packing.difference(s, k)
        assert len(part) == n and part.min() >= 0 and part.max() < k
        if n > 4 * k:
            loads = np.bincount(part, s, minlength=k)
            assert loads.max() - loads.min() < 0.2 * loads.mean()
        w = packing.near_equal_windows(s, 4096)
        assert np.bincount(w, s).max() <= 4096
    assert sorted(packing.difference(np.array([8, 7, 6, 5, 4]), 2).tolist()).count(0) in (2, 3)


@settings(max_examples=150, deadline=None)
@given(st.text(max_size=60))
def test_ids_are_the_tokenizers(text):
    enc = packing.encoder(public_tokenizers.path("word_bpe_49k.json"))
    assert enc.merges is not None
    text = text.encode("utf-8", "ignore").decode()
    assert enc.encode(text.encode()) == np.array([*enc.tokenizer.encode(text, add_special_tokens=False).ids, 2], "<u4").tobytes()


def test_quality(spark, sf, odd):
    got = quality_classifier.op1(spark, sf).toPandas()
    labels = pd.read_parquet(f"{sf}/labels.parquet")
    m = got.merge(labels, on="doc_id")
    held = m[m["held_out"]]
    assert ((held["score"] >= 0.5) == (held["quality"] == 1)).mean() > 0.85 and got["score"].between(0, 1).all()
    assert (got["held_out"] == [zlib.crc32(str(i).encode()) % 4 == 2 for i in got["doc_id"]]).all()
    assert quality_classifier.op1(spark, odd).where("score is null").count() == 0


def test_isotonic():
    got = quality_classifier.pool_adjacent_violators(np.array([0.1, 0.5, 0.3, 0.2, 0.9]), np.array([1, 1, 1, 2, 1.0]))
    assert np.allclose(got, [0.1, 0.3, 0.3, 0.3, 0.9])


def test_language(spark, sf, odd, odd_rows):
    got = language_id.op4(spark, sf).toPandas().merge(pd.read_parquet(f"{sf}/documents.parquet")[["doc_id", "lang"]], on="doc_id")
    held = got[got["held_out"]]
    assert (held["lang_pred"] == held["lang"]).mean() > 0.9 and got["score"].between(0, 1).all()
    found = language_id.op4(spark, odd).toPandas()
    und = sum(t is None or not any(c.isalpha() for c in t) for _, t in odd_rows)
    assert (found["lang_pred"] == "und").sum() == und and set(found["lang_pred"]) == {"en", "fr", "und"}


@settings(max_examples=60, deadline=None)
@given(st.lists(st.text(alphabet="aB é.\n\t-", max_size=30), min_size=1, max_size=6))
def test_text_kernels(texts):
    import pyarrow as pa

    for b in textkernel.blocks(pa.array(texts), 20):
        mine = texts[b.first : b.first + b.n]
        s, e, d = b.words(textkernel.NOT_SPACE)
        got = [[] for _ in mine]
        h = b.hashes(b.prefix(b.buf), s, e)
        names = {}
        for x, y, i, k in zip(s, e, d, h):
            w = b.buf[x:y].tobytes()
            got[i].append(w)
            assert names.setdefault(int(k), w) == w
        assert got == [t.encode().split() for t in mine]
        s, e, d = b.lines()
        assert [b.buf[x:y].tobytes() for x, y in zip(s, e)] == [x for t in mine for x in t.encode().split(b"\n")]
