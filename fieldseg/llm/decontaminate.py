"""Benchmark decontamination over sparse suffix arrays of the training words.

Each block of documents is a shard: its suffixes that begin with a word gram that some test window begins with are
sorted into a suffix array (no other suffix can be reached by a search), and every distinct test suffix of one window
whose gram the shard holds is binary-searched in it.  Consecutive hits of an item join into its longest verbatim
stretches, with their locations.

The benchmark is dealt into blocks of bounded bytes.  Executors turn each into an index of flat arrays (word hashes, word
places, the distinct windows in suffix order, their items), which passes the driver one at a time on its way to being
broadcast; a pass over the documents takes `PASS_BLOCKS` of them, so neither the driver nor a worker holds more.

Nulls and empty texts have no words and no hits.  Items without words find nothing; a null item id counts as "null".
Repeated documents and items are judged each for itself (equal item ids count once).  No row of the documents is dropped
by `match_items`; `remove_contaminated` drops those with a hit.
"""

from __future__ import annotations

import pickle

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from fieldseg.llm.textkernel import ALNUM, LOWER, Block, blocks, grams, per_doc

WINDOW = 10
PRUNE = 3
#: Bytes of one index, the bytes it takes for each word beside the text, and the indexes of one pass over the documents.
INDEX_BYTES = 64 << 20
WORD_BYTES = 44
PASS_BLOCKS = 4
#: Most bits of the table that is asked before the sorted grams are.
SEEN_BITS = 25
MATCH = T.StructType([
    T.StructField("n_words", T.LongType()),
    T.StructField("n_hit", T.LongType()),
    T.StructField("spans", T.ArrayType(T.StructType([T.StructField("item_id", T.StringType()), T.StructField("doc_word", T.LongType()), T.StructField("n_words", T.LongType())]))),
])
_SPAN = pa.struct([("item_id", pa.string()), ("doc_word", pa.int64()), ("n_words", pa.int64())])
#: Words before A-Z are lower-cased.
WORDS = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


def word_hashes(b: Block) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Hash, document, start and end of each word, lower-cased."""
    low = LOWER[b.buf]
    s, e, d = b.words(ALNUM, low)
    return b.hashes(b.prefix(low), s, e), d, s, e


def _ranges(lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The numbers lo to hi - 1 of each row, and the row of each."""
    n = np.maximum(hi - lo, 0)
    row = np.repeat(np.arange(len(n)), n)
    return np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n) + lo[row], row


class Windows:
    """Distinct windows of the items whose first `gram` words are told apart, in suffix order, and the items of each."""

    def __init__(self, h: np.ndarray, start: np.ndarray, length: np.ndarray, item: np.ndarray, width: int, gram: int):
        cols = [np.where(length > j, h[np.minimum(start + j, len(h) - 1)], np.uint64(0)) for j in range(width)]
        order = np.lexsort((item, length, *cols[::-1]))
        start, length, item = start[order], length[order], item[order]
        apart = np.ones((2, len(order)), bool)
        for k, c in enumerate(cols):
            c = c[order]
            apart[1, 1:] = apart[1, 1:] & (c[1:] == c[:-1]) if k else c[1:] == c[:-1]
            if k == gram - 1:
                apart[0, 1:] = ~apart[1, 1:]
        new = np.concatenate([[True], ~apart[1, 1:] | (length[1:] != length[:-1])])
        fresh = new.copy()
        fresh[1:] |= item[1:] != item[:-1]
        self.gram = gram
        self.start, self.length = start[new].astype(np.int32), length[new].astype(np.int16)
        self.item, self.item_at = item[fresh].astype(np.int32), np.append(np.flatnonzero(new[fresh]), fresh.sum()).astype(np.int32)
        # windows that begin alike lie together
        first = np.flatnonzero(apart[0][new])
        flat = h[self.start[first][:, None] + np.arange(gram)]
        known, _ = grams(flat.reshape(-1), np.repeat(np.arange(len(first)), gram), gram)
        by = np.argsort(known, kind="stable")
        self.known, self.lo, self.hi = known[by], first[by].astype(np.int32), np.append(first[1:], len(self.start))[by].astype(np.int32)


class TestIndex:
    """Flat arrays over the words of some items, for searches in blocks of documents."""

    __test__ = False

    def __init__(self, ids: pa.Array, texts: pa.Array, window: int = WINDOW):
        self.window, self.ids = window, ids
        none = np.zeros(0, np.int64)
        h, s, e, d, low, base = [none.astype(np.uint64)], [none], [none], [none], [], 0
        for b in blocks(texts):
            bh, bd, bs, be = word_hashes(b)
            h.append(bh)
            s.append(bs + base)
            e.append(be + base)
            d.append(bd + b.first)
            low.append(LOWER[b.buf].tobytes())
            base += len(b.buf)
        self.h, self.low, d = np.concatenate(h), b"".join(low), np.concatenate(d)
        kind = np.int32 if base < 1 << 31 else np.int64
        self.s, self.e = np.concatenate(s).astype(kind), np.concatenate(e).astype(kind)
        n, first = np.bincount(d, minlength=len(ids)), np.searchsorted(d, np.arange(len(ids)))
        w = np.minimum(window, n)
        start, item = _ranges(first, first + np.where(n > 0, n - w + 1, 0))
        self.parts = []
        for g in range(1, PRUNE + 1):
            mine = np.flatnonzero(np.minimum(PRUNE, w[item]) == g)
            if len(mine):
                self.parts.append(Windows(self.h, start[mine], w[item[mine]], item[mine], window, g))
        self.seen: list[np.ndarray] | None = None

    def n_bytes(self) -> int:
        arrays = [self.h, self.s, self.e, *(x for p in self.parts for x in vars(p).values() if isinstance(x, np.ndarray))]
        return len(self.low) + self.ids.nbytes + sum(x.nbytes for x in arrays)

    def words(self, p: int, n: int) -> bytes:
        return b" ".join([self.low[self.s[q] : self.e[q]] for q in range(p, p + n)])

    def _tables(self) -> list[np.ndarray]:
        if self.seen is None:
            self.seen = []
            for p in self.parts:
                t = np.zeros(1 << max(16, min(SEEN_BITS, int(len(p.known) * 32).bit_length())), bool)
                t[p.known & np.uint64(len(t) - 1)] = True
                self.seen.append(t)
        return self.seen

    def search(self, b: Block, words: tuple, found_grams: dict) -> list[tuple[int, int, int, int]]:
        """(word position, number of words, part, window) of each verbatim occurrence of a window in the block."""
        h, d, s, e = words
        out, low = [], None
        for k, (p, seen) in enumerate(zip(self.parts, self._tables())):
            if p.gram not in found_grams:
                found_grams[p.gram] = grams(h, d, p.gram)
            got, at = found_grams[p.gram]
            maybe = np.flatnonzero(seen[got & np.uint64(len(seen) - 1)])
            got, at = got[maybe], at[maybe]
            near = np.minimum(np.searchsorted(p.known, got), len(p.known) - 1)
            hit = p.known[near] == got
            if not hit.any():
                continue
            got, at = np.unique(got[hit]), at[hit]
            gram, _ = _ranges(np.searchsorted(p.known, got, "left"), np.searchsorted(p.known, got, "right"))
            wanted, _ = _ranges(p.lo[gram], p.hi[gram])
            table = np.zeros((len(at), self.window), ">u8")
            for j in range(self.window):
                ok = at + j < len(h)
                ok[ok] = d[at[ok] + j] == d[at[ok]]
                table[ok, j] = h[at[ok] + j]
            keys = _keys(table)
            order = np.argsort(keys, kind="stable")
            sa, keys = at[order], keys[order]
            least, most = (np.full((len(wanted), self.window), x, ">u8") for x in (0, (1 << 64) - 1))
            for j in range(self.window):
                ok = p.length[wanted] > j
                least[ok, j] = most[ok, j] = self.h[p.start[wanted[ok]] + j]
            here, row = _ranges(np.searchsorted(keys, _keys(least), "left"), np.searchsorted(keys, _keys(most), "right"))
            if low is None:
                low = LOWER[b.buf].tobytes()
            for x, w in zip(sa[here].tolist(), wanted[row].tolist()):
                n = int(p.length[w])
                # a range of keys takes in suffixes that end early, so words are compared themselves
                if x + n <= len(h) and d[x + n - 1] == d[x] and b" ".join([low[s[q] : e[q]] for q in range(x, x + n)]) == self.words(int(p.start[w]), n):
                    out.append((x, n, k, w))
        return out


def index_blocks(items: DataFrame, window: int, index_bytes: int):
    """The indexes of (i, t), one after another; executors build them."""
    size = items.agg(F.sum(F.octet_length("t")), F.sum(F.regexp_count("t", F.lit(WORDS)))).first()
    parts = int(1 + ((size[0] or 0) + WORD_BYTES * (size[1] or 0)) // index_bytes)

    def build(table):
        table = table.combine_chunks()
        column = lambda c: table[c].combine_chunks() if table.num_rows else pa.array([], pa.string())
        index = TestIndex(column("i").cast(pa.string()), column("t").cast(pa.string()), window)
        return pa.table({"pickled": pa.array([pickle.dumps(index, 5)], pa.binary())})

    dealt = items.withColumn("k", F.pmod(F.xxhash64("i", "t"), F.lit(parts)).cast("int"))
    # each pickle is a partition of its own, fetched by itself
    for r in dealt.repartitionById(parts, "k").groupBy("k").applyInArrow(build, "pickled binary").toLocalIterator():
        yield pickle.loads(r.pickled)


def _keys(table: np.ndarray) -> np.ndarray:
    """Rows of big-endian words as byte strings, which compare as the rows do."""
    return np.ascontiguousarray(table).view(f"S{8 * table.shape[1]}").ravel() if table.size else np.zeros(0, f"S{8 * max(1, table.shape[1])}")


def _match_block(b: Block, indexes: list[TestIndex], before: list) -> list[dict]:
    words = word_hashes(b)
    d, found_grams = words[1], {}
    n_words, first = per_doc(d, b.n), np.searchsorted(d, np.arange(b.n + 1))
    out = [{"n_words": int(n), "n_hit": 0, "spans": []} for n in n_words]
    by_doc: dict[int, dict[tuple, list]] = {}
    for at, index in enumerate(indexes):
        for p, n, part, w in index.search(b, words, found_grams):
            items, own = by_doc.setdefault(int(d[p]), {}), index.parts[part]
            for i in own.item[own.item_at[w] : own.item_at[w + 1]].tolist():
                items.setdefault((at, i), []).append((p, p + n))
    for k in {*by_doc, *(i for i in range(b.n) if before[i])}:
        runs = {(x["item_id"], x["doc_word"], x["n_words"]) for x in before[k] or []}
        for (at, i), spans in by_doc.get(k, {}).items():
            spans.sort()
            name, (start, end) = indexes[at].ids[i].as_py(), spans[0]
            for a, z in spans[1:]:
                if a > end:
                    runs.add((name, start - int(first[k]), end - start))
                    start, end = a, z
                end = max(end, z)
            runs.add((name, start - int(first[k]), end - start))
        hit = np.zeros(out[k]["n_words"] + 1, np.int64)
        for _, a, n in runs:
            hit[a] += 1
            hit[a + n] -= 1
        out[k]["n_hit"] = int((np.cumsum(hit)[:-1] > 0).sum())
        out[k]["spans"] = [{"item_id": i, "doc_word": a, "n_words": n} for i, a, n in sorted(runs)]
    return out


def _pass(indexes, text: str, name: str, keep: list[str], last: bool):
    kind = pa.struct([("n_words", pa.int64()), ("n_hit", pa.int64()), ("spans", pa.list_(_SPAN))])

    def run(batches):
        own = [x.value for x in indexes]
        for rb in batches:
            before = rb.column(rb.schema.get_field_index(name)) if name in rb.schema.names else None
            found: list[dict] = []
            for b in blocks(rb.column(rb.schema.get_field_index(text))):
                earlier = [(x or {}).get("spans") for x in before.slice(b.first, b.n).to_pylist()] if before is not None else [None] * b.n
                found += _match_block(b, own, earlier)
            cols = [c for c in rb.schema.names if c != name and (not last or c in keep)]
            yield pa.RecordBatch.from_arrays([rb.column(rb.schema.get_field_index(c)) for c in cols] + [pa.array(found, kind)], cols + [name])

    return run


def match_items(docs: DataFrame, items: DataFrame, text: str = "text", item_id: str = "item_id", item_text: str = "text", window: int = WINDOW, keep: list[str] | None = None, name: str = "match", index_bytes: int = INDEX_BYTES) -> DataFrame:
    """The kept columns of `docs` and a struct `match` (n_words, n_hit, spans), before which a column of its name gives way; one row per document."""
    spark = docs.sparkSession
    keep = list(docs.columns) if keep is None else keep
    keep = [c for c in keep if c != name]
    items = items.select(F.coalesce(F.col(item_id).cast("string"), F.lit("null")).alias("i"), F.coalesce(F.col(item_text), F.lit("")).alias("t"))
    held = [spark.sparkContext.broadcast(x) for x in index_blocks(items, window, index_bytes)]
    passes = [held[k : k + PASS_BLOCKS] for k in range(0, len(held), PASS_BLOCKS)] or [[]]
    out = docs.select(*dict.fromkeys([*keep, text]))
    for k, indexes in enumerate(passes):
        last = k == len(passes) - 1
        cols = [f for f in out.schema.fields if f.name != name and (not last or f.name in keep)]
        out = out.mapInArrow(_pass(indexes, text, name, keep, last), T.StructType([*cols, T.StructField(name, MATCH)]))
    return out


def remove_contaminated(docs: DataFrame, items: DataFrame, **options) -> DataFrame:
    """The documents in which no window of any item occurs, with their columns unchanged."""
    name = "_fs_match"
    return match_items(docs, items, name=name, **options).where(F.col(f"{name}.n_hit") == 0).drop(name)


def op3(spark, sf_dir: str) -> DataFrame:
    docs, items = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    found = match_items(docs, items, keep=["doc_id"])
    ids = F.array_sort(F.array_distinct(F.col("match.spans.item_id")))
    return found.select(
        "doc_id",
        F.col("match.n_words").alias("n_words"),
        F.col("match.n_hit").alias("n_hit"),
        F.size(ids).cast("long").alias("n_items"),
        F.sha2(F.array_join(ids, ","), 256).alias("items_sha256"),
        (F.col("match.n_hit") > 0).alias("contaminated"),
    )


OP3_SQL = r"""
with dw as (
  select row_number() over () as r, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w from documents),
iw as (
  select item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w from benchmark),
ig as (
  select distinct item_id, l, list_slice(w, i, i + l - 1) as g
  from (select item_id, w, least(10, len(w)) as l, unnest(range(1, len(w) - least(10, len(w)) + 2)) as i from iw where len(w) > 0)),
sizes as (select distinct l from ig),
dg as (select r, i, l, list_slice(w, i, i + l - 1) as g from (select r, w, l, unnest(range(1, cast(len(w) as bigint) - l + 2)) as i from dw, sizes where len(w) >= l)),
hit as (select dg.r, dg.i, dg.l, ig.item_id from dg join ig on dg.l = ig.l and dg.g = ig.g),
hw as (select r, count(distinct p) as n_hit from (select r, unnest(range(i, i + l)) as p from hit) group by r),
hi as (select r, count(*) as n_items, string_agg(id, ',' order by id) as ids from (select distinct r, cast(item_id as varchar) as id from hit) group by r)
select doc_id, cast(len(w) as bigint) as n_words, coalesce(n_hit, 0) as n_hit, coalesce(n_items, 0) as n_items, sha256(coalesce(ids, '')) as items_sha256, coalesce(n_hit, 0) > 0 as contaminated
from dw left join hw using (r) left join hi using (r)
"""
