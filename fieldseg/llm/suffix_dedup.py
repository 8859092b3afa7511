"""Suffix-array dedup of verbatim repeats by difference-cover suffix sorting, distributed by content-chosen anchors.

Which bytes are compared.  Every window of `WINDOW` bytes has an anchor: the place in it where the hash of `GRAM` bytes is
smallest (the leftmost such).  Equal windows have equal anchors at equal places, so only windows whose anchor gram starts at two places
or more can repeat, and all copies of a window meet under one anchor hash.  Those windows, with the bytes they need, are the
contexts; each task holds whole anchor groups.  This loses no repeat, and leaves out the text that has none.

How they are compared.  A task joins its contexts to one string and sorts its suffixes by the difference cover {1, 2} modulo 3:
the sampled triples are sorted and named, the string of names is sorted by recursion (deep enough for a whole window), the
remaining suffixes are sorted by first symbol and rank and merged in.  Adjacent suffixes whose prefixes of `WINDOW` bytes are equal,
byte by byte, are repeats.  Windows that repeat within one text are found where the anchors are made, and one of each goes on, so periodic
text stays small.  Anchors at more than `HOT_ANCHORS` places are compared by hashes of their windows in an aggregation.

Texts are known by a 128-bit hash; a text that has copies repeats as a whole.  Null and empty texts have no bytes; texts
shorter than a window have no repeat.  The bytes that stay need not be valid UTF-8, so they are returned as binary.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from fieldseg.llm.textkernel import Block, blocks
from fieldseg.runtime import Scratch, cut

WINDOW = 400
GRAM = 128
HOT_ANCHORS = 20_000
#: Bytes of contexts that are sorted at a time (a larger anchor group is sorted by itself), and of a stretch of text.
SORT_BYTES = 3 << 19
STRETCH = 2 << 20
#: Bytes that are compared at a time.
COMPARE_BYTES = 1 << 20
_LOW = (1 << 24) - 1


def text_hash(text: Column) -> list[Column]:
    t = F.coalesce(text, F.lit(""))
    return [F.xxhash64(t).alias("h1"), F.xxhash64(F.lit(31), t).alias("h2")]


def stretches(b: Block, window: int):
    """The block, or overlapping parts of its one long text; with the place of each part in the text."""
    if len(b.buf) <= 4 * STRETCH or b.n > 1:
        yield b, 0
        return
    for a in range(0, len(b.buf), STRETCH):
        part = b.buf[a : a + STRETCH + window - 1]
        if len(part) >= window or a == 0:
            yield Block(part, np.array([0, len(part)]), b.first), a


def anchors(b: Block, window: int = WINDOW, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """Runs of windows under one anchor: (document, first start, number, anchor hash), and the runs that repeat in their text."""
    none = np.zeros(0, np.int64)
    count = np.maximum(np.diff(b.off) - window + 1, 0)
    if not count.sum():
        return none, none, none, none.astype(np.uint64), none, none, none
    sums = b.prefix(b.buf)
    at = np.arange(len(b.buf) - gram + 1)
    g = b.hashes(sums, at, at + gram)
    least, have = (g & np.uint64(~_LOW & (1 << 64) - 1)) | at.astype(np.uint64), 1
    width = window - gram + 1
    while have < width:
        step = min(have, width - have)
        least = np.minimum(least[:-step], least[step:])
        have += step
    doc = np.repeat(np.arange(b.n), count)
    pos = b.off[doc] + np.arange(len(doc)) - np.repeat(np.cumsum(count) - count, count)
    anchor = (least[pos] & np.uint64(_LOW)).astype(np.int64)
    del least

    def runs(a, d, p):
        f = np.flatnonzero(np.concatenate([[True], (a[1:] != a[:-1]) | (d[1:] != d[:-1]) | (p[1:] != p[:-1] + 1)]))
        return f, np.diff(np.concatenate([f, [len(a)]]))

    first, n = runs(anchor, doc, pos)
    hashes, own = g[anchor[first]], doc[first]
    order = np.lexsort((hashes, own))
    same = (hashes[order][1:] == hashes[order][:-1]) & (own[order][1:] == own[order][:-1])
    local = np.zeros(len(first), bool)
    local[order[1:][same]] = local[order[:-1][same]] = True
    if not local.any():
        return own, pos[first] - b.off[own], n, hashes, none, none, none
    # windows under an anchor that its text holds twice: all but the first of equal ones leave, and all of them repeat
    mine = np.flatnonzero(np.repeat(local, n))
    h, d = b.hashes(sums, pos[mine], pos[mine] + window), doc[mine]
    order = np.lexsort((mine, h, d))
    same = (h[order][1:] == h[order][:-1]) & (d[order][1:] == d[order][:-1])
    later, twice = np.zeros(len(pos), bool), np.zeros(len(pos), bool)
    later[mine[order[1:][same]]] = True
    twice[mine[order[1:][same]]] = twice[mine[order[:-1][same]]] = True
    rf, rn = runs(np.zeros(int(twice.sum())), doc[twice], pos[twice]) if twice.any() else (none, none)
    rd, rp = doc[twice][rf], pos[twice][rf]
    anchor, doc, pos = anchor[~later], doc[~later], pos[~later]
    first, n = runs(anchor, doc, pos) if len(pos) else (none, none)
    own = doc[first]
    return own, pos[first] - b.off[own], n, g[anchor[first]], rd, rp - b.off[rd], rn


def anchor_runs(texts: DataFrame, window: int, gram: int) -> DataFrame:
    """(anchor, h1, h2, lo, n, kind): kind 0 runs of windows to compare, kind 1 runs known to repeat (no anchor)."""

    def run(batches):
        for rb in batches:
            h1, h2 = rb.column(0), rb.column(1)
            for whole in blocks(rb.column(2), STRETCH):
                for b, base in stretches(whole, window):
                    own, lo, n, g, rd, rlo, rn = anchors(b, window, gram)
                    d = pa.array(np.concatenate([own, rd]) + b.first)
                    a1 = h1.take(d)
                    key = np.concatenate([g.view(np.int64), a1.to_numpy()[len(own) :]])
                    kind = np.concatenate([np.zeros(len(own), np.int8), np.ones(len(rd), np.int8)])
                    yield pa.RecordBatch.from_arrays([pa.array(key), a1, h2.take(d), pa.array(np.concatenate([lo, rlo]) + base), pa.array(np.concatenate([n, rn])), pa.array(kind)], ["anchor", "h1", "h2", "lo", "n", "kind"])

    return texts.mapInArrow(run, "anchor long, h1 long, h2 long, lo long, n long, kind byte")


def repeated_anchors(runs: DataFrame, hot: int = HOT_ANCHORS) -> DataFrame:
    """The runs whose anchor starts at two places or more (and all of kind 1); kind 2 where it does at more than `hot`."""
    several = F.min(F.struct("h1", "h2", "lo")) < F.max(F.struct("h1", "h2", "lo"))
    counts = runs.where("kind = 0").groupBy("anchor").agg(several.alias("several"), (F.count("*") > hot).alias("hot")).where("several").drop("several")
    compared = runs.where("kind = 0").join(counts, "anchor").withColumn("kind", F.when(F.col("hot"), 2).otherwise(0).cast("byte")).drop("hot")
    return compared.unionByName(runs.where("kind = 1"))


def contexts(texts: DataFrame, wanted: DataFrame, window: int) -> DataFrame:
    """(anchor, h1, h2, lo, n, part, hash): the bytes of each run, or for kind 2 a row for each window with its hash."""
    per_text = wanted.where("kind <> 1").groupBy("h1", "h2").agg(F.collect_set(F.struct("lo", "n", "anchor", "kind")).alias("runs"))
    reps = texts.groupBy("h1", "h2").agg(F.min("doc_id").alias("rep"))
    per_text = per_text.join(reps, ["h1", "h2"])
    joined = texts.join(per_text, ["h1", "h2"]).where(F.col("doc_id").eqNullSafe(F.col("rep"))).select("h1", "h2", "text", "runs")

    def run(batches):
        for rb in batches:
            for i in range(rb.num_rows):
                data, out, size = memoryview(rb.column(2)[i].as_py().encode()), [], 0
                h = (rb.column(0)[i].as_py(), rb.column(1)[i].as_py())
                sums = None
                for r in rb.column(3)[i].as_py():
                    lo, n = r["lo"], r["n"]
                    if r["kind"] == 0:
                        out.append((r["anchor"], *h, lo, n, bytes(data[lo : lo + n + window - 1]), 0))
                        size += n + window
                    else:
                        part = Block(np.frombuffer(data[lo : lo + n + window - 1], np.uint8), np.array([0, n + window - 1]), 0)
                        sums, at = part.prefix(part.buf), np.arange(n)
                        out += [(r["anchor"], *h, lo + k, 1, b"", x) for k, x in enumerate(part.hashes(sums, at, at + window).view(np.int64).tolist())]
                        size += 40 * n
                    if size > STRETCH:
                        yield _rows(out)
                        out, size = [], 0
                if out:
                    yield _rows(out)

    def _rows(out):
        cols = list(zip(*out))
        return pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in cols[:5]), pa.array(cols[5], pa.binary()), pa.array(cols[6], pa.int64())], ["anchor", "h1", "h2", "lo", "n", "part", "hash"])

    return joined.mapInArrow(run, "anchor long, h1 long, h2 long, lo long, n long, part binary, hash long")


def suffix_order(t: np.ndarray, covered: int = 1, enough: int = WINDOW + 2) -> np.ndarray:
    """Suffixes of t (symbols of 1 and more) in order of their first `enough` symbols at least, by difference cover modulo 3.

    `covered` says how many symbols of the first string one symbol of t stands for.
    """
    n = len(t)
    if n < 3:
        return np.array(sorted(range(n), key=lambda i: t[i:].tolist()), np.int64)
    s = np.concatenate([t, np.zeros(3, np.int64)])
    bits = np.int64(max(1, int(max(int(t.max()), n + 2)).bit_length()))
    one, two = np.arange(1, n + (n % 3 == 1), 3), np.arange(2, n, 3)
    sample = np.concatenate([one, two])
    if 3 * bits > 63:
        order = np.lexsort((s[sample + 2], s[sample + 1], s[sample]))
        new = np.zeros(len(order), bool)
        for k in range(3):
            x = s[sample[order] + k]
            new[1:] |= x[1:] != x[:-1]
    else:
        key = (s[sample] << 2 * bits) | (s[sample + 1] << bits) | s[sample + 2]
        order = np.argsort(key, kind="stable")
        new = np.concatenate([[False], key[order][1:] != key[order][:-1]])
    name = np.empty(len(order), np.int64)
    name[order] = np.cumsum(new) + 1
    if not new[1:].all() and 3 * covered < enough:
        order = suffix_order(name, 3 * covered, enough)
    place = np.zeros(n + 3, np.int64)
    place[sample[order]] = np.arange(1, len(order) + 1)
    sorted12 = sample[order]
    sorted12 = sorted12[sorted12 < n]
    zero = np.arange(0, n, 3)
    k0 = (s[zero] << bits) | place[zero + 1]
    order = np.argsort(k0, kind="stable")
    zero, k0 = zero[order], k0[order]
    s1, s2 = sorted12[sorted12 % 3 == 1], sorted12[sorted12 % 3 == 2]
    before = np.searchsorted((s[s1] << bits) | place[s1 + 1], k0)
    if 3 * bits > 63:
        # symbol pairs by rank, so that they fit with a place
        pair0, pair2 = (s[zero] << bits) | s[zero + 1], (s[s2] << bits) | s[s2 + 1]
        known = np.unique(np.concatenate([pair0, pair2]))
        pair0, pair2 = np.searchsorted(known, pair0), np.searchsorted(known, pair2)
    else:
        pair0, pair2 = (s[zero] << bits) | s[zero + 1], (s[s2] << bits) | s[s2 + 1]
    before += np.searchsorted((pair2 << bits) | place[s2 + 2], (pair0 << bits) | place[zero + 2])
    # suffixes that are equal as far as they are compared may lie in any order, but each has a place of its own
    at = np.arange(len(zero)) + np.maximum.accumulate(before)
    out = np.empty(n, np.int64)
    free = np.ones(n, bool)
    free[at] = False
    out[at], out[free] = zero, sorted12
    return out


def equal_prefixes(data: np.ndarray, order: np.ndarray, window: int) -> np.ndarray:
    """Whether each suffix in an order and the next have equal first `window` bytes, by the bytes themselves.

    Hashes pick the pairs to compare.  Pairs at one distance whose starts follow each other share their bytes, so each
    stretch of them is compared once.
    """
    b = Block(data, np.array([0, len(data)]), 0)
    h = b.hashes(b.prefix(data), order, order + window)
    same = h[1:] == h[:-1]
    at = np.flatnonzero(same)
    p, far = order[at], order[at + 1] - order[at]
    by = np.lexsort((p, far))
    at, p, far = at[by], p[by], far[by]
    first = np.flatnonzero(np.concatenate([[True], (far[1:] != far[:-1]) | (p[1:] != p[:-1] + 1)])) if len(p) else at
    n = np.diff(np.concatenate([first, [len(p)]]))
    for a, z in _spans(n + window, COMPARE_BYTES):
        size = n[a:z] + window - 1
        base = np.cumsum(size) - size
        place = np.arange(size.sum()) - np.repeat(base - p[first[a:z]], size)
        wrong = np.concatenate([[0], np.cumsum(data[place] != data[place + np.repeat(far[first[a:z]], size)])])
        if wrong[-1]:
            rows = np.arange(first[a], first[z - 1] + n[z - 1])
            start = rows - first[a] - np.repeat(np.cumsum(n[a:z]) - n[a:z], n[a:z]) + np.repeat(base, n[a:z])
            same[at[rows]] = wrong[start + window] == wrong[start]
    return same


def _spans(sizes: np.ndarray, limit: int):
    """Ranges of items whose sizes add up to about `limit`."""
    ends, a = np.cumsum(sizes), 0
    while a < len(sizes):
        z = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + limit, "right")))
        yield a, z
        a = z


def repeated_starts(parts: list[bytes], counts: np.ndarray, window: int = WINDOW) -> tuple[np.ndarray, np.ndarray]:
    """(part, start in it) of the windows that occur at two places or more among the parts."""
    size = np.array([len(p) for p in parts], np.int64)
    data = np.frombuffer(b"".join(parts), np.uint8)
    base = np.cumsum(size) - size
    order = suffix_order(data.astype(np.int64) + 1, 1, window + 2)
    part = np.repeat(np.arange(len(parts)), size)[order]
    start = order - base[part]
    valid = start < counts[part]
    order, part, start = order[valid], part[valid], start[valid]
    same = equal_prefixes(data, order, window)
    twice = np.concatenate([same, [False]]) | np.concatenate([[False], same]) if len(order) else np.zeros(0, bool)
    return part[twice], start[twice]


def _merged(owner: np.ndarray, a: np.ndarray, z: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Unions of the intervals a..z of each owner."""
    order = np.lexsort((a, owner))
    owner, a, z = owner[order], a[order], z[order]
    if not len(a):
        return owner, a, z
    far = int(z.max()) + 1
    reach = np.maximum.accumulate(z + owner * far)
    new = np.concatenate([[True], a[1:] + owner[1:] * far > reach[:-1]])
    f = np.flatnonzero(new)
    last = np.concatenate([f[1:], [len(a)]]) - 1
    return owner[f], a[f], reach[last] - owner[f] * far


def compare_contexts(rows: DataFrame, window: int) -> DataFrame:
    """(h1, h2, a, z): byte ranges of repeats, from contexts of whole anchor groups in each partition."""

    def run(batches):
        held: list[tuple] = []
        size = 0

        def solve(rows):
            seen = {}
            for r in rows:
                seen[r[1:4]] = r
            rows = list(seen.values())
            counts = np.array([r[4] for r in rows], np.int64)
            part, start = repeated_starts([r[5] for r in rows], counts, window)
            lo = np.array([r[3] for r in rows], np.int64)[part] + start
            own, a, z = _merged(part, lo, lo + window)
            h1, h2 = np.array([r[1] for r in rows], np.int64)[own], np.array([r[2] for r in rows], np.int64)[own]
            return pa.RecordBatch.from_arrays([pa.array(x) for x in (h1, h2, a, z)], ["h1", "h2", "a", "z"])

        for rb in batches:
            for r in zip(*(c.to_pylist() for c in rb.columns)):
                if size >= SORT_BYTES and held[-1][0] != r[0]:
                    yield solve(held)
                    held, size = [], 0
                held.append(r)
                size += len(r[5])
        if held:
            yield solve(held)

    own = rows.select("anchor", "h1", "h2", "lo", "n", "part").repartition("anchor").sortWithinPartitions("anchor")
    return own.mapInArrow(run, "h1 long, h2 long, a long, z long")


def repeated_ranges(texts: DataFrame, window: int = WINDOW, gram: int = GRAM, hot: int = HOT_ANCHORS) -> DataFrame:
    """(h1, h2, a, z) for (doc_id, text, h1, h2): byte ranges of the distinct texts that are covered by repeated windows."""
    runs = anchor_runs(texts.select("h1", "h2", "text"), window, gram)
    written = Scratch(runs, "anchors")
    wanted = cut(repeated_anchors(written.table, hot))
    written.drop()
    found = contexts(texts, wanted, window)
    known = wanted.where("kind = 1").select("h1", "h2", F.col("lo").alias("a"), (F.col("lo") + F.col("n") + window - 1).alias("z"))
    if wanted.where("kind = 2").isEmpty():
        return cut(compare_contexts(found, window)).unionByName(known)
    found = cut(found)
    hot_rows = found.where("part = x''")
    place = F.struct("h1", "h2", "lo")
    twice = hot_rows.groupBy("anchor", "hash").agg((F.min(place) < F.max(place)).alias("t")).where("t").drop("t")
    hits = hot_rows.join(twice, ["anchor", "hash"]).select("h1", "h2", F.col("lo").alias("a"), (F.col("lo") + window).alias("z"))
    return cut(compare_contexts(found.where("part <> x''"), window)).unionByName(known).unionByName(hits)


KEPT = "n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary"


def remove_repeats(docs: DataFrame, keep: list[str], doc_id: str = "doc_id", text: str = "text", window: int = WINDOW, with_bytes: bool = True, **options) -> DataFrame:
    """The kept columns of every row with `n_bytes`, `n_removed`, `n_spans`, `kept_sha256` and the bytes that stay."""
    names = ["n_bytes", "n_removed", "n_spans", "kept_sha256", *(["kept"] if with_bytes else [])]
    keep = [c for c in keep if c not in names]  # columns of the new names give way
    texts = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"), *text_hash(F.col(text)))
    ranges = repeated_ranges(texts, window, **options).groupBy("h1", "h2").agg(F.collect_set(F.struct("a", "z")).alias("_fs_spans"))
    copies = texts.groupBy("h1", "h2").agg((F.count("*") > 1).alias("_fs_copies"))
    about = copies.join(ranges, ["h1", "h2"], "left").where("_fs_copies or _fs_spans is not null")
    about = about.select(F.col("h1").alias("_fs_h1"), F.col("h2").alias("_fs_h2"), "_fs_copies", "_fs_spans")
    h1, h2 = text_hash(F.col(text))
    own = docs.select(*keep, F.coalesce(F.col(text), F.lit("")).alias("_fs_text"), h1.alias("_fs_own1"), h2.alias("_fs_own2"))
    joined = own.join(about, (F.col("_fs_own1") == F.col("_fs_h1")) & (F.col("_fs_own2") == F.col("_fs_h2")), "left").select(*keep, "_fs_text", F.coalesce("_fs_copies", F.lit(False)).alias("_fs_copies"), "_fs_spans")
    k = len(keep)

    def run(batches):
        for rb in batches:
            out: list[tuple] = []
            for t, copies, spans in zip(rb.column(k).to_pylist(), rb.column(k + 1).to_pylist(), rb.column(k + 2).to_pylist()):
                data = t.encode()
                if copies and len(data) >= window:
                    out.append((len(data), len(data), 1, hashlib.sha256().hexdigest(), b""))
                    continue
                kept, at, removed, n, end = [], 0, 0, 0, -1
                for a, z in sorted((s["a"], s["z"]) for s in spans or ()):
                    n += a > end
                    end = max(end, z)
                    if z > at:
                        kept.append(data[at : max(a, at)])
                        removed += z - max(a, at)
                        at = z
                left = b"".join([*kept, data[at:]])
                out.append((len(data), removed, n, hashlib.sha256(left).hexdigest(), left if with_bytes else b""))
            cols = list(zip(*out)) if out else [()] * 5
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary()]
            yield pa.RecordBatch.from_arrays([*rb.columns[:k], *(pa.array(c, kind) for c, kind in list(zip(cols, kinds))[: len(names)])], [*keep, *names])

    fields = T._parse_datatype_string(KEPT).fields[: len(names)]
    return joined.mapInArrow(run, T.StructType([*docs.select(*keep).schema.fields, *fields]))


def op8(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return remove_repeats(docs, ["doc_id"], with_bytes=False).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
