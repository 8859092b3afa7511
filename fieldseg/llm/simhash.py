"""SimHash near-dedup with Golay-code fuzzy hashing.

The 64 fingerprint bits are three segments of 22, 21 and 21 bits.  Where two fingerprints differ in two bits at most, some
segment is equal, and the next one differs in two bits at most.  Every vector of 23 bits lies within three bits of exactly one
codeword of the (23, 12) Golay code; a segment takes the codeword index of itself and of each vector one bit away, six at
most, and two segments that differ in two bits at most share one (that of a vector between them).  So a key is the number
and bits of a segment with one codeword index of the next: some sixteen keys a fingerprint, which lose no link.

Keys are made for distinct fingerprints only.  Keys with few members give pairs, which are verified; a key with more than
`RUN` members links its fingerprints through their one-bit neighbours instead, which joins exactly those within two bits and
costs 65 rows a member, so no group makes all its pairs.  Components are found by distributed contraction.

`near_dedup` drops similar texts.  The fingerprints, their Golay keys and links are those above; each linked pair is checked
by its sets of five-word windows.  Texts of a similarity of 0.8 may differ in more bits than a pigeonhole bears, so an exact way
follows for the pairs of those that are still apart: in one order of all windows, rare ones first, similar texts share one of their
first fifth.  Sketches rule out chance candidates, and sets of windows decide all others.

Nulls and texts without words have fingerprint zero, linked like any other.  Repeated rows are returned each.
"""

from __future__ import annotations

from itertools import accumulate, chain

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fieldseg.llm.textkernel import LOWER, NOT_SPACE, blocks, grams, mix
from fieldseg.operators.contraction import contract_components
from fieldseg.runtime import cut

SHINGLE = 3
SEED = 42
RUN = 64
GENERATOR = 0xC75  # x^11 + x^10 + x^6 + x^5 + x^4 + x^2 + 1
SEGMENTS = ((0, 22), (22, 21), (43, 21))
_BITS = ((np.arange(256)[:, None] >> np.arange(8)) & 1).astype(np.float64)


def shingle_hashes(text: bytes, k: int = SHINGLE, seed: int = SEED) -> list[int]:
    words = text.split()
    if not words:
        return []
    joined, digest = b" ".join(words), xxhash.xxh64_intdigest
    if len(words) <= k:
        return [digest(joined, seed)]
    ends = list(accumulate(len(w) + 1 for w in words))
    starts = [0, *ends[: len(words) - k]]
    return [digest(joined[a : b - 1], seed) for a, b in zip(starts, ends[k - 1 :])]


def majority(h: np.ndarray, docs: np.ndarray, n: int) -> np.ndarray:
    """Fingerprint of each of n documents: the bits set in over half of its hashes."""
    out = np.zeros(n, np.uint64)
    first = np.searchsorted(docs, np.arange(n + 1))
    for a in range(0, n, 512):
        z = min(n, a + 512)
        part, own = h[first[a] : first[z]], docs[first[a] : first[z]] - a
        planes = part.view(np.uint8).reshape(-1, 8).astype(np.int64) + np.arange(8) * 256 + (own * 2048)[:, None]
        counts = np.bincount(planes.ravel(), minlength=(z - a) * 2048).reshape(-1, 256)
        bits = (counts @ _BITS).reshape(z - a, 64)
        over = 2 * bits > np.diff(first[a : z + 1])[:, None]
        out[a:z] = (over.astype(np.uint64) << np.arange(64, dtype=np.uint64)).sum(axis=1, dtype=np.uint64)
    return out


def fingerprints(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", k: int = SHINGLE, extra: dict | None = None) -> DataFrame:
    """(doc_id, fp LONG) of every row, with further LONG columns by name."""
    extra = extra or {}

    def run(batches):
        for rb in batches:
            fps = [np.zeros(0, np.uint64)]
            for b in blocks(rb.column(1)):
                low = LOWER[b.buf].tobytes()
                lists = [shingle_hashes(low[b.off[i] : b.off[i + 1]], k) for i in range(b.n)]
                own = np.repeat(np.arange(b.n), [len(x) for x in lists])
                fps.append(majority(np.array([y for x in lists for y in x], np.uint64), own, b.n))
            yield pa.RecordBatch.from_arrays([rb.column(0), pa.array(np.concatenate(fps).view(np.int64)), *rb.columns[2:]], ["doc_id", "fp", *names])

    names = list(extra)
    own = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"), *(c.alias(n) for n, c in extra.items()))
    return own.mapInArrow(run, ", ".join(f"`{n}` long" for n in ["doc_id", "fp", *names]))


def golay_tables() -> tuple[np.ndarray, np.ndarray]:
    """Syndromes of the 12 upper bits, and the error pattern of weight three or less for each syndrome."""
    rest = np.zeros(1 << 12, np.int64)
    for m in range(1 << 12):
        v = m << 11
        for bit in range(22, 10, -1):
            if v >> bit & 1:
                v ^= GENERATOR << (bit - 11)
        rest[m] = v
    err = np.zeros(1 << 11, np.int64)
    one = [1 << i for i in range(23)]
    for e in [*one, *(a | b for i, a in enumerate(one) for b in one[:i]), *(a | b | c for i, a in enumerate(one) for j, b in enumerate(one[:i]) for c in one[:j])]:
        err[(e & 0x7FF) ^ rest[e >> 11]] = e
    return rest, err


class Golay:
    def __init__(self):
        self.rest, self.err = golay_tables()

    def index(self, v: np.ndarray) -> np.ndarray:
        """Index of the codeword nearest to each 23-bit vector."""
        return (v ^ self.err[(v & 0x7FF) ^ self.rest[v >> 11]]) >> 11

    def indices(self, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row, index) for the distinct codewords reached from each vector with one flip at most."""
        flips = np.concatenate([[0], 1 << np.arange(23)])
        got = np.sort(self.index(v[:, None] ^ flips[None, :]), axis=1)
        new = np.ones(got.shape, bool)
        new[:, 1:] = got[:, 1:] != got[:, :-1]
        row, col = np.nonzero(new)
        return row, got[row, col]


def fuzzy_keys(fps: DataFrame) -> DataFrame:
    """(key, fp): the Golay keys of distinct fingerprints."""

    def run(batches):
        code = Golay()
        for rb in batches:
            fp = rb.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
            for a in range(0, len(fp), 1 << 15):
                part = fp[a : a + (1 << 15)]
                seg = [(part.view(np.uint64) >> np.uint64(at) & np.uint64((1 << n) - 1)).astype(np.int64) for at, n in SEGMENTS]
                for i in range(3):
                    row, idx = code.indices(seg[(i + 1) % 3])
                    yield pa.RecordBatch.from_arrays([pa.array(i << 40 | seg[i][row] << 12 | idx), pa.array(part[row])], ["key", "fp"])

    return fps.select("fp").mapInArrow(run, "key long, fp long")


def _links(batches):
    """Runs of equal keys, sorted; kind 0: a verified pair (a, b); kind 1: fingerprint b under its one-bit neighbour a."""
    flips = np.concatenate([[np.uint64(0)], np.uint64(1) << np.arange(64, dtype=np.uint64)])
    tail_k, tail_f, wide = np.zeros(0, np.int64), np.zeros(0, np.uint64), None

    def batch(kind, a, b):
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(a), kind, np.int32)), pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], ["kind", "a", "b"])

    def hubs(f):
        for i in range(0, len(f), 4096):
            part = f[i : i + 4096]
            yield batch(1, (part[:, None] ^ flips[None, :]).ravel(), np.repeat(part, 65))

    def pairs(k, f):
        for d in range(1, RUN):
            near = np.flatnonzero(k[d:] == k[:-d]) if len(k) > d else np.zeros(0, np.int64)
            if not len(near):
                break
            a, b = f[near], f[near + d]
            ok = np.bitwise_count(a ^ b) <= 2
            if ok.any():
                yield batch(0, a[ok], b[ok])

    for rb in chain(batches, (None,)):
        end = rb is None
        if not end:
            k = np.concatenate([tail_k, rb.column(0).to_numpy(zero_copy_only=False).astype(np.int64)])
            f = np.concatenate([tail_f, rb.column(1).to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)])
        else:
            k, f = tail_k, tail_f
        if not len(k):
            continue
        if wide is not None:  # the run of a key with many members goes on
            n = int(np.searchsorted(k, wide, "right"))
            yield from hubs(f[:n])
            k, f = k[n:], f[n:]
            if not len(k):
                tail_k, tail_f = k, f
                continue
            wide = None
        cuts = np.concatenate([[0], np.flatnonzero(k[1:] != k[:-1]) + 1, [len(k)]])
        size, whole = np.diff(cuts), len(k) if end else int(cuts[-2])
        big = size > RUN
        for i in np.flatnonzero(big):
            if cuts[i] >= whole:
                wide = k[cuts[i]]
            yield from hubs(f[cuts[i] : cuts[i + 1]])
        if wide is not None:
            whole = len(k)
        small = np.repeat(~big, size)[:whole]
        yield from pairs(k[:whole][small], f[:whole][small])
        tail_k, tail_f = k[whole:], f[whole:]


def near_links(fps: DataFrame) -> DataFrame:
    """(a, b): links that join exactly the distinct fingerprints within two bits (not all pairs of a large group)."""
    keyed = fuzzy_keys(fps).repartition("key").sortWithinPartitions("key", "fp")
    found = cut(keyed.mapInArrow(_links, "kind int, a long, b long"))
    pairs = found.where("kind = 0").select("a", "b")
    # each hub has 65 members at most, all within one bit of it
    hubs = found.where("kind = 1").groupBy("a").agg(F.collect_set("b").alias("f")).where(F.size("f") > 1)
    stars = hubs.select(F.array_min("f").alias("a"), F.explode("f").alias("b")).where("a <> b")
    return pairs.unionByName(stars)


def component_map(prints: DataFrame) -> DataFrame:
    """(fp, label): each distinct fingerprint and the smallest fingerprint of its component."""
    fps = cut(prints.select("fp").distinct())
    linked = contract_components(near_links(fps), "a", "b").select(F.col("id").alias("fp"), "label")
    return fps.join(linked, "fp", "left").select("fp", F.coalesce("label", "fp").alias("label"))


def near_components(prints: DataFrame) -> DataFrame:
    """(doc_id, fp, component_id) from (doc_id, fp); a null id is never the smallest."""
    prints = cut(prints)
    per_fp = prints.groupBy("fp").agg(F.min("doc_id").alias("rep"))
    labels = cut(component_map(prints).join(per_fp, "fp"))
    least = labels.groupBy("label").agg(F.min("rep").alias("component_id"))
    return prints.join(labels.join(least, "label").select("fp", "component_id"), "fp").select("doc_id", "fp", "component_id")


SIMILARITY = 0.8
#: Least hashes of a text's windows that bring it to leaders before all others are compared, and the leaders drawn by lot
#: for each least hash.
LEADERS = 3
DRAWN = 2
#: 64-bit words of the sketch, and the share of its bits, over what the similarity lets expect, beyond which a pair is ruled out
#: (some eight standard errors).
SKETCH = 4
RULED_OUT = 0.2
#: 64-bit words of the parities: each differing bit is a window that one text alone has, so this bound is exact.
PARITY = 4
#: Texts (expected) that are asked for common windows, how often such a window is in them, and how many are told to the tasks.
COMMON_TEXTS = 8000
COMMON_COUNT = 3
COMMON_WINDOWS = 50_000
#: Nodes whose windows are fetched by broadcast; of more, all texts are shuffled.
BROADCAST_ENDS = 200_000
#: Bytes of text whose windows a task holds at a time.
KERNEL_BYTES = 1 << 19
#: Runs of so many rows are compared together with others; longer ones by themselves, so many rows at a time.
RUN_ROWS = 64
BLOCK_ROWS = 512
#: Pairs that a task holds before it sends them on.
PAIR_ROWS = 250_000


def windows(b, low: np.ndarray, sizes: tuple[int, ...]):
    """For each size, the hashes of the windows of so many words and their documents; a shorter text is one window."""
    s, e, d = b.words(NOT_SPACE, low)
    h = b.hashes(b.prefix(low), s, e)
    n = np.bincount(d, minlength=b.n)
    for size in sizes:
        g, at = grams(h, d, size)
        own = d[at]
        short = np.flatnonzero((n > 0) & (n < size))
        if len(short):
            first = np.searchsorted(d, short)
            whole = np.array([int(np.bitwise_xor.reduce(mix(h[f : f + n[i]] + np.arange(n[i], dtype=np.uint64)))) for i, f in zip(short, first)], np.uint64)
            g, own = np.concatenate([g, whole]), np.concatenate([own, short])
            order = np.argsort(own, kind="stable")
            g, own = g[order], own[order]
        yield g, own


def distinct(g: np.ndarray, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each window of a document once."""
    if not len(g):
        return g, own
    order = np.lexsort((g, own))
    g, own = g[order], own[order]
    new = np.concatenate([[True], (g[1:] != g[:-1]) | (own[1:] != own[:-1])])
    return g[new], own[new]


def window_sets(texts: DataFrame, shingle: int) -> DataFrame:
    """(node, hashes): the distinct windows of the texts in (node, text)."""

    def run(batches):
        for rb in batches:
            for b in blocks(rb.column(1), KERNEL_BYTES):
                (pair,) = windows(b, LOWER[b.buf], (shingle,))
                g, own = distinct(*pair)
                off = np.searchsorted(own, np.arange(b.n + 1)).astype(np.int32)
                yield pa.RecordBatch.from_arrays([rb.column(0).slice(b.first, b.n), pa.ListArray.from_arrays(pa.array(off), pa.array(g.view(np.int64)))], ["node", "hashes"])

    return texts.mapInArrow(run, "node long, hashes array<long>")


def common_windows(docs: DataFrame, text: str, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """Windows that many of some texts hold, ascending, and in how many they are.

    They come last in the order of windows, so that few prefixes hold them.  The order changes the cost alone: pairs are found by any.
    """
    body = F.coalesce(F.col(text), F.lit(""))
    few = docs.select(F.xxhash64(body).alias("node"), body.alias("text")).where(F.pmod(F.xxhash64(F.lit(5), "text"), F.lit(max(1, docs.count()))) < COMMON_TEXTS)
    counts = window_sets(few.dropDuplicates(["node"]), shingle).select(F.explode("hashes").alias("h")).groupBy("h").agg(F.count("*").alias("n"))
    found = counts.where(F.col("n") >= COMMON_COUNT).orderBy(F.desc("n"), "h").limit(COMMON_WINDOWS).toPandas()
    h, n = found["h"].to_numpy(np.int64).view(np.uint64), found["n"].to_numpy(np.int64)
    order = np.argsort(h)
    return h[order], n[order]


def digests(docs: DataFrame, text: str, node: list, shingle: int, similarity: float, common: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """(n1, n2, doc_id, size, score, prefix, least, sketch, parity) of the distinct windows of each text; a text without words has one.

    `prefix`: in the order of (times found common, hash), as many first windows as any text of the similarity shares one with.
    `least`: least hashes under several mixes.  `score`: common windows in a thousand.  `sketch`: the majority of each bit.
    `parity`: for each of 256 classes of windows, whether an odd number is there.
    """

    def arrays(m):
        return pa.ListArray.from_arrays(pa.array(np.arange(len(m) + 1, dtype=np.int32) * m.shape[1]), pa.array(m.view(np.int64).ravel()))

    def salted(h, salt):
        return mix(h + np.uint64(salt * 0x9E3779B97F4A7C15 & (1 << 64) - 1))

    def run(batches):
        names, times = common
        for rb in batches:
            size, score, taken, prefix = ([np.zeros(0, np.int64)] for _ in range(4))
            least, sketch, parity = ([np.zeros((0, k), np.uint64)] for k in (LEADERS, SKETCH, PARITY))
            for b in blocks(rb.column(3), KERNEL_BYTES):
                (pair,) = windows(b, LOWER[b.buf], (shingle,))
                g, own = distinct(*pair)
                bare = np.flatnonzero(np.bincount(own, minlength=b.n) == 0)
                g, own = np.concatenate([g, np.zeros(len(bare), np.uint64)]), np.concatenate([own, bare])
                heat = np.zeros(len(g), np.int64)
                if len(names):
                    place = np.minimum(np.searchsorted(names, g), len(names) - 1)
                    heat = np.where(names[place] == g, times[place], 0)
                order = np.lexsort((g, heat, own))
                g, own, heat = g[order], own[order], heat[order]
                n = np.bincount(own, minlength=b.n)
                first = np.cumsum(n) - n
                take = n - np.ceil(similarity * n - 1e-9).astype(np.int64) + 1
                prefix.append(g[np.arange(len(g)) - first[own] < take[own]].view(np.int64))
                size.append(n)
                taken.append(take)
                score.append(np.bincount(own, heat > 0, minlength=b.n).astype(np.int64) * 1000 // n)
                least.append(np.stack([np.minimum.reduceat(salted(g, 1 + k), first) for k in range(LEADERS)], axis=1))
                sketch.append(np.stack([majority(salted(g, 101 + k), own, b.n) for k in range(SKETCH)], axis=1))
                place = salted(g, 201)
                bit, word = np.uint64(1) << (place & np.uint64(63)), (place >> np.uint64(6)) % np.uint64(PARITY)
                parity.append(np.stack([np.bitwise_xor.reduceat(np.where(word == k, bit, np.uint64(0)), first) for k in range(PARITY)], axis=1))
            ends = np.concatenate([[0], np.cumsum(np.concatenate(taken))]).astype(np.int32)
            lists = [pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(prefix))), arrays(np.concatenate(least)), arrays(np.concatenate(sketch)), arrays(np.concatenate(parity))]
            yield pa.RecordBatch.from_arrays([*rb.columns[:3], pa.array(np.concatenate(size)), pa.array(np.concatenate(score)), *lists], ["n1", "n2", "doc_id", "size", "score", "prefix", "least", "sketch", "parity"])

    own = docs.select(*node, F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    return own.mapInArrow(run, "n1 long, n2 long, doc_id long, size long, score long, prefix array<long>, least array<long>, sketch array<long>, parity array<long>")


def simhash_pairs(prints: DataFrame) -> DataFrame:
    """(a, b): links that join exactly the nodes of (node, fp) whose fingerprints are equal or within two bits, by Golay keys.

    Nodes of one fingerprint are tied to the least of them, which stands for them in the links between fingerprints.
    """
    prints = cut(prints)
    hubs = cut(prints.groupBy("fp").agg(F.min("node").alias("hub")))
    same = prints.join(hubs, "fp").where("node <> hub").select(F.col("node").alias("a"), F.col("hub").alias("b"))
    a, b = (hubs.select(F.col("fp").alias(x), F.col("hub").alias(f"hub_{x}")) for x in "ab")
    links = near_links(hubs.select("fp")).join(a, "a").join(b, "b").select(F.col("hub_a").alias("a"), F.col("hub_b").alias("b"))
    return same.unionByName(links).select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def leader_pairs(nodes: DataFrame) -> DataFrame:
    """(a, b): each node with some that share a least hash.

    These are the one of most common windows, which is likely what the others derive from, and some drawn by lot, so that one text
    that isn't like the others leads few astray.
    """
    each = nodes.select("node", "score", F.posexplode("least").alias("k", "h"))
    leads = [F.max(F.struct("score", "node"))["node"], *(F.max(F.struct(F.xxhash64(F.lit(i), "node").alias("o"), "node"))["node"] for i in range(DRAWN))]
    led = each.groupBy("k", "h").agg(F.array(*leads).alias("leads"), F.count("*").alias("n")).where("n > 1")
    pairs = each.join(led, ["k", "h"]).select(F.col("node").alias("a"), F.explode(F.array_distinct("leads")).alias("b")).where("a <> b")
    return pairs.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def _whole_runs(batches):
    """(columns, cuts) of the rows of whole runs of equal keys, from batches sorted by `key`; arrays of words stay matrices."""

    def arrays(rb):
        return {c: rb.column(c).flatten().to_numpy().reshape(rb.num_rows, -1) if pa.types.is_list(rb.schema.field(c).type) else rb.column(c).to_numpy() for c in rb.schema.names}

    held = None
    for rb in chain(batches, (None,)):
        if rb is not None and not rb.num_rows:
            continue
        x = None if rb is None else arrays(rb)
        if held is not None:
            x = held if x is None else {c: np.concatenate([held[c], x[c]]) for c in held}
        if x is None or not len(x["key"]):
            continue
        cuts = np.concatenate([[0], np.flatnonzero(x["key"][1:] != x["key"][:-1]) + 1, [len(x["key"])]])
        last = len(cuts) - 1 if rb is None else len(cuts) - 2
        whole = int(cuts[last])
        held = {c: v[whole:] for c, v in x.items()}
        if last:
            yield {c: v[:whole] for c, v in x.items()}, cuts[: last + 1]


def _fits(x, i, j, similarity: float):
    """Whether rows i and j of one run have two labels and can be similar by what is left of them behind their key."""
    # if no window before this one is shared, no more than the shorter rest is; the first shared window of a pair counts
    return (x["label"][i] != x["label"][j]) & (np.minimum(x["rest"][i], x["rest"][j]) >= similarity / (1 + similarity) * (x["size"][i] + x["size"][j]) - 1e-9)


class _Pairs:
    """Pairs of nodes, each once as long as they are held; `full` are sent on."""

    def __init__(self):
        self.parts, self.n = [np.zeros((0, 2), np.int64)], 0

    def add(self, a, b):
        if len(a):
            self.parts.append(np.stack([np.minimum(a, b), np.maximum(a, b)], axis=1))
            self.n += len(a)

    def full(self, most: int = PAIR_ROWS):
        if self.n <= most:
            return np.zeros((0, 2), np.int64)
        both = np.unique(np.concatenate(self.parts), axis=0)
        # what is held is sent when it takes half of the room even so
        out, keep = (both, both[:0]) if len(both) > most // 2 else (both[:0], both)
        self.parts, self.n = [keep], len(keep)
        return out


def _short_runs(similarity: float):
    """From rows (key, node, label, size, rest), sorted by (key, size): pairs (a, b) of runs of `RUN_ROWS` at most, and the rows of longer ones."""

    def rows(**cols):
        n = len(next(iter(cols.values())))
        return pa.RecordBatch.from_arrays([pa.array(cols.get(c, np.zeros(n, np.int64))) for c in ("a", "b", "key", "label", "size", "rest")], ["a", "b", "key", "label", "size", "rest"])

    def run(batches):
        ready = _Pairs()
        for x, cuts in _whole_runs(batches):
            size = np.diff(cuts)
            mixed = np.minimum.reduceat(x["label"], cuts[:-1]) < np.maximum.reduceat(x["label"], cuts[:-1])
            some = np.repeat(mixed & (size <= RUN_ROWS), size)
            y = {c: v[some] for c, v in x.items()}
            for d in range(1, RUN_ROWS):
                at = np.flatnonzero(y["key"][d:] == y["key"][:-d]) if len(y["key"]) > d else np.zeros(0, np.int64)
                if not len(at):
                    break
                at = at[_fits(y, at, at + d, similarity)]
                ready.add(y["node"][at], y["node"][at + d])
            many = np.repeat(mixed & (size > RUN_ROWS), size)
            if many.any():
                y = {c: v[many] for c, v in x.items()}
                yield rows(a=y["node"], b=y["node"], key=y["key"], label=y["label"], size=y["size"], rest=y["rest"])
            if len(out := ready.full()):
                yield rows(a=out[:, 0], b=out[:, 1])
        if len(out := ready.full(-1)):
            yield rows(a=out[:, 0], b=out[:, 1])

    return run


def _long_runs(similarity: float):
    """From rows (key, node, label, size, rest, parity), sorted by (key, size): pairs (a, b) that parities don't rule out, block by block."""

    def run(batches):
        ready = _Pairs()
        for x, cuts in _whole_runs(batches):
            for first, last in zip(cuts[:-1], cuts[1:]):
                y = {c: v[first:last] for c, v in x.items()}
                n = len(y["node"])
                for a in range(0, n, BLOCK_ROWS):
                    z = min(n, a + BLOCK_ROWS)
                    top = int(np.searchsorted(y["size"], y["size"][z - 1] / similarity + 1e-6, "right"))
                    for c in range(a, top, BLOCK_ROWS):
                        i, j = np.arange(a, z)[:, None], np.arange(c, min(top, c + BLOCK_ROWS))[None, :]
                        i, j = np.nonzero(_fits(y, i, j, similarity) & (i < j))
                        i, j = a + i, c + j
                        apart = np.bitwise_count((y["parity"][i] ^ y["parity"][j]).view(np.uint64)).sum(axis=1)
                        ok = apart <= (y["size"][i] + y["size"][j]) * ((1 - similarity) / (1 + similarity)) + 1e-6
                        ready.add(y["node"][i[ok]], y["node"][j[ok]])
                        if len(out := ready.full()):
                            yield pa.RecordBatch.from_arrays([pa.array(out[:, 0]), pa.array(out[:, 1])], ["a", "b"])
        if len(out := ready.full(-1)):
            yield pa.RecordBatch.from_arrays([pa.array(out[:, 0]), pa.array(out[:, 1])], ["a", "b"])

    return run


def prefix_pairs(nodes: DataFrame, labels: DataFrame, similarity: float) -> DataFrame:
    """(a, b): every pair of nodes with different labels (id, label) whose prefixes let them have the similarity.

    The rows of long runs fetch their parities and are compared in a second step, so that a large group whose members are all
    just below the similarity sends few of its pairs on.
    """
    own = nodes.select("node", "size", "prefix").join(labels.withColumnRenamed("id", "node"), "node", "left").withColumn("label", F.coalesce("label", "node"))
    rows = own.select("node", "label", "size", F.posexplode("prefix").alias("pos", "key")).select("key", "node", "label", "size", (F.col("size") - F.col("pos")).alias("rest"))
    found = cut(rows.repartition("key").sortWithinPartitions("key", "size").mapInArrow(_short_runs(similarity), "a long, b long, key long, label long, size long, rest long"))
    pairs = found.where("a <> b").select("a", "b")
    members = found.where("a = b").select("key", F.col("a").alias("node"), "label", "size", "rest")
    if not members.isEmpty():
        members = members.join(nodes.select("node", "parity"), "node").select("key", "node", "label", "size", "rest", "parity")
        pairs = pairs.unionByName(members.repartition("key").sortWithinPartitions("key", "size").mapInArrow(_long_runs(similarity), "a long, b long"))
    return pairs.distinct()


def verified(pairs: DataFrame, nodes: DataFrame, texts: DataFrame, shingle: int, similarity: float) -> DataFrame:
    """(a, b): the pairs whose sets of windows have the similarity, from (node, head, size, sketch, parity) and (node, doc_id, text).

    Parities that differ in more bits than the similarity allows windows of one text alone rule a pair out for certain (short texts
    mostly), sketches with the margin of `RULED_OUT` (long ones).
    """

    def differ(column, n):
        return sum((F.bit_count(F.col(f"{column}_a")[i].bitwiseXOR(F.col(f"{column}_b")[i])) for i in range(1, n)), F.bit_count(F.col(f"{column}_a")[0].bitwiseXOR(F.col(f"{column}_b")[0])))

    a, b = (nodes.select(F.col("node").alias(x), *(F.col(c).alias(f"{c}_{x}") for c in ("size", "sketch", "parity"))) for x in "ab")
    both = pairs.join(a, "a").join(b, "b")
    most = 64 * SKETCH * (np.arccos(2 * similarity / (1 + similarity)) / np.pi + RULED_OUT)
    apart = (F.col("size_a") + F.col("size_b")) * ((1 - similarity) / (1 + similarity)) + 1e-6
    near = cut(both.where((differ("parity", PARITY) <= apart) & (differ("sketch", SKETCH) <= F.lit(float(most)))).select("a", "b"))
    ends = near.select(F.col("a").alias("node")).union(near.select(F.col("b").alias("node"))).distinct()
    heads = cut(nodes.join(ends, "node", "left_semi").select("node", F.col("head.doc_id").alias("_fs_head")))
    # few ends go to all tasks, so that texts stay where they are
    heads = F.broadcast(heads) if heads.count() <= BROADCAST_ENDS else heads
    wanted = texts.join(heads, "node").where(F.col("doc_id").eqNullSafe(F.col("_fs_head"))).select("node", "text")
    sets = cut(window_sets(wanted, shingle).dropDuplicates(["node"]))
    exact = near.join(sets.select(F.col("node").alias("a"), F.col("hashes").alias("ha")), "a").join(sets.select(F.col("node").alias("b"), F.col("hashes").alias("hb")), "b")
    shared, total = F.size(F.array_intersect("ha", "hb")), F.size("ha") + F.size("hb")
    return cut(exact.where(shared >= (total - shared) * similarity).select("a", "b"))


def similar_pairs(nodes: DataFrame, prints: DataFrame, texts: DataFrame, shingle: int, similarity: float) -> DataFrame:
    """(a, b): pairs of the similarity that join exactly the nodes that all such pairs join.

    Nodes are linked by their fingerprints (node, fp) and to leaders first, which tie what two bits don't reach.  Then every node
    takes part in the search for all other pairs, which leaves out those alone that have one label by then.
    """
    found = verified(simhash_pairs(prints).unionByName(leader_pairs(nodes)).distinct(), nodes, texts, shingle, similarity)
    labels = cut(contract_components(found, "a", "b"))
    return found.unionByName(verified(prefix_pairs(nodes, labels, similarity), nodes, texts, shingle, similarity))


def near_dedup(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", shingle: int = 5, similarity: float = SIMILARITY) -> DataFrame:
    """One document of each group of near copies: the smallest id (nulls last), one of its copies; columns unchanged.

    Groups are joined by pairs whose `shingle`-word windows have a Jaccard similarity of `similarity` or more.  Fingerprints within
    two bits link first, verified by windows.  All such pairs share a window of their prefixes, by which those that fingerprints leave
    apart are candidates, verified likewise.  Copies of a text are one node from the start.
    """
    body = F.coalesce(F.col(text), F.lit(""))
    n1, n2 = F.xxhash64(body), F.xxhash64(F.lit(13), body)
    named = docs.withColumnRenamed(doc_id, "doc_id") if doc_id != "doc_id" else docs
    prints = cut(digests(named, text, [n1.alias("n1"), n2.alias("n2")], shingle, similarity, common_windows(docs, text, shingle)))
    row = F.struct(F.col("doc_id").isNull().alias("n"), "doc_id", "n1", "n2")
    # copies of a text share their node, so the map-side minimum leaves one row a text and task
    nodes = cut(prints.groupBy("n1", "n2").agg(F.min(row).alias("head"), *(F.first(c).alias(c) for c in ("size", "score", "prefix", "least", "sketch", "parity"))).withColumnRenamed("n1", "node"))
    texts = docs.select(n1.alias("node"), F.col(doc_id).cast("long").alias("doc_id"), body.alias("text"))
    own = fingerprints(docs.select(n1.alias("node"), body.alias("text")), "node").select(F.col("doc_id").alias("node"), "fp").distinct()
    labels = contract_components(similar_pairs(nodes, own, texts, shingle, similarity), "a", "b")
    heads = nodes.select("node", "head").join(labels.withColumnRenamed("id", "node"), "node", "left").groupBy(F.coalesce("label", "node").alias("label")).agg(F.min("head").alias("head"))
    heads = heads.select(F.col("head.doc_id").alias("_fs_id"), F.col("head.n1").alias("_fs_n1"), F.col("head.n2").alias("_fs_n2"))
    kept = docs.join(heads, F.col(doc_id).cast("long").eqNullSafe(F.col("_fs_id")) & (n1 == F.col("_fs_n1")) & (n2 == F.col("_fs_n2")), "left_semi")
    if prints.groupBy("doc_id", "n1", "n2").count().where("count > 1").isEmpty():
        return kept
    return kept.withColumn("_fs_body", n1).dropDuplicates([doc_id, "_fs_body"]).drop("_fs_body")


def op6(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return near_components(fingerprints(docs)).select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
