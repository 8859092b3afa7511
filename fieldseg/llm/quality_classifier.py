"""Quality classifier: random Fourier features of document statistics, ridge regression, isotonic calibration.

The statistics of a text come from its bytes, words and lines.  They are standardised on the training rows, and `FEATURES`
random Fourier features approximate a Gaussian kernel on them.  Tasks sum the normal equations, the driver solves them, and
the rows held back from the fit calibrate the scores: they are counted in `BINS` bins, whose rates are made monotone by
pooling adjacent violators.

Null and empty texts have the statistics of no words and are scored too.  A document with several labels counts as 1 if their
mean is 0.5 or more; null labels and labels of unknown documents are ignored.  Without usable labels every score is 0.5.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from fieldseg.llm.linear_fit import summed_products
from fieldseg.llm.quality_rules import count_block
from fieldseg.llm.textkernel import NOT_SPACE, blocks, per_doc
from fieldseg.runtime import cut

FEATURES = 256
BANDWIDTH = 3.0
RIDGE = 1e-3
BINS = 1000
SEED = 11
THRESHOLD = 0.7
STATISTICS = (
    "log_words", "word_length", "symbols", "dup_lines", "repeats", "distinct", "upper", "digits", "marks", "beyond_ascii", "lines", "pipes", "commonest", "one_letter",
)
_table = lambda members: np.isin(np.arange(256), list(members))
_UPPER, _DIGIT = _table(range(65, 91)), _table(range(48, 58))
_MARK = _table(b"!\"'(),-./:;?[]`{}~_=+\\@^")
_PIPE, _HIGH = _table(b"|"), _table(range(192, 256))


def statistics(b) -> np.ndarray:
    """Documents x statistics of a block."""
    base = count_block(b)
    n = np.maximum(base["n_words"], 1).astype(float)
    size = np.maximum(np.diff(b.off), 1).astype(float)
    s, e, d = b.words(NOT_SPACE)
    h = b.hashes(b.prefix(b.buf), s, e)
    order = np.lexsort((h, d))
    new = np.concatenate([[True], (h[order][1:] != h[order][:-1]) | (d[order][1:] != d[order][:-1])]) if len(h) else np.zeros(0, bool)
    first = np.flatnonzero(new)
    runs, own = np.diff(np.concatenate([first, [len(h)]])), d[order][first]
    commonest = np.zeros(b.n)
    np.maximum.at(commonest, own, runs)
    share = lambda t: per_doc(b.docs_of(np.flatnonzero(t[b.buf])), b.n)
    one = per_doc(d[e - s == 1], b.n)
    lines = share(_table(b"\n"))
    cols = (
        np.log1p(base["n_words"]), np.log1p(base["word_chars"] / n), np.log1p(10 * base["n_symbols"] / n), base["n_dup_lines"] / (lines + 1.0), base["n_repeat_words"] / n,
        per_doc(own, b.n) / np.sqrt(n), share(_UPPER) / size * 10, share(_DIGIT) / size * 10, share(_MARK) / size * 10, share(_HIGH) / size, np.log1p(lines) / np.log1p(n + 1), share(_PIPE) / n, commonest / n, one / n,
    )
    return np.stack([np.asarray(c, float) for c in cols], axis=1)


def document_statistics(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, stats array<double>) of every row."""

    def run(batches):
        for rb in batches:
            found = [np.zeros((0, len(STATISTICS)))]
            found += [statistics(b) for b in blocks(rb.column(1))]
            m = np.concatenate(found)
            yield pa.RecordBatch.from_arrays([rb.column(0), _lists(m)], ["doc_id", "stats"])

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, "doc_id long, stats array<double>")


def _lists(m: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(m) + 1, dtype=np.int32) * m.shape[1], pa.int32()), pa.array(m.ravel()))


def _matrix(column: pa.Array) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, len(STATISTICS)))


class Model:
    """Standardisation, Fourier features, weights and the calibration curve."""

    def __init__(self, mean, std, features: int = FEATURES, seed: int = SEED):
        rng = np.random.default_rng(seed)
        self.mean, self.std = np.asarray(mean, float), np.maximum(np.asarray(std, float), 1e-9)
        self.w = rng.normal(size=(len(self.mean), features)) / BANDWIDTH
        self.b = rng.uniform(0, 2 * np.pi, features)
        self.weights, self.curve = np.zeros(features + 1), (np.array([0.0, 1.0]), np.array([0.5, 0.5]))

    def phi(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.mean) / self.std, -8, 8)
        f = np.sqrt(2 / self.w.shape[1]) * np.cos(z @ self.w + self.b)
        return np.concatenate([f, np.ones((len(x), 1))], axis=1)

    def raw(self, x: np.ndarray) -> np.ndarray:
        return np.clip(self.phi(x) @ self.weights, 0, 1)

    def score(self, x: np.ndarray) -> np.ndarray:
        return np.interp(self.raw(x), *self.curve)


def pool_adjacent_violators(value: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """The non-decreasing sequence nearest to `value` in weighted squares."""
    stack: list[list[float]] = []
    for v, w in zip(value.tolist(), weight.tolist()):
        stack.append([v, w, 1])
        while len(stack) > 1 and stack[-2][0] >= stack[-1][0]:
            v2, w2, n2 = stack.pop()
            v1, w1, n1 = stack.pop()
            stack.append([(v1 * w1 + v2 * w2) / (w1 + w2), w1 + w2, n1 + n2])
    return np.concatenate([[v] * n for v, _, n in stack]) if stack else np.zeros(0)


def fold(doc_id: Column, parts: int) -> Column:
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(parts))


def fit(stats: DataFrame, labels: DataFrame) -> Model | None:
    """The model for (doc_id, stats) and (doc_id, quality); None without two usable rows."""
    y = labels.where("doc_id is not null and quality is not null").groupBy("doc_id").agg((F.avg("quality") >= 0.5).cast("double").alias("y"))
    rows = cut(stats.join(y, "doc_id").withColumn("hold", F.pmod(F.xxhash64(F.lit(3), "doc_id"), F.lit(4)) == 0))
    k = len(STATISTICS)
    one = rows.agg(F.count("*").alias("n"), *(f(F.col("stats")[i]).alias(f"{n}{i}") for i in range(k) for n, f in (("m", F.avg), ("s", F.stddev_pop)))).first()
    if one.n < 2:
        return None
    model = Model([one[f"m{i}"] for i in range(k)], [one[f"s{i}"] for i in range(k)])

    def products(rb):
        yield np.concatenate([model.phi(_matrix(rb.column(0))), rb.column(1).to_numpy(zero_copy_only=False)[:, None]], axis=1)

    a = summed_products(rows.where("not hold").select("stats", "y"), FEATURES + 2, products)
    n, c = a[-2, -2], a[:-1, :-1]
    model.weights = np.linalg.solve(c + RIDGE * max(n, 1.0) * np.eye(len(c)) / len(c), a[:-1, -1])

    def scores(batches):
        for rb in batches:
            yield pa.RecordBatch.from_arrays([pa.array(model.raw(_matrix(rb.column(0)))), rb.column(1)], ["s", "y"])

    raw = rows.where("hold").select("stats", "y").mapInArrow(scores, "s double, y double")
    bins = raw.groupBy(F.least(F.floor(F.col("s") * BINS), F.lit(BINS - 1)).alias("bin")).agg(F.avg("s").alias("s"), F.sum("y").alias("y"), F.count("*").alias("n")).collect()
    if bins:
        bins.sort(key=lambda r: r.bin)
        x, w = np.array([r.s for r in bins]), np.array([r.n for r in bins], float)
        rate = pool_adjacent_violators(np.array([r.y for r in bins]) / w, w)
        model.curve = (np.concatenate([[0.0], x, [1.0]]), np.concatenate([rate[:1], rate, rate[-1:]]))
    else:
        model.curve = (np.array([0.0, 1.0]), np.array([0.0, 1.0]))
    return model


def with_scores(df: DataFrame, model: Model | None, stats: str = "stats", name: str = "score") -> DataFrame:
    """`df` with the score of its statistics, in place of them."""
    keep = [c for c in df.columns if c != stats]

    def run(batches):
        for rb in batches:
            yield pa.RecordBatch.from_arrays([*rb.columns[:-1], pa.array(model.score(_matrix(rb.columns[-1])))], [*keep, name])

    if model is None:
        return df.drop(stats).withColumn(name, F.lit(0.5))
    schema = T.StructType([*(df.schema[c] for c in keep), T.StructField(name, T.DoubleType())])
    return df.select(*keep, stats).mapInArrow(run, schema)


def score_documents(docs: DataFrame, labels: DataFrame, train: Column | None = None) -> DataFrame:
    """(doc_id, score) of every row; `train` (over doc_id) says which labels may be learnt from."""
    stats = cut(document_statistics(docs))
    usable = labels.select(F.col("doc_id").cast("long").alias("doc_id"), "quality")
    return with_scores(stats, fit(stats, usable if train is None else usable.where(train)))


def training(parts: int = 4, out: int = 2) -> Column:
    return fold(F.col("doc_id"), parts) != out


def keep_good(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """The documents that score `threshold` or more, with their columns; scored as they are read, without a join."""
    model = fit(cut(document_statistics(docs)), labels.select(F.col("doc_id").cast("long").alias("doc_id"), "quality").where(training()))
    if model is None:
        return docs
    at = docs.columns.index("text")

    def run(batches):
        for rb in batches:
            keep = [np.zeros(0, bool)] + [model.score(statistics(b)) >= threshold for b in blocks(rb.column(at))]
            yield rb.filter(pa.array(np.concatenate(keep)))

    return docs.mapInArrow(run, docs.schema)


def op1(spark, sf_dir: str) -> DataFrame:
    docs, labels = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet")
    scored = score_documents(docs, labels, training())
    held = F.coalesce(fold(F.col("doc_id"), 4) == 2, F.lit(False))
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
