"""Language identification by string kernels.

The kernel of two strings is the cosine of their blended spectra: presence of byte n-grams of 1 to `MAX_N`, hashed to `WIDTH`
places.  Landmarks are pieces of training texts, the same number for each language; ridge regression on the kernels with
them (Nystroem), one language against the rest, is solved from sums that tasks make.  A text is scored in pieces, all of
them, by products of presence matrices with the landmarks' combined weights, and its scores are the means by length.

The fit uses `FIT_ROWS` training texts at most in expectation, as many of each language; scoring covers every text.  Null
texts and texts without a letter are `und` with score 0, as is everything where there is no training row.  A language is a
column of the model, so more than `MOST_LANGUAGES` distinct values of `lang` are an error and not a larger model.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fieldseg.llm.linear_fit import summed_products
from fieldseg.llm.textkernel import LOWER, blocks, mix

MAX_N = 4
WIDTH = 1 << 14
PIECE = 2000
LANDMARKS = 160
FIT_ROWS = 6000
MOST_LANGUAGES = 500
RIDGE = 1e-3
_LETTER = np.zeros(256, bool)
_LETTER[65:91] = _LETTER[97:123] = True
UNKNOWN = "und"


def pieces(b, size: int = PIECE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts, ends and documents of equal pieces of each text of a block, `size` bytes at most."""
    length = np.diff(b.off)
    n = -(-length // size)
    docs = np.repeat(np.arange(b.n), n)
    k = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
    each = -(-length // np.maximum(n, 1))
    starts = b.off[docs] + k * each[docs]
    return starts, np.minimum(starts + each[docs], b.off[docs + 1]), docs


def presence(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Pieces x WIDTH: the normalised presence of hashed n-grams."""
    out = np.zeros((len(starts), WIDTH), np.float32)
    if len(starts):
        base, stop = int(starts[0]), int(ends[-1])
        part = LOWER[data[base:stop]].astype(np.uint64)
        own = np.repeat(np.arange(len(starts)), ends - starts)  # pieces that follow each other without a gap
        code = np.zeros(len(part), np.uint64)
        for n in range(1, MAX_N + 1):
            m = len(part) - n + 1
            if m <= 0:
                break
            code = (code[:m] << np.uint64(8)) | part[n - 1 :]
            place = (mix(code + np.uint64(n << 40)) >> np.uint64(50)).astype(np.int64)
            same = own[:m] == own[n - 1 :]
            out[own[:m][same], place[same]] = 1
        out /= np.sqrt(np.maximum(out.sum(axis=1, keepdims=True), 1))
    return out


def chunks(starts: np.ndarray, size: int = 512):
    for a in range(0, len(starts), size):
        yield slice(a, min(len(starts), a + size))


class Model:
    def __init__(self, languages: list[str], weights: np.ndarray):
        self.languages, self.weights = languages, weights.astype(np.float32)

    def predict(self, b) -> tuple[np.ndarray, np.ndarray]:
        """Index of the language (-1: none) and score of each text of a block."""
        s, e, d = pieces(b)
        total = np.zeros((b.n, len(self.languages)))
        for c in chunks(s):
            # one text's pieces and the next's are neighbours, so a chunk is one stretch of bytes
            got = presence(b.buf, s[c], e[c]) @ self.weights
            np.add.at(total, d[c], got * (e[c] - s[c])[:, None])
        mean = total / np.maximum(np.diff(b.off), 1)[:, None]
        best = mean.argmax(axis=1) if len(self.languages) else np.full(b.n, -1)
        score = np.clip((mean.max(axis=1) + 1) / 2, 0, 1) if len(self.languages) else np.zeros(b.n)
        letters = np.bincount(b.docs_of(np.flatnonzero(_LETTER[b.buf])), minlength=b.n) > 0
        for i in np.flatnonzero(~letters):
            letters[i] = any(x.isalpha() for x in b.text(i).decode("utf-8", "replace"))
        return np.where(letters, best, -1), np.where(letters, score, 0.0)


def fit(rows: DataFrame, seed: int = 5) -> Model:
    """The model from (doc_id, text, lang) training rows; rows without a language are ignored."""
    rows = rows.where("lang is not null and text is not null and text <> ''")
    counts = {r.lang: r["count"] for r in rows.groupBy("lang").count().limit(MOST_LANGUAGES + 1).collect()}
    if len(counts) > MOST_LANGUAGES:
        raise ValueError(f"more than {MOST_LANGUAGES} languages")
    languages = sorted(counts)
    if not languages:
        return Model([], np.zeros((WIDTH, 0)))
    dice = (F.pmod(F.xxhash64(F.lit(seed), "doc_id", "text"), F.lit(1 << 30)) / float(1 << 30)).alias("dice")

    def share(want: float) -> Column:
        pairs = [F.lit(x) for k in languages for x in (k, min(1.0, want / len(languages) / counts[k]))]
        return F.create_map(*pairs)[F.col("lang")]

    def one_piece(batches):
        for rb in batches:
            got = []
            for b in blocks(rb.column(1)):
                s, e, d = pieces(b)
                first = np.searchsorted(d, np.arange(b.n))
                pick = first + (np.searchsorted(d, np.arange(b.n), "right") - first) // 2
                got += [b.buf[s[p] : e[p]].tobytes() for p in pick]
            yield pa.RecordBatch.from_arrays([rb.column(0), pa.array(got, pa.binary()), rb.column(2)], ["lang", "piece", "dice"])

    drawn = rows.select("lang", "text", dice).where(F.col("dice") < share(2.0 * LANDMARKS)).mapInArrow(one_piece, "lang string, piece binary, dice double")
    marks: list[bytes] = []
    by_lang: dict[str, list] = {k: [] for k in languages}
    for r in drawn.collect():
        by_lang[r.lang].append((r.dice, bytes(r.piece)))
    for k in languages:
        marks += [p for _, p in sorted(by_lang[k])[: max(1, LANDMARKS // len(languages))]]
    if not marks:
        return Model([], np.zeros((WIDTH, 0)))
    flat, off = np.frombuffer(b"".join(marks), np.uint8), np.cumsum([0, *map(len, marks)])
    land = presence(flat, off[:-1], off[1:]).astype(np.float64)
    m, place = len(land), {k: i for i, k in enumerate(languages)}
    cross = land.T.astype(np.float32)

    def kernels(rb):
        langs = rb.column(0).to_pylist()
        for b in blocks(rb.column(1)):
            s, e, d = pieces(b)
            for c in chunks(s):
                y = -np.ones((len(s[c]), len(languages)))
                y[np.arange(len(y)), [place[langs[b.first + i]] for i in d[c]]] = 1
                # each text weighs one, however many its pieces
                w = 1 / np.sqrt(np.bincount(d, minlength=b.n)[d[c]])[:, None]
                yield np.concatenate([presence(b.buf, s[c], e[c]) @ cross, y], axis=1) * w

    sample = rows.select("lang", "text", dice).where(F.col("dice") < share(float(FIT_ROWS))).select("lang", "text")
    a = summed_products(sample, m + len(languages), kernels)
    left = a[:m, :m] + RIDGE * (land @ land.T) * max(1.0, np.trace(a[:m, :m])) / m + 1e-8 * np.eye(m)
    alpha = np.linalg.lstsq(left, a[:m, m:], rcond=None)[0]
    return Model(languages, land.T @ alpha)


def identify(docs: DataFrame, model: Model, keep: list[str], text: str = "text") -> DataFrame:
    """The kept columns with `lang_pred` and `score`; one row for each document."""
    from pyspark.sql import types as T

    keep = [c for c in keep if c not in ("lang_pred", "score")]  # columns of the new names give way

    def run(batches):
        names = np.array([*model.languages, UNKNOWN], object)
        for rb in batches:
            best, score = [np.zeros(0, np.int64)], [np.zeros(0)]
            for b in blocks(rb.column(len(keep))):
                x, y = model.predict(b)
                best.append(x)
                score.append(y)
            yield pa.RecordBatch.from_arrays([*rb.columns[: len(keep)], pa.array(names[np.concatenate(best)].tolist(), pa.string()), pa.array(np.concatenate(score).astype(float))], [*keep, "lang_pred", "score"])

    schema = T.StructType([*docs.select(*keep).schema.fields, T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])
    return docs.select(*keep, F.col(text).alias("_fs_text")).mapInArrow(run, schema)


def held_out(doc_id: Column, parts: int = 3, out: int = 1) -> Column:
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(parts)) == out, F.lit(False))


def op4(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = fit(docs.select("doc_id", "text", "lang").where(~held_out(F.col("doc_id"))))
    found = identify(docs, model, ["doc_id"])
    return found.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
