"""Classifiers and packing held against plain versions, one document after another."""

import math
import zlib
from collections import Counter

import numpy as np
import pandas as pd
import public_tokenizers
import pytest
from brute import SPACED, base_counts
from tokenizers import Tokenizer

from fieldseg.llm import language_id, packing, quality_classifier


def whole(sf, name="documents"):
    return pd.read_parquet(f"{sf}/{name}.parquet")


def plain_statistics(text):
    t, b = text or "", (text or "").encode()
    w, lines = SPACED.findall(t), t.count("\n")
    _, n_words, chars, symbols, dup, repeat, _ = base_counts([(0, t)])[0]
    n, size = max(1, n_words), max(1, len(b))
    count = Counter(w)
    marks = set(b"!\"'(),-./:;?[]`{}~_=+\\@^")
    return [
        math.log1p(n_words), math.log1p(chars / n), math.log1p(10 * symbols / n), dup / (lines + 1), repeat / n, len(count) / math.sqrt(n), sum(65 <= x < 91 for x in b) / size * 10,
        sum(48 <= x < 58 for x in b) / size * 10, sum(x in marks for x in b) / size * 10, sum(x >= 192 for x in b) / size, math.log1p(lines) / math.log1p(n + 1), b.count(b"|") / n,
        max(count.values(), default=0) / n, sum(len(x.encode()) == 1 for x in w) / n,
    ]


def test_statistics(spark, odd, odd_rows, sf):
    """Every statistic of every text, odd ones too."""
    for d, rows in ((odd, odd_rows), (sf, list(zip(whole(sf)["doc_id"], whole(sf)["text"])))):
        got = [(r.doc_id, r.stats) for r in quality_classifier.document_statistics(spark.read.parquet(f"{d}/documents.parquet")).collect()]
        assert [i for i, _ in got] == [i for i, _ in rows]
        assert np.allclose([s for _, s in got], [plain_statistics(t) for _, t in rows], rtol=1e-9, atol=1e-12)


def test_scores(spark, sf):
    """The ridge fit on the Fourier features and the isotonic curve, solved directly, give the scores."""
    docs, labels = whole(sf), whole(sf, "labels")
    crc = lambda i: zlib.crc32(str(i).encode())
    x = np.array([plain_statistics(t) for t in docs["text"]])
    mean = labels.groupby("doc_id")["quality"].mean()
    use = np.array([i in mean.index and crc(i) % 4 != 2 for i in docs["doc_id"]])
    y = np.array([float(mean.get(i, 0) >= 0.5) for i in docs["doc_id"]])
    hold = {r.doc_id for r in spark.createDataFrame([(int(i),) for i in docs["doc_id"]], "doc_id long").where("pmod(xxhash64(3, doc_id), 4) = 0").collect()}
    hold = np.array([i in hold for i in docs["doc_id"]])
    model = quality_classifier.Model(x[use].mean(axis=0), x[use].std(axis=0))
    z = np.clip((x - model.mean) / model.std, -8, 8)
    phi = np.concatenate([np.sqrt(2 / 256) * np.cos(z @ model.w + model.b), np.ones((len(x), 1))], axis=1)
    a, n = phi[use & ~hold], (use & ~hold).sum()
    weights = np.linalg.solve(a.T @ a + quality_classifier.RIDGE * n * np.eye(257) / 257, a.T @ y[use & ~hold])
    raw = np.clip(phi @ weights, 0, 1)
    cell = np.minimum(np.floor(raw * quality_classifier.BINS), quality_classifier.BINS - 1)
    at = [use & hold & (cell == c) for c in np.unique(cell[use & hold])]
    rate, w = np.array([y[m].mean() for m in at]), np.array([m.sum() for m in at])
    # the least-squares monotone sequence by its min-max formula
    best = [max(min(np.average(rate[i : j + 1], weights=w[i : j + 1]) for j in range(k, len(at))) for i in range(k + 1)) for k in range(len(at))]
    curve = (np.array([0.0, *(raw[m].mean() for m in at), 1.0]), np.array([best[0], *best, best[-1]]))
    want = np.interp(raw, *curve)
    got = quality_classifier.op1(spark, sf).toPandas().set_index("doc_id").loc[docs["doc_id"]]
    near = np.abs(got["score"].to_numpy() - want)
    assert near.max() < 1e-5
    assert ((got["score"] >= 0.7) == (got["predicted"] == 1)).all()


def plain_language(model, text):
    data = (text or "").encode()
    if not any(c.isalpha() for c in text or ""):
        return "und", 0.0
    n = -(-len(data) // language_id.PIECE)
    each = -(-len(data) // n)
    total = np.zeros(len(model.languages))
    for k in range(n):
        part = bytes(x + 32 if 65 <= x < 91 else x for x in data[k * each : (k + 1) * each])
        seen = set()
        for m in range(1, language_id.MAX_N + 1):
            for i in range(len(part) - m + 1):
                h = (int.from_bytes(part[i : i + m], "big") + (m << 40)) & (1 << 64) - 1
                h ^= h >> 30
                h = h * 0xBF58476D1CE4E5B9 & (1 << 64) - 1
                h ^= h >> 27
                h = h * 0x94D049BB133111EB & (1 << 64) - 1
                seen.add((h ^ h >> 31) >> 50)
        total += len(part) * model.weights[sorted(seen)].astype(float).sum(axis=0) / math.sqrt(max(1, len(seen)))
    mean = total / len(data)
    return model.languages[int(mean.argmax())], float(np.clip((mean.max() + 1) / 2, 0, 1))


def test_languages(spark, sf, odd, odd_rows):
    """Every prediction and score by sets of n-grams, one after another."""
    for d, rows in ((odd, odd_rows), (sf, list(zip(whole(sf)["doc_id"], whole(sf)["text"]))[:120])):
        docs = spark.read.parquet(f"{d}/documents.parquet")
        model = language_id.fit(docs.select("doc_id", "text", "lang").where(~language_id.held_out(docs.doc_id)))
        got = [(r.lang_pred, r.score) for r in language_id.identify(docs, model, ["doc_id"]).collect()]
        for (name, score), (i, t) in zip(got, rows):
            want = plain_language(model, t)
            assert name == want[0] and abs(score - want[1]) < 1e-3, i


def test_too_many_languages(spark, monkeypatch):
    monkeypatch.setattr(language_id, "MOST_LANGUAGES", 3)
    df = spark.createDataFrame([(i, f"some words {i}", f"l{i % 4}") for i in range(40)], "doc_id long, text string, lang string")
    with pytest.raises(ValueError):
        language_id.fit(df)
    monkeypatch.setattr(language_id, "MOST_LANGUAGES", 4)
    assert language_id.fit(df).languages == ["l0", "l1", "l2", "l3"]


def test_every_piece_of_every_document(spark, sf, odd, odd_rows):
    """Ids, cuts, checksums and places of all pieces against the tokenizer itself."""
    tok = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    for d, rows in ((odd, odd_rows), (sf, list(zip(whole(sf)["doc_id"], whole(sf)["text"])))):
        got = packing.op10(spark, d).toPandas()
        want = Counter()
        for i, t in rows:
            ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 2], "<u4")
            for s in range(0, len(ids), 4096):
                part = ids[s : s + 4096]
                want[(i, s, len(part), zlib.crc32(part.tobytes()), len(ids))] += 1
        ids = got["doc_id"].astype(object).where(got["doc_id"].notna(), None)
        assert Counter(zip(ids, got["start"], got["length"], got["ids_crc32"], got["doc_tokens"])) == want
        for _, g in got.groupby("sequence_id"):
            g = g.sort_values("offset")
            assert (g["offset"] == g["length"].cumsum() - g["length"]).all() and g["length"].sum() <= 4096
        if d == sf:
            padded = sum(4096 if n & (n - 1) else n for n in got.groupby("sequence_id")["length"].sum())
            assert got["length"].sum() > 0.95 * padded
