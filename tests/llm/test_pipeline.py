import brute
import corpus_pipeline
import pandas as pd

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def test_stages_on_odd_rows(spark, odd, tmp_path):
    """Every stage keeps the columns of its documents and survives every odd row."""
    docs = spark.read.parquet(f"{odd}/documents.parquet")
    kinds = docs.dtypes
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, odd)
        if name != "packing":
            assert out.dtypes == kinds, name
        out.write.parquet(str(tmp_path / str(i)))
        docs = spark.read.parquet(str(tmp_path / str(i)))
    assert docs.count() > 0


def test_stages_on_empty_tables(spark, empty):
    assert corpus_pipeline.run(spark, empty).count() == 0


def test_line_stage(spark, odd, odd_rows):
    docs = spark.read.parquet(f"{odd}/documents.parquet")
    got = corpus_pipeline.lines(spark, docs, odd).collect()
    want = [(i, (t if d == 0 else k)) for (i, t), (_, _, d, k) in zip(odd_rows, brute.line_dedup(odd_rows))]
    assert sorted(str((r.doc_id, r.text)) for r in got) == sorted(map(str, want))
    assert all(r.n_chars == len(r.text) for r in got if r.text is not None and r.doc_id is not None)


def test_rejected_documents_go(spark, sf):
    kept = corpus_pipeline.quality(spark, spark.read.parquet(f"{sf}/documents.parquet"), sf).toPandas()
    labels = pd.read_parquet(f"{sf}/labels.parquet")
    good, bad = labels[labels["quality"] == 1], labels[labels["quality"] == 0]
    assert good["doc_id"].isin(kept["doc_id"]).mean() > 0.95 and bad["doc_id"].isin(kept["doc_id"]).mean() < 0.3


def test_contaminated_documents_go(spark, sf):
    docs, items = (pd.read_parquet(f"{sf}/{t}.parquet") for t in ("documents", "benchmark"))
    want = {r[0] for r in brute.decontaminate(list(zip(docs["doc_id"], docs["text"])), list(zip(items["item_id"], items["text"]))) if not r[5]}
    got = corpus_pipeline.benchmark_passages(spark, spark.read.parquet(f"{sf}/documents.parquet"), sf)
    assert {r.doc_id for r in got.collect()} == want


def test_run(spark, sf):
    out = corpus_pipeline.run(spark, sf).toPandas()
    assert len(out) and out.groupby("sequence_id")["length"].sum().max() <= 4096


def test_near_copies_go(spark, odd, odd_rows):
    docs = spark.read.parquet(f"{odd}/documents.parquet")
    got = corpus_pipeline.near_duplicates(spark, docs, odd).collect()
    want = brute.near_survivors(odd_rows)
    assert sorted(str(r.doc_id) for r in got) == sorted(str(i) for i, _ in want)


def test_near_copies_of_prose(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = {r.doc_id for r in corpus_pipeline.near_duplicates(spark, docs, sf).collect()}
    d = docs.toPandas()
    want = {i for i, _ in brute.near_survivors(list(zip(d["doc_id"].tolist(), d["text"])))}
    assert len(kept ^ want) <= 2
