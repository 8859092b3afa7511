"""Corpus pipeline: quality, line dedup, near dedup, decontamination and packing, each stage over all its predecessor kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fieldseg.llm import decontaminate, line_dedup, packing, quality_classifier, simhash
from fieldseg.runtime import Scratch, ship


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop the documents that the quality classifier rejects; labels of the held-out remainder aren't learnt from."""
    ship(spark)
    return quality_classifier.keep_good(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop repeated long lines; texts that lose none, null ones too, stay as they are.  `n_chars` follows the text."""
    ship(spark)
    hidden = docs.withColumnsRenamed({c: f"_fs_own_{c}" for c in ("n_lines", "n_dropped")})
    out = line_dedup.dedup_lines(hidden, kept="_fs_kept_text")
    lost = F.col("n_dropped") > 0
    out = out.withColumns({"text": F.when(lost, F.col("_fs_kept_text")).otherwise(F.col("text")), "n_chars": F.when(lost, F.char_length("_fs_kept_text").cast("long")).otherwise(F.col("n_chars"))})
    return out.drop("n_lines", "n_dropped").withColumnsRenamed({f"_fs_own_{c}": c for c in ("n_lines", "n_dropped")}).select(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep one document of each group of near duplicates: SimHash links by Golay keys, checked by windows, then an exact search for what they leave apart."""
    ship(spark)
    return simhash.near_dedup(docs)


def benchmark_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop the documents that hold a window of a benchmark item."""
    ship(spark)
    return decontaminate.remove_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def windows(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pack what is left into token windows."""
    ship(spark)
    import public_tokenizers

    return packing.pack(packing.token_pieces(docs, public_tokenizers.path("word_bpe_49k.json")))


STAGES = [("quality", quality), ("line_dedup", lines), ("near_dedup", near_duplicates), ("decontamination", benchmark_passages), ("packing", windows)]

#: The classifier's scores can't be had from SQL; tests hold the pipeline against plain versions of its stages.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage; each stage but the last is written and read again, and removed once the next is written."""
    docs, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    for name, stage in STAGES[:-1]:
        written = Scratch(stage(spark, docs, sf_dir), f"pipeline-{name}")
        if before is not None:
            before.drop()
        docs, before = written.table, written
    packed = STAGES[-1][1](spark, docs, sf_dir)
    before.drop()  # the lengths that are packed have been cut off by a checkpoint
    return packed
