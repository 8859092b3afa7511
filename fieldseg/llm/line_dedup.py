"""Line dedup with levelled sorted runs of line hashes.

A run is a table bucketed and sorted by the 128-bit hash of a line key, with the number of documents that hold the line and the
largest (and smallest) of their ids.  Each batch of documents is merge-anti-joined with the runs: lines that no run holds are
`fresh` rows of the new run, so each line is fresh in one run alone; lines that are known add their counts beside.  `fan` runs
of a level are compacted into one of the next level, counts added, so a hash is rewritten once a level.  Runs share their
buckets, so the anti-join does not shuffle them.  A line's key is the line without white space at its ends, A-Z lower-cased.

Null and empty texts are one empty line.  A null document id counts as one document smaller than all others.  Repeated rows
of a document hold its lines once and keep or lose them alike.  Extra columns pass through.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fieldseg.runtime import Scratch, cut, shared_dir, shuffle_width

MIN_CHARS = 40
MIN_DOCS = 5
SPACES = " \t\n\x0b\x0c\r"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
NO_ID = -(1 << 63)
#: A line in more than this share of all entries is hot; so many lines at most can be.
HOT_LINES = 10_000
RUN_FIELDS = "h1 long, h2 long, n_docs long, max_id long, min_id long, fresh boolean"


def line_key(line: Column) -> Column:
    return F.translate(F.btrim(line, F.lit(SPACES)), UPPER, LOWER)


def line_hash(key: Column) -> Column:
    """Two chained 64-bit hashes with different seeds."""
    return F.struct(F.xxhash64(key).alias("h1"), F.xxhash64(F.lit(20_011), key).alias("h2"))


def lines_of(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def line_entries(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", min_chars: int = MIN_CHARS) -> DataFrame:
    """(id, h1, h2): the distinct long lines of each row."""
    keys = F.array_distinct(F.transform(F.filter(lines_of(F.col(text)), lambda x: F.length(x) >= min_chars), line_key))
    long = F.filter(keys, lambda k: F.char_length(k) >= min_chars)
    return docs.select(F.coalesce(F.col(doc_id).cast("long"), F.lit(NO_ID)).alias("id"), F.explode(F.transform(long, line_hash)).alias("h")).select("id", "h.h1", "h.h2")


class LineRuns:
    """The levelled store; runs live in the shared folder, as bucketed tables whose names `self.levels` holds."""

    def __init__(self, spark: SparkSession, path: str | None = None, fan: int = 4, buckets: int | None = None):
        self.spark, self.fan, self.n = spark, fan, 0
        self.name = f"line_runs_{uuid.uuid4().hex}"
        self.path = path or f"{shared_dir(spark)}/{self.name}"
        self.buckets = buckets or shuffle_width(spark)
        self.levels: list[list[str]] = [[]]

    def _write(self, run: DataFrame, level: int) -> str:
        name = f"{self.name}_{self.n}"
        self.n += 1
        out = run.write.bucketBy(self.buckets, "h1", "h2").sortBy("h1", "h2").option("compression", "zstd")
        out.option("path", f"{self.path}/{name}").saveAsTable(name)
        return name

    @staticmethod
    def _merge(runs: DataFrame) -> DataFrame:
        return runs.groupBy("h1", "h2").agg(F.sum("n_docs").alias("n_docs"), F.max("max_id").alias("max_id"), F.min("min_id").alias("min_id"), F.bool_or("fresh").alias("fresh"))

    def _files(self, names: list[str]) -> DataFrame:
        # not a union of the tables: Spark 4.1 takes that for bucketed even where it reads the files without their buckets
        return self.spark.read.schema(RUN_FIELDS).parquet(*(f"{self.path}/{name}" for name in names))

    def _all(self) -> list[DataFrame]:
        return [self.spark.table(name) for level in self.levels for name in level]

    def _marked(self, rows: DataFrame) -> DataFrame:
        """`rows` (h1, h2, ...) with `fresh`: no run holds the line."""
        rows = rows.withColumn("fresh", F.lit(True))
        for run in self._all():
            held = run.where("fresh").select("h1", "h2", F.lit(True).alias("_held"))
            rows = rows.join(held.hint("merge"), ["h1", "h2"], "left").withColumn("fresh", F.col("fresh") & F.col("_held").isNull()).drop("_held")
        return rows

    def add(self, entries: DataFrame) -> None:
        """Add a batch of (id, h1, h2) whose documents are in no earlier batch."""
        one = entries.groupBy("h1", "h2", "id").agg(F.lit(1).alias("one"))
        lines = one.groupBy("h1", "h2").agg(F.count("*").alias("n_docs"), F.max("id").alias("max_id"), F.min("id").alias("min_id"))
        self.levels[0].append(self._write(self._marked(lines), 0))
        level = 0
        while len(self.levels[level]) >= self.fan:
            old, self.levels[level] = self.levels[level], []
            if level + 1 == len(self.levels):
                self.levels.append([])
            self.levels[level + 1].append(self._write(self._merge(self._files(old)), level + 1))
            self._drop(old)
            level += 1

    def new_lines(self, entries: DataFrame) -> DataFrame:
        """The entries whose line is in no run yet."""
        return self._marked(entries).where("fresh").drop("fresh")

    def counts(self) -> DataFrame | None:
        """(h1, h2, n_docs, max_id, min_id) of every line: its fresh row, and what later batches added to it."""
        names = [name for level in self.levels for name in level]
        if not names:
            return None
        # after a compaction of all, every line has its one row
        return (self.spark.table(names[0]) if len(names) == 1 else self._merge(self._files(names))).drop("fresh")

    def _drop(self, names: list[str]) -> None:
        sc = self.spark.sparkContext
        for name in names:
            self.spark.sql(f"drop table if exists {name}")
            at = sc._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")
            at.getFileSystem(sc._jsc.hadoopConfiguration()).delete(at, True)

    def close(self) -> None:
        self._drop([name for level in self.levels for name in level])
        sc = self.spark.sparkContext
        at = sc._jvm.org.apache.hadoop.fs.Path(self.path)
        at.getFileSystem(sc._jsc.hadoopConfiguration()).delete(at, True)


def dropped_lines(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", min_chars: int = MIN_CHARS, min_docs: int = MIN_DOCS, batches: int = 4, fan: int = 4, hot_lines: int = HOT_LINES) -> DataFrame:
    """(id, gone array<struct<h1,h2>>): line hashes that a document loses; documents that lose none are absent."""
    spark = docs.sparkSession
    # a folder for each batch, which reads no other
    batch = F.pmod(F.xxhash64(F.lit(7), "id"), F.lit(batches)).cast("int").alias("batch")
    entries = Scratch(line_entries(docs, doc_id, text, min_chars).select("id", "h1", "h2", batch), "line-entries", partition_by="batch")
    store = LineRuns(spark, fan=fan)
    for k in range(batches):
        store.add(entries.table.where(F.col("batch") == k).drop("batch"))
    often = store.counts().where(F.col("n_docs") >= min_docs).select("h1", "h2", "n_docs", "max_id")
    rows, total = entries.table.select("id", "h1", "h2"), store.counts().agg(F.sum("n_docs")).first()[0] or 0
    # lines that hold a large share of all entries are few, whatever the table: they go to all tasks, the rest are dealt by hash
    is_hot = F.col("n_docs") * hot_lines > F.lit(total)
    hot, rest = (often.where(x).drop("n_docs") for x in (is_hot, ~is_hot))
    hot = F.broadcast(hot)
    cold = rows.join(hot, ["h1", "h2"], "left_anti").join(rest, ["h1", "h2"])
    gone = rows.join(hot, ["h1", "h2"]).unionByName(cold).where("id <> max_id")
    out = cut(gone.groupBy("id").agg(F.collect_set(F.struct("h1", "h2")).alias("gone")))
    store.close()
    entries.drop()
    return out


def dedup_lines(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", kept: str = "kept_text", **options) -> DataFrame:
    """`docs` with `kept` (the lines that stay, joined), `n_lines` (before) and `n_dropped`; columns of these names give way."""
    docs = docs.drop(*({kept, "n_lines", "n_dropped"} - {doc_id, text}))
    gone = dropped_lines(docs, doc_id, text, **options).select(F.col("id").alias("_fs_id"), F.col("gone").alias("_fs_gone"))
    joined = docs.join(gone, F.coalesce(F.col(doc_id).cast("long"), F.lit(NO_ID)) == F.col("_fs_id"), "left")
    lines = lines_of(F.col(text))
    min_chars = options.get("min_chars", MIN_CHARS)
    stay = F.filter(lines, lambda x: (F.length(x) < min_chars) | ~F.array_contains(F.col("_fs_gone"), line_hash(line_key(x))))
    left = F.when(F.col("_fs_gone").isNull(), lines).otherwise(stay)
    return (
        joined.withColumn("_fs_left", left)
        .withColumns({kept: F.array_join("_fs_left", "\n"), "n_lines": F.size(lines).cast("long"), "n_dropped": (F.size(lines) - F.size("_fs_left")).cast("long")})
        .drop("_fs_id", "_fs_gone", "_fs_left")
    )


def op9(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return dedup_lines(docs).select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("kept_text").cast("binary"), 256).alias("kept_sha256"))


OP9_SQL = """
with l as (
  select rowid_ as r, doc_id, unnest(string_split(coalesce(text, ''), chr(10))) as line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) as i
  from (select row_number() over () as rowid_, doc_id, text from documents)),
k as (select *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as key from l),
h as (select key, count(distinct doc_id) as n, max(doc_id) as m from k where length(key) >= 40 group by key having count(distinct doc_id) >= 5)
select k.doc_id, count(*) as n_lines, count(*) filter (where h.key is not null and k.doc_id <> h.m) as n_dropped,
  sha256(coalesce(string_agg(k.line, chr(10) order by k.i) filter (where h.key is null or k.doc_id = h.m), '')) as kept_sha256
from k left join h using (key) group by k.r, k.doc_id
"""
