"""Two-pass external shuffle into shards, with DataFrame functions only.

Pass one scatters whole records into buckets of bounded bytes by a seeded hash; pass two shuffles each bucket by Fisher-Yates
(the `shuffle` function) and numbers it from the bucket's first position, so the whole is one permutation of all records.  The
shards are equal stretches of it: their counts are one apart at most (law `rows`), and a bucket is written to one shard or two.
Bucket offsets are running sums over the table of bucket counts, which the hashes of records alone give, so records move once.

Nulls are values like any other.  Copies of a record are numbered, after a map-side count of their hashes, so a record that is a
third of the table fills no bucket; records that occur once are not grouped.  A bucket is a partition, whose number seeds its
shuffle, so the result depends on seed, records and number of buckets, and not on the order or partitioning of the input; a lost
task gives the same again.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fieldseg.runtime import cut

SHARDS = 16
SEED = 20_260_801
#: Bytes of a bucket, of which one task holds some copies; there are MIN_BUCKETS at least.  A shuffle of more than some 100,000
#: buckets burdens the driver, so large tables want larger buckets and executors.
BUCKET_BYTES = 64 << 20
MIN_BUCKETS = 64
#: Hashes of repeated records that are broadcast; more are joined by shuffle.
BROADCAST_COPIES = 100_000
#: Copies of a record that one row is spread into by one task.
COPIES_A_ROW = 1000
LAW = "rows"


def text_size(text: Column) -> Column:
    """UTF-8 bytes of the text (null: none) and one."""
    return (F.coalesce(F.octet_length(text), F.lit(0)) + 1).cast("long")


def record_hash(columns: list[str]) -> list[Column]:
    """Two 64-bit hashes of a record, in which a null differs from all values."""
    each = [x for c in columns for x in (F.col(c).isNull(), F.col(c))]
    return [F.xxhash64(F.lit(i), *each).alias(f"_fs_h{i}") for i in (1, 2)]


def _dice(seed: int, n_buckets: int) -> dict[str, Column]:
    dice = F.xxhash64(F.lit(seed), "_fs_h1", "_fs_h2", "_fs_copy")
    return {"_fs_dice": dice, "_fs_bucket": F.pmod(F.xxhash64(F.lit(seed + 1), dice), F.lit(n_buckets)).cast("int")}


def _copies(rows: DataFrame, count: str) -> DataFrame:
    """`rows` once for each of their copies, with `_fs_copy`; many copies of a row are spread by several tasks."""
    stretch = F.explode(F.sequence(F.lit(0).cast("long"), F.expr(f"({count} - 1) div {COPIES_A_ROW}"))).alias("_fs_part")
    parts = rows.select("*", stretch).repartition("_fs_h1", "_fs_h2", "_fs_part")
    first = F.col("_fs_part") * COPIES_A_ROW
    return parts.withColumn("_fs_copy", F.explode(F.sequence(first + 1, F.least(F.col(count), first + COPIES_A_ROW)))).drop("_fs_part", count)


def scatter(records: DataFrame, n_buckets: int, seed: int = SEED) -> tuple[DataFrame, DataFrame]:
    """Pass one: (`records` with `_fs_copy`, its number among equal records, `_fs_dice` and `_fs_bucket`; (bucket, rows) of all buckets)."""
    cols, hashes = records.columns, ["_fs_h1", "_fs_h2"]
    keyed = records.select(*cols, *record_hash(cols))
    keys = cut(records.select(*record_hash(cols)).groupBy(*hashes).agg(F.count("*").alias("_fs_n")))
    twice = keys.where("_fs_n > 1")
    one = F.lit(1).cast("long").alias("_fs_copy")
    copies = _copies(twice, "_fs_n")
    counts = keys.where("_fs_n = 1").select(*hashes, one).unionByName(copies.select(*hashes, "_fs_copy")).withColumns(_dice(seed, n_buckets)).groupBy("_fs_bucket").agg(F.count("*").alias("_fs_rows"))
    n_twice = twice.limit(BROADCAST_COPIES + 1).count()
    if not n_twice:
        return keyed.select("*", one).withColumns(_dice(seed, n_buckets)).drop(*hashes), counts
    known = twice.select(*hashes)
    known = F.broadcast(known) if n_twice <= BROADCAST_COPIES else known
    # equal hashes of unequal records would number them apart from the counts, which two hashes of 64 bits rule out
    grouped = keyed.join(known, hashes, "left_semi").groupBy(*cols, *hashes).agg(F.count("*").alias("_fs_n"))
    every = keyed.join(known, hashes, "left_anti").select(*cols, *hashes, one).unionByName(_copies(grouped, "_fs_n").select(*cols, *hashes, "_fs_copy"))
    return every.withColumns(_dice(seed, n_buckets)).drop(*hashes), counts


def external_shuffle(records: DataFrame, size: str | Column, n_shards: int = SHARDS, seed: int = SEED, bucket_bytes: int = BUCKET_BYTES, min_buckets: int = MIN_BUCKETS) -> DataFrame:
    """`records` with `shard` (0 to n_shards - 1) and `slot` (gapless in each shard); `size` gives the bytes of a record.

    Columns named as the two new ones give way.
    """
    records = records.drop("shard", "slot")
    total = records.agg(F.sum(size)).first()[0] or 0
    n_buckets = max(min_buckets, 1 + int(total) // bucket_bytes)
    scattered, counts = scatter(records, n_buckets, seed)
    counts = cut(counts)
    n = counts.agg(F.sum("_fs_rows")).first()[0] or 0
    before = F.coalesce(F.sum("_fs_rows").over(Window.orderBy("_fs_bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = counts.select("_fs_bucket", before.alias("_fs_start"))
    row = F.struct("_fs_dice", "_fs_copy", *records.columns)
    # sorted by the dice first, so that the permutation doesn't depend on the order of arrival
    dealt = scattered.repartitionById(n_buckets, "_fs_bucket").groupBy("_fs_bucket").agg(F.shuffle(F.array_sort(F.collect_list(row)), seed).alias("_fs_rows"))
    # as many rows as buckets
    placed = dealt.join(F.broadcast(starts), "_fs_bucket").select("_fs_start", F.posexplode("_fs_rows").alias("_fs_i", "_fs_row"))
    out = placed.select("_fs_row.*", (F.col("_fs_start") + F.col("_fs_i")).alias("_fs_at")).drop("_fs_dice", "_fs_copy")
    out = out.withColumn("shard", F.expr(f"_fs_at * {n_shards} div {max(1, n)}").cast("int"))
    return out.withColumn("slot", F.expr(f"_fs_at - (shard * {n}L + {n_shards - 1}) div {n_shards}").cast("long")).drop("_fs_at")


def write_shards(docs: DataFrame, path: str, text: str = "text", **options) -> None:
    """Write whole documents as parquet, one folder a shard; a bucket's rows are one file, or two at a border, in slot order."""
    out = external_shuffle(docs, text_size(F.col(text)), **options)
    out.sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)


def op2(spark, sf_dir: str) -> DataFrame:
    """The digest of whole records where the shuffle has put them."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    dealt = external_shuffle(docs, text_size(F.col("text")))
    crc = F.crc32(F.coalesce("text", F.lit("")).cast("binary"))
    return dealt.select("doc_id", text_size(F.col("text")).alias("size"), crc.alias("text_crc32"), F.lit(LAW).alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
