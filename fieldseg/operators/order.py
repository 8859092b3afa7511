"""Order fields: the dense rank of (value, id), which makes any field injective."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from fieldseg.runtime import cut

_POSITION_BITS = 33


def numbered(df: DataFrame, by: list[str], name: str, partitions: int | None = None) -> DataFrame:
    """`df` with its 0-based position in the order of `by`, from one range shuffle.

    Partitions are sorted ranges; their counts, one number each, are summed on the driver and added to the position of a
    row in its partition.  Heavy ties spread over partitions if `by` ends with an id.
    """
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = df.repartitionByRange(n, *by).sortWithinPartitions(*by).withColumn("_fs_at", F.monotonically_increasing_id())
    ranged = cut(ranged)
    part, pos = F.shiftrightunsigned("_fs_at", _POSITION_BITS), F.col("_fs_at").bitwiseAND((1 << _POSITION_BITS) - 1)
    counts = {r.p: r.n for r in ranged.groupBy(part.alias("p")).agg(F.count("*").alias("n")).collect()}
    before, offsets = 0, []
    for p in sorted(counts):
        offsets.append((p, before))
        before += counts[p]
    table = df.sparkSession.createDataFrame(offsets, "_fs_part long, _fs_before long")
    # as many rows as partitions
    out = ranged.withColumn("_fs_part", part.cast("long")).join(F.broadcast(table), "_fs_part")
    return out.withColumn(name, pos + F.col("_fs_before")).drop("_fs_at", "_fs_part", "_fs_before")


def order_field(df: DataFrame, by: str = "f", tie: str = "id", method: str = "range", name: str = "ord") -> DataFrame:
    """`df` with `ord`, the rank of (by, tie): `range` for any size, `window` in one task for small tables."""
    if method == "range":
        return numbered(df, [by, tie], name)
    if method == "window":
        return df.withColumn(name, (F.row_number().over(Window.orderBy(by, tie)) - 1).cast("long"))
    raise ValueError(f"unknown method {method}")
