"""Scalar fields on the given tables, as (id LONG, f LONG), and their grids."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fieldseg.functions.grid import GridSpec


@dataclass
class Field:
    """A field and the grid its ids lie on."""

    df: DataFrame
    spec: GridSpec


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cents(column: str):
    return F.round(F.col(column) * 100).cast("long")


def _plane_width(n: int) -> int:
    w = int(n**0.5)
    return w if w * w == n else w + 1


def orders_plane(spark: SparkSession, sf_dir: str, connectivity: str = "simplicial") -> Field:
    """Order totals on a plane as square as it can be; the last row may be short."""
    orders = table(spark, sf_dir, "orders")
    n = orders.count()
    w = max(1, _plane_width(n))
    df = orders.select(F.col("o_orderkey").alias("id"), cents("o_totalprice").alias("f"))
    return Field(df, GridSpec((w, max(1, -(-n // w))), connectivity))


def lineitem_cube(spark: SparkSession, sf_dir: str, connectivity: str = "simplicial") -> Field:
    """Number of lines for each quantity, discount and tax; absent cells are 0."""
    spec = GridSpec((50, 11, 9), connectivity)
    line = table(spark, sf_dir, "lineitem")
    x, y, z = F.col("l_quantity").cast("long") - 1, cents("l_discount"), cents("l_tax")
    counts = line.groupBy((x + 50 * (y + 11 * z)).alias("id")).agg(F.count("*").alias("f"))
    return Field(_filled(spark, spec, counts), spec)


def _filled(spark: SparkSession, spec: GridSpec, cells: DataFrame) -> DataFrame:
    return spark.range(spec.n).join(cells, "id", "left").select("id", F.coalesce("f", F.lit(0)).cast("long").alias("f"))


def shipday_line(spark: SparkSession, sf_dir: str) -> Field:
    """Quantity shipped on each day, by days since the first; days without a line are 0."""
    line = table(spark, sf_dir, "lineitem")
    day = F.unix_date(F.to_date("l_shipdate"))
    lo, hi = line.agg(F.min(day), F.max(day)).first()
    sums = line.groupBy((day - F.lit(lo)).cast("long").alias("id")).agg(F.sum(F.col("l_quantity").cast("long")).alias("f"))
    spec = GridSpec((hi - lo + 1,))
    return Field(_filled(spark, spec, sums), spec)


def user_day_plane(spark: SparkSession, sf_dir: str, fill: bool = True, connectivity: str = "simplicial") -> Field:
    """Value of the events of each user and day of month; absent cells are 0, or left out."""
    events = table(spark, sf_dir, "events")
    last, days = events.agg(F.max("user_id"), F.max(F.dayofmonth("ts"))).first()
    spec = GridSpec((int(days), int(last) + 1), connectivity)
    x = F.dayofmonth("ts").cast("long") - 1
    sums = events.groupBy((x + spec.dims[0] * F.col("user_id")).alias("id")).agg(F.sum(cents("value")).alias("f"))
    return Field(_filled(spark, spec, sums) if fill else sums, spec)


def smoothed(field: Field, rounds: int = 1) -> Field:
    """Sums over the closed star, `rounds` times; integers, so no rounding."""
    df = field.df
    for _ in range(rounds):
        # vertices that don't exist never hear from themselves and are left out
        spread = df.select(F.explode(field.spec.neighbours(closed=True)).alias("_fs_to"), "f", F.col("id").alias("_fs_from"))
        sums = spread.groupBy("_fs_to").agg(F.sum("f").alias("f"), F.bool_or(F.col("_fs_to") == F.col("_fs_from")).alias("_fs_own"))
        df = sums.where("_fs_own").select(F.col("_fs_to").alias("id"), "f")
    return Field(df, field.spec)


FIELDS = {"orders": orders_plane, "cube": lineitem_cube, "line": shipday_line, "user_day": user_day_plane}
