"""Generated fields by column maths: on grids of any size, made in place from `spark.range`, and at the rows of a given table."""

from __future__ import annotations

from itertools import product
from math import prod

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fieldseg.functions.grid import GridSpec
from fieldseg.sources.fields import Field, table

#: Field values are kept as integers of this many parts of one, so no sum or comparison depends on rounding.
SCALE = 1_000_000


def _fade(t: Column) -> Column:
    return t * t * t * (t * (t * 6 - 15) + 10)


def _with_noise(df: DataFrame, axes: list[str], frequency: float, amplitude: float, seed: int) -> DataFrame:
    """`df` with the noise `f` at the places that its columns `axes` tell.

    Gradients are unit steps along the axes, chosen by a hash of the corner, so no table of them is kept.
    """
    at = {a: F.col(a) * F.lit(frequency) for a in axes}
    df = df.withColumns({f"{a}0": F.floor(at[a]).cast("long") for a in axes} | {f"{a}t": at[a] - F.floor(at[a]) for a in axes})
    total = F.lit(0.0)
    for corner in product((0, 1), repeat=len(axes)):
        pick = F.pmod(F.xxhash64(F.lit(seed), *(F.col(f"{a}0") + c for a, c in zip(axes, corner))), F.lit(2 * len(axes)))
        steps = [F.when(pick == 2 * i, F.col(f"{a}t") - c).when(pick == 2 * i + 1, c - F.col(f"{a}t")).otherwise(0.0) for i, (a, c) in enumerate(zip(axes, corner))]
        weight = F.lit(1.0)
        for a, c in zip(axes, corner):
            fade = _fade(F.col(f"{a}t"))
            weight = weight * (fade if c else 1 - fade)
        total = total + weight * sum(steps[1:], steps[0])
    return df.withColumn("f", F.round(total * amplitude * SCALE).cast("long")).drop(*(f"{a}{k}" for a in axes for k in "0t"))


def noise_grid(spark: SparkSession, dims: tuple[int, ...], frequency: float = 0.1, amplitude: float = 1.0, seed: int = 42, connectivity: str = "simplicial") -> Field:
    """One layer of gradient noise: zero at lattice corners, blended between pseudo-random gradients."""
    spec = GridSpec(dims, connectivity)
    df = spec.with_coords(spark.range(spec.n))
    return Field(_with_noise(df, ["x", "y", "z"][: spec.d], frequency, amplitude, seed).select("id", "f"), spec)


def line_noise(spark: SparkSession, sf_dir: str, frequency: float = 0.1, amplitude: float = 1.0, seed: int = 42) -> DataFrame:
    """(x, y, z, f): the same noise at the vertex of each line, which is its ship day, part and supplier."""
    line = table(spark, sf_dir, "lineitem")
    places = line.select(F.unix_date(F.to_date("l_shipdate")).cast("long").alias("x"), F.col("l_partkey").cast("long").alias("y"), F.col("l_suppkey").cast("long").alias("z"))
    return _with_noise(places, ["x", "y", "z"], frequency, amplitude, seed)


def bump_grid(spark: SparkSession, sf_dir: str, dims: tuple[int, ...] = (32, 32, 32), n_centres: int | None = None, width: float = 4.0, connectivity: str = "simplicial") -> Field:
    """A sum of Gaussians around all suppliers: the place of each follows from its key, its height from its balance.

    Heights are summed by vertex as integers, then spread along one axis after another, as a Gaussian is the product of those of
    its axes; each sum runs in the order of its places, so it doesn't depend on the shuffle.  `n_centres` takes the first by key.
    """
    spec = GridSpec(dims, connectivity)
    axes = ["x", "y", "z"][: spec.d]
    s = table(spark, sf_dir, "supplier")
    s = s if n_centres is None else s.orderBy("s_suppkey").limit(n_centres)
    place = [F.pmod(F.xxhash64(F.lit(7 + i), "s_suppkey"), F.lit(n)).alias(a) for i, (a, n) in enumerate(zip(axes, dims))]
    heights = s.select(*place, F.round(F.abs("s_acctbal") * 100).cast("long").alias("cents")).groupBy(*axes).agg(F.sum("cents").alias("cents"))
    sums = heights.select(*axes, (F.col("cents") / 100.0).cast("double").alias("v"))
    for a, n in zip(axes, dims):
        far = F.col("_fs_to") - F.col(a)
        spread = sums.withColumn("_fs_to", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long")))).withColumn("v", F.col("v") * F.exp(-far * far / (2 * width * width)))
        parts = spread.groupBy("_fs_to", *(o for o in axes if o != a)).agg(F.array_sort(F.collect_list(F.struct(a, "v"))).alias("parts"))
        sums = parts.withColumn("v", F.aggregate("parts", F.lit(0.0), lambda t, c: t + c["v"])).drop("parts").withColumnRenamed("_fs_to", a)
    df = spec.with_coords(spark.range(spec.n)).join(sums, axes, "left")
    return Field(df.select("id", F.round(F.coalesce("v", F.lit(0.0)) * SCALE).cast("long").alias("f")), spec)


def resample(field: Field, factor: int) -> Field:
    """Nearest-vertex resampling to a grid `factor` times as fine along each axis; factor 1 is the identity."""
    spec = GridSpec(tuple(n * factor for n in field.spec.dims), field.spec.connectivity)
    fine = spec.with_coords(field.df.sparkSession.range(spec.n))
    coarse = F.lit(0).cast("long")
    for a in range(spec.d):
        coarse = coarse + F.call_function("div", F.col("xyz"[a]), F.lit(factor)) * prod(field.spec.dims[:a])
    joined = fine.select("id", coarse.alias("_fs_at")).join(field.df.select(F.col("id").alias("_fs_at"), "f"), "_fs_at")
    return Field(joined.select("id", "f"), spec)
