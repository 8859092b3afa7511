"""Extremum graph: maxima whose segments touch, with the highest pass between them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fieldseg.functions.grid import GridSpec


def build(segments: DataFrame, ords: DataFrame, spec: GridSpec, side: str = "max_id") -> DataFrame:
    """(a, b, saddle_ord): pairs of extrema a < b, and the best over their common edges of the worse end's order.

    `segments` has (id, max_id) or (id, min_id), `ords` (id, ord).  Every edge is looked at from its lower id once.
    """
    up = side == "max_id"
    v = segments.join(ords.select("id", "ord"), "id").select("id", F.col(side).alias("ext"), "ord")
    half = [s for s in spec.stencil() if spec.offset(s) > 0]
    ahead = F.explode(F.array_compact(F.array(*(F.when(spec.inside(s), F.col("id") + F.lit(spec.offset(s))) for s in half)))).alias("n")
    other = v.select(F.col("id").alias("n"), F.col("ext").alias("ext2"), F.col("ord").alias("ord2"))
    edges = v.select("ext", "ord", ahead).join(other, "n").where("ext <> ext2")
    ends = [F.least("ext", "ext2").alias("a"), F.greatest("ext", "ext2").alias("b")]
    pass_at = F.max(F.least("ord", "ord2")) if up else F.min(F.greatest("ord", "ord2"))
    return edges.groupBy(*ends).agg(pass_at.alias("saddle_ord"))
