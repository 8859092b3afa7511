"""Schemas of the data model and checks of inputs against it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

L, B = T.LongType(), T.BooleanType()


def _schema(**fields) -> T.StructType:
    return T.StructType([T.StructField(k, v) for k, v in fields.items()])


VERTEX = _schema(id=L, f=L)
MASKED_VERTEX = _schema(id=L, f=L, m=B)
EDGE = _schema(src=L, dst=L)
CELL = _schema(cell_id=L, verts=T.ArrayType(L))
HALO = _schema(block=L, id=L, is_ghost=B, ord=L)
GHOST_REQUEST = _schema(id=L, owner=L, needed_by=L, target=L)
POINTER = _schema(id=L, ptr=L)
BOUNDARY = _schema(id=L, ptr=L)
SEGMENTATION = _schema(id=L, max_id=L, min_id=L, seg=L)
COMPONENTS = _schema(id=L, label=L)
EXTREMUM_GRAPH = _schema(a=L, b=L, saddle_ord=L)
OUTSIDE = -1


class FieldError(ValueError):
    """An input that breaks an invariant of the model."""


def check_field(df: DataFrame, value: str = "f") -> DataFrame:
    """Raise where ids or values are null, values are NaN, or an id occurs twice; returns the input."""
    nan = F.isnan(value) if dict(df.dtypes)[value] in ("double", "float") else F.lit(False)
    bad = df.agg(
        F.count_if(F.col("id").isNull()).alias("null_ids"),
        F.count_if(F.col(value).isNull()).alias("null_values"),
        F.count_if(nan).alias("nan_values"),
    ).first()
    found = {k: v for k, v in bad.asDict().items() if v}
    if found:
        raise FieldError(f"field has {found}")
    if not df.groupBy("id").count().where("count > 1").isEmpty():
        raise FieldError("field has repeated ids")
    return df


def edges_from_cells(cells: DataFrame) -> DataFrame:
    """(src, dst), both directions once each, of the pairs of vertices that share a cell."""
    pair = cells.select(F.explode("verts").alias("src"), "verts").select("src", F.explode("verts").alias("dst"))
    return pair.where("src <> dst").distinct()


def both_directions(edges: DataFrame) -> DataFrame:
    """Edges in both directions, without loops, nulls and repeats."""
    e = edges.select("src", "dst").where("src <> dst")
    return e.unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def adjacency(edges: DataFrame) -> DataFrame:
    """(id, nbrs) with the sorted neighbours of each vertex that has one."""
    return both_directions(edges).groupBy(F.col("src").alias("id")).agg(F.array_sort(F.collect_list("dst")).alias("nbrs"))


def induced(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """The edges both of whose ends are among `vertices` (id)."""
    v = vertices.select("id")
    return edges.join(v, F.col("src") == F.col("id"), "left_semi").join(v, F.col("dst") == F.col("id"), "left_semi")
