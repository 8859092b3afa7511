"""Connected components of an edge table by hooking to the smallest neighbour and contracting.

Every round hooks each vertex to the smallest id it sees, doubles the pointers, renames the edges and
drops those whose ends agree, so the edge table shrinks from round to round.  Once `ONE_TASK` edges or fewer are left, one task
solves them by union-find.  Nothing reaches the driver but a count.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fieldseg.operators.kernels import union_find
from fieldseg.runtime import cut, fresh

MAX_ROUNDS = 64
#: Edges that one task may solve (some 50 MB in Python).
ONE_TASK = 200_000


def double_pointers(ptr: DataFrame, times: int) -> DataFrame:
    """`ptr` (id, to) after `times` jumps through itself; an absent target is a root."""
    for _ in range(times):
        far = ptr.select(F.col("id").alias("_via"), F.col("to").alias("_far"))
        ptr = ptr.join(far, F.col("to") == F.col("_via"), "left").select("id", F.coalesce("_far", "to").alias("to"))
    return ptr


def _ordered(edges: DataFrame) -> DataFrame:
    return edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def _through(df: DataFrame, column: str, pointers: DataFrame) -> DataFrame:
    m = pointers.select(F.col("id").alias("_id"), F.col("to").alias("_to"))
    return df.join(m, F.col(column) == F.col("_id"), "left").withColumn(column, F.coalesce("_to", column)).drop("_id", "_to")


def _solve_in_one_task(edges: DataFrame) -> DataFrame:
    """(id, to): the smallest id of the component of each vertex that isn't it."""

    def solve(table):
        found = union_find(-table["a"].to_numpy(), -table["b"].to_numpy())
        pairs = [(-k, -v) for k, v in found.items() if k != v]
        cols = list(zip(*pairs)) if pairs else [(), ()]
        return pa.table({"id": pa.array(cols[0], pa.int64()), "to": pa.array(cols[1], pa.int64())})

    return edges.withColumn("_one", F.lit("one")).groupBy("_one").applyInArrow(solve, "id long, to long")


def contract_components(edges: DataFrame, src: str = "src", dst: str = "dst", winner: str = "min", jumps: int = 2, one_task: int = ONE_TASK) -> DataFrame:
    """(id, label) for every vertex that has an edge; label = smallest (or largest) id of its component.

    Null ends and self-loops are dropped; repeated edges are one edge; an empty table gives an empty result.
    `jumps` pointer doublings run in each round before the edges are renamed.
    """
    sign = F.lit(1 if winner == "min" else -1)
    live = fresh(_ordered(edges.select((F.col(src).cast("long") * sign).alias("a"), (F.col(dst).cast("long") * sign).alias("b")).where("a is not null and b is not null")))
    label = cut(live.select(F.col("a").alias("id")).union(live.select(F.col("b").alias("id"))).distinct()).select("id", F.col("id").alias("label"))
    for _ in range(MAX_ROUNDS):
        left = live.count()
        if not left:
            break
        if left <= one_task:
            label = _through(label, "label", _solve_in_one_task(live))
            break
        # a > b always, so the hook of `a` is its smallest neighbour and pointers strictly descend
        hooks = fresh(double_pointers(live.groupBy(F.col("a").alias("id")).agg(F.min("b").alias("to")), jumps))
        label = fresh(_through(label, "label", hooks))
        live = fresh(_ordered(_through(_through(live, "a", hooks), "b", hooks)))
    else:
        raise RuntimeError("contraction did not converge")
    return label.select((F.col("id") * sign).alias("id"), (F.col("label") * sign).alias("label"))
