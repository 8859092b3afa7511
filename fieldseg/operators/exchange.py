"""The exchange between blocks: pointers of boundary vertices, followed across blocks to their ends.

`boundary` is (id, ptr) with one row for each vertex that some other block holds as a ghost.  A pointer to an id without a row
has reached its end.  All strategies give the same rows:

* `replicate`: the raw table goes to every task, and each follows its own copy;
* `coordinator`: the driver follows the table once and sends the result;
* `neighbour`: each round a block hears from the blocks it touches alone, so an end travels one block a round;
* `shuffle`: pointer doubling on the distributed table, for boundaries of any size;
* `auto`: the driver where the counted boundary is small, else `shuffle`.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fieldseg.operators.kernels import double
from fieldseg.operators.pointers import compress
from fieldseg.runtime import cut, fresh

STRATEGIES = ("replicate", "coordinator", "neighbour", "shuffle")
#: Rows of a boundary that the driver or a broadcast may hold.
SMALL_BOUNDARY = 2_000_000
#: Blocks that a path may cross, one after another, in the exchange between neighbours.
MOST_BLOCKS_CROSSED = 1 << 20


class BoundaryTooLarge(RuntimeError):
    """A boundary that was asked to fit on one machine and doesn't."""


def _arrays(boundary: DataFrame, names: list[str]) -> dict[str, np.ndarray]:
    t = boundary.toArrow()
    return {c: t[c].to_numpy() for c in ["id", *names]}


def resolve(boundary: DataFrame, names: list[str], strategy: str = "auto", small: int = SMALL_BOUNDARY) -> tuple[DataFrame, int]:
    """(id, names...) with every pointer at its end, and the most rounds that a column took."""
    if strategy == "auto" or strategy in ("replicate", "coordinator"):
        fits = boundary.limit(small + 1).count() <= small
        if strategy == "auto":
            strategy = "coordinator" if fits else "shuffle"
        elif not fits:
            raise BoundaryTooLarge(f"the boundary has more than {small} rows")
    spark = boundary.sparkSession
    schema = ", ".join(f"{c} long" for c in ["id", *names])
    if strategy == "coordinator":
        a = _arrays(boundary, names)
        done = {c: double(a["id"], a[c]) for c in names}
        table = pa.table({"id": a["id"], **{c: done[c][0] for c in names}})
        return spark.createDataFrame(table, schema), max([0, *(r for _, r in done.values())])
    if strategy == "replicate":
        a = _arrays(boundary, names)
        copy = spark.sparkContext.broadcast(a)

        def follow(batches):
            whole = copy.value
            ends = {c: double(whole["id"], whole[c])[0] for c in names}
            order = np.argsort(whole["id"])
            for rb in batches:
                at = order[np.searchsorted(whole["id"], rb.column(0).to_numpy(), sorter=order)]
                yield pa.RecordBatch.from_arrays([rb.column(0), *(pa.array(ends[c][at]) for c in names)], ["id", *names])

        rounds = max([0, *(double(a["id"], a[c])[1] for c in names)])
        return boundary.select("id").mapInArrow(follow, schema), rounds
    if strategy == "neighbour":
        out, messages = by_neighbours(boundary, names)
        return out, len(messages)
    if strategy == "shuffle":
        return compress(boundary, name=names)
    raise ValueError(f"unknown strategy {strategy}")


def by_neighbours(boundary: DataFrame, names: list[str]) -> tuple[DataFrame, list[int]]:
    """(id, names...) with every pointer at its end, and the vertices that had news in each round.

    A pointer of the table leads to a ghost, whose owner touches the block.  All that a vertex is told, round by round, is where
    that ghost has got to, so no block asks one that it doesn't touch.
    """
    firsts = [f"_first_{c}" for c in names]
    state = cut(boundary.select("id", *(F.col(c).alias(f) for c, f in zip(names, firsts)), *names))
    news = F.lit(False)
    for c in names:
        news |= F.col(c) != F.col(f"_q_{c}")
    messages: list[int] = []
    while True:
        moved = state
        for c, first in zip(names, firsts):
            heard = state.select(F.col("id").alias("_i"), F.col(c).alias("_p"))
            moved = moved.join(heard, F.col(first) == F.col("_i"), "left").withColumn(f"_q_{c}", F.coalesce("_p", c)).drop("_i", "_p")
        moved = fresh(moved)
        changed = moved.where(news).count()
        if not changed:
            return state.select("id", *names), messages
        messages.append(changed)
        if len(messages) > MOST_BLOCKS_CROSSED:
            raise RuntimeError("pointers form a cycle")
        state = moved.select("id", *firsts, *(F.col(f"_q_{c}").alias(c) for c in names))


def substitute(owned: DataFrame, boundary: DataFrame, names: list[str], small: int = SMALL_BOUNDARY) -> DataFrame:
    """`owned` with each pointer that ends at a boundary vertex moved on to that one's end; one sweep."""
    fits = boundary.limit(small + 1).count() <= small
    out = owned
    for c in names:
        ends = boundary.select(F.col("id").alias("_fs_id"), F.col(c).alias("_fs_end"))
        ends = F.broadcast(ends) if fits else ends
        out = out.join(ends, F.col(c) == F.col("_fs_id"), "left").withColumn(c, F.coalesce("_fs_end", c)).drop("_fs_id", "_fs_end")
    return out
