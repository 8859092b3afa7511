"""Cost and accuracy measures."""

from __future__ import annotations

import time
from collections.abc import Callable
from functools import reduce

from py4j.protocol import Py4JError
from pyspark.errors import PySparkException
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from fieldseg.functions.grid import Blocks, GridSpec

#: What an error says where memory ran out: in the JVM, in a Python worker, or where the machine's killer ended one.
OUT_OF_MEMORY = ("OutOfMemoryError", "MemoryError", "Python worker exited unexpectedly", "exit code 137")
TIMING = "workload string, method string, blocks int, threads int, n long, seconds double, ghosts long, rounds int, status string"


def timed(df: DataFrame) -> float:
    """Seconds to compute a DataFrame and discard it; inputs should be materialised before."""
    start = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start


def attempt(run: Callable[[], DataFrame]) -> tuple[float | None, str]:
    """(seconds, "ok") or (None, why): configurations that don't fit are recorded, not raised.

    Memory that ran out in a task or its Python worker comes back as a Spark error, so its text tells.
    """
    try:
        start = time.perf_counter()
        timed(run())
        return time.perf_counter() - start, "ok"
    except MemoryError:
        return None, "OOM"
    except (PySparkException, Py4JError) as e:
        text = str(e)
        if any(sign in text for sign in OUT_OF_MEMORY):
            return None, "OOM"
        raise
    except RuntimeError as e:
        return None, type(e).__name__


def speedup(timings: DataFrame) -> DataFrame:
    """`speedup` against the smallest feasible number of blocks of the same workload and method, and `efficiency` per block added."""
    w = Window.partitionBy("workload", "method", "n").orderBy("blocks").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    ok = timings.where("status = 'ok'")
    first, at = F.first("seconds").over(w), F.first("blocks").over(w)
    return ok.withColumn("speedup", first / F.col("seconds")).withColumn("efficiency", F.col("speedup") * at / F.col("blocks"))


def weak_efficiency(timings: DataFrame) -> DataFrame:
    """Time on the fewest blocks over the time on more with as much more data; 1 is ideal."""
    w = Window.partitionBy("workload", "method").orderBy("blocks").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return timings.where("status = 'ok'").withColumn("weak_efficiency", F.first("seconds").over(w) / F.col("seconds"))


def ghost_counts(df: DataFrame, blocks: Blocks) -> DataFrame:
    """(block, ghosts): vertices of other owners that each block holds."""
    return blocks.halo(df.select("id")).groupBy("block").agg(F.count_if("is_ghost").alias("ghosts"))


def memory_model(df: DataFrame, blocks: Blocks, id_bytes: int = 8) -> DataFrame:
    """(blocks, vertices, ghosts, bytes): one id array of the grid and a record of three ids for each ghost."""
    h = blocks.halo(df.select("id")).agg(F.count_if(~F.col("is_ghost")).alias("vertices"), F.count_if("is_ghost").alias("ghosts"))
    return h.select(F.lit(blocks.n).cast("long").alias("blocks"), "vertices", "ghosts", (F.col("vertices") * id_bytes + F.col("ghosts") * 3 * id_bytes).alias("bytes"))


def observed_memory(df: DataFrame, blocks: Blocks) -> DataFrame:
    """(block, vertices, ghosts, model, peak): bytes of the model, and the most that the kernel of each block held at a time.

    The peak is what Python and NumPy allocate while the block is solved, without its input table.
    """
    import tracemalloc

    import numpy as np
    import pyarrow as pa

    from fieldseg.operators.segment import block_tables, solver

    solve = solver(blocks.spec)

    def run(key, table):
        tracemalloc.start()
        try:
            solve(table.drop_columns(["block"]))
            peak = tracemalloc.get_traced_memory()[1]
        finally:
            tracemalloc.stop()
        ghosts = int(np.sum(table["is_ghost"].to_numpy(zero_copy_only=False)))
        vertices = table.num_rows - ghosts
        return pa.table({"block": [key[0].as_py()], "vertices": [vertices], "ghosts": [ghosts], "model": [8 * vertices + 24 * ghosts], "peak": [peak]})

    return block_tables(df, blocks).groupBy("block").applyInArrow(run, "block long, vertices long, ghosts long, model long, peak long")


def _beside(*rows: DataFrame) -> DataFrame:
    """The columns of one-row tables of counts side by side, without a join."""
    names = [c for r in rows for c in r.columns]
    padded = [r.select(*(F.col(c) if c in r.columns else F.lit(0).cast("long").alias(c) for c in names)) for r in rows]
    return reduce(DataFrame.unionByName, padded).agg(*(F.sum(c).alias(c) for c in names))


def partition_diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """(parts_a, parts_b, apart): how many parts two labellings of the same ids have, and how many of b's lie in several of a's."""
    both = a.select("id", F.col("label").alias("la")).join(b.select("id", F.col("label").alias("lb")), "id")
    pairs = both.select("la", "lb").distinct()
    per_b = pairs.groupBy("lb").agg(F.count("*").alias("n"))
    right = per_b.agg(F.count("*").alias("parts_b"), F.count_if(F.col("n") > 1).alias("apart"))
    left = pairs.agg(F.countDistinct("la").alias("parts_a"))
    return _beside(left, right)


def selectivity(df: DataFrame, mask: str = "m") -> DataFrame:
    return df.agg(F.count("*").alias("n"), F.count_if(mask).alias("inside"))


def spanning(labels: DataFrame, blocks: Blocks, label: str = "label") -> DataFrame:
    """(segments, spanning): how many labels there are, and how many lie in several blocks."""
    per = labels.where(F.col(label) >= 0).groupBy(label).agg((F.min(blocks.block()) < F.max(blocks.block())).alias("s"))
    return per.agg(F.count("*").alias("segments"), F.count_if("s").alias("spanning"))


def size_histogram(labels: DataFrame, label: str = "label") -> DataFrame:
    """(size, segments): how many labels have each number of vertices."""
    return labels.where(F.col(label) >= 0).groupBy(label).agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("segments"))


def extracted_geometry(df: DataFrame, spec: GridSpec, mask: str = "m") -> DataFrame:
    """(vertices, cells) of the masked part as an explicit grid."""
    from fieldseg.operators.baselines import to_unstructured

    inside = df.where(mask).select("id")
    return _beside(inside.agg(F.count("*").alias("vertices")), to_unstructured(inside, spec).agg(F.count("*").alias("cells")))


def stability(timings: DataFrame) -> DataFrame:
    """Median and spread of repeated runs of a configuration."""
    return timings.where("status = 'ok'").groupBy("workload", "method", "blocks", "threads", "n").agg(F.median("seconds").alias("median"), (F.max("seconds") - F.min("seconds")).alias("spread"), F.count("*").alias("repeats"))


def communication(df: DataFrame, blocks: Blocks, strategy: str = "auto", id_bytes: int = 8) -> dict[str, int]:
    """What one segmentation moves between blocks: ghost records, boundary vertices, bytes of the boundary table, rounds.

    `neighbour_rounds` and `neighbour_bytes` are those of the exchange between touching blocks, in which a vertex with news sends
    its id and two pointers to each block that holds it; the others gather the boundary once and hand it out once.
    """
    from fieldseg.operators import exchange, segment
    from fieldseg.runtime import cut

    local = cut(segment.block_pointers(df, blocks))
    boundary = local.where("shared").select("id", "max_id", "min_id")
    _, rounds = exchange.resolve(boundary, ["max_id", "min_id"], strategy)
    _, messages = exchange.by_neighbours(boundary, ["max_id", "min_id"])
    n, ghosts = boundary.count(), blocks.requests(df).count()
    copies = ghosts / max(1, n)
    near = {"neighbour_rounds": len(messages), "neighbour_bytes": round(3 * id_bytes * copies * (n + sum(messages)))}
    return {"ghosts": ghosts, "boundary": n, "bytes": 3 * id_bytes * n, "exchange_rounds": rounds, **near, "local_rounds": local.agg(F.max("rounds")).first()[0] or 0}
