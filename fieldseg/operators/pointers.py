"""Steepest-neighbour pointers and pointer doubling as DataFrame plans (the block-less form)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from fieldseg.functions.grid import GridSpec
from fieldseg.operators.kernels import double
from fieldseg.runtime import cut, fresh

MAX_ROUNDS = 64
#: Ids of a line that one task holds, and pointers that one task may compress.
LINE_STRETCH = 1 << 20
ONE_TASK = 4 << 20


def _extreme(direction: str):
    if direction not in ("up", "down"):
        raise ValueError(f"unknown direction {direction}")
    return F.max if direction == "up" else F.min


def steepest(df: DataFrame, spec: GridSpec | None = None, edges: DataFrame | None = None, direction: str = "up", by: str = "f", name: str = "ptr") -> DataFrame:
    """(id, ptr): the largest (or smallest) vertex of the closed star by (by, id); an extremum points to itself.

    On a grid every vertex sends its value to the ids of its star, so there is one shuffle and no join: targets that don't
    exist never hear from themselves and are left out.
    """
    pick = _extreme(direction)
    if spec is not None:
        value = F.struct(F.col(by).alias("v"), F.col("id").alias("i"))
        sent = df.select(F.explode(spec.neighbours(closed=True)).alias("to"), value.alias("v"), F.col("id").alias("src"))
        best = sent.groupBy("to").agg(pick("v").alias("best"), F.bool_or(F.col("to") == F.col("src")).alias("_fs_own"))
        return best.where("_fs_own").select(F.col("to").alias("id"), F.col("best.i").alias(name))
    own = df.select(F.col("id").alias("src"), F.col("id").alias("dst"))
    value = df.select(F.col("id").alias("dst"), F.struct(F.col(by).alias("v"), F.col("id").alias("i")).alias("v"))
    both = edges.select("src", "dst").unionByName(own).join(value, "dst").join(df.select(F.col("id").alias("src")), "src", "left_semi")
    return both.groupBy("src").agg(pick("v").alias("best")).select(F.col("src").alias("id"), F.col("best.i").alias(name))


def steepest_on_line(df: DataFrame, direction: str = "up", by: str = "f", name: str = "ptr", stretch: int = LINE_STRETCH) -> DataFrame:
    """The pointers of a line from its two neighbours in the order of ids (a window, no join).

    The line is cut into stretches of ids, each with the vertex before and behind it, so that a task holds one stretch.
    """
    of = lambda i: F.call_function("div", i, F.lit(stretch))
    i = F.col("id")
    cut_up = df.select("id", by, F.explode(F.array_distinct(F.array(of(i - 1), of(i), of(i + 1)))).alias("_fs_part"))
    order = Window.partitionBy("_fs_part").orderBy("id")
    star = [F.struct(F.col(by).alias("v"), i.alias("i"))]
    for shift in (F.lag, F.lead):
        star.append(F.when((F.abs(shift("id").over(order) - i)) == 1, F.struct(shift(by).over(order).alias("v"), shift("id").over(order).alias("i"))))
    best = (F.greatest if direction == "up" else F.least)(*star)
    return cut_up.select("id", best["i"].alias(name), "_fs_part").where(of(i) == F.col("_fs_part")).drop("_fs_part")


def compress(ptr: DataFrame, mode: str = "doubling", active: bool = True, name: str | list[str] = "ptr") -> tuple[DataFrame, int]:
    """Follow (id, ptr) to the fixed points; returns the table and the rounds that changed something.

    `doubling` jumps through the current pointers, `chase` one step of the first pointers a round.  With `active`, rows whose
    pointers are fixed points leave the loop.  A target that is no id is a fixed point.  Several pointers of a row, by a list of
    names, are followed side by side.
    """
    if mode not in ("doubling", "chase"):
        raise ValueError(f"unknown mode {mode}")
    names = [name] if isinstance(name, str) else list(name)
    state = cut(ptr.select("id", *names))
    first, done, rounds = state, None, 0
    live = state
    moves = F.lit(False)
    for c in names:
        moves |= F.col(c) != F.col(f"_q_{c}")
    old, new = ["id", *names], ["id", *(F.col(f"_q_{c}").alias(c) for c in names)]
    for _ in range(MAX_ROUNDS if mode == "doubling" else 1 << 20):
        moved = live
        for c in names:
            through = (state if mode == "doubling" else first).select(F.col("id").alias("_i"), F.col(c).alias("_p"))
            moved = moved.join(through, F.col(c) == F.col("_i"), "left").withColumn(f"_q_{c}", F.coalesce("_p", c)).drop("_i", "_p")
        moved = fresh(moved)
        if moved.where(moves).isEmpty():
            live = moved.select(*old)
            break
        rounds += 1
        if active:
            still = moved.where(~moves).select(*old)
            done = still if done is None else done.unionByName(still)
            live = moved.where(moves).select(*new)
            state = live if mode == "chase" else live.unionByName(done)
        else:
            live = state = moved.select(*new)
    else:
        raise RuntimeError("pointers form a cycle")
    return live if done is None else live.unionByName(done), rounds


def compress_partition(ptr: DataFrame, name: str = "ptr", in_place: bool = True, limit: int = ONE_TASK) -> DataFrame:
    """The whole table in one task, updating one array in place or writing a second one (for tables of one block)."""
    import pyarrow as pa

    if ptr.limit(limit + 1).count() > limit:
        raise ValueError(f"more than {limit} pointers don't fit in one task")

    def run(table):
        ids, p = table["id"].to_numpy(), table[name].to_numpy()
        return pa.table({"id": ids, name: double(ids, p, in_place)[0]})

    return ptr.select("id", name, F.lit("one").alias("_one")).groupBy("_one").applyInArrow(run, f"id long, {name} long")


def trace(ptr: DataFrame, seeds: DataFrame, name: str = "ptr") -> DataFrame:
    """(seed, path): the ids on the way of each seed along (id, ptr), the seed first and the fixed point last."""
    step = ptr.select(F.col("id").alias("_i"), F.col(name).alias("_p"))
    live = cut(seeds.select(F.col("id").alias("seed"), F.array("id").alias("path")))
    done = None
    while True:
        last = F.element_at("path", -1)
        moved = fresh(live.join(step, last == F.col("_i"), "left").withColumn("_end", F.coalesce(F.col("_p"), last) == last))
        ended = moved.where("_end").select("seed", "path")
        done = ended if done is None else done.unionByName(ended)
        live = moved.where("not _end").select("seed", F.array_append("path", F.col("_p")).alias("path"))
        if live.isEmpty():
            return done


def extrema(ptr: DataFrame, name: str = "ptr") -> DataFrame:
    return ptr.where(F.col("id") == F.col(name)).select("id")

