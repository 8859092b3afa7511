"""Critical points from the links of vertices on a grid.

A vertex's lower and upper link are bit masks over its stencil; the numbers of their components come from a table over all
masks, which has 4, 64 or 16,384 rows (1, 2 or 3 dimensions) and is made by rule.  On the border the link is what is left of it.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fieldseg.functions.grid import GridSpec
from fieldseg.operators.pointers import trace
from fieldseg.runtime import cut


def link_table(spec: GridSpec) -> np.ndarray:
    """(mask, components, euler): of the part of the link whose stencil steps are set in the mask.

    Steps are joined in the link if their difference is a step.  `euler` counts vertices less edges plus triangles.
    """
    steps = spec.stencil()
    if len(steps) > 14:
        raise ValueError("tables of links exist for simplicial and axis grids")
    k, known = len(steps), {s: i for i, s in enumerate(steps)}
    joined = [[tuple(b - a for a, b in zip(s, t)) in known for t in steps] for s in steps]
    masks = np.arange(1 << k)
    near = [sum(1 << j for j in range(k) if joined[i][j]) for i in range(k)]
    # the component of the lowest bit is grown until it stands still, and taken away, for all masks at once
    left, count = masks.copy(), np.zeros(1 << k, np.int64)
    while left.any():
        seen = left & -left
        while True:
            grown = seen.copy()
            for i in range(k):
                grown |= np.where(seen >> i & 1 == 1, near[i], 0)
            grown &= left
            if (grown == seen).all():
                break
            seen = grown
        count += left > 0
        left &= ~seen
    euler = sum((masks >> i & 1) for i in range(k))
    for i in range(k):
        for j in range(i):
            if joined[i][j]:
                euler = euler - ((masks >> i & 1) & (masks >> j & 1))
                for m in range(j):
                    if joined[i][m] and joined[j][m]:
                        euler = euler + ((masks >> i & 1) & (masks >> j & 1) & (masks >> m & 1))
    return np.stack([masks, count, euler], axis=1)


def links(df: DataFrame, spec: GridSpec, by: str = "f") -> DataFrame:
    """(id, lower, upper): bit masks over the stencil.  One shuffle: vertices send their values to their neighbours."""
    steps = spec.stencil()
    place = {s: i for i, s in enumerate(steps)}
    value = F.struct(F.col(by).alias("v"), F.col("id").alias("i"))
    sent = [F.struct(F.col("id").alias("to"), F.lit(-1).alias("bit"))]
    for s in steps:
        back = place[tuple(-x for x in s)]
        sent.append(F.when(spec.inside(s), F.struct((F.col("id") + F.lit(spec.offset(s))).alias("to"), F.lit(back).alias("bit"))))
    rows = df.select(value.alias("v"), F.explode(F.array_compact(F.array(*sent))).alias("s")).select("s.to", "s.bit", "v")
    # a star has as many rows as steps and one at most
    star = rows.groupBy("to").agg(F.collect_list(F.struct("bit", "v")).alias("star"), F.max(F.when(F.col("bit") < 0, F.col("v"))).alias("own")).where("own is not null")
    bits = lambda side: F.aggregate(F.filter("star", lambda x: (x["bit"] >= 0) & side(x["v"], F.col("own"))), F.lit(0), lambda a, x: a.bitwiseOR(F.call_function("shiftleft", F.lit(1), x["bit"])))
    return star.select(F.col("to").alias("id"), bits(lambda a, b: a < b).alias("lower"), bits(lambda a, b: a > b).alias("upper"))


def classify(df: DataFrame, spec: GridSpec, by: str = "f") -> DataFrame:
    """(id, kind, n_lower, n_upper, degenerate, chi): one row for each vertex; chi is 1 less the Euler number of the lower link."""
    t = link_table(spec)
    table = df.sparkSession.createDataFrame(pa.table({"mask": t[:, 0], "n": t[:, 1], "e": t[:, 2]}), "mask long, n long, e long")
    side = lambda c: F.broadcast(table.select(F.col("mask").alias(c), F.col("n").alias(f"n_{c}"), F.col("e").alias(f"e_{c}")))
    x = links(df, spec, by).select("id", F.col("lower").cast("long").alias("lower"), F.col("upper").cast("long").alias("upper")).join(side("lower"), "lower").join(side("upper"), "upper")
    top = f"{spec.d - 1}-saddle"
    kind = (
        F.when(F.col("n_lower") == 0, "minimum").when(F.col("n_upper") == 0, "maximum").when((F.col("n_lower") == 1) & (F.col("n_upper") == 1), "regular")
        .when(F.col("n_lower") >= 2, "1-saddle").otherwise(top)
    )
    return x.select("id", kind.alias("kind"), "n_lower", "n_upper", ((F.col("n_lower") > 2) | (F.col("n_upper") > 2)).alias("degenerate"), (1 - F.col("e_lower")).alias("chi"))


def level_set(df: DataFrame, w, side: str = "below", by: str = "f") -> DataFrame:
    return df.where(F.col(by) < w if side == "below" else F.col(by) > w)


def separatrices(df: DataFrame, spec: GridSpec, ptr_up: DataFrame, ptr_down: DataFrame, by: str = "f") -> DataFrame:
    """(saddle, side, seed, path): paths from the steepest neighbour in each component of each saddle's links.

    A saddle has two or more components on a side; each sends one path, from its largest (or smallest) member.
    """
    steps = spec.stencil()
    known = set(steps)
    near = [sum(1 << j for j, t in enumerate(steps) if tuple(b - a for a, b in zip(s, t)) in known) for s in steps]
    saddles = classify(df, spec, by).where((F.col("n_lower") > 1) | (F.col("n_upper") > 1)).select("id")
    masks = links(df, spec, by).join(saddles, "id")
    around = F.explode(F.array(*(F.struct(F.lit(i).alias("bit"), F.lit(spec.offset(s)).cast("long").alias("by")) for i, s in enumerate(steps)))).alias("s")
    reach = masks.select("id", "lower", "upper", around).select("id", "lower", "upper", "s.bit", (F.col("id") + F.col("s.by")).alias("n"))
    reach = reach.where(((F.col("lower").bitwiseOR(F.col("upper"))).bitwiseAND(F.expr("shiftleft(1, bit)"))) != 0)
    value = df.select(F.col("id").alias("n"), F.col(by).alias("v"))
    rows = reach.join(value, "n").groupBy("id", "lower", "upper").agg(F.collect_list(F.struct("v", "n", "bit")).alias("star"))

    def pick(batches):
        for rb in batches:
            out = []
            for saddle, lower, upper, star in zip(*(c.to_pylist() for c in rb.columns)):
                for side, mask in (("down", lower), ("up", upper)):
                    left, groups = mask, []
                    while left:
                        seen, front = 0, left & -left
                        while front:
                            seen |= front
                            front = sum_bits(near, front) & left & ~seen
                        groups.append(seen)
                        left &= ~seen
                    if len(groups) > 1:
                        for g in groups:
                            mine = [(x["v"], x["n"]) for x in star if g >> x["bit"] & 1]
                            out.append((saddle, side, (max if side == "up" else min)(mine)[1]))
            cols = list(zip(*out)) if out else [(), (), ()]
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.string()), pa.array(cols[2], pa.int64())], ["saddle", "side", "seed"])

    seeds = cut(rows.mapInArrow(pick, "saddle long, side string, seed long"))
    out = None
    for side, ptr in (("up", ptr_up), ("down", ptr_down)):
        mine = seeds.where(F.col("side") == side)
        paths = trace(ptr, mine.select(F.col("seed").alias("id")).distinct())
        part = mine.join(paths, "seed").select("saddle", "side", "seed", "path")
        out = part if out is None else out.unionByName(part)
    return out


def sum_bits(near: list[int], front: int) -> int:
    out, i = 0, 0
    while front:
        if front & 1:
            out |= near[i]
        front >>= 1
        i += 1
    return out
