"""Connected components of a feature mask: every masked vertex gets the largest (or smallest) id of its component.

Blocks are solved by hooking and pointer doubling on ids alone; labels that meet at a ghost are paired, and the pairs are
contracted.  This is exact for any tiling.  The once-only form (`stitch="once"`, `exchange="pointer"`), which attaches each root
once and exchanges pointers, is kept to measure how often it leaves components apart.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fieldseg.functions.grid import Blocks, GridSpec
from fieldseg.model import OUTSIDE, both_directions, induced
from fieldseg.operators import exchange as ex
from fieldseg.operators.contraction import contract_components
from fieldseg.operators.kernels import GridNeighbours, compress_local, local_components, union_find
from fieldseg.operators.order import numbered
from fieldseg.runtime import cut

#: Pairs of labels that the driver may solve by union-find.
DRIVER_PAIRS = 2_000_000


def quantile_value(df: DataFrame, quantile: float, by: str = "f") -> float | None:
    """The quantile of the values with interpolation between the two nearest, from positions in a range shuffle; null values don't count."""
    own = numbered(df.where(F.col(by).isNotNull()).select(F.col(by).alias("v"), F.monotonically_increasing_id().alias("tie")), ["v", "tie"], "at")
    n = own.count()
    if not n:
        return None
    at = (n - 1) * quantile
    lo, hi = math.floor(at), math.ceil(at)
    found = {r.at: r.v for r in own.where(F.col("at").isin(lo, hi)).select("at", "v").collect()}
    return float(found[lo]) if lo == hi else (hi - at) * found[lo] + (at - lo) * found[hi]


def mask(df: DataFrame, predicate: str | Column | None = None, above: float | None = None, below: float | None = None, between: tuple[float, float] | None = None, quantile: float | None = None, normalised: bool = False, closed: bool = False, by: str = "f", name: str = "m") -> DataFrame:
    """`df` with a boolean column: a predicate, or thresholds on the value, on its min-max scale (`normalised`) or its quantiles.

    Thresholds are strict unless `closed`.  `quantile` keeps the values above the given quantile.
    """
    v = F.col(by)
    if predicate is not None:
        return df.withColumn(name, F.expr(predicate) if isinstance(predicate, str) else predicate)
    if quantile is not None:
        above, normalised = quantile_value(df, quantile, by), False
    if normalised:
        lo, hi = df.agg(F.min(by), F.max(by)).first()
        v = (v - F.lit(lo)).cast("double") / F.lit(float(hi - lo) or 1.0)
    ok = F.lit(True)
    if above is not None:
        ok &= (v >= above) if closed else (v > above)
    if below is not None:
        ok &= (v <= below) if closed else (v < below)
    if between is not None:
        ok &= v.between(*between)
    return df.withColumn(name, ok)


def _block_labels(vertices: DataFrame, blocks: Blocks, winner: str, limit: int | None) -> DataFrame:
    """(id, is_ghost, label): labels of the components inside each block, for owned vertices and ghosts."""
    neighbours = GridNeighbours(blocks.spec.dims, blocks.spec.stencil())

    def solve(table):
        ids = table["id"].to_numpy()
        order = np.argsort(ids)
        ids, ghost = ids[order], table["is_ghost"].to_numpy(zero_copy_only=False)[order]
        d, _ = local_components(ids, neighbours, limit)
        label = ids[d]
        if winner == "min":
            least = np.full(len(ids), np.iinfo(np.int64).max)
            np.minimum.at(least, d, ids)
            label = least[d]
        return pa.table({"id": ids, "is_ghost": ghost, "label": label})

    return blocks.halo(vertices.select("id")).groupBy("block").applyInArrow(solve, "id long, is_ghost boolean, label long")


def cross_pairs(local: DataFrame) -> DataFrame:
    """(a, b): distinct pairs of different labels that a ghost and its owner's copy carry."""
    ghost = local.where("is_ghost").select("id", F.col("label").alias("a"))
    own = local.where("not is_ghost").select("id", F.col("label").alias("b"))
    return ghost.join(own, "id").where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def solve_roots(pairs: DataFrame, winner: str = "max", driver_pairs: int = DRIVER_PAIRS) -> DataFrame:
    """(id, label) for the labels in pairs: on the driver where they are few, else by distributed contraction."""
    pairs = cut(pairs)
    if pairs.limit(driver_pairs + 1).count() > driver_pairs:
        return contract_components(pairs, "a", "b", winner)
    t, sign = pairs.toArrow(), 1 if winner == "max" else -1
    found = union_find(sign * t["a"].to_numpy(), sign * t["b"].to_numpy())
    table = pa.table({"id": pa.array([sign * k for k in found], pa.int64()), "label": pa.array([sign * v for v in found.values()], pa.int64())})
    return pairs.sparkSession.createDataFrame(table, "id long, label long")


def relabel(labels: DataFrame, roots: DataFrame) -> DataFrame:
    final = roots.select(F.col("id").alias("_fs_id"), F.col("label").alias("_fs_label"))
    return labels.join(final, F.col("label") == F.col("_fs_id"), "left").select("id", F.coalesce("_fs_label", "label").alias("label"))


def finish(df: DataFrame, labels: DataFrame, implicit: bool) -> DataFrame:
    """Labels of all vertices, -1 outside the mask, if implicit; else of the masked ones."""
    if not implicit:
        return labels
    return labels.unionByName(df.where("not coalesce(m, false)").select("id", F.lit(OUTSIDE).cast("long").alias("label")))


def connected(df: DataFrame, spec: GridSpec, mask: str = "m", blocks: Blocks | int | None = None, implicit: bool = True, stitch: str = "fixpoint", exchange: str = "label_pairs", winner: str = "max", driver_pairs: int = DRIVER_PAIRS) -> DataFrame:
    """(id, label) on a grid for (id, m); a null mask is outside.  By default there are as few blocks as memory allows."""
    tiles = Blocks.of(spec, blocks)
    df = df.select("id", F.col(mask).alias("m"))
    inside = df.where("m")
    if stitch == "once":
        return finish(df, _printed(inside, tiles, exchange), implicit)
    if stitch != "fixpoint":
        raise ValueError(f"unknown stitch {stitch}")
    local = _block_labels(inside, tiles, winner, None)
    if tiles.n == 1:
        return finish(df, local.select("id", "label"), implicit)
    local = cut(local)
    labels = local.where("not is_ghost").select("id", "label")
    return finish(df, relabel(labels, solve_roots(cross_pairs(local), winner, driver_pairs)), implicit)


def _printed(inside: DataFrame, blocks: Blocks, exchange: str) -> DataFrame:
    """One attachment of each root and one exchange of pointers (or of label pairs)."""
    neighbours = GridNeighbours(blocks.spec.dims, blocks.spec.stencil())

    def solve(table):
        ids = table["id"].to_numpy()
        order = np.argsort(ids)
        ids, ghost, shared = ids[order], table["is_ghost"].to_numpy(zero_copy_only=False)[order], table["shared"].to_numpy(zero_copy_only=False)[order]
        d = np.arange(len(ids))
        pairs = list(neighbours(ids))
        for src, dst in pairs:
            own = ~ghost[src]
            np.maximum.at(d, src[own], dst[own])
        compress_local(d)
        grown = d.copy()
        for src, dst in pairs:
            own = ~ghost[src] & ~ghost[d[src]] & (d[dst] > d[src])
            np.maximum.at(grown, d[src[own]], d[dst[own]])
        compress_local(grown)
        return pa.table({"id": ids[~ghost], "label": ids[grown][~ghost], "shared": shared[~ghost]})

    halo = blocks.halo(inside.select("id")).withColumn("shared", F.size(blocks.needed_by()) > 1 if blocks.n > 1 else F.lit(False))
    local = halo.groupBy("block").applyInArrow(solve, "id long, label long, shared boolean")
    if blocks.n == 1:
        return local.select("id", "label")
    local = cut(local)
    if exchange != "pointer":
        raise ValueError("the once-only form exchanges pointers")
    ends, _ = ex.resolve(local.where("shared").select("id", "label"), ["label"])
    return ex.substitute(local.select("id", "label"), ends, ["label"])


def connected_graph(vertices: DataFrame, edges: DataFrame, winner: str = "max", local_first: bool = False) -> DataFrame:
    """(id, label) of the components of an explicit graph; vertices without an edge are their own.

    With `local_first`, each task merges the edges it holds before the first shuffle.
    """
    e = edges.select("src", "dst")
    if local_first:
        e = locally_merged(e, winner)
    found = contract_components(e, winner=winner).select(F.col("id").alias("_fs_id"), "label")
    return vertices.select("id").join(found, F.col("id") == F.col("_fs_id"), "left").select("id", F.coalesce("label", "id").alias("label"))


def locally_merged(edges: DataFrame, winner: str = "max") -> DataFrame:
    """Star edges of the components of each task's batches of edges (the same components with fewer edges)."""
    sign = 1 if winner == "max" else -1

    def run(batches):
        for rb in batches:
            found = union_find(sign * rb.column(0).to_numpy(), sign * rb.column(1).to_numpy())
            rows = [(sign * k, sign * v) for k, v in found.items() if k != v]
            cols = list(zip(*rows)) if rows else [(), ()]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], ["src", "dst"])

    return edges.where("src is not null and dst is not null").mapInArrow(run, "src long, dst long")


def connected_explicit(df: DataFrame, spec: GridSpec, mask: str = "m", winner: str = "max") -> DataFrame:
    """The same labels by extracting the masked vertices and their edges first; unmasked vertices are left out."""
    inside = df.where(F.col(mask)).select("id")
    return connected_graph(inside, spec.edges(inside), winner)


def extract(labels: DataFrame) -> DataFrame:
    """The labelled vertices; a label 0 is a label."""
    return labels.where(F.col("label") >= 0)


def stitch_once(labels: DataFrame, edges: DataFrame, winner: str = "max") -> DataFrame:
    """Each label moved to the best label next to it, once (id, label)."""
    pick, better = (F.max, F.greatest) if winner == "max" else (F.min, F.least)
    l1 = labels.select(F.col("id").alias("src"), F.col("label").alias("a"))
    l2 = labels.select(F.col("id").alias("dst"), F.col("label").alias("b"))
    near = both_directions(edges).join(l1, "src").join(l2, "dst").where("a <> b").groupBy(F.col("a").alias("_fs_id")).agg(pick("b").alias("_fs_best"))
    out = labels.join(near, F.col("label") == F.col("_fs_id"), "left")
    return out.select("id", F.coalesce(better("label", "_fs_best"), "label").alias("label"))


def induced_graph(vertices: DataFrame, edges: DataFrame, mask: str = "m") -> tuple[DataFrame, DataFrame]:
    inside = vertices.where(F.col(mask)).select("id")
    return inside, induced(edges, inside)
