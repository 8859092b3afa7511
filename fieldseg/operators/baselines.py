"""Methods that the pointer-doubling ones are compared with."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fieldseg.functions.grid import Blocks, GridSpec
from fieldseg.model import both_directions
from fieldseg.operators import components as comp
from fieldseg.operators.contraction import contract_components
from fieldseg.operators.kernels import GridNeighbours, breadth_first, union_find
from fieldseg.runtime import cut, fresh

#: Edges that a baseline may bring to the driver or to one task.
ONE_PROCESS = 5_000_000
#: Points of a group of the nearest-neighbour search.
CELL_POINTS = 20_000


class TooLarge(RuntimeError):
    """A baseline that needs everything in one process, and doesn't fit."""


def to_unstructured(df: DataFrame, spec: GridSpec) -> DataFrame:
    """(cell_id, verts): the simplices of the grid all of whose corners are in `df` (id)."""
    shapes = spec.cells()
    corner = F.lit(True)
    for a in range(spec.d):
        corner &= (spec.coord(a) <= spec.dims[a] - 2) if spec.dims[a] > 1 else F.lit(False)
    kinds = F.array(*(F.struct(F.lit(k).alias("k"), F.array(*(F.col("id") + F.lit(spec.offset(c)) for c in shape)).alias("verts")) for k, shape in enumerate(shapes)))
    cells = df.where(corner).select("id", F.explode(kinds).alias("c")).select((F.col("id") * len(shapes) + F.col("c.k")).alias("cell_id"), "c.verts")
    corners = cells.select("cell_id", F.explode("verts").alias("v")).join(df.select(F.col("id").alias("v")), "v", "left_semi")
    whole = corners.groupBy("cell_id").count().where(F.col("count") == spec.d + 1).select("cell_id")
    return cells.join(whole, "cell_id", "left_semi")


def wave_filter(df: DataFrame, spec: GridSpec, mask: str = "m", blocks: Blocks | int = 4) -> DataFrame:
    """(id, label) of masked vertices: extraction, waves in each block, a region graph that every block gets, relabelling."""
    tiles = blocks if isinstance(blocks, Blocks) else Blocks.about(spec, blocks)
    neighbours = GridNeighbours(spec.dims, spec.stencil())
    inside = df.where(F.col(mask)).select("id")

    def waves(table):
        ids = table["id"].to_numpy()
        order = np.argsort(ids)
        ids, ghost = ids[order], table["is_ghost"].to_numpy(zero_copy_only=False)[order]
        region = breadth_first(ids, neighbours)
        most = np.zeros(int(region.max()) + 1, np.int64)
        np.maximum.at(most, region, ids)
        return pa.table({"id": ids, "is_ghost": ghost, "label": most[region]})

    local = cut(tiles.halo(inside).groupBy("block").applyInArrow(waves, "id long, is_ghost boolean, label long"))
    labels = local.where("not is_ghost").select("id", "label")
    if tiles.n == 1:
        return labels
    pairs = comp.cross_pairs(local)
    if pairs.limit(ONE_PROCESS + 1).count() > ONE_PROCESS:
        raise TooLarge("the region graph doesn't fit in every block")
    return comp.relabel(labels, F.broadcast(comp.solve_roots(pairs, driver_pairs=ONE_PROCESS)))


def label_propagation(vertices: DataFrame, edges: DataFrame, max_rounds: int = 100_000) -> tuple[DataFrame, int]:
    """(id, label) and the rounds: every vertex takes the largest label around it until none changes (as many as the diameter)."""
    e = cut(both_directions(edges))
    state, rounds = cut(vertices.select("id", F.col("id").alias("label"))), 0
    for _ in range(max_rounds):
        best = e.join(state.select(F.col("id").alias("dst"), F.col("label").alias("seen")), "dst").groupBy("src").agg(F.max("seen").alias("seen"))
        moved = fresh(state.join(best, F.col("id") == F.col("src"), "left").select("id", "label", F.greatest("label", F.coalesce("seen", "label")).alias("now")))
        if moved.where("now > label").isEmpty():
            return state, rounds
        state, rounds = moved.select("id", F.col("now").alias("label")), rounds + 1
    raise RuntimeError("labels did not settle")


def hook_compress(vertices: DataFrame, edges: DataFrame) -> DataFrame:
    """(id, label) by hooking and contraction of the plain edge list."""
    return comp.connected_graph(vertices, edges)


def union_find_driver(vertices: DataFrame, edges: DataFrame, limit: int = ONE_PROCESS) -> DataFrame:
    """(id, label) by sequential union-find over all edges in the driver."""
    if edges.limit(limit + 1).count() > limit:
        raise TooLarge("the edges don't fit in one process")
    t = edges.select("src", "dst").toArrow()
    found = union_find(t["src"].to_numpy(), t["dst"].to_numpy())
    table = pa.table({"_fs_id": pa.array(list(found), pa.int64()), "label": pa.array(list(found.values()), pa.int64())})
    labels = vertices.sparkSession.createDataFrame(table, "_fs_id long, label long")
    return vertices.select("id").join(labels, F.col("id") == F.col("_fs_id"), "left").select("id", F.coalesce("label", "id").alias("label"))


def tree_merge(vertices: DataFrame, edges: DataFrame, parts: int = 8, fan_in: int = 2) -> DataFrame:
    """(id, label): parts of the edges are solved apart and merged `fan_in` at a time, up to one process."""

    def solve(table):
        found = union_find(table["src"].to_numpy(), table["dst"].to_numpy())
        rows = [(table["part"][0].as_py() // fan_in, k, v) for k, v in found.items()]
        cols = list(zip(*rows)) if rows else [(), (), ()]
        return pa.table({n: pa.array(c, pa.int64()) for n, c in zip(("part", "src", "dst"), cols)})

    state = edges.select(F.pmod(F.xxhash64("src", "dst"), F.lit(parts)).alias("part"), "src", "dst")
    left = parts
    while True:
        state = state.groupBy("part").applyInArrow(solve, "part long, src long, dst long")
        if left <= 1:
            break
        left = -(-left // fan_in)
    found = state.select(F.col("src").alias("_fs_id"), F.col("dst").alias("label"))
    return vertices.select("id").join(found, F.col("id") == F.col("_fs_id"), "left").select("id", F.coalesce("label", "id").alias("label"))


def any_representative(vertices: DataFrame, edges: DataFrame, seed: int = 1) -> DataFrame:
    """(id, label) with an arbitrary member of each component as label: the one whose hash is smallest."""
    code = lambda c: F.xxhash64(F.lit(seed), F.col(c))
    names = vertices.select("id", code("id").alias("code"))
    found = contract_components(edges.select(code("src").alias("src"), code("dst").alias("dst")))
    coded = names.join(found.select(F.col("id").alias("code"), F.col("label").alias("best")), "code", "left").select("id", F.coalesce("best", "code").alias("best"))
    return coded.join(names.select(F.col("id").alias("label"), F.col("code").alias("best")), "best").select("id", "label")


def sampled_components(vertices: DataFrame, edges: DataFrame, fraction: float = 0.2, seed: int = 1) -> DataFrame:
    """(id, label): a sample of the edges first, then those that still join different labels."""
    e = edges.select("src", "dst", (F.pmod(F.xxhash64(F.lit(seed), "src", "dst"), F.lit(10_000)) < int(fraction * 10_000)).alias("first"))
    found = cut(comp.connected_graph(vertices, e.where("first")))
    a = found.select(F.col("id").alias("src"), F.col("label").alias("a"))
    b = found.select(F.col("id").alias("dst"), F.col("label").alias("b"))
    rest = e.where("not first").join(a, "src").join(b, "dst").where("a <> b").select(F.col("a").alias("src"), F.col("b").alias("dst"))
    return comp.relabel(found, contract_components(rest, winner="max"))


def grow_from_extrema(ptr: DataFrame, name: str = "ptr", max_rounds: int = 1 << 20) -> tuple[DataFrame, int]:
    """(id, ptr at its end) and the rounds: segments grow from their extrema against the pointers, one step a round."""
    back = cut(ptr.select("id", F.col(name).alias("p")).where(F.col("id") != F.col("p")))
    front = ptr.where(F.col("id") == F.col(name)).select("id", F.col("id").alias("ext"))
    out, rounds = front, 0
    for _ in range(max_rounds):
        front = fresh(back.join(front.select(F.col("id").alias("p"), "ext"), "p").select("id", "ext"))
        if front.isEmpty():
            return out.select("id", F.col("ext").alias(name)), rounds
        out, rounds = out.unionByName(front), rounds + 1
    raise RuntimeError("growth did not end")


def nearest(points: DataFrame, k: int, scale: int = 1000, cells: int | None = None) -> DataFrame:
    """(id, nbr, sim): the k most similar other points by the exact product of quantised components, ties to the smaller id.

    Points are dealt to `cells` groups, by default so many that a group has `CELL_POINTS`; each pair of groups is one task with a
    matrix product, whose best k a row are merged.  The work is the square of the points (this is a baseline), and no task holds more than two groups.
    """
    cells = cells or max(4, -(-points.count() // CELL_POINTS))
    q = points.select("id", F.transform("vec", lambda x: F.round(x.cast("double") * scale).cast("long")).alias("v")).withColumn("g", F.pmod(F.xxhash64("id"), F.lit(cells)))
    left = q.select("id", "v", F.explode(F.sequence(F.lit(0), F.lit(cells - 1))).alias("o"), "g").withColumn("q", F.lit(True)).select("id", "v", "q", (F.col("g") * cells + F.col("o")).alias("cell"))
    right = q.select("id", "v", F.explode(F.sequence(F.lit(0), F.lit(cells - 1))).alias("o"), "g").withColumn("q", F.lit(False)).select("id", "v", "q", (F.col("o") * cells + F.col("g")).alias("cell"))

    def best(table):
        ids = table["id"].to_numpy()
        vec = np.array(table["v"].to_pylist(), np.int64)
        asks = table["q"].to_numpy(zero_copy_only=False)
        a, b, ia, ib = vec[asks], vec[~asks], ids[asks], ids[~asks]
        rows = []
        order = np.argsort(ib)
        b, ib = b[order], ib[order]
        for at in range(0, len(a), 512):
            # sums of 64 products below 10^6 are exact in doubles
            sim = (a[at : at + 512].astype(float) @ b.T.astype(float)).astype(np.int64) if len(b) else np.zeros((len(a[at : at + 512]), 0), np.int64)
            for i, s in enumerate(sim):
                pick = [j for j in np.argsort(-s, kind="stable")[: k + 1] if ib[j] != ia[at + i]][:k]
                rows += [(int(ia[at + i]), int(ib[j]), int(s[j])) for j in pick]
        cols = list(zip(*rows)) if rows else [(), (), ()]
        return pa.table({n: pa.array(c, pa.int64()) for n, c in zip(("id", "nbr", "sim"), cols)})

    found = left.unionByName(right).groupBy("cell").applyInArrow(best, "id long, nbr long, sim long")
    top = found.groupBy("id").agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("sim")).alias("s"), "nbr"))), 1, k).alias("top"))
    return top.select("id", F.explode("top").alias("t")).select("id", F.col("t.nbr").alias("nbr"), (-F.col("t.s")).alias("sim"))


def knn_ascent(points: DataFrame, k: int = 8) -> DataFrame:
    """(id, max_id): ascent over the k nearest neighbours by local density (the sum of the k similarities)."""
    from fieldseg.operators.pointers import compress, steepest

    near = cut(nearest(points, k))
    density = near.groupBy("id").agg(F.sum("sim").alias("f"))
    ptr = steepest(density, edges=near.select(F.col("id").alias("src"), F.col("nbr").alias("dst")), name="max_id")
    return compress(ptr, name="max_id")[0]
