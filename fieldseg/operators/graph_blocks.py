"""Blocks of explicit graphs: any assignment of vertices to blocks, one layer of ghosts, and the block kernels over them."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fieldseg.operators import exchange as ex
from fieldseg.operators.components import cross_pairs, relabel, solve_roots
from fieldseg.operators.kernels import EdgeNeighbours, compress_local, local_components, steepest_local
from fieldseg.runtime import cut


def by_hash(vertices: DataFrame, n_blocks: int) -> DataFrame:
    """`vertices` with `block` by a hash of the id."""
    return vertices.withColumn("block", F.pmod(F.xxhash64("id"), F.lit(n_blocks)))


def halo_graph(vertices: DataFrame, edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Ghost layer of (id, block, ...) under (src, dst): (id, block, is_ghost, shared, ...) and (block, src, dst).

    An edge belongs to the blocks of both its ends; its other end is a ghost there.  `shared` marks vertices that another block
    holds.  Edges between two ghosts of a block aren't kept, as neither of their ends is solved there.
    """
    own = vertices.select("id", "block")
    e = edges.select("src", "dst").where("src <> dst")
    e = e.join(own.select(F.col("id").alias("src"), F.col("block").alias("bs")), "src").join(own.select(F.col("id").alias("dst"), F.col("block").alias("bd")), "dst")
    local = e.select(F.explode(F.array_distinct(F.array("bs", "bd"))).alias("block"), "src", "dst")
    crossing = e.where("bs <> bd")
    ghosts = crossing.select(F.col("src").alias("id"), F.col("bd").alias("needed_by")).union(crossing.select(F.col("dst").alias("id"), F.col("bs").alias("needed_by"))).distinct()
    shared = ghosts.select("id").distinct().withColumn("shared", F.lit(True))
    owned = vertices.join(shared, "id", "left").withColumns({"shared": F.coalesce("shared", F.lit(False)), "is_ghost": F.lit(False)})
    others = vertices.drop("block").join(ghosts.withColumnRenamed("needed_by", "block"), "id").withColumns({"shared": F.lit(True), "is_ghost": F.lit(True)})
    return owned.unionByName(others), local


def requests(halo: DataFrame, vertices: DataFrame) -> DataFrame:
    """(owner, needed_by, ids): what each block asks of each owner; blocks know the owners, owners don't know who asks."""
    g = halo.where("is_ghost").select("id", F.col("block").alias("needed_by"))
    return g.join(vertices.select("id", F.col("block").alias("owner")), "id").groupBy("owner", "needed_by").agg(F.sort_array(F.collect_list("id")).alias("ids"))


def _solve(halo: DataFrame, edges: DataFrame, kernel, schema: str) -> DataFrame:
    return halo.groupBy("block").cogroup(edges.groupBy("block")).applyInArrow(kernel, schema)


def local_pointers(halo: DataFrame, edges: DataFrame, by: str = "f") -> DataFrame:
    """(id, max_id, min_id, shared) of the owned vertices after local compression; pointers end at an extremum or a ghost."""

    def solve(left, right):
        ids = left["id"].to_numpy()
        order = np.argsort(ids)
        ids, f, ghost, shared = (left[c].to_numpy()[order] for c in ("id", by, "is_ghost", "shared"))
        near = EdgeNeighbours(right["src"].to_numpy(), right["dst"].to_numpy())
        rank = np.empty(len(ids), np.int64)
        rank[np.lexsort((ids, f))] = np.arange(len(ids))
        cols = {}
        for name, up in (("max_id", True), ("min_id", False)):
            p = steepest_local(ids, rank, near, ghost.astype(bool), up)
            compress_local(p)
            cols[name] = ids[p][~ghost.astype(bool)]
        own = ~ghost.astype(bool)
        return pa.table({"id": ids[own], **cols, "shared": shared[own]})

    return _solve(halo, edges, solve, "id long, max_id long, min_id long, shared boolean")


def segmentation(vertices: DataFrame, edges: DataFrame, by: str = "f", exchange: str = "auto") -> DataFrame:
    """(id, max_id, min_id) for vertices (id, f, block)."""
    halo, local_edges = halo_graph(vertices, edges)
    local = cut(local_pointers(halo, local_edges, by))
    names = ["max_id", "min_id"]
    ends, _ = ex.resolve(local.where("shared").select("id", *names), names, exchange)
    return ex.substitute(local.select("id", *names), ends, names)


def components(vertices: DataFrame, edges: DataFrame, winner: str = "max") -> DataFrame:
    """(id, label) for vertices (id, block): components inside blocks, then of the labels that meet at ghosts."""
    halo, local_edges = halo_graph(vertices.select("id", "block"), edges)

    def solve(left, right):
        ids = left["id"].to_numpy()
        order = np.argsort(ids)
        ids, ghost = ids[order], left["is_ghost"].to_numpy()[order]
        d, _ = local_components(ids, EdgeNeighbours(right["src"].to_numpy(), right["dst"].to_numpy()))
        label = ids[d]
        if winner == "min":
            least = np.full(len(ids), np.iinfo(np.int64).max)
            np.minimum.at(least, d, ids)
            label = least[d]
        return pa.table({"id": ids, "is_ghost": ghost, "label": label})

    local = cut(_solve(halo, local_edges, solve, "id long, is_ghost boolean, label long"))
    return relabel(local.where("not is_ghost").select("id", "label"), solve_roots(cross_pairs(local), winner))
