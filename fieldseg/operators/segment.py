"""Segmentation by steepest paths: every vertex to the maximum and the minimum it reaches.

Blocks are solved each by one Arrow kernel (both directions at once), their boundary pointers are resolved by one exchange, and
one sweep substitutes the ends.  Values are compared as (value, id), so no order field is needed.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fieldseg.functions.grid import Blocks, GridSpec
from fieldseg.operators import exchange as ex
from fieldseg.operators.kernels import GridNeighbours, compress_local, steepest_local
from fieldseg.operators.order import numbered
from fieldseg.operators.pointers import compress, steepest, trace
from fieldseg.runtime import cut

NAMES = {"up": "max_id", "down": "min_id"}


def solver(spec: GridSpec, directions: tuple[str, ...] = ("up", "down"), in_place: bool = True, precompress: bool = False):
    """The kernel of one block: its halo table (id, f, is_ghost, shared) to (id, max_id, min_id, shared, rounds)."""
    neighbours = GridNeighbours(spec.dims, spec.stencil())
    names = [NAMES[d] for d in directions]

    def solve(table):
        ids = table["id"].to_numpy()
        order = np.argsort(ids)
        ids, f, ghost = ids[order], table["f"].to_numpy()[order], table["is_ghost"].to_numpy(zero_copy_only=False)[order]
        rank = np.empty(len(ids), np.int64)
        rank[np.lexsort((ids, f))] = np.arange(len(ids))
        own, cols, rounds = ~ghost, {}, 0
        leaves = np.zeros(len(ids), bool)
        for d, name in zip(directions, names):
            p = steepest_local(ids, rank, neighbours, ghost, d == "up")
            rounds = max(rounds, compress_local(p, in_place))
            cols[name] = ids[p][own]
            leaves |= ghost[p]
        shared = table["shared"].to_numpy(zero_copy_only=False)[order]
        if precompress:
            # an end inside the block must still be known where it isn't the vertex itself
            for name in names:
                leaves[own] |= cols[name] != ids[own]
            shared = shared & leaves
        return pa.table({"id": ids[own], **cols, "shared": shared[own], "rounds": np.full(int(own.sum()), rounds)})

    return solve


def block_tables(df: DataFrame, blocks: Blocks, by: str = "f") -> DataFrame:
    """(id, f, block, is_ghost, shared): what the blocks hold."""
    halo = blocks.halo(df.select("id", F.col(by).alias("f")))
    return halo.withColumn("shared", F.size(blocks.needed_by()) > 1 if blocks.n > 1 else F.lit(False))


def block_pointers(df: DataFrame, blocks: Blocks, directions: tuple[str, ...] = ("up", "down"), by: str = "f", in_place: bool = True, precompress: bool = False) -> DataFrame:
    """(id, max_id, min_id, shared, rounds) of the owned vertices after the local compression.

    Pointers end at an extremum of the block or at a ghost.  `shared` marks vertices that other blocks hold as ghosts; with
    `precompress`, only those whose pointer leaves the block (others are ends for whoever points there).
    """
    names = [NAMES[d] for d in directions]
    schema = "id long, " + ", ".join(f"{n} long" for n in names) + ", shared boolean, rounds long"
    return block_tables(df, blocks, by).groupBy("block").applyInArrow(solver(blocks.spec, directions, in_place, precompress), schema)


def blockwise(df: DataFrame, spec: GridSpec, blocks: Blocks | int | None = None, directions: tuple[str, ...] = ("up", "down"), exchange: str = "auto", precompress: bool = False, by: str = "f", in_place: bool = True) -> DataFrame:
    """(id, max_id, min_id) of every vertex, whatever the number of blocks; by default as few as memory allows."""
    tiles = Blocks.of(spec, blocks)
    names = [NAMES[d] for d in directions]
    local = block_pointers(df, tiles, directions, by, in_place, precompress)
    if tiles.n == 1:
        return local.select("id", *names)
    local = cut(local)
    ends, _ = ex.resolve(local.where("shared").select("id", *names), names, exchange)
    return ex.substitute(local.select("id", *names), ends, names)


def descending(df: DataFrame, spec: GridSpec, blocks: Blocks | int | None = None, **options) -> DataFrame:
    """(id, max_id)."""
    return blockwise(df, spec, blocks, ("up",), **options)


def ascending(df: DataFrame, spec: GridSpec, blocks: Blocks | int | None = None, **options) -> DataFrame:
    """(id, min_id)."""
    return blockwise(df, spec, blocks, ("down",), **options)


def two_sided(df: DataFrame, spec: GridSpec, blocks: Blocks | int | None = None, **options) -> DataFrame:
    """(id, max_id, min_id, seg); `seg` numbers the pairs from 0 in the order of (max_id, min_id)."""
    both = cut(blockwise(df, spec, blocks, ("up", "down"), **options))
    pairs = numbered(both.select("max_id", "min_id").distinct(), ["max_id", "min_id"], "seg")
    return both.join(pairs, ["max_id", "min_id"]).select("id", "max_id", "min_id", "seg")


def graph_segmentation(df: DataFrame, edges: DataFrame, direction: str = "up", by: str = "f") -> DataFrame:
    """(id, max_id) or (id, min_id) on an explicit graph, by doubling over the whole table."""
    name = NAMES[direction]
    ptr = steepest(df, edges=edges, direction=direction, by=by, name=name)
    return compress(ptr, name=name)[0]


def integral_lines(df: DataFrame, spec: GridSpec, seeds: DataFrame, direction: str = "up") -> DataFrame:
    """(seed, path) of the steepest paths from some vertices."""
    return trace(cut(steepest(df, spec=spec, direction=direction)), seeds)
