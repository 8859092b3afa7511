"""The experiment workloads: each returns a table of timings with the schema of `measures.TIMING`.

Inputs are materialised before the clock starts, so only the method is timed, as in the reference.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from fieldseg.functions.grid import VERTEX_BYTES, Blocks
from fieldseg.operators import baselines, components, pointers, segment
from fieldseg.operators.order import order_field
from fieldseg.plans import measures
from fieldseg.runtime import cut
from fieldseg.sources import fields, graphs, synthetic
from fieldseg.sources.fields import Field

Case = tuple[str, int, Callable[[], DataFrame], int]


def _run(spark: SparkSession, workload: str, cases: list[Case], n: int, repeats: int) -> list[tuple]:
    rows = []
    threads = spark.sparkContext.defaultParallelism
    for method, blocks, make, ghosts in cases:
        for _ in range(repeats):
            seconds, status = measures.attempt(make)
            rows.append((workload, method, blocks, threads, n, seconds, ghosts, None, status))
    return rows


def _table(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, measures.TIMING)


def _ready(f: Field) -> Field:
    return Field(cut(f.df), f.spec)


def _ghosts(f: Field, blocks: Blocks) -> int:
    return blocks.requests(f.df).count() if blocks.n > 1 else 0


def _noise(spark: SparkSession, dims) -> Field:
    return _ready(synthetic.noise_grid(spark, dims))


def strong_segmentation(spark: SparkSession, sf_dir: str, blocks=(1, 4, 16, 64), repeats: int = 3, sizes=((64, 64, 64), (96, 96, 96))) -> DataFrame:
    """Two-sided segmentation of one field on more and more blocks, with the ghosts of each."""
    rows = []
    for name, f in [("orders", _ready(fields.orders_plane(spark, sf_dir))), *((f"noise {d[0]}", _noise(spark, d)) for d in sizes)]:
        tiles = [Blocks.about(f.spec, b) for b in blocks]
        cases = [("pointer doubling", t.n, lambda f=f, t=t: segment.blockwise(f.df, f.spec, t), _ghosts(f, t)) for t in tiles]
        rows += _run(spark, f"strong segmentation, {name}", cases, f.spec.n, repeats)
    return _table(spark, rows)


def _three_ways(m: DataFrame, f: Field, tiles: Blocks) -> list[Case]:
    return [
        ("implicit", tiles.n, lambda: components.connected(m, f.spec, blocks=tiles), 0),
        ("explicit", tiles.n, lambda: components.connected_explicit(m, f.spec), 0),
        ("wave filter", tiles.n, lambda: baselines.wave_filter(m, f.spec, blocks=tiles), 0),
    ]


def strong_components(spark: SparkSession, sf_dir: str, blocks=(1, 4, 16), repeats: int = 3, sizes=((64, 64, 64),), quantile: float = 0.9) -> DataFrame:
    """Components of the top tenth: implicit, explicit and by waves."""
    rows = []
    for name, f in [("orders", _ready(fields.orders_plane(spark, sf_dir))), *((f"noise {d[0]}", _noise(spark, d)) for d in sizes)]:
        m = cut(components.mask(f.df, quantile=quantile))
        for b in blocks:
            rows += _run(spark, f"strong components, {name}", _three_ways(m, f, Blocks.about(f.spec, b)), f.spec.n, repeats)
    return _table(spark, rows)


def largest_that_fits(spark: SparkSession, sf_dir: str, blocks=(8, 64), start: int = 32, memory: int = 64 << 20, repeats: int = 1) -> DataFrame:
    """Noise cubes of doubling sides on the two largest tilings, as long as a block stays within its memory; the first beyond is told and not run."""
    rows, threads = [], spark.sparkContext.defaultParallelism
    for b in blocks:
        side = start
        while side**3 * VERTEX_BYTES <= memory * b:
            f = _noise(spark, (side,) * 3)
            rows += _run(spark, "largest", [("pointer doubling", b, lambda f=f, b=b: segment.blockwise(f.df, f.spec, b), 0)], f.spec.n, repeats)
            if rows[-1][-1] != "ok":
                break
            side *= 2
        else:
            rows.append(("largest", "pointer doubling", b, threads, side**3, None, 0, None, "beyond memory"))
    return _table(spark, rows)


def weak_noise(spark: SparkSession, sf_dir: str, blocks=(1, 2, 4, 8), side: int = 40, quantile: float = 0.9994, repeats: int = 3) -> DataFrame:
    """Noise that grows with the blocks, few vertices in the mask."""
    rows = []
    for b in blocks:
        f = _noise(spark, (side, side, side * b))
        m = cut(components.mask(f.df, quantile=quantile))
        rows += _run(spark, "weak noise", _three_ways(m, f, Blocks(f.spec, (1, 1, b))), f.spec.n, repeats)
    return _table(spark, rows)


def weak_density(spark: SparkSession, sf_dir: str, blocks=(1, 8), side: int = 24, above: float = 0.2, repeats: int = 3) -> DataFrame:
    """A sum of bumps, resampled with the number of blocks, much of it in the mask."""
    rows, f0 = [], _ready(synthetic.bump_grid(spark, sf_dir, (side,) * 3))
    for b in blocks:
        f = _ready(synthetic.resample(f0, round(b ** (1 / 3))))
        m = cut(components.mask(f.df, above=above, normalised=True))
        rows += _run(spark, "weak density", _three_ways(m, f, Blocks.about(f.spec, b)), f.spec.n, repeats)
    return _table(spark, rows)


def thresholds(spark: SparkSession, sf_dir: str, repeats: int = 3, dims=(64, 64, 64), blocks: int = 4) -> DataFrame:
    """Sparse, half and nearly full masks: by threshold on the orders plane, by quantile on noise."""
    rows = []
    orders, noise = _ready(fields.orders_plane(spark, sf_dir)), _noise(spark, dims)
    kinds = [(orders, f"orders above {t}", {"above": t, "normalised": True}) for t in (0.9, 0.5, 0.1)] + [(noise, f"noise quantile {q}", {"quantile": q}) for q in (0.9994, 0.5, 0.0006)]
    for f, name, how in kinds:
        m = cut(components.mask(f.df, **how))
        rows += _run(spark, name, _three_ways(m, f, Blocks.about(f.spec, blocks)), f.spec.n, repeats)
    return _table(spark, rows)


def feature_masks(spark: SparkSession, sf_dir: str, repeats: int = 1) -> DataFrame:
    """Features above, between and below thresholds on three fields."""
    rows = []
    for f, name, how in ((fields.lineitem_cube(spark, sf_dir), "above", {"above": 0.8}), (fields.user_day_plane(spark, sf_dir), "between", {"between": (0.3, 0.6)}), (fields.smoothed(fields.orders_plane(spark, sf_dir), 2), "below", {"below": 0.3})):
        f = _ready(f)
        m = cut(components.mask(f.df, normalised=True, **how))
        rows += _run(spark, f"feature {name}", _three_ways(m, f, Blocks.about(f.spec, 4)), f.spec.n, repeats)
    return _table(spark, rows)


def threads_against_blocks(spark: SparkSession, sf_dir: str, repeats: int = 3, dims=(96, 96, 96)) -> DataFrame:
    """One block for all threads against one block for each of them."""
    f, k = _noise(spark, dims), spark.sparkContext.defaultParallelism
    cases = [("pointer doubling", b, lambda b=b: segment.blockwise(f.df, f.spec, b), _ghosts(f, Blocks.about(f.spec, b))) for b in (1, k)]
    return _table(spark, _run(spark, "threads against blocks", cases, f.spec.n, repeats))


def crossing_components(spark: SparkSession, sf_dir: str, repeats: int = 1) -> DataFrame:
    """Few components over several blocks (copies of documents) against many (a smooth plane)."""
    f = _ready(fields.smoothed(fields.orders_plane(spark, sf_dir), 4))
    m = cut(components.mask(f.df, quantile=0.5))
    v, e = graphs.doc_copies(spark, sf_dir)
    rows = _run(spark, "crossing, smooth", [("implicit", 16, lambda: components.connected(m, f.spec, blocks=16), _ghosts(f, Blocks.about(f.spec, 16)))], f.spec.n, repeats)
    return _table(spark, rows + _run(spark, "crossing, copies", [("graph", 1, lambda: components.connected_graph(v, e), 0)], v.count(), repeats))


def structured_against_unstructured(spark: SparkSession, sf_dir: str, repeats: int = 1) -> DataFrame:
    """The same plane with absent cells filled, left out, and as an explicit graph."""
    rows = []
    for fill in (True, False):
        f = _ready(fields.user_day_plane(spark, sf_dir, fill))
        e = cut(f.spec.edges(f.df))
        cases = [("structured", 4, lambda f=f: segment.descending(f.df, f.spec, 4), 0), ("unstructured", 1, lambda f=f, e=e: segment.graph_segmentation(f.df, e), 0)]
        rows += _run(spark, f"user days, {'filled' if fill else 'sparse'}", cases, f.df.count(), repeats)
    return _table(spark, rows)


def preprocessing(spark: SparkSession, sf_dir: str, repeats: int = 1, dims=(64, 64, 64)) -> DataFrame:
    """What isn't counted elsewhere: the order field, the ghost layer and the pointers."""
    f = _noise(spark, dims)
    t = Blocks.about(f.spec, 8)
    cases = [("order field", 1, lambda: order_field(f.df), 0), ("ghost layer", t.n, lambda: t.halo(f.df), 0), ("pointers", 1, lambda: pointers.steepest(f.df, spec=f.spec), 0)]
    return _table(spark, _run(spark, "preprocessing", cases, f.spec.n, repeats))


ALL = (strong_segmentation, strong_components, largest_that_fits, weak_noise, weak_density, thresholds, feature_masks, threads_against_blocks, crossing_components, structured_against_unstructured, preprocessing)
