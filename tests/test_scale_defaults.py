"""What holds at any size: blocks from memory, stretches of a line, quantiles by position, measures of runs that don't fit; and generated fields by plain loops."""

import math
from itertools import product

import pytest
from helpers import rows
from pyspark.sql import functions as F

from fieldseg.functions import grid
from fieldseg.functions.grid import Blocks, GridSpec
from fieldseg.operators import baselines, components, exchange, pointers, segment
from fieldseg.plans import measures, oracles, queries
from fieldseg.sources import fields, graphs, synthetic


@pytest.mark.parametrize("name", ["descending_orders", "two_sided_cube", "components_orders_t05", "percolation_sweep"])
def test_blocks_follow_memory(spark, duck, sf, name, monkeypatch):
    """No group holds more than the budget, and the rows stay those of the SQL."""
    monkeypatch.setattr(grid, "BLOCK_BYTES", 20_000)
    spec = fields.orders_plane(spark, sf).spec
    tiles = Blocks.of(spec, None)
    assert tiles.n > 4 and math.ceil(spec.n / tiles.n) * grid.VERTEX_BYTES <= 20_000
    largest = spark.range(spec.n).groupBy(tiles.block().alias("b")).count().agg(F.max("count")).first()[0]
    assert largest <= 1.3 * spec.n / tiles.n
    assert rows(queries.build()[name](spark, sf)) == rows(duck.sql(oracles.build()[name]).df())


def test_a_line_in_stretches(spark, sf):
    f = fields.shipday_line(spark, sf)
    gaps = f.df.where("id % 37 <> 5")
    for df in (f.df, gaps):
        want = rows(pointers.steepest_on_line(df))
        assert rows(pointers.steepest_on_line(df, stretch=10)) == want
    assert rows(pointers.steepest_on_line(f.df, stretch=7, direction="down")) == rows(pointers.steepest(f.df, spec=f.spec, direction="down"))


@pytest.mark.parametrize("q", [0.0, 0.37, 0.5, 1.0])
def test_quantiles(spark, q):
    df = spark.createDataFrame([(i, v) for i, v in enumerate([5, None, 1, 1, 1, 9, 2, 2, 40, 3])], "id long, f long")
    assert components.quantile_value(df, q) == pytest.approx(df.agg(F.percentile("f", F.lit(q))).first()[0])
    assert components.quantile_value(df.limit(0), q) is None


def test_pointers_side_by_side(spark, sf):
    f = fields.orders_plane(spark, sf)
    tiles = Blocks(f.spec, (4, 4))
    local = segment.block_pointers(f.df, tiles).where("shared").select("id", "max_id", "min_id").cache()
    want = exchange.resolve(local, ["max_id", "min_id"], "coordinator")
    for how in ("shuffle", "neighbour"):
        got = exchange.resolve(local, ["max_id", "min_id"], how)
        assert rows(got[0]) == rows(want[0])
        one = [pointers.compress(local, mode="doubling" if how == "shuffle" else "chase", name=c)[1] for c in ("max_id", "min_id")]
        assert got[1] == max(one)


def test_one_task_has_a_limit(spark):
    with pytest.raises(ValueError):
        pointers.compress_partition(spark.range(20).select("id", F.col("id").alias("ptr")), limit=10)


def test_stars_tie_what_chains_tie(spark):
    df = spark.createDataFrame([(1, "a"), (5, "a"), (3, "a"), (4, "b"), (7, None), (8, None), (3, "c"), (4, "c")], "id long, k string")
    assert sorted(map(tuple, graphs._stars(df, "k").collect())) == [(1, 3), (1, 5), (3, 4)]


def test_nearest_in_any_number_of_cells(spark, sf):
    p = graphs.embedding_points(spark, sf).limit(60).cache()
    assert rows(baselines.nearest(p, 5, cells=1)) == rows(baselines.nearest(p, 5, cells=7)) == rows(baselines.nearest(p, 5))


def test_runs_that_do_not_fit_are_recorded(spark):
    def full(batches):
        raise MemoryError("no room")
        yield

    assert measures.attempt(lambda: spark.range(3).mapInArrow(full, "id long")) == (None, "OOM")
    assert measures.attempt(lambda: spark.range(3))[1] == "ok"
    with pytest.raises(Exception, match="NO_SUCH|cannot be resolved|UNRESOLVED"):
        measures.attempt(lambda: spark.range(3).select("absent"))

    def large():
        raise baselines.TooLarge("edges")

    assert measures.attempt(large) == (None, "TooLarge")


def test_noise_by_loops(spark):
    """Gradient noise evaluated vertex by vertex; only the hash of the lattice corners is taken from Spark."""
    dims, freq = (13, 11, 12), 0.1
    corner = spark.range(3 * 3 * 3).selectExpr("id % 3 x", "id div 3 % 3 y", "id div 9 z")
    pick = {(r.x, r.y, r.z): r.p for r in corner.withColumn("p", F.pmod(F.xxhash64(F.lit(42), "x", "y", "z"), F.lit(6))).collect()}
    fade = lambda t: t * t * t * (t * (t * 6 - 15) + 10)
    got = {r.id: r.f for r in synthetic.noise_grid(spark, dims).df.collect()}
    spec = GridSpec(dims)
    for i in range(spec.n):
        at = [c * freq for c in (i % 13, i // 13 % 11, i // 143)]
        base, t = [math.floor(a) for a in at], [a - math.floor(a) for a in at]
        total = 0.0
        for dx in (0, 1):
            for dy in (0, 1):
                for dz in (0, 1):
                    d = (dx, dy, dz)
                    g = pick[tuple(b + s for b, s in zip(base, d))]
                    step = (t[g // 2] - d[g // 2]) * (1 if g % 2 == 0 else -1)
                    weight = math.prod(fade(x) if s else 1 - fade(x) for x, s in zip(t, d))
                    total += weight * step
        assert abs(got[i] - total * synthetic.SCALE) <= 1, i


def test_noise_of_lines_by_loops(spark, sf):
    """The noise statistics come from the lines: each line's ship day, part and supplier is a vertex of its own lattice cell."""
    import duckdb

    places = duckdb.sql(f"select cast(l_shipdate as date) - date '1970-01-01', l_partkey, l_suppkey from '{sf}/lineitem.parquet'").fetchall()
    cells = {tuple(math.floor(c * 0.1) + s for c, s in zip(p, d)) for p in places for d in product((0, 1), repeat=3)}
    corner = spark.createDataFrame(sorted(cells), "x long, y long, z long")
    pick = {(r.x, r.y, r.z): r.p for r in corner.withColumn("p", F.pmod(F.xxhash64(F.lit(42), "x", "y", "z"), F.lit(6))).collect()}
    want = []
    for p in places:
        base, t = [math.floor(c * 0.1) for c in p], [c * 0.1 - math.floor(c * 0.1) for c in p]
        fade, total = [x * x * x * (x * (x * 6 - 15) + 10) for x in t], 0.0
        for d in product((0, 1), repeat=3):
            g = pick[tuple(b + s for b, s in zip(base, d))]
            step = (t[g // 2] - d[g // 2]) * (1 if g % 2 == 0 else -1)
            total += math.prod(x if s else 1 - x for x, s in zip(fade, d)) * step
        want.append(total * synthetic.SCALE)
    r = queries.build()["noise_grid_stats"](spark, sf).first()
    assert r.n == len(places) and abs(r.lo - min(want)) <= 1 and abs(r.hi - max(want)) <= 1 and abs(r.total - sum(want)) <= len(want)


def test_resampled_by_loops(spark, sf):
    f = synthetic.bump_grid(spark, sf, (5, 4, 3))
    coarse = {r.id: r.f for r in f.df.collect()}
    fine = {r.id: r.f for r in synthetic.resample(f, 3).df.collect()}
    assert len(fine) == 27 * 60
    for i, v in fine.items():
        x, y, z = i % 15 // 3, i // 15 % 12 // 3, i // 180 // 3
        assert v == coarse[x + 5 * (y + 4 * z)]


def test_neighbours_hear_from_blocks_they_touch(spark):
    """A ramp over eight blocks: an end travels one block a round, and fewer vertices have news from round to round."""
    spec = GridSpec((32, 2))
    df = spark.range(spec.n).select("id", (F.col("id") % 32).alias("f"))
    local = segment.block_pointers(df, Blocks(spec, (8, 1))).where("shared").select("id", "max_id", "min_id")
    ends, messages = exchange.by_neighbours(local, ["max_id", "min_id"])
    assert rows(ends) == rows(exchange.resolve(local, ["max_id", "min_id"], "coordinator")[0])
    assert len(messages) >= 6 and messages == sorted(messages, reverse=True)
    assert len(messages) > exchange.resolve(local, ["max_id", "min_id"], "shuffle")[1]


def test_observed_memory(spark, sf):
    f = fields.lineitem_cube(spark, sf)
    got = measures.observed_memory(f.df, Blocks.about(f.spec, 4)).collect()
    assert sum(r.vertices for r in got) == f.spec.n and all(r.peak > r.model > 0 for r in got)
