import numpy as np
import pytest
from helpers import rows
from pyspark.sql import functions as F

from fieldseg.functions.grid import Blocks, GridSpec
from fieldseg.functions.sql import register
from fieldseg.model import FieldError, adjacency, check_field, edges_from_cells
from fieldseg.operators import baselines, components, critical, exchange, graph_blocks, kernels, pointers, segment
from fieldseg.operators.frame import FieldFrame
from fieldseg.operators.contraction import contract_components
from fieldseg.operators.order import order_field
from fieldseg.plans import measures, workloads
from fieldseg.sources import fields, files, synthetic
from fieldseg.streaming import feeds


def field(spark, values, dims=None, connectivity="simplicial"):
    values = [int(v) for v in np.ravel(values)]
    return spark.createDataFrame(list(enumerate(values)), "id long, f long"), GridSpec(dims or (len(values),), connectivity)


def as_map(df, value):
    return {r["id"]: r[value] for r in df.collect()}


def test_constant_field_has_one_maximum(spark):
    df, spec = field(spark, [7] * 16, (4, 4))
    assert set(as_map(segment.descending(df, spec), "max_id").values()) == {15}
    assert set(as_map(segment.ascending(df, spec, 4), "min_id").values()) == {0}


def test_ramp_takes_ten_rounds(spark):
    df, spec = field(spark, range(1024))
    ends, rounds = pointers.compress(pointers.steepest(df, spec=spec))
    assert rounds == 10 and set(as_map(ends, "ptr").values()) == {1023}


def test_checkerboard(spark):
    v = [(x + y) % 2 for y in range(8) for x in range(8)]
    df, spec = field(spark, v, (8, 8), "axis")
    up = as_map(segment.descending(df, spec), "max_id")
    assert all(up[i] == i for i in range(64) if v[i]) and len(set(up.values())) == 32


def test_bump_in_three_dimensions(spark):
    v = [-(x - 4) ** 2 - (y - 4) ** 2 - (z - 4) ** 2 for z in range(9) for y in range(9) for x in range(9)]
    df, spec = field(spark, v, (9, 9, 9))
    assert set(as_map(segment.descending(df, spec, 8), "max_id").values()) == {364}


@pytest.mark.parametrize("tiles", [(1, 1), (2, 3), (5, 1), (7, 6)])
def test_any_tiling_gives_the_same(spark, tiles):
    v = np.random.default_rng(1).integers(0, 9, 42)
    df, spec = field(spark, v, (7, 6))
    blocks = Blocks(spec, tiles)
    want = rows(segment.blockwise(df, spec, 1))
    for e in exchange.STRATEGIES:
        assert rows(segment.blockwise(df, spec, blocks, exchange=e)) == want
    assert rows(segment.blockwise(df, spec, blocks, precompress=True, in_place=False)) == want
    m = components.mask(df, above=3)
    assert rows(components.connected(m, spec, blocks=blocks)) == rows(components.connected(m, spec))


def test_boundary_too_large_raises(spark):
    b = spark.createDataFrame([(1, 2), (2, 3)], "id long, p long")
    with pytest.raises(exchange.BoundaryTooLarge):
        exchange.resolve(b, ["p"], "coordinator", small=1)
    assert rows(exchange.resolve(b, ["p"], "auto", small=1)[0]) == rows(exchange.resolve(b, ["p"], "coordinator")[0])


def test_masks(spark):
    df, spec = field(spark, range(10))
    count = lambda **k: components.mask(df, **k).where("m").count()
    assert [count(above=8), count(above=8, closed=True), count(below=2), count(between=(2, 4)), count(quantile=0.5), count(above=0.5, normalised=True), count(predicate="f % 2 = 0")] == [1, 2, 2, 3, 5, 5, 5]


def test_components_edge_cases(spark):
    df, spec = field(spark, [1] + [0] * 5)
    labels = components.connected(components.mask(df, above=0), spec)
    assert as_map(labels, "label")[0] == 0 and components.extract(labels).count() == 1
    assert set(as_map(components.connected(components.mask(df, above=5), spec), "label").values()) == {-1}
    assert set(as_map(components.connected(components.mask(df, above=-1), spec, blocks=2), "label").values()) == {5}


def test_pairs_across_blocks_are_not_lost(spark):
    """Roots 10 and 20 whose edge lies between lower vertices of two blocks."""
    v = spark.createDataFrame([(x,) for x in (10, 1, 2, 20)], "id long")
    e = spark.createDataFrame([(10, 1), (1, 2), (2, 20)], "src long, dst long")
    assert set(as_map(components.connected_graph(v, e, local_first=True), "label").values()) == {20}
    path = spark.createDataFrame([(10, 1), (1, 5), (5, 2), (2, 9)], "src long, dst long")
    assert set(as_map(contract_components(path, winner="max"), "label").values()) == {10}


def test_printed_form_leaves_components_apart(spark, sf):
    f = fields.orders_plane(spark, sf)
    m = components.mask(f.df, above=0.5, normalised=True)
    exact, once = components.connected(m, f.spec, implicit=False), components.connected(m, f.spec, implicit=False, stitch="once", exchange="pointer", blocks=4)
    d = measures.partition_diff(once, exact).first()
    assert d.parts_a >= d.parts_b


@pytest.mark.parametrize("winner", ["min", "max"])
def test_contraction_without_the_last_task(spark, winner):
    rng = np.random.default_rng(3)
    e = [(int(a), int(b)) for a, b in rng.integers(0, 60, (45, 2))]
    df = spark.createDataFrame([*e, (None, 3), (4, 4)], "src long, dst long")
    want = kernels.union_find(*(np.array([x[i] for x in e if x[0] != x[1]]) * (1 if winner == "max" else -1) for i in (0, 1)))
    sign = 1 if winner == "max" else -1
    for one_task in (0, 10**6):
        assert as_map(contract_components(df, winner=winner, one_task=one_task), "label") == {sign * k: sign * v for k, v in want.items()}


def test_baselines_agree(spark):
    rng = np.random.default_rng(5)
    e = spark.createDataFrame([(int(a), int(b)) for a, b in rng.integers(0, 50, (40, 2)) if a != b], "src long, dst long")
    v = spark.range(50)
    want = rows(baselines.union_find_driver(v, e))
    for f in (baselines.hook_compress, baselines.tree_merge, baselines.sampled_components, lambda v, e: baselines.label_propagation(v, e)[0]):
        assert rows(f(v, e)) == want
    d = measures.partition_diff(baselines.any_representative(v, e), baselines.union_find_driver(v, e)).first()
    assert d.parts_a == d.parts_b and d.apart == 0
    with pytest.raises(baselines.TooLarge):
        baselines.union_find_driver(v, e, limit=3)


@pytest.mark.parametrize("name", ["orders", "cube", "line", "user_day"])
def test_euler_sum_is_one(spark, sf, name):
    f = fields.FIELDS[name](spark, sf)
    assert critical.classify(f.df, f.spec).agg(F.sum("chi")).first()[0] == 1


def test_order_field_ways_agree(spark, sf):
    f = fields.lineitem_cube(spark, sf)
    assert rows(order_field(f.df)) == rows(order_field(f.df, method="window"))


def test_check_field(spark):
    with pytest.raises(FieldError):
        check_field(spark.createDataFrame([(1, float("nan"))], "id long, f double"))
    with pytest.raises(FieldError):
        check_field(spark.createDataFrame([(1, 1), (1, 2)], "id long, f long"))
    with pytest.raises(FieldError):
        check_field(spark.createDataFrame([(None, 1)], "id long, f long"))


def test_cells_give_the_stencil(spark):
    spec = GridSpec((3, 3, 3))
    e = edges_from_cells(baselines.to_unstructured(spark.range(spec.n), spec))
    assert rows(e) == rows(spec.edges(spark.range(spec.n)))
    assert len(adjacency(e).where("id = 13").first().nbrs) == 14


def test_noise(spark):
    f = synthetic.noise_grid(spark, (41, 31), seed=3)
    v = as_map(f.df, "f")
    assert all(v[x + 41 * y] == 0 for x in range(0, 41, 10) for y in range(0, 31, 10))
    assert v == as_map(synthetic.noise_grid(spark, (41, 31), seed=3).df, "f") and -10**6 <= min(v.values()) and max(v.values()) <= 10**6
    # a share above a threshold of the normalised field is about the share below its mirror image
    hi, lo = (components.mask(f.df, normalised=True, **k).where("m").count() for k in ({"above": 0.7}, {"below": 0.3}))
    assert abs(hi - lo) < 0.2 * f.spec.n


def test_resample_and_bumps(spark, sf):
    f = synthetic.bump_grid(spark, sf, (8, 8, 8), n_centres=1)
    assert rows(synthetic.resample(f, 1).df) == rows(f.df)
    assert pointers.extrema(pointers.steepest(f.df, spec=f.spec)).count() == 1
    assert synthetic.resample(f, 2).df.count() == 8 * f.spec.n


def test_sql_functions_and_source(spark):
    register(spark)
    spec = GridSpec((4, 4))
    got = sorted(r[0] for r in spark.sql("select * from stencil(5, 4, 4, 1)").collect())
    assert got == sorted(spark.range(16).where("id = 5").select(F.explode(spec.neighbours())).toPandas().iloc[:, 0])
    assert spark.sql("select count(*) from grid_cells(3, 3, 2)").first()[0] == 18
    df = spark.read.format("noise_grid").option("dims", "11,11").load()
    assert df.count() == 121 and df.where("id = 0").first().f == 0


def test_files(spark, tmp_path):
    df, spec = field(spark, range(12), (4, 3))
    df.write.json(str(tmp_path / "j"))
    assert rows(files.read_field(spark, str(tmp_path / "j"), "json")) == rows(df)
    for z, part in enumerate(np.arange(12, dtype="<f4").reshape(2, 6)):
        (tmp_path / "v").mkdir(exist_ok=True)
        part.tofile(tmp_path / "v" / f"slab{z}.raw")
    assert rows(files.read_volume(spark, str(tmp_path / "v"), spec)) == rows(df)
    files.write_by_block(df, str(tmp_path / "b"), Blocks(spec, (2, 1)).block())
    assert spark.read.parquet(str(tmp_path / "b")).where("block = 1").count() == 6


def test_streams_and_batches_agree(spark, sf):
    batch = spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    stream = feeds.events_stream(spark, feeds.stream_path(sf, "events"))
    assert rows(feeds.drained(feeds.sessions(stream, "30 minutes"))) == rows(feeds.sessions(batch, "30 minutes"))


def test_workload_tables(spark, sf):
    t = workloads.strong_segmentation(spark, sf, blocks=(1, 4), repeats=1, sizes=((16, 16, 16),))
    s = measures.speedup(t).collect()
    assert s and all(r.speedup > 0 for r in s)
    t = workloads.thresholds(spark, sf, repeats=1, dims=(12, 12, 12))
    assert {r.status for r in t.collect()} <= {"ok", "OOM", "TooLarge"}


def test_plans(spark, sf):
    """One shuffle to the blocks, hash aggregation in order space, and a scan of two columns."""
    f = fields.orders_plane(spark, sf)
    plan = segment.block_pointers(f.df, Blocks(f.spec, (2, 2)))._jdf.queryExecution().toString()
    assert plan.split("== Physical Plan ==")[1].count("Exchange hashpartitioning") == 1
    assert "ReadSchema: struct<o_orderkey:bigint,o_totalprice:double>" in plan
    o = order_field(f.df)
    plan = pointers.steepest(o, spec=f.spec, by="ord")._jdf.queryExecution().toString()
    assert "HashAggregate" in plan.split("== Physical Plan ==")[1] or "SortAggregate" in plan


SPIRAL = {0: "AFGH", 1: "BIJK", 2: "CLMN", 3: "DEOP"}


def spiral(spark):
    v = spark.createDataFrame([(ord(c), ord(c), b) for b, own in SPIRAL.items() for c in own], "id long, f long, block int")
    path = "ABCDEFGHIJKLMNOP"
    return v, spark.createDataFrame([(ord(a), ord(b)) for a, b in zip(path, path[1:])], "src long, dst long")


def test_spiral_blocks(spark):
    """Ghosts, local pointers and the result of the worked example."""
    v, e = spiral(spark)
    halo, edges = graph_blocks.halo_graph(v, e)
    ghosts = {}
    for r in halo.where("is_ghost").collect():
        ghosts.setdefault(r.block, set()).add(chr(r.id))
    assert ghosts == {0: set("BEI"), 1: set("ACHL"), 2: set("BDKO"), 3: set("CFN")}
    local = {chr(r.id): chr(r.max_id) for r in graph_blocks.local_pointers(halo, edges).collect()}
    assert local == dict(zip("AFGHBIJKCLMNDEOP", "BIIICLLLDOOOFFPP"))
    for s in exchange.STRATEGIES:
        assert {r.max_id for r in graph_blocks.segmentation(v, e, exchange=s).collect()} == {ord("P")}
    asked = {(r.owner, r.needed_by): "".join(map(chr, r.ids)) for r in graph_blocks.requests(halo, v).collect()}
    assert asked[(1, 0)] == "BI" and asked[(0, 1)] == "AH" and asked[(3, 0)] == "E"


def test_graph_blocks_agree(spark):
    rng = np.random.default_rng(8)
    e = spark.createDataFrame([(int(a), int(b)) for a, b in rng.integers(0, 80, (90, 2)) if a != b], "src long, dst long")
    v = spark.range(80).withColumn("f", F.pmod(F.xxhash64("id"), F.lit(9)))
    want = components.connected_graph(v, e)
    for n in (1, 3, 80):
        parts = graph_blocks.by_hash(v, n)
        assert rows(graph_blocks.components(parts, e)) == rows(want)
        both = graph_blocks.segmentation(parts, e)
        up = e.unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
        assert rows(both.select("id", "max_id")) == rows(segment.graph_segmentation(v, up))


def test_requests_and_supply_are_the_same(spark):
    spec = GridSpec((6, 5))
    t = Blocks(spec, (3, 2))
    a = t.requests(spark.range(30))
    b = t.supply(spark.range(30)).select("id", "owner", F.explode("needed_by").alias("needed_by"))
    assert rows(a) == rows(b)


def test_frame_and_communication(spark, sf):
    f = fields.lineitem_cube(spark, sf)
    frame = FieldFrame(f.df, f.spec, 4)
    assert rows(frame.ends) == rows(segment.blockwise(f.df, f.spec))
    assert frame.extremum_graph().count() > 0 and frame.separatrices().count() > 0 and frame.components(above=0.5, normalised=True).count() == f.spec.n
    c = measures.communication(f.df, Blocks.about(f.spec, 4))
    assert c["ghosts"] >= c["boundary"] > 0 and c["local_rounds"] > 0


def test_running_maxima(spark, sf):
    stream = feeds.running_maxima(feeds.events_stream(spark, feeds.stream_path(sf, "events")))
    got = {(r.user_id, r.ts) for r in feeds.drained(stream, "append").collect()}
    ev = spark.read.parquet(f"{sf}/events.parquet").orderBy("user_id", "ts").toPandas()
    want = set()
    for u, g in ev.groupby("user_id"):
        v, t = g["value"].tolist(), g["ts"].tolist()
        want |= {(u, t[i].to_pydatetime()) for i in range(len(v) - 1) if v[i] > v[i + 1] and (i == 0 or v[i] > v[i - 1])}
    assert got == want
