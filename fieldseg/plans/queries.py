"""One query for each method, variant, baseline and measure, over the given tables."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fieldseg.functions.grid import Blocks
from fieldseg.operators import baselines as base
from fieldseg.operators import components as comp
from fieldseg.operators import critical, extremum_graph, graph_blocks, pointers, segment
from fieldseg.operators.order import order_field
from fieldseg.plans import measures
from fieldseg.runtime import cut
from fieldseg.sources import fields, graphs, synthetic
from fieldseg.streaming import feeds

Query = Callable[[SparkSession, str], DataFrame]


def _field(name: str) -> Callable:
    if name == "sparse":
        return lambda s, d: fields.user_day_plane(s, d, fill=False)
    if name == "smooth":
        return lambda s, d: fields.smoothed(fields.orders_plane(s, d), 2)
    return fields.FIELDS[name]


def on(name: str, run: Callable) -> Query:
    """A query over a field."""
    return lambda s, d: run(_field(name)(s, d))


def _orders(counts: tuple[int, int] | None, run: Callable) -> Query:
    """A query over the orders plane with a tiling."""

    def query(s, d):
        f = fields.orders_plane(s, d)
        return run(f, Blocks(f.spec, counts))

    return query


def _masked(name: str, run: Callable, **how) -> Query:
    """A query over a field with a mask; the one pass for a threshold is its only extra work."""

    def query(s, d):
        f = _field(name)(s, d)
        return run(f, comp.mask(f.df, **how))

    return query


def _graph(make: Callable, run: Callable) -> Query:
    return lambda s, d: run(*make(s, d))


def _two_sided_sizes(f) -> DataFrame:
    sizes = segment.two_sided(f.df, f.spec).groupBy("seg").agg(F.count("*").alias("size"))
    return sizes.groupBy("size").agg(F.count("*").alias("segments"))


def _compressed(mode: str) -> Query:
    def run(f):
        ptr = pointers.steepest_on_line(f.df, "up", name="max_id")
        if mode == "inplace":
            return pointers.compress_partition(ptr, "max_id")
        return pointers.compress(ptr, mode="chase" if mode == "chase" else "doubling", name="max_id")[0]

    return on("line", run)


def _extrema(f) -> DataFrame:
    both = [pointers.extrema(pointers.steepest(f.df, spec=f.spec, direction=d)).withColumn("kind", F.lit(k)) for d, k in (("up", "maximum"), ("down", "minimum"))]
    return both[0].unionByName(both[1])


def _kinds(f) -> DataFrame:
    return critical.classify(f.df, f.spec).select("id", "kind", "n_lower", "n_upper", "degenerate")


def _level_sets(f) -> DataFrame:
    w = f.df.select("f", F.explode(F.array(*(F.lit(x).cast("long") for x in (1_000_000, 10_000_000, 20_000_000)))).alias("w"))
    return w.groupBy("w").agg(F.count_if(F.col("f") < F.col("w")).alias("below"), F.count_if(F.col("f") > F.col("w")).alias("above"))


def _percolation(s, d) -> DataFrame:
    f = fields.orders_plane(s, d)
    parts = []
    for t in range(1, 10):
        labels = comp.connected(comp.mask(f.df, above=t / 10, normalised=True), f.spec, implicit=False)
        parts.append(labels.groupBy("label").agg(F.count("*").alias("size")).agg(F.lit(t).cast("long").alias("tenths"), F.sum("size").alias("inside"), F.count("*").alias("components"), F.max("size").alias("largest")))
    return reduce(DataFrame.unionByName, parts).where("components > 0")


def _half(run: Callable) -> Query:
    return _masked("orders", lambda f, m: run(f, comp.connected(m, f.spec)), above=0.5, normalised=True)


def _topk(f) -> DataFrame:
    sizes = segment.descending(f.df, f.spec).groupBy("max_id").agg(F.count("*").alias("size"))
    return sizes.orderBy(F.desc("size"), "max_id").limit(10)


def _grouped(how: str) -> Query:
    def run(f, m):
        labels = segment.descending(f.df, f.spec).join(m.select("id", F.col("m").alias("inside")), "id")
        rows = labels.select(Blocks(f.spec, (2, 2)).block().alias("block"), "inside", "max_id")
        out = getattr(rows, how)("block", "inside").agg(F.count("*").alias("vertices"), F.countDistinct("max_id").alias("segments"))
        return out.select(F.coalesce("block", F.lit(-1)).cast("long").alias("block"), F.coalesce(F.col("inside").cast("string"), F.lit("all")).alias("inside"), "vertices", "segments")

    return _masked("orders", run, above=0.5, normalised=True)


def _traces(f) -> DataFrame:
    paths = segment.integral_lines(f.df, f.spec, f.df.select("id"))
    return paths.select("seed", F.array_join("path", ",").alias("path"))


def _separatrices(f) -> DataFrame:
    up, down = (cut(pointers.steepest(f.df, spec=f.spec, direction=d)) for d in ("up", "down"))
    return critical.separatrices(f.df, f.spec, up, down).select("saddle", "side", "seed", F.element_at("path", -1).alias("end_id"))


def _extremum_graph(f) -> DataFrame:
    return extremum_graph.build(segment.descending(f.df, f.spec), order_field(f.df), f.spec)


def _geo(s, d) -> DataFrame:
    return pointers.compress(graphs.geo_forest(s, d))[0]


def _cells(f) -> DataFrame:
    c = base.to_unstructured(f.df.select("id"), f.spec)
    return c.select("cell_id", *(F.col("verts")[i].alias(f"v{i}") for i in range(3)))


def _cells_by_threshold(s, d) -> DataFrame:
    f = fields.orders_plane(s, d)
    each = [measures.extracted_geometry(comp.mask(f.df, above=t / 10, normalised=True), f.spec).select(F.lit(t).cast("long").alias("tenths"), "vertices", "cells") for t in (9, 5, 1)]
    return reduce(DataFrame.unionByName, each)


def _representatives(v, e) -> DataFrame:
    sizes = base.any_representative(v, e).groupBy("label").agg(F.count("*").alias("size"))
    return sizes.groupBy("size").agg(F.count("*").alias("components"))


def _incremental(s, d) -> DataFrame:
    """Edges of orders and parts as a stream of lines, merged in three steps a batch."""
    line = s.read.parquet(f"{d}/lineitem.parquet").schema
    stream = s.readStream.schema(line).parquet(feeds.stream_path(d, "lineitem"))
    edges = stream.where((F.round(F.col("l_discount") * 100).cast("long") == 10) & (F.col("l_quantity") >= 45)).select((F.col("l_orderkey") * 2).alias("src"), (F.col("l_partkey") * 2 + 1).alias("dst"))
    state = feeds.IncrementalComponents(s)

    def each(batch, n):
        for k in range(3):
            state.update(batch.where(F.pmod(F.xxhash64("src"), F.lit(3)) == k))

    feeds.drain(edges, each)
    return state.labels()


def _printed(blocks: int) -> Query:
    return _masked("orders", lambda f, m: measures.partition_diff(comp.connected(m, f.spec, implicit=False, blocks=blocks, stitch="once", exchange="pointer"), comp.connected(m, f.spec, implicit=False)), above=0.5, normalised=True)


def _stitched(f, m) -> DataFrame:
    """Labels of one hook to the largest neighbour and its ends, then one pass that moves each label to the best next to it."""
    inside = m.where("m").select("id")
    edges = cut(f.spec.edges(inside))
    ptr = pointers.steepest(inside.withColumn("f", F.col("id")), edges=edges, name="label")
    return comp.stitch_once(pointers.compress(ptr, name="label")[0], edges)


def _noise(df) -> DataFrame:
    return df.agg(F.count("*").alias("n"), F.min("f").alias("lo"), F.max("f").alias("hi"), F.sum("f").alias("total"))


def build() -> dict[str, Query]:
    q: dict[str, Query] = {}
    for name, f in (("field_orders_plane", "orders"), ("field_lineitem_cube", "cube"), ("field_shipday_line", "line"), ("field_user_day", "user_day")):
        q[name] = on(f, lambda x: x.df)
    for name, f in (("order_field_orders", "orders"), ("order_field_cube_ties", "cube"), ("order_field_line", "line")):
        q[name] = on(f, lambda x: order_field(x.df).select("id", "ord"))
    for name, f, way in (("pointer_up_orders", "orders", "up"), ("pointer_down_orders", "orders", "down"), ("pointer_up_cube", "cube", "up")):
        q[name] = on(f, lambda x, way=way: pointers.steepest(x.df, spec=x.spec, direction=way))
    q["pointer_up_line_window"] = on("line", lambda x: pointers.steepest_on_line(x.df))
    for f in ("orders", "cube", "line", "user_day"):
        q[f"descending_{f}"] = on(f, lambda x: segment.descending(x.df, x.spec))
        q[f"ascending_{f}"] = on(f, lambda x: segment.ascending(x.df, x.spec))
    q["descending_smooth"] = on("smooth", lambda x: segment.descending(x.df, x.spec, 4))
    for b, counts in ((1, (1, 1)), (4, (2, 2)), (16, (4, 4))):
        q[f"descending_block_{b}"] = _orders(counts, lambda x, t: segment.descending(x.df, x.spec, t))
    for e in ("replicate", "coordinator", "neighbour", "shuffle"):
        q[f"exchange_{e}"] = _orders((4, 4), lambda x, t, e=e: segment.blockwise(x.df, x.spec, t, exchange=e))
    q["exchange_precompress"] = _orders((4, 4), lambda x, t: segment.blockwise(x.df, x.spec, t, precompress=True))
    for f in ("orders", "cube", "line"):
        q[f"two_sided_{f}"] = on(f, lambda x: segment.two_sided(x.df, x.spec))
    q["two_sided_sizes"] = on("orders", _two_sided_sizes)
    for m in ("sync", "inplace", "chase"):
        q[f"compress_{m}_line"] = _compressed(m)
    q["geo_forest_roots"] = _geo
    q["extrema_orders"] = on("orders", _extrema)
    q["critical_line"], q["critical_cube"], q["critical_orders_kinds"], q["critical_user_day"] = on("line", _kinds), on("cube", _kinds), on("orders", _kinds), on("user_day", _kinds)
    q["level_set_counts"] = on("orders", _level_sets)
    for name, how in {"above": {"above": 20_000_000}, "below": {"below": 10_000_000}, "between": {"between": (10_000_000, 20_000_000)}, "quantile": {"quantile": 0.9}, "normalised": {"above": 0.5, "normalised": True}}.items():
        q[f"mask_{name}"] = _masked("orders", lambda f, m: m.select("id", "m"), **how)
    for t, name in ((0.9, "09"), (0.5, "05"), (0.1, "01")):
        q[f"components_orders_t{name}"] = _masked("orders", lambda f, m: comp.connected(m, f.spec), above=t, normalised=True)
    q["components_blocks_16"] = _masked("orders", lambda f, m: comp.connected(m, f.spec, blocks=Blocks(f.spec, (4, 4))), above=0.5, normalised=True)
    q["components_min_label"] = _masked("orders", lambda f, m: comp.connected(m, f.spec, blocks=4, implicit=False, winner="min"), above=0.5, normalised=True)
    q["components_cube"] = _masked("cube", lambda f, m: comp.connected(m, f.spec), predicate="f >= 14")
    q["components_user_day_fill0"] = _masked("user_day", lambda f, m: comp.connected(m, f.spec), above=2000)
    q["components_user_day_sparse"] = _masked("sparse", lambda f, m: comp.connected(m, f.spec), above=2000)
    q["components_line_above"] = _masked("line", lambda f, m: comp.connected(m, f.spec), above=600)
    q["components_explicit_orders"] = _masked("orders", lambda f, m: comp.connected_explicit(m, f.spec), above=0.5, normalised=True)
    q["components_extract_nonneg"] = _half(lambda f, labels: comp.extract(labels))
    q["components_printed_diff_1"], q["components_printed_diff_16"] = _printed(1), _printed(16)
    q["components_printed_1"] = _masked("orders", lambda f, m: comp.connected(m, f.spec, implicit=False, blocks=1, stitch="once", exchange="pointer"), above=0.5, normalised=True)
    q["stitch_once_orders"] = _masked("orders", _stitched, above=0.5, normalised=True)
    for name, make in {"turn_chain": graphs.turn_chain, "order_part": graphs.order_part, "doc_lines": graphs.doc_shared_lines, "doc_copies": graphs.doc_copies, "pages": graphs.page_links, "sessions": graphs.user_sessions}.items():
        q[f"components_{name}"] = _graph(make, comp.connected_graph)
    q["wave_filter_orders"] = _masked("orders", lambda f, m: base.wave_filter(m, f.spec), above=0.5, normalised=True)
    q["label_propagation_orders"] = _masked("orders", lambda f, m: base.label_propagation(m.where("m").select("id"), f.spec.edges(m.where("m").select("id")))[0], above=0.9, normalised=True)
    parts = graphs.order_part
    q["label_propagation_parts"] = _graph(parts, lambda v, e: base.label_propagation(v, e)[0])
    q["hook_compress_parts"], q["union_find_parts"] = _graph(parts, base.hook_compress), _graph(parts, base.union_find_driver)
    q["tree_merge_parts"], q["sampled_components_parts"] = _graph(parts, base.tree_merge), _graph(parts, base.sampled_components)
    q["local_first_parts"] = _graph(parts, lambda v, e: comp.connected_graph(v, e, local_first=True))
    q["any_representative_parts"] = _graph(parts, _representatives)
    q["graph_blocks_parts"] = _graph(parts, lambda v, e: graph_blocks.components(graph_blocks.by_hash(v, 4), e))
    q["graph_blocks_sparse"] = on("sparse", lambda f: graph_blocks.segmentation(graph_blocks.by_hash(f.df, 4), f.spec.edges(f.df)))
    q["descending_graph_sparse"] = on("sparse", lambda f: segment.graph_segmentation(f.df, f.spec.edges(f.df)))
    q["supply_counts"] = _orders((4, 4), lambda f, t: t.supply(f.df).select("owner", F.explode("needed_by").alias("needed_by")).groupBy("owner", "needed_by").agg(F.count("*").alias("requests")))
    q["edge_degrees_order_part"] = _graph(parts, lambda v, e: e.select(F.col("src").alias("id")).union(e.select(F.col("dst").alias("id"))).groupBy("id").agg(F.count("*").alias("degree")))
    q["grow_from_extrema_orders"] = on("orders", lambda f: base.grow_from_extrema(pointers.steepest(f.df, spec=f.spec, name="max_id"), "max_id")[0])
    q["percolation_sweep"] = _percolation
    q["component_size_hist"] = _half(lambda f, labels: measures.size_histogram(labels))
    q["spanning_segments"] = _half(lambda f, labels: measures.spanning(labels, Blocks(f.spec, (4, 4))))
    q["topk_segments"] = on("orders", _topk)
    q["segments_rollup"], q["segments_cube"] = _grouped("rollup"), _grouped("cube")
    q["trace_paths_line"], q["separatrices_line"] = on("line", _traces), on("line", _separatrices)
    q["extremum_graph_cube"], q["extremum_graph_orders"] = on("cube", _extremum_graph), on("orders", _extremum_graph)
    q["nearest_embeddings"] = lambda s, d: base.nearest(graphs.embedding_points(s, d), 8)
    q["knn_ascent_embeddings"] = lambda s, d: base.knn_ascent(graphs.embedding_points(s, d), 8)
    q["ghost_counts_blocks"] = _orders((4, 4), lambda f, t: measures.ghost_counts(f.df, t))
    q["memory_model_blocks"] = _orders((4, 4), lambda f, t: measures.memory_model(f.df, t))
    q["cross_edge_pairs"] = _orders((4, 4), lambda f, t: t.requests(f.df).groupBy("owner", "needed_by").agg(F.count("*").alias("requests")))
    q["cells_from_grid"], q["extracted_cells_by_threshold"] = on("orders", _cells), _cells_by_threshold
    q["noise_grid_stats"] = lambda s, d: _noise(synthetic.line_noise(s, d))
    q["bump_grid_stats"] = lambda s, d: _noise(synthetic.bump_grid(s, d).df)
    q["resample_grid"] = lambda s, d: _noise(synthetic.resample(synthetic.bump_grid(s, d, (16, 16, 16)), 2).df)
    q["stream_sessions"] = lambda s, d: feeds.drained(feeds.sessions(feeds.events_stream(s, feeds.stream_path(d, "events")), "6 hours")).withColumn("first_ts", F.col("first_ts").cast("timestamp_ntz"))
    q["stream_window_field"] = lambda s, d: feeds.drained(feeds.windowed_field(feeds.events_stream(s, feeds.stream_path(d, "events")))).withColumn("day", F.col("day").cast("timestamp_ntz"))
    q["stream_incremental_components"] = _incremental
    return q
