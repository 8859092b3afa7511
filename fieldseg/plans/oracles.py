"""The same answers in plain SQL: fields, steepest stars, recursive walks and keyed component recursion."""

from __future__ import annotations

FIELD = {
    "orders": "select o_orderkey as id, cast(round(o_totalprice * 100) as bigint) as f from orders",
    "cube": """select s.id, coalesce(c.f, 0) as f from (select unnest(range(4950)) as id) s left join (
        select (cast(l_quantity as bigint) - 1) + 50 * (cast(round(l_discount * 100) as bigint) + 11 * cast(round(l_tax * 100) as bigint)) as id, count(*) as f from lineitem group by 1) c using (id)""",
    "line": """select d.id, coalesce(c.f, 0) as f from (select unnest(range(cast(max(cast(l_shipdate as date)) - min(cast(l_shipdate as date)) + 1 as bigint))) as id from lineitem) d left join (
        select cast(cast(l_shipdate as date) - (select min(cast(l_shipdate as date)) from lineitem) as bigint) as id, cast(sum(cast(l_quantity as bigint)) as bigint) as f from lineitem group by 1) c using (id)""",
    "user_day": """select s.id, coalesce(c.f, 0) as f from (select unnest(range((select max(day(ts)) from events) * (select max(user_id) + 1 from events))) as id) s left join (
        select day(ts) - 1 + (select max(day(ts)) from events) * user_id as id, cast(sum(cast(round(value * 100) as bigint)) as bigint) as f from events group by 1) c using (id)""",
    "sparse": "select day(ts) - 1 + (select max(day(ts)) from events) * user_id as id, cast(sum(cast(round(value * 100) as bigint)) as bigint) as f from events group by 1",
}
_W = "(select cast(ceil(sqrt(count(*))) as bigint) from orders)"
NX = {"orders": _W, "cube": "50", "line": "cast(1000000000 as bigint)", "user_day": "(select max(day(ts)) from events)", "sparse": "(select max(day(ts)) from events)"}
NY = {"orders": "cast(1000000000 as bigint)", "cube": "11", "line": "cast(1000000000 as bigint)", "user_day": "cast(1000000000 as bigint)", "sparse": "cast(1000000000 as bigint)"}
DIM = {"orders": 2, "cube": 3, "line": 1, "user_day": 2, "sparse": 2}


def vertices(field: str, smooth: int = 0) -> str:
    """CTEs up to v(id, f, x, y, z) and steps(dx, dy, dz), the closed star."""
    from itertools import product

    steps = [s for s in product((-1, 0, 1), repeat=DIM[field]) if min(s) >= 0 or max(s) <= 0]
    rows = ", ".join("(" + ", ".join(map(str, (*s, 0, 0)[:3])) + ")" for s in steps)
    at = f"cast(id % {NX[field]} as bigint) as x, cast(id // {NX[field]} % {NY[field]} as bigint) as y, cast(id // ({NX[field]} * {NY[field]}) as bigint) as z"
    out = f"steps(dx, dy, dz) as (values {rows}), v0 as materialized (select cast(id as bigint) as id, cast(f as bigint) as f, {at} from ({FIELD[field]}))"
    for k in range(smooth):
        out += f", v{k + 1} as (select a.id, cast(sum(b.f) as bigint) as f, any_value(a.x) as x, any_value(a.y) as y, any_value(a.z) as z from v{k} a, steps s join v{k} b on b.x = a.x + dx and b.y = a.y + dy and b.z = a.z + dz group by a.id)"
    return out + f", v as materialized (select * from v{smooth})"


STAR = "v a, steps s join v b on b.x = a.x + dx and b.y = a.y + dy and b.z = a.z + dz"


def pointers(field: str, smooth: int = 0) -> str:
    return vertices(field, smooth) + f", ptr as materialized (select a.id, arg_max(b.id, row(b.f, b.id)) as up, arg_min(b.id, row(b.f, b.id)) as down from {STAR} group by a.id)"


def walks(field: str, smooth: int = 0, sides: tuple[str, ...] = ("up", "down")) -> str:
    out = pointers(field, smooth)
    for s in sides:
        out += f", w_{s}(id, p) as (select id, {s} from ptr union all select w.id, q.{s} from w_{s} w join ptr q on w.p = q.id where q.{s} <> w.p), e_{s} as (select w.id, w.p as ext from w_{s} w join ptr q on w.p = q.id where q.{s} = w.p)"
    return out


def one_sided(field: str, side: str, smooth: int = 0) -> str:
    name = {"up": "max_id", "down": "min_id"}[side]
    return f"with recursive {walks(field, smooth, (side,))} select id, ext as {name} from e_{side}"


def both_sides(field: str) -> str:
    return f"with recursive {walks(field)}, seg as (select id, e_up.ext as max_id, e_down.ext as min_id from e_up join e_down using (id))"


NORM = "cast(f - (select min(f) from v) as double) / cast((select max(f) - min(f) from v) as double)"


def masked(field: str, predicate: str) -> str:
    """CTEs up to m(id) and e(src, dst) for a predicate over f and `norm`."""
    p = predicate.replace("norm", f"({NORM})")
    return vertices(field) + f", m as materialized (select id, x, y, z from v where {p}), e as materialized (select a.id as src, b.id as dst from m a, steps s join m b on b.x = a.x + dx and b.y = a.y + dy and b.z = a.z + dz where a.id <> b.id)"


CC = """, c(id, label) using key (id) as (select id, id from m union (
  select u.id, max(w.label) from c w join e on e.dst = w.id join recurring.c u on u.id = e.src where w.label > u.label group by u.id))"""


def components(field: str, predicate: str, implicit: bool = True) -> str:
    rest = " union all select id, cast(-1 as bigint) from v where id not in (select id from m)" if implicit else ""
    return f"with recursive {masked(field, predicate)}{CC} select id, label from c{rest}"


GRAPH = {
    "turn_chain": "m as (select distinct conv_id * 16 + turn as id from conversations), e0 as (select id - 1 as src, id as dst from m where id % 16 > 0 and id - 1 in (select id from m))",
    "order_part": "e0 as (select distinct l_orderkey * 2 as src, l_partkey * 2 + 1 as dst from lineitem where cast(round(l_discount * 100) as bigint) = 10 and cast(l_quantity as bigint) >= 45), m as (select src as id from e0 union select dst from e0)",
    "doc_lines": "m as (select doc_id as id from documents), l as (select distinct doc_id as id, line from (select doc_id, unnest(string_split(text, chr(10))) as line from documents) where length(line) > 40), e0 as (select distinct src, dst from (select lag(id) over (partition by line order by id) as src, id as dst from l) where src is not null)",
    "doc_copies": "m as (select doc_id as id from documents), e0 as (select src, dst from (select lag(doc_id) over (partition by text order by doc_id) as src, doc_id as dst from documents) where src is not null)",
    "pages": """l as (select page_id * 2 as src, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) as href from pages), t as (select href, 2 * row_number() over (order by href) - 1 as dst from (select distinct href from l)),
        e0 as (select distinct src, dst from l join t using (href)), m as (select page_id * 2 as id from pages union all select dst from t)""",
    "sessions": "m as (select event_id as id from events), e0 as (select src, dst from (select lag(event_id) over w as src, event_id as dst, ts - lag(ts) over w as gap from events window w as (partition by user_id order by ts, event_id)) where gap < interval 30 minute)",
}


def graph_components(graph: str) -> str:
    return f"with recursive {GRAPH[graph]}, e as materialized (select src, dst from e0 union select dst, src from e0){CC} select id, label from c"


def block_of(alias: str, nx: str, ny: str, kx: int, ky: int) -> str:
    """The block of a vertex of the orders plane in a tiling of kx * ky."""
    return f"({alias}.x * {kx} // {nx} + {kx} * ({alias}.y * {ky} // {ny}))"


NYO = f"(select cast(ceil(count(*) / {_W}) as bigint) from orders)"
GHOSTS = f"""with {vertices("orders")}, g as (select distinct {block_of("a", _W, NYO, 4, 4)} as block, b.id from {STAR} where {block_of("a", _W, NYO, 4, 4)} <> {block_of("b", _W, NYO, 4, 4)})"""

#: The ring of a vertex of a plane, in order around it.
RING = ((1, 0), (1, 1), (0, 1), (-1, 0), (-1, -1), (0, -1))


def plane_kinds(field: str) -> str:
    """Kinds of critical points by changes of side around the ring; an absent neighbour is on neither side."""
    joins = " ".join(f"left join v r{i} on r{i}.x = a.x + {dx} and r{i}.y = a.y + {dy}" for i, (dx, dy) in enumerate(RING))
    low = [f"coalesce(row(r{i}.f, r{i}.id) < row(a.f, a.id) and r{i}.id is not null, false)" for i in range(6)]
    high = [f"coalesce(row(r{i}.f, r{i}.id) > row(a.f, a.id) and r{i}.id is not null, false)" for i in range(6)]
    count = lambda s: f"case when {' and '.join(s)} then 1 else {' + '.join(f'cast({s[i]} and not {s[(i + 1) % 6]} as bigint)' for i in range(6))} end"
    return f"""with {vertices(field)}, k as (select a.id, {count(low)} as n_lower, {count(high)} as n_upper from v a {joins})
        select id, case when n_lower = 0 then 'minimum' when n_upper = 0 then 'maximum' when n_lower = 1 and n_upper = 1 then 'regular' else '1-saddle' end as kind,
          cast(n_lower as bigint) as n_lower, cast(n_upper as bigint) as n_upper, n_lower > 2 or n_upper > 2 as degenerate from k"""


def cube_kinds(field: str) -> str:
    """Kinds of critical points in three dimensions: components of the lower and the upper link by reachability inside the link."""
    far = "greatest(s.dx - t.dx, s.dy - t.dy, s.dz - t.dz)", "least(s.dx - t.dx, s.dy - t.dy, s.dz - t.dz)"
    return f"""with recursive {vertices(field)}, n as materialized (select a.id, s.dx, s.dy, s.dz, row(b.f, b.id) < row(a.f, a.id) as low from {STAR} where a.id <> b.id),
        link as materialized (select id, low, row_number() over (partition by id, low order by dx, dy, dz) as i, dx, dy, dz from n),
        tie as materialized (select s.id, s.low, s.i as a, t.i as b from link s join link t on s.id = t.id and s.low = t.low and s.i <> t.i where {far[0]} <= 1 and {far[1]} >= -1 and ({far[1]} >= 0 or {far[0]} <= 0)),
        r(id, low, a, b) as (select id, low, i, i from link union select r.id, r.low, r.a, t.b from r join tie t on t.id = r.id and t.low = r.low and t.a = r.b),
        heads as (select id, low, a from r group by id, low, a having min(b) = a),
        k as (select v.id, count(*) filter (where h.low) as n_lower, count(*) filter (where not h.low) as n_upper from v left join heads h on h.id = v.id group by v.id)
        select id, case when n_lower = 0 then 'minimum' when n_upper = 0 then 'maximum' when n_lower = 1 and n_upper = 1 then 'regular' when n_lower >= 2 then '1-saddle' else '2-saddle' end as kind,
          n_lower, n_upper, n_lower > 2 or n_upper > 2 as degenerate from k"""


def hooked(field: str, predicate: str) -> str:
    """CTEs up to d(id, label): each masked vertex at the end of its pointers to the largest neighbour."""
    return f"""{masked(field, predicate)}, hook as materialized (select m.id, greatest(m.id, coalesce(max(e.dst), m.id)) as p from m left join e on e.src = m.id group by m.id),
        hw(id, p) as (select id, p from hook union all select w.id, q.p from hw w join hook q on w.p = q.id where q.p <> w.p), d as materialized (select w.id, w.p as label from hw w join hook q on q.id = w.p where q.p = w.p),
        best as materialized (select a.label, max(b.label) as next from e join d a on a.id = e.src join d b on b.id = e.dst where b.label > a.label group by a.label)"""


def printed(field: str, predicate: str) -> str:
    """CTEs up to once(id, label): roots attached once to the largest root next to them, and pointers followed."""
    return f"""{hooked(field, predicate)}, root as materialized (select r.label as id, coalesce(best.next, r.label) as p from (select distinct label from d) r left join best using (label)),
        rw(id, p) as (select id, p from root union all select w.id, q.p from rw w join root q on w.p = q.id where q.p <> w.p),
        ends as (select w.id, w.p from rw w join root q on q.id = w.p where q.p = w.p), once as materialized (select d.id, ends.p as label from d join ends on ends.id = d.label)"""


def build() -> dict[str, str]:
    o: dict[str, str] = {}
    for q, f in {"field_orders_plane": "orders", "field_lineitem_cube": "cube", "field_shipday_line": "line", "field_user_day": "user_day"}.items():
        o[q] = f"with {vertices(f)} select id, f from v"
    for q, f in {"order_field_orders": "orders", "order_field_cube_ties": "cube", "order_field_line": "line"}.items():
        o[q] = f"with {vertices(f)} select id, row_number() over (order by f, id) - 1 as ord from v"
    for q, f, s in (("pointer_up_orders", "orders", "up"), ("pointer_down_orders", "orders", "down"), ("pointer_up_cube", "cube", "up"), ("pointer_up_line_window", "line", "up")):
        o[q] = f"with {pointers(f)} select id, {s} as ptr from ptr"
    for f in ("orders", "cube", "line", "user_day"):
        o[f"descending_{f}"] = one_sided(f, "up")
        o[f"ascending_{f}"] = one_sided(f, "down")
    o["descending_smooth"] = one_sided("orders", "up", 2)
    for b in (1, 4, 16):
        o[f"descending_block_{b}"] = o["descending_orders"]
    for s in ("replicate", "coordinator", "neighbour", "shuffle", "precompress"):
        o[f"exchange_{s}"] = f"{both_sides('orders')} select id, max_id, min_id from seg"
    for f in ("orders", "cube", "line"):
        o[f"two_sided_{f}"] = f"{both_sides(f)} select id, max_id, min_id, dense_rank() over (order by max_id, min_id) - 1 as seg from seg"
    o["two_sided_sizes"] = f"{both_sides('orders')}, s as (select count(*) as size from seg group by max_id, min_id) select size, count(*) as segments from s group by size"
    for m in ("sync", "inplace", "chase"):
        o[f"compress_{m}_line"] = o["descending_line"]
    o["grow_from_extrema_orders"] = o["descending_orders"]
    o["geo_forest_roots"] = """select cast(r_regionkey as bigint) as id, cast(r_regionkey as bigint) as ptr from region union all select cast(n_nationkey + 100 as bigint), cast(n_regionkey as bigint) from nation
        union all select c_custkey * 2 + 1000, cast(n_regionkey as bigint) from customer join nation on c_nationkey = n_nationkey union all select s_suppkey * 2 + 1001, cast(n_regionkey as bigint) from supplier join nation on s_nationkey = n_nationkey"""
    o["extrema_orders"] = f"with {pointers('orders')} select id, 'maximum' as kind from ptr where id = up union all select id, 'minimum' from ptr where id = down"
    o["critical_orders_kinds"], o["critical_user_day"] = plane_kinds("orders"), plane_kinds("user_day")
    o["critical_line"] = f"""with {vertices("line")}, k as (select a.id, count(*) filter (where row(b.f, b.id) < row(a.f, a.id)) as n_lower, count(*) filter (where row(b.f, b.id) > row(a.f, a.id)) as n_upper from {STAR} group by a.id)
        select id, case when n_lower = 0 then 'minimum' when n_upper = 0 then 'maximum' when n_lower = 1 and n_upper = 1 then 'regular' else '1-saddle' end as kind, n_lower, n_upper, false as degenerate from k"""
    o["level_set_counts"] = f"with {vertices('orders')}, w as (select cast(unnest([1000000, 10000000, 20000000]) as bigint) as w) select w, count(*) filter (where f < w) as below, count(*) filter (where f > w) as above from v, w group by w"
    q90 = "(select quantile_cont(f, 0.9) from v)"
    for k, p in {"above": "f > 20000000", "below": "f < 10000000", "between": "f between 10000000 and 20000000", "quantile": f"f > {q90}", "normalised": "norm > 0.5"}.items():
        o[f"mask_{k}"] = f"with {vertices('orders')} select id, {p.replace('norm', f'({NORM})')} as m from v"
    for t, name in (("0.9", "09"), ("0.5", "05"), ("0.1", "01")):
        o[f"components_orders_t{name}"] = components("orders", f"norm > {t}")
    o["components_cube"] = components("cube", "f >= 14")
    o["components_user_day_fill0"], o["components_user_day_sparse"] = components("user_day", "f > 2000"), components("sparse", "f > 2000")
    o["components_line_above"] = components("line", "f > 600")
    o["components_blocks_16"] = o["components_orders_t05"]
    o["components_min_label"] = f"with recursive {masked('orders', 'norm > 0.5')}{CC} select id, min(id) over (partition by label) as label from c"
    o["components_explicit_orders"] = components("orders", "norm > 0.5", implicit=False)
    o["components_extract_nonneg"] = o["components_explicit_orders"]
    o["wave_filter_orders"] = o["components_explicit_orders"]
    o["label_propagation_orders"] = components("orders", "norm > 0.9", implicit=False)
    o["critical_cube"] = cube_kinds("cube")
    o["components_printed_1"] = f"with recursive {printed('orders', 'norm > 0.5')} select id, label from once"
    o["stitch_once_orders"] = f"with recursive {hooked('orders', 'norm > 0.5')} select d.id, coalesce(best.next, d.label) as label from d left join best using (label)"
    o["components_printed_diff_1"] = f"""with recursive {printed('orders', 'norm > 0.5')}{CC}, pairs as (select distinct once.label as la, c.label as lb from once join c using (id))
        select count(distinct la) as parts_a, count(distinct lb) as parts_b, (select count(*) from (select lb from pairs group by lb having count(*) > 1)) as apart from pairs"""
    for g, q in {"turn_chain": "turn_chain", "order_part": "order_part", "doc_lines": "doc_lines", "doc_copies": "doc_copies", "pages": "pages", "sessions": "sessions"}.items():
        o[f"components_{q}"] = graph_components(g)
    for b in ("hook_compress_parts", "union_find_parts", "tree_merge_parts", "sampled_components_parts", "local_first_parts", "label_propagation_parts"):
        o[b] = o["components_order_part"]
    o["graph_blocks_parts"] = o["components_order_part"]
    o["graph_blocks_sparse"], o["descending_graph_sparse"] = f"{both_sides('sparse')} select id, max_id, min_id from seg", one_sided("sparse", "up")
    o["any_representative_parts"] = f"with recursive {GRAPH['order_part']}, e as materialized (select src, dst from e0 union select dst, src from e0){CC} select size, count(*) as components from (select count(*) as size from c group by label) group by size"
    sweep = "t as (select cast(unnest(range(1, 10)) as bigint) as t)"
    o["percolation_sweep"] = f"""with recursive {vertices("orders")}, {sweep}, n as (select id, x, y, z, {NORM} as norm from v), mt as (select t, id, x, y, z from t, n where norm > t / 10.0),
        e as materialized (select a.t, a.id as src, b.id as dst from mt a, steps s join mt b on b.t = a.t and b.x = a.x + dx and b.y = a.y + dy where a.id <> b.id),
        c(t, id, label) using key (t, id) as (select t, id, id from mt union (select distinct on (u.t, u.id) u.t, u.id, w.label from recurring.c u, c w, e where e.t = u.t and w.t = u.t and e.src = u.id and e.dst = w.id and w.label > u.label order by u.t, u.id, w.label desc)),
        s as (select t, label, count(*) as size from c group by t, label)
        select t as tenths, cast(sum(size) as bigint) as inside, count(*) as components, max(size) as largest from s group by t"""
    comp5 = f"with recursive {masked('orders', 'norm > 0.5')}{CC}"
    o["component_size_hist"] = f"{comp5}, s as (select count(*) as size from c group by label) select size, count(*) as segments from s group by size"
    o["spanning_segments"] = f"{comp5}, b as (select c.label, {block_of('v', _W, NYO, 4, 4)} as block from c join v using (id)), s as (select label, min(block) < max(block) as s from b group by label) select count(*) as segments, count(*) filter (where s) as spanning from s"
    o["topk_segments"] = f"{both_sides('orders')}, s as (select max_id, count(*) as size from seg group by max_id) select max_id, size from s order by size desc, max_id limit 10"
    kinds = f"{both_sides('orders')}, r as (select {block_of('v', _W, NYO, 2, 2)} as block, {NORM} > 0.5 as inside, seg.max_id from seg join v using (id))"
    o["segments_rollup"] = f"{kinds} select coalesce(block, -1) as block, coalesce(cast(inside as varchar), 'all') as inside, count(*) as vertices, count(distinct max_id) as segments from r group by rollup (block, inside)"
    o["segments_cube"] = f"{kinds} select coalesce(block, -1) as block, coalesce(cast(inside as varchar), 'all') as inside, count(*) as vertices, count(distinct max_id) as segments from r group by cube (block, inside)"
    o["trace_paths_line"] = f"with recursive {pointers('line')}, w(seed, p, path) as (select id, id, cast(id as varchar) from ptr union all select w.seed, q.up, w.path || ',' || q.up from w join ptr q on w.p = q.id where q.up <> q.id) select seed, path from w join ptr q on w.p = q.id where q.up = q.id"
    o["separatrices_line"] = f"""with recursive {walks("line")}, k as (select a.id, count(*) filter (where row(b.f, b.id) < row(a.f, a.id)) as lo, count(*) filter (where row(b.f, b.id) > row(a.f, a.id)) as hi from {STAR} group by a.id)
        select a.id as saddle, 'down' as side, b.id as seed, e.ext as end_id from {STAR} join k on k.id = a.id join e_down e on e.id = b.id where k.lo > 1 and row(b.f, b.id) < row(a.f, a.id)
        union all select a.id, 'up', b.id, e.ext from {STAR} join k on k.id = a.id join e_up e on e.id = b.id where k.hi > 1 and row(b.f, b.id) > row(a.f, a.id)"""
    for f in ("cube", "orders"):
        o[f"extremum_graph_{f}"] = f"""with recursive {walks(f, 0, ("up",))}, r as (select v.*, row_number() over (order by f, id) - 1 as ord, e.ext from v join e_up e using (id))
            select least(a.ext, b.ext) as a, greatest(a.ext, b.ext) as b, max(least(a.ord, b.ord)) as saddle_ord from r a, steps s join r b on b.x = a.x + dx and b.y = a.y + dy and b.z = a.z + dz where a.ext <> b.ext group by 1, 2"""
    near = """q as (select vec_id as id, list_transform(embedding, lambda x: round(cast(x as double) * 1000)) as v from embeddings),
        n as (select a.id, b.id as nbr, cast(list_dot_product(a.v, b.v) as bigint) as sim from q a, q b where a.id <> b.id),
        k as (select id, nbr, sim from n qualify row_number() over (partition by id order by sim desc, nbr) <= 8)"""
    o["nearest_embeddings"] = f"with {near} select id, nbr, sim from k"
    o["knn_ascent_embeddings"] = f"""with recursive {near}, d as (select id, cast(sum(sim) as bigint) as f from k group by id), st as (select id, nbr from k union all select id, id from d),
        ptr as (select st.id, arg_max(d.id, row(d.f, d.id)) as up from st join d on d.id = st.nbr group by st.id),
        w(id, p) as (select id, up from ptr union all select w.id, q.up from w join ptr q on w.p = q.id where q.up <> w.p) select w.id, w.p as max_id from w join ptr q on w.p = q.id where q.up = w.p"""
    o["ghost_counts_blocks"] = f"{GHOSTS} select block, count(*) as ghosts from g group by block"
    o["memory_model_blocks"] = f"{GHOSTS} select cast(16 as bigint) as blocks, (select count(*) from v) as vertices, count(*) as ghosts, (select count(*) from v) * 8 + count(*) * 24 as bytes from g"
    o["cross_edge_pairs"] = f"{GHOSTS} select {block_of('b', _W, NYO, 4, 4)} as owner, g.block as needed_by, count(*) as requests from g join v b on b.id = g.id group by 1, 2"
    o["supply_counts"] = o["cross_edge_pairs"]
    cells = f"""with {vertices("orders")}, cells as (select a.id * 2 + k as cell_id, a.id as v0, b.id as v1, c.id as v2 from v a, (values (0, 1, 0), (1, 0, 1)) t(k, dx, dy) join v b on b.x = a.x + t.dx and b.y = a.y + t.dy join v c on c.x = a.x + 1 and c.y = a.y + 1)"""
    o["cells_from_grid"] = f"{cells} select cast(cell_id as bigint) as cell_id, v0, v1, v2 from cells"
    o["extracted_cells_by_threshold"] = f"""{cells}, t as (select unnest([9, 5, 1]) as t), n as (select id, {NORM} as norm from v)
        select cast(t as bigint) as tenths, (select count(*) from n where norm > t / 10.0) as vertices, count(*) as cells from t, cells join n a on a.id = v0 join n b on b.id = v1 join n c on c.id = v2 where a.norm > t / 10.0 and b.norm > t / 10.0 and c.norm > t / 10.0 group by t"""
    o["stream_sessions"] = "with g as (select user_id, ts, ts - lag(ts) over (partition by user_id order by ts) >= interval 6 hour as far from events), s as (select user_id, ts, sum(cast(coalesce(far, true) as int)) over (partition by user_id order by ts) as n from g) select user_id, min(ts) as first_ts, count(*) as events from s group by user_id, n"
    o["stream_window_field"] = "select date_trunc('day', ts) as day, user_id as id, cast(sum(cast(round(value * 100) as bigint)) as bigint) as f from events group by 1, 2"
    o["stream_incremental_components"] = o["components_order_part"]
    o["edge_degrees_order_part"] = f"with {GRAPH['order_part']}, d as (select src as id from e0 union all select dst from e0) select id, count(*) as degree from d group by id"
    return o
