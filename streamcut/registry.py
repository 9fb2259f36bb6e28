"""Queries of the partitioning engine and their oracle SQL (DuckDB), as ``__spark_entry__`` lists them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import edgecut, greedy, metrics, ordering, relational, schedule, stateless, theory, transforms
from .operators.stateless import constraint_set, grid_shape
from .plans import api, experiments, sqlapi
from .plans.scratch import keep
from .sources import graphs, zipf
from .sources.graphs import GRAPHS, load
from .streaming import live, snapshot

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def _add(name: str, query: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def _on(graph: str, f: Callable[[DataFrame], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, d: f(graphs.edges(spark, d, graph))


def _sql(graph: str, body: str) -> str:
    return f"WITH RECURSIVE e AS ({GRAPHS[graph].sql}) {body}"


def h32(*cols: str, seed: int = 0) -> str:
    text = " || ':' || ".join(f"CAST({c} AS VARCHAR)" for c in (str(seed), *cols))
    return f"CAST(('0x' || substr(md5({text}), 1, 8)) AS BIGINT)"


_ENDS = "ends AS (SELECT src AS v, 0 AS i, 1 AS o FROM e UNION ALL SELECT dst, 1, 0 FROM e)"
_DEG = _ENDS + ", deg AS (SELECT v, CAST(sum(i) AS BIGINT) AS d_in, CAST(sum(o) AS BIGINT) AS d_out, count(*) AS d FROM ends GROUP BY v)"

# --- graphs, degrees, skew -------------------------------------------------------------------------------------------
for _g, _graph in GRAPHS.items():
    _add(f"edges_{_g}", lambda s, d, g=_g: graphs.edges(s, d, g), _graph.sql)

for _g in ("word_next_conv", "doc_word", "order_part"):
    _add(f"degrees_{_g}", _on(_g, transforms.degrees), _sql(_g, f", {_DEG} SELECT * FROM deg"))
    _add(f"degree_distribution_{_g}", _on(_g, metrics.degree_distribution), _sql(_g, f", {_DEG} SELECT d AS degree, count(*) AS n_vertices, count(*) / (SELECT count(*) FROM deg) AS share FROM deg GROUP BY d"))
    _add(
        f"skew_profile_{_g}", _on(_g, metrics.skew_profile),
        _sql(_g, f", {_DEG} SELECT " + ", ".join(f"round(stddev_pop({x}) / avg({x}), 6) AS cv_{n}, round(max({x}) / avg({x}), 6) AS peak_{n}" for n, x in (("in", "CASE WHEN d_in > 0 THEN d_in END"), ("out", "CASE WHEN d_out > 0 THEN d_out END"))) + " FROM deg"),
    )
    _add(f"power_law_alpha_{_g}", _on(_g, metrics.power_law_alpha), _sql(_g, f", {_DEG} SELECT count(*) AS n, round(1 + count(*) / sum(ln(d / 0.5)), 6) AS alpha FROM deg"))
    _add(f"power_law_slope_{_g}", _on(_g, lambda e: metrics.power_law_alpha(e, method="slope")), _sql(_g, f", {_DEG}, h AS (SELECT d, count(*) AS n FROM deg GROUP BY d) SELECT CAST(sum(n) AS BIGINT) AS n, round(-regr_slope(ln(n), ln(d)), 6) AS alpha FROM h"))
_CV = {n: f"round(stddev_pop({x}) / avg({x}), 6)" for n, x in (("in", "CASE WHEN d_in > 0 THEN d_in END"), ("out", "CASE WHEN d_out > 0 THEN d_out END"))}
_ADVISED = ("word_next_conv", "doc_word", "word_doc", "order_part", "user_next")
_add(
    "advise", lambda s, d: _union([graphs.edges(s, d, g).transform(metrics.advise).select(F.lit(g).alias("graph"), "method") for g in _ADVISED]),
    " UNION ALL ".join(
        "SELECT * FROM (" + _sql(g, f""", {_DEG}, c AS (SELECT {_CV['in']} AS i, {_CV['out']} AS o FROM deg)
        SELECT '{g}' AS graph, CASE WHEN greatest(i, o) < 0.6 THEN 'greedy_affinity' WHEN i > 1.5 * o THEN 'greedy_indegree' ELSE 'greedy_total_degree' END AS method FROM c""") + ")"
        for g in _ADVISED
    ),
)


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


# --- hash placements ---------------------------------------------------------------------------------------------------
_EDGE = {"directed": h32("src", "dst"), "canonical": h32("least(src, dst)", "greatest(src, dst)"), "src": h32("src"), "dst": h32("dst")}
for _g in ("doc_word", "order_part"):
    for _m, _h in _EDGE.items():
        _add(f"edge_hash_{_m}_{_g}", _on(_g, lambda e, m=_m: stateless.edge_hash(e, 48, mode=m)), _sql(_g, f"SELECT src, dst, CAST({_h} % 48 AS INTEGER) AS part FROM e"))


def _grid_sql(p: int) -> str:
    shape = grid_shape(p)
    cells = shape[0] * shape[1]
    sets = "[" + ", ".join(str(constraint_set(k, p, shape)) for k in range(cells)) + "]"
    return f"""SELECT src, dst, CAST(c[CAST(h % len(c) AS INTEGER) + 1] AS INTEGER) AS part FROM (SELECT src, dst, {h32('src', 'dst', seed=1)} AS h,
      list_filter(s[{h32('src')} % {cells} + 1], lambda x: list_contains(s[{h32('dst')} % {cells} + 1], x)) AS c FROM e, (SELECT {sets} AS s))"""


def _corner_sql(p: int) -> str:
    r, c = grid_shape(p)
    cell = lambda v: f"({h32(v)} % {r * c})"
    return f"SELECT src, dst, CAST((CASE WHEN {h32('src', 'dst', seed=1)} % 2 = 0 THEN ({cell('src')} // {c}) * {c} + {cell('dst')} % {c} ELSE ({cell('dst')} // {c}) * {c} + {cell('src')} % {c} END) % {p} AS INTEGER) AS part FROM e"


for _g in ("doc_word", "order_part"):
    for _p in (16, 48, 7):
        _add(f"grid_hash_p{_p}_{_g}", _on(_g, lambda e, p=_p: stateless.grid_hash(e, p)), _sql(_g, _grid_sql(_p)))
    _add(f"grid_hash_corners_{_g}", _on(_g, lambda e: stateless.grid_hash(e, 48, pick="corners")), _sql(_g, _corner_sql(48)))

_LOW = "CASE WHEN du < dv THEN src WHEN dv < du THEN dst ELSE least(src, dst) END"


def _low_sql(col: str, tail: str) -> str:
    return f", {_DEG}, x AS (SELECT src, dst, a.{col} AS du, b.{col} AS dv FROM e JOIN deg a ON a.v = src JOIN deg b ON b.v = dst), lo AS (SELECT *, {_LOW} AS lo FROM x) {tail}"


for _g in ("word_next_conv", "doc_word"):
    for _k, _c in (("total", "d"), ("in", "d_in"), ("out", "d_out")):
        _add(f"low_degree_hash_{_k}_{_g}", _on(_g, lambda e, k=_k: stateless.low_degree_hash(e, 48, degree=k)), _sql(_g, _low_sql(_c, f"SELECT src, dst, CAST({h32('lo')} % 48 AS INTEGER) AS part FROM lo")))
_add("hybrid_threshold_doc_word", _on("doc_word", lambda e: edgecut.hybrid_threshold(e, 48, 20)), _sql("doc_word", f", {_DEG} SELECT src, dst, CAST((CASE WHEN d_in <= 20 THEN {h32('dst')} ELSE {h32('src')} END) % 48 AS INTEGER) AS part FROM e JOIN deg ON v = dst"))

# --- orders and schedules ----------------------------------------------------------------------------------------------
_STREAM = """o AS (SELECT src, row_number() OVER (ORDER BY md5('0:' || src), src) - 1 AS arrival FROM (SELECT DISTINCT src FROM e)),
s AS (SELECT src, dst, arrival, row_number() OVER (ORDER BY arrival, md5('0:' || src || ':' || dst), dst) - 1 AS seq FROM e JOIN o USING (src))"""
for _g in ("user_next", "nation_flow", "word_next_conv"):
    _add(f"order_random_{_g}", _on(_g, lambda e: ordering.stream(e, "random")), _sql(_g, f", {_STREAM} SELECT * FROM s"))
_add("order_time_user_next", lambda s, d: ordering.order_by_time(load(s, d, "events"), "user_id", "ts", "event_id"), "SELECT user_id AS src, row_number() OVER (ORDER BY t) - 1 AS arrival FROM (SELECT user_id, min(struct_pack(ts := ts, i := event_id)) AS t FROM events GROUP BY user_id)")
_add(
    "bfs_depth_user_next", _on("user_next", lambda e: ordering.bfs_levels(e, start=0).where("tree = 0").select("v", F.col("depth").cast("int").alias("depth"))),
    _sql("user_next", ", r AS (SELECT 0::BIGINT AS v, 0 AS depth UNION SELECT dst, depth + 1 FROM r JOIN e ON e.src = r.v WHERE depth < 12) SELECT v, CAST(min(depth) AS INTEGER) AS depth FROM r GROUP BY v"),
)


def _search_sql(graph: str, key: str, deep: bool) -> str:
    """Breadth- or depth-first search as a recursion over one row: the vertices found, or a stack and the vertices out."""
    by = "v" if key == "id" else "md5('0:' || v), v"
    head = f""", vs AS (SELECT v, max(s) AS s FROM (SELECT src AS v, 1 AS s FROM e UNION ALL SELECT dst, 0 FROM e) GROUP BY v),
    k AS (SELECT v, row_number() OVER (ORDER BY {by}) AS n, row_number() OVER (ORDER BY 1 - s, {by}) AS place FROM vs),
    near AS (SELECT src AS v, list(dst ORDER BY n) AS near FROM e JOIN k ON k.v = dst GROUP BY src),
    all_ AS (SELECT list(v ORDER BY place) AS roots, count(*) AS total FROM k)"""
    new = "list_filter(coalesce(near, CAST([] AS BIGINT[])), lambda x: NOT list_contains(q, x))"
    root = "(list_filter(roots, lambda x: NOT list_contains(q, x)))[1]"
    if deep:
        walk = f"""r AS (SELECT 0 AS t, CAST([] AS BIGINT[]) AS stack, CAST([] AS BIGINT[]) AS q UNION ALL
        SELECT t + 1, CASE WHEN len(stack) = 0 THEN [{root}] WHEN list_contains(q, stack[1]) THEN stack[2:] ELSE list_concat({new}, stack[2:]) END,
          CASE WHEN len(stack) = 0 OR list_contains(q, stack[1]) THEN q ELSE list_append(q, stack[1]) END
        FROM r LEFT JOIN near ON near.v = stack[1], all_ WHERE len(q) < total)"""
    else:
        walk = f"""r AS (SELECT 0 AS t, CAST([] AS BIGINT[]) AS q UNION ALL
        SELECT CASE WHEN t < len(q) THEN t + 1 ELSE t END, CASE WHEN t < len(q) THEN list_concat(q, {new}) ELSE list_append(q, {root}) END
        FROM r LEFT JOIN near ON near.v = q[t + 1], all_ WHERE t < total)"""
    tail = """f AS (SELECT q FROM r, all_ WHERE len(q) = total LIMIT 1),
    o AS (SELECT v AS src, row_number() OVER (ORDER BY i) - 1 AS arrival FROM (SELECT unnest(q) AS v, generate_subscripts(q, 1) AS i FROM f) WHERE v IN (SELECT src FROM e)),
    s AS (SELECT src, dst, arrival, row_number() OVER (ORDER BY arrival, md5('0:' || src || ':' || dst), dst) - 1 AS seq FROM e JOIN o USING (src)) SELECT * FROM s"""
    return _sql(graph, f"{head}, {walk}, {tail}")


for _g, _k in (("nation_flow", "id"), ("user_next", "hash"), ("host_link", "hash")):
    _add(f"order_bfs_{_g}", _on(_g, lambda e, k=_k: ordering.stream(e, "bfs", key=k)), _search_sql(_g, _k, False))
    _add(f"order_dfs_{_g}", _on(_g, lambda e, k=_k: ordering.stream(e, "dfs", key=k)), _search_sql(_g, _k, True))

_INDEG = """q AS (SELECT seq, arrival, src, dst, count(*) OVER (PARTITION BY dst ORDER BY seq) AS in_v FROM s),
d AS (SELECT q.*, (SELECT count(*) FROM s x WHERE x.dst = q.src AND x.seq <= q.seq) AS in_u FROM q)"""


def _total_sql(p: int) -> str:
    """The schedule of the total-degree method, release first, direct guard."""
    return f"""b AS (SELECT src AS v, count(*) AS n, min(arrival) AS came, min(seq) AS f FROM s GROUP BY src),
c AS (SELECT s.*, bu.n AS out_u, coalesce(bv.n, 0) AS out_v, bv.came, bv.f, CASE WHEN bv.came IS NOT NULL AND bv.came <= s.arrival THEN 'known' WHEN bu.n < {p} THEN 'small' ELSE 'postponed' END AS class
  FROM s JOIN b bu ON bu.v = s.src LEFT JOIN b bv ON bv.v = s.dst),
k AS (SELECT *, CASE WHEN class <> 'postponed' THEN arrival WHEN came IS NOT NULL THEN came ELSE {schedule.END} END AS place_arrival, CASE WHEN class = 'postponed' THEN 0 ELSE 1 END AS phase,
  CASE WHEN class <> 'postponed' THEN seq WHEN came IS NULL THEN {schedule.END} ELSE f - 1 END AS pos FROM c),
di AS (SELECT k.*, coalesce(u.n, 0) AS in_u, coalesce(w.n, 0) AS in_v FROM k
  ASOF LEFT JOIN (SELECT dst AS v, seq, count(*) OVER (PARTITION BY dst ORDER BY seq) AS n FROM s) u ON u.v = k.src AND k.pos >= u.seq
  ASOF LEFT JOIN (SELECT dst AS v, seq, count(*) OVER (PARTITION BY dst ORDER BY seq) AS n FROM s) w ON w.v = k.dst AND k.pos >= w.seq),
sched AS (SELECT src, dst, arrival, seq, CAST(sign(CASE WHEN class = 'small' THEN in_u - in_v ELSE in_u + out_u - in_v - out_v END) AS INTEGER) AS cmp, class, class <> 'postponed' AS guarded, place_arrival, phase,
  row_number() OVER (ORDER BY place_arrival, phase, seq) - 1 AS place_seq FROM di)"""


for _g in ("user_next", "word_next_conv", "nation_flow"):
    _add(f"placement_schedule_{_g}", _on(_g, lambda e: schedule.total_degree_schedule(keep(ordering.stream(e)), 8)), _sql(_g, f", {_STREAM}, {_total_sql(8)} SELECT * FROM sched"))
_add(
    "buffer_occupancy_word_next_conv", _on("word_next_conv", lambda e: schedule.buffer_occupancy(schedule.total_degree_schedule(keep(ordering.stream(e)), 8))),
    _sql("word_next_conv", f", {_STREAM}, {_total_sql(8)}, m AS (SELECT arrival AS a, 1 AS d FROM sched WHERE class = 'postponed' UNION ALL SELECT place_arrival, -1 FROM sched WHERE class = 'postponed') SELECT a AS arrival, CAST(sum(sum(d)) OVER (ORDER BY a) AS BIGINT) AS buffered FROM m GROUP BY a"),
)
_add(
    "low_degree_hash_online_user_next", _on("user_next", lambda e: stateless.low_degree_hash_online(keep(ordering.stream(e)), 16)),
    _sql("user_next", f""", {_STREAM}, ev AS (SELECT src AS v, seq FROM s UNION ALL SELECT dst, seq FROM s), cum AS (SELECT DISTINCT v, seq, count(*) OVER (PARTITION BY v ORDER BY seq) AS n FROM ev),
    x AS (SELECT s.*, a.n AS du, b.n AS dv FROM s JOIN cum a ON a.v = src AND a.seq = s.seq JOIN cum b ON b.v = dst AND b.seq = s.seq), lo AS (SELECT *, {_LOW} AS lo FROM x) SELECT src, dst, arrival, seq, CAST({h32('lo')} % 16 AS INTEGER) AS part FROM lo"""),
)


# --- greedy placements against a recursive query -----------------------------------------------------------------------
def _greedy_sql(graph: str, sched: str, p: int, guard: bool) -> str:
    """The sequential method as a recursion over the schedule: masks and loads are lists."""
    every = (1 << p) - 1
    over = f"sc.guarded AND r.t > 0 AND 10 * {p} * list_max(r.loads) >= 11 * r.t" if guard else "FALSE"
    return _sql(graph, f""", {_STREAM}, {sched},
    vs AS (SELECT v, row_number() OVER (ORDER BY v) AS i FROM (SELECT src AS v FROM e UNION SELECT dst FROM e)),
    sc AS MATERIALIZED (SELECT place_seq, cmp, guarded, a.i AS iu, b.i AS iv FROM sched JOIN vs a ON a.v = src JOIN vs b ON b.v = dst),
    r AS (SELECT CAST(0 AS BIGINT) AS t, (SELECT list_transform(range(count(*)), lambda x: CAST(0 AS BIGINT)) FROM vs) AS masks, list_transform(range({p}), lambda x: CAST(0 AS BIGINT)) AS loads, CAST(-1 AS BIGINT) AS part
      UNION ALL
      SELECT t + 1, list_transform(masks, lambda x, i: CASE WHEN i = iu OR i = iv THEN x | (CAST(1 AS BIGINT) << CAST(k AS INTEGER)) ELSE x END), list_transform(loads, lambda x, i: CASE WHEN i = k + 1 THEN x + 1 ELSE x END), k FROM (
        SELECT t, masks, loads, iu, iv, list_min(list_transform(list_filter(range({p}), lambda j: (cand >> CAST(j AS INTEGER)) & 1 = 1), lambda j: loads[j + 1] * {p} + j)) % {p} AS k FROM (
          SELECT r.t, r.masks, r.loads, sc.iu, sc.iv, CASE WHEN {over} THEN {every} WHEN r.masks[iu] & r.masks[iv] <> 0 THEN r.masks[iu] & r.masks[iv] WHEN r.masks[iu] | r.masks[iv] = 0 THEN {every}
            WHEN sc.cmp = 0 OR r.masks[iu] = 0 OR r.masks[iv] = 0 THEN r.masks[iu] | r.masks[iv] WHEN sc.cmp < 0 THEN r.masks[iu] ELSE r.masks[iv] END AS cand
          FROM r JOIN sc ON sc.place_seq = r.t)))
    SELECT src, dst, seq, CAST(part AS INTEGER) AS part FROM sched JOIN r ON r.t = place_seq + 1""")


_PLAIN = "sched AS (SELECT src, dst, seq, seq AS place_seq, 0 AS cmp, TRUE AS guarded FROM s)"
_BYIN = f"{_INDEG}, sched AS (SELECT src, dst, seq, seq AS place_seq, CAST(sign(in_u - in_v) AS INTEGER) AS cmp, TRUE AS guarded FROM d)"
for _g in ("nation_trade", "nation_flow", "host_link"):
    for _p in (4, 8):
        for _tag, _guard in (("", 1.1), ("_unguarded", None)):
            if _tag and (_p == 8 or _g == "host_link"):
                continue
            for _m, _f, _s in (("greedy_affinity", greedy.greedy_affinity, _PLAIN), ("greedy_indegree", greedy.greedy_indegree, _BYIN), ("greedy_total_degree", greedy.greedy_total_degree, _total_sql(_p))):
                _add(f"{_m}_{_g}_p{_p}{_tag}", _on(_g, lambda e, f=_f, p=_p, guard=_guard: f(keep(ordering.stream(e)), p, guard=guard).select("src", "dst", "seq", "part")), _greedy_sql(_g, _s, _p, _guard is not None))


for _m, _f, _s in (("greedy_affinity", greedy.greedy_affinity, _PLAIN), ("greedy_indegree", greedy.greedy_indegree, _BYIN), ("greedy_total_degree", greedy.greedy_total_degree, _total_sql(8))):
    _add(f"{_m}_user_next_p8", _on("user_next", lambda e, f=_f: f(keep(ordering.stream(e)), 8).select("src", "dst", "seq", "part")), _greedy_sql("user_next", _s, 8, True))

for _tag, _opts, _p in (("hold_all", {"hub_threshold": 0}, 4), ("hold_nothing", {"hub_threshold": 1000}, 4), ("guard_all", {"guard_scope": "all"}, 4), ("guard_none", {"guard_scope": "none"}, 4)):
    _s = _total_sql(_p).replace(f"bu.n < {_p}", f"bu.n < {_opts.get('hub_threshold', _p)}").replace("class <> 'postponed' AS guarded", {"all": "TRUE AS guarded", "none": "FALSE AS guarded"}.get(_opts.get("guard_scope"), "class <> 'postponed' AS guarded"))
    _add(f"greedy_total_degree_nation_flow_{_tag}", _on("nation_flow", lambda e, o=_opts, p=_p: greedy.greedy_total_degree(keep(ordering.stream(e)), p, **o).select("src", "dst", "seq", "part")), _greedy_sql("nation_flow", _s, _p, True))


def _improvement(edges: DataFrame, graph: str, p: int) -> DataFrame:
    table = _union([api.partition(edges, m, p).metrics(graph) for m in ("edge_hash", *experiments.GREEDY)])
    return metrics.improvement(table).select("graph", "method", "n_vertices", "copies", "replication_factor", F.round("improvement", 9).alias("improvement"))


def _improvement_sql(graph: str, p: int) -> str:
    placements = {"edge_hash": _sql(graph, f"SELECT src, dst, CAST({h32('src', 'dst')} % {p} AS INTEGER) AS part FROM e")}
    placements |= {m: _greedy_sql(graph, s, p, True) for m, s in zip(experiments.GREEDY, (_PLAIN, _BYIN, _total_sql(p)))}
    each = " UNION ALL ".join(f"SELECT '{m}' AS method, count(DISTINCT v) AS n_vertices, count(*) AS copies FROM (SELECT DISTINCT unnest([src, dst]) AS v, part FROM ({q}))" for m, q in placements.items())
    return f"""WITH t AS ({each}), f AS (SELECT *, copies / n_vertices AS replication_factor FROM t)
    SELECT '{graph}' AS graph, method, n_vertices, copies, replication_factor, round(100 * ((SELECT replication_factor FROM f WHERE method = 'greedy_affinity') - replication_factor) / (SELECT replication_factor FROM f WHERE method = 'greedy_affinity'), 9) AS improvement FROM f"""


for _g in ("nation_flow", "host_link"):
    _add(f"improvement_{_g}", _on(_g, lambda e, g=_g: _improvement(e, g, 4)), _improvement_sql(_g, 4))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Measures of the total-degree method on the conversation word graph."""
    return api.partition(graphs.edges(spark, sf_dir, "word_next_conv"), "greedy_total_degree", 8, engine="exact").metrics("word_next_conv")


_add("flagship", flagship)
for _m in ("greedy_affinity", "greedy_indegree", "greedy_total_degree"):
    _add(f"metrics_{_m}_word_next_conv", _on("word_next_conv", lambda e, m=_m: api.partition(e, m, 16, engine="exact").metrics("word_next_conv")))


def _with_gap(edges: DataFrame, **opts) -> DataFrame:
    """Measures of an engine that isn't exact, with what it loses against the exact one."""
    edges = keep(edges, "edges")
    stream = keep(ordering.stream(edges), "stream")
    other, exact = api.partition(edges, "greedy_indegree", 8, stream=stream, **opts), api.partition(edges, "greedy_indegree", 8, engine="exact", stream=stream)
    return other.metrics("word_next_conv").crossJoin(metrics.engine_gap(exact.placed, other.placed).withColumnRenamed("gap", "engine_gap"))  # two single rows


_add("greedy_sharded_word_next_conv", _on("word_next_conv", lambda e: _with_gap(e, engine="sharded", shards=4)))
_add("greedy_snapshot_word_next_conv", _on("word_next_conv", lambda e: _with_gap(e, engine="snapshot", batch=20000)))

# --- measures over hash placements -------------------------------------------------------------------------------------
_PLACED = f"pl AS (SELECT src, dst, CAST({h32('src', 'dst')} % 16 AS INTEGER) AS part FROM e), rep AS (SELECT DISTINCT v, part FROM (SELECT src AS v, part FROM pl UNION ALL SELECT dst, part FROM pl))"
for _g in ("word_next_conv", "order_part"):
    _h = lambda e: stateless.edge_hash(e, 16)
    _add(f"replication_factor_{_g}", _on(_g, lambda e: metrics.replication_factor(stateless.edge_hash(e, 16))), _sql(_g, f", {_PLACED} SELECT count(DISTINCT v) AS n_vertices, count(*) AS copies, count(*) / count(DISTINCT v) AS replication_factor FROM rep"))
    _add(f"replica_sets_{_g}", _on(_g, lambda e: metrics.replica_sets(stateless.edge_hash(e, 16)).select("v", F.array_join("parts", ",").alias("parts"), "copies", "mirrors")), _sql(_g, f", {_PLACED} SELECT v, string_agg(CAST(part AS VARCHAR), ',' ORDER BY part) AS parts, count(*) AS copies, count(*) - 1 AS mirrors FROM rep GROUP BY v"))
    _add(f"replica_masks_{_g}", _on(_g, lambda e: metrics.replica_masks(stateless.edge_hash(e, 16))), _sql(_g, f", {_PLACED} SELECT v, CAST(sum(CAST(1 AS BIGINT) << part) AS BIGINT) AS mask, count(*) AS copies FROM rep GROUP BY v"))
    _add(f"part_loads_{_g}", _on(_g, lambda e: metrics.part_loads(stateless.edge_hash(e, 16), 16)), _sql(_g, f", {_PLACED} SELECT CAST(k AS INTEGER) AS part, count(src) AS edges FROM range(16) t(k) LEFT JOIN pl ON part = k GROUP BY k"))
    _add(f"imbalance_{_g}", _on(_g, lambda e: metrics.imbalance(stateless.edge_hash(e, 16), 16)), _sql(_g, f", {_PLACED} SELECT CAST(sum(n) AS BIGINT) AS n_edges, max(n) AS max_edges, max(n) * 16 / sum(n) AS imbalance FROM (SELECT part, count(*) AS n FROM pl GROUP BY part)"))
    _add(f"vertex_cut_feasible_{_g}", _on(_g, lambda e: metrics.vertex_cut_feasible(stateless.edge_hash(e, 16), 16, 11, 10).select("n_edges", "feasible")), _sql(_g, f", {_PLACED} SELECT CAST(sum(n) AS BIGINT) AS n_edges, max(n) * 160 < sum(n) * 11 AS feasible FROM (SELECT part, count(*) AS n FROM pl GROUP BY part)"))
    _add(f"masters_{_g}", _on(_g, lambda e: metrics.masters(stateless.edge_hash(e, 16))), _sql(_g, f", {_PLACED}, n AS (SELECT v, part, count(*) AS n FROM (SELECT src AS v, part FROM pl UNION ALL SELECT dst, part FROM pl WHERE src <> dst) GROUP BY v, part) SELECT v, part FROM n QUALIFY row_number() OVER (PARTITION BY v ORDER BY n DESC, part) = 1"))
    _add(f"message_count_{_g}", _on(_g, lambda e: metrics.message_count(stateless.edge_hash(e, 16))), _sql(_g, f", {_PLACED} SELECT count(*) - count(DISTINCT v) AS messages FROM rep"))
    _VP = f"vp AS (SELECT v, CAST({h32('v')} % 16 AS INTEGER) AS part FROM (SELECT src AS v FROM e UNION SELECT dst FROM e))"
    _add(f"edge_cut_{_g}", _on(_g, lambda e: edgecut.edge_cut(e, edgecut.hash_vertices(e, 16))), _sql(_g, f", {_VP} SELECT count(*) AS n_edges, CAST(count(*) FILTER (a.part <> b.part) AS BIGINT) AS cut_edges FROM e JOIN vp a ON a.v = src JOIN vp b ON b.v = dst"))
    _add(f"vertex_balance_{_g}", _on(_g, lambda e: edgecut.vertex_balance(edgecut.hash_vertices(e, 16), 16)), _sql(_g, f", {_VP} SELECT CAST(sum(n) AS BIGINT) AS n_vertices, max(n) AS max_vertices, max(n) * 16 / sum(n) AS balance, max(n) * 160 <= sum(n) * 11 AS feasible FROM (SELECT count(*) AS n FROM vp GROUP BY part)"))

# --- expectations ------------------------------------------------------------------------------------------------------
_OCC = "(1 - pow(1 - 1.0::DOUBLE / 16, {}))"
for _g in ("word_next_conv", "doc_word"):
    _two = "x AS (SELECT src, dst, a.d AS du, b.d AS dv FROM e JOIN deg a ON a.v = src JOIN deg b ON b.v = dst)"
    _add(f"expected_rf_paper_{_g}", _on(_g, lambda e: theory.expected_rf_low_degree(e, 16)), _sql(_g, f", {_DEG}, {_two}, n AS (SELECT v, count(*) FILTER (d > o) AS r FROM (SELECT src AS v, du AS d, dv AS o FROM x UNION ALL SELECT dst, dv, du FROM x) GROUP BY v) SELECT count(*) AS n_vertices, round(avg(1 + 15 * {_OCC.format('r')}), 6) AS expected_rf FROM n"))
    _add(f"expected_rf_exact_{_g}", _on(_g, lambda e: theory.expected_rf_low_degree(e, 16, form="exact")), _sql(_g, _low_sql("d", f", hit AS (SELECT DISTINCT v, lo FROM (SELECT src AS v, lo FROM lo UNION ALL SELECT dst, lo FROM lo)), n AS (SELECT v, count(*) FILTER (lo = v) AS home, count(*) FILTER (lo <> v) AS r FROM hit GROUP BY v) SELECT count(*) AS n_vertices, round(avg(CASE WHEN home > 0 THEN 1 + 15 * {_OCC.format('r')} ELSE 16 * {_OCC.format('r')} END), 6) AS expected_rf FROM n")))
    _add(f"expected_rf_law_{_g}", _on(_g, lambda e: theory.expected_rf_low_degree(e, 16, form="law", alpha=2.0)), _sql(_g, f", {_DEG}, k AS (SELECT d, count(*) AS n, pow(d, -2.0::DOUBLE) AS w FROM deg GROUP BY d), c AS (SELECT d, n, sum(w) OVER (ORDER BY d) / (SELECT sum(w) FROM k) AS s FROM k) SELECT CAST(sum(n) AS BIGINT) AS n_vertices, round(sum(n * (1 + 15 * {_OCC.format('d * s')})) / sum(n), 6) AS expected_rf FROM c"))
    _add(f"expected_rf_edge_hash_{_g}", _on(_g, lambda e: theory.expected_rf_edge_hash(e, 16)), _sql(_g, f", n AS (SELECT v, count(*) AS d FROM (SELECT src AS v FROM e UNION ALL SELECT dst FROM e WHERE src <> dst) GROUP BY v) SELECT count(*) AS n_vertices, round(avg(16 * {_OCC.format('d')}), 6) AS expected_rf FROM n"))
_add(
    "theorem_check_nation_flow", _on("nation_flow", lambda e: api.theorem_check(e, 8, 50).select(F.round("mean", 9).alias("mean"), F.round("stddev", 9).alias("stddev"), "runs")),
    _sql("nation_flow", _low_sql("d", """, z AS (SELECT src, dst, k, CAST(('0x' || substr(md5(k || ':' || lo), 1, 8)) AS BIGINT) % 8 AS part FROM lo, range(50) t(k)),
    c AS (SELECT DISTINCT k, unnest([src, dst]) AS v, part FROM z), f AS (SELECT k, count(*) / count(DISTINCT v) AS rf FROM c GROUP BY k)
    SELECT round(avg(rf), 9) AS mean, round(stddev_samp(rf), 9) AS stddev, count(*) AS runs FROM f""")),
)

# --- synthetic graphs and experiments ----------------------------------------------------------------------------------
for _a, _b in ((2.2, 2.2), (1.9, 2.2), (2.1, 1.9)):
    _add(f"zipf_graph_{_a}_{_b}".replace(".", ""), lambda s, d, a=_a, b=_b: zipf.zipf_on(load(s, d, "customer").select("c_custkey"), a, b, 200), zipf.zipf_on_sql("SELECT c_custkey AS v FROM customer", _a, _b, 200))
for _n, _f in (
    ("rf", experiments.replication), ("imbalance", experiments.imbalance), ("synthetic", experiments.exponents), ("exponents", experiments.exponent_scaling), ("parts", experiments.parts),
    ("out_skew", experiments.out_skew), ("theorem", experiments.theorem), ("ablations", experiments.ablations), ("buffer_bounds", experiments.buffer_bounds),
):
    _add(f"experiment_{_n}", _f)


def _edge_cut_sql(graph: str, p: int, linear: bool) -> str:
    """The edge-cut relatives as a recursion over the vertex stream: parts of the vertices and sizes are lists."""
    score = "held[k + 1] * (1 - sizes[k + 1] / room)" if linear else "CASE WHEN sizes[k + 1] < room THEN held[k + 1] - scale * 1.5::DOUBLE * pow(sizes[k + 1], 0.5::DOUBLE) ELSE -1e300::DOUBLE END"
    return _sql(graph, f""", o AS (SELECT src, row_number() OVER (ORDER BY md5('0:' || src), src) - 1 AS arrival FROM (SELECT DISTINCT src FROM e)),
    u AS (SELECT src AS v, dst AS w FROM e UNION SELECT dst, src FROM e), vs AS (SELECT v, row_number() OVER (ORDER BY arrival IS NULL, arrival, v) AS i FROM (SELECT DISTINCT v FROM u) LEFT JOIN o ON o.src = v),
    n AS (SELECT a.v, a.i, list(b.i) AS near FROM u JOIN vs a ON a.v = u.v JOIN vs b ON b.v = u.w GROUP BY a.v, a.i),
    c AS (SELECT CAST((SELECT count(*) FROM vs) AS DOUBLE) / {p} * 1.1::DOUBLE + 1 AS room, (SELECT count(*) FROM e) * pow({p}::DOUBLE, 0.5::DOUBLE) / pow(CAST((SELECT count(*) FROM vs) AS DOUBLE), 1.5::DOUBLE) AS scale),
    r AS (SELECT CAST(0 AS BIGINT) AS t, (SELECT list_transform(range(count(*)), lambda x: CAST(-1 AS BIGINT)) FROM vs) AS parts, list_transform(range({p}), lambda x: CAST(0 AS BIGINT)) AS sizes
      UNION ALL
      SELECT t + 1, list_transform(parts, lambda x, j: CASE WHEN j = t + 1 THEN part ELSE x END), list_transform(sizes, lambda x, j: CASE WHEN j = part + 1 THEN x + 1 ELSE x END) FROM (
        SELECT t, parts, sizes, (list_sort(list_transform(range({p}), lambda k: {{'a': -({score}), 'b': sizes[k + 1], 'k': k}})))[1].k AS part FROM (
          SELECT r.t, r.parts, r.sizes, c.room, c.scale, list_transform(range({p}), lambda k: len(list_filter(near, lambda x: parts[x] = k))) AS held FROM r JOIN n ON n.i = r.t + 1, c))),
    f AS (SELECT parts FROM r ORDER BY t DESC LIMIT 1)
    SELECT count(*) AS n_edges, CAST(count(*) FILTER (f.parts[a.i] <> f.parts[b.i]) AS BIGINT) AS cut_edges FROM e JOIN vs a ON a.v = src JOIN vs b ON b.v = dst, f""")


for _g, _p in (("user_next", 4), ("host_link", 4), ("part_next", 8)):
    for _n, _f in (("linear_greedy", edgecut.edge_cut_linear_greedy), ("interpolated", edgecut.edge_cut_interpolated)):
        _add(f"edge_cut_{_n}_{_g}", _on(_g, lambda e, f=_f, p=_p: edgecut.edge_cut(e, f(e, keep(ordering.order_random(e)), p))), None if _g == "part_next" else _edge_cut_sql(_g, _p, _n == "linear_greedy"))

# --- windows and relational shaping ------------------------------------------------------------------------------------
_add("windowed_load_tumbling", lambda s, d: live.windowed_load(load(s, d, "events")).select("start", "edges"), "SELECT date_trunc('day', ts) AS start, count(*) AS edges FROM events GROUP BY 1")
_add("windowed_load_sliding", lambda s, d: live.windowed_load(load(s, d, "events"), "1 day", "6 hours").select("start", "edges"), "SELECT time_bucket(INTERVAL 6 HOUR, ts) - k * INTERVAL 6 HOUR AS start, count(*) AS edges FROM events, range(4) t(k) GROUP BY 1")
_add("session_load", lambda s, d: live.session_load(load(s, d, "events"), "6 hours"), "SELECT user_id, min(ts) AS start, count(*) AS edges FROM (SELECT *, sum(n) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS n FROM events)) GROUP BY user_id, g")
_add("filter_min_degree_user_key", _on("user_key", lambda e: transforms.filter_min_degree(e, 20)), _sql("user_key", f", {_DEG} SELECT src, dst FROM e JOIN deg a ON a.v = src JOIN deg b ON b.v = dst WHERE a.d >= 20 AND b.d >= 20"))
_add("hub_filter_doc_word", _on("doc_word", lambda e: transforms.hub_filter(e, 400)), _sql("doc_word", "SELECT e.src, e.dst FROM e JOIN (SELECT src FROM e GROUP BY src HAVING count(*) >= 400) h ON h.src = e.src"))
_add("induced_quality_doc_word", lambda s, d: graphs.edges(s, d, "doc_word").join(load(s, d, "labels").where("quality = 1").select(F.col("doc_id").alias("src")).distinct(), "src", "left_semi"), _sql("doc_word", "SELECT src, dst FROM e WHERE src IN (SELECT doc_id FROM labels WHERE quality = 1)"))
_add("targets_that_never_arrive", _on("word_next_conv", lambda e: e.select(F.col("dst").alias("v")).distinct().join(e.select(F.col("src").alias("v")).distinct(), "v", "left_anti")), _sql("word_next_conv", "SELECT DISTINCT dst AS v FROM e WHERE dst NOT IN (SELECT src FROM e)"))
_add("undirect_part_next", _on("part_next", transforms.undirect), _sql("part_next", "SELECT src, dst FROM e UNION SELECT dst, src FROM e"))
_add("canonical_part_next", _on("part_next", transforms.canonical), _sql("part_next", "SELECT DISTINCT least(src, dst) AS src, greatest(src, dst) AS dst FROM e"))
_add("sample_edges_doc_word", _on("doc_word", lambda e: transforms.sample_edges(e, 10)), _sql("doc_word", f"SELECT src, dst FROM e WHERE {h32('src', 'dst')} % 100 < 10"))
_add("top_hubs_doc_word", _on("doc_word", lambda e: transforms.degrees(e).orderBy(F.desc("d"), "v").limit(20)), _sql("doc_word", f", {_DEG} SELECT * FROM deg ORDER BY d DESC, v LIMIT 20"))


# --- relational operators around a graph -------------------------------------------------------------------------------
def _timed(events: DataFrame) -> DataFrame:
    return events.select(F.col("user_id").alias("src"), F.get_json_object("props", "$.k").cast("long").alias("dst"), "ts", "event_id").where("dst is not null")


_TIMED = "x AS (SELECT user_id AS src, CAST(json_extract(props, '$.k') AS BIGINT) AS dst, ts, event_id FROM events WHERE json_extract(props, '$.k') IS NOT NULL)"
_add(
    "asof_last_click", lambda s, d: relational.asof_join(load(s, d, "events").where("event_id % 2 = 0").select("event_id", "user_id", "ts"), load(s, d, "events").where("event_id % 2 = 1").select("user_id", "ts", "value", F.col("event_id").alias("n")), "user_id", "ts", "value", "n").select("event_id", "asof_value"),
    """WITH u AS (SELECT event_id, user_id, ts, value, event_id % 2 AS odd FROM events)
    SELECT event_id, l.value AS asof_value FROM (SELECT event_id, odd, last_value(CASE WHEN odd = 1 THEN {'value': value} END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, 1 - odd, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS l FROM u) WHERE odd = 0""",
)
_add("interval_matched_reverse", lambda s, d: live.matched_reverse(_timed(load(s, d, "events")), "1 HOUR"), f"WITH {_TIMED} SELECT a.src, a.dst, a.ts, b.ts AS back FROM x a JOIN x b ON a.src = b.dst AND a.dst = b.src AND a.src <> a.dst AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
_add("mutual_user_next", _on("user_next", relational.mutual), _sql("user_next", "SELECT a.src, a.dst FROM e a JOIN e b ON a.src = b.dst AND a.dst = b.src"))
_add("lateral_first_neighbour_part_next", _on("part_next", relational.first_neighbour), _sql("part_next", "SELECT src AS v, min(dst) AS dst FROM e GROUP BY src"))
_REGIONS = "SELECT a.n_regionkey AS from_region, b.n_regionkey AS to_region FROM e JOIN nation a ON a.n_nationkey = src JOIN nation b ON b.n_nationkey = dst"


def _regions(s: SparkSession, d: str) -> DataFrame:
    n = load(s, d, "nation")
    e = graphs.edges(s, d, "nation_flow").join(F.broadcast(n.select(F.col("n_nationkey").cast("long").alias("src"), F.col("n_regionkey").alias("from_region"))), "src")  # one row a nation
    return e.join(F.broadcast(n.select(F.col("n_nationkey").cast("long").alias("dst"), F.col("n_regionkey").alias("to_region"))), "dst")


_LEVEL = "CAST(grouping(from_region) * 2 + grouping(to_region) AS INTEGER) AS level, count(*) AS n"
_add("cube_nation_flow", lambda s, d: relational.cube_report(_regions(s, d), ["from_region", "to_region"]), _sql("nation_flow", f"SELECT from_region, to_region, {_LEVEL} FROM ({_REGIONS}) GROUP BY CUBE (from_region, to_region)"))
_add("rollup_nation_flow", lambda s, d: relational.rollup_report(_regions(s, d), ["from_region", "to_region"]), _sql("nation_flow", f"SELECT from_region, to_region, {_LEVEL} FROM ({_REGIONS}) GROUP BY ROLLUP (from_region, to_region)"))
_add("degree_ranks_user_key", _on("user_key", lambda e: relational.degree_ranks(transforms.degrees(e))), _sql("user_key", f", {_DEG} SELECT v, d, rank() OVER w AS rank, dense_rank() OVER w AS dense, percent_rank() OVER w AS percent, cume_dist() OVER w AS share FROM deg WINDOW w AS (ORDER BY d DESC)"))
_add("edges_in_both_word_next", lambda s, d: relational.edges_in_both(graphs.edges(s, d, "word_next_conv"), graphs.edges(s, d, "word_next_doc")), f"SELECT src, dst FROM ({GRAPHS['word_next_conv'].sql}) INTERSECT SELECT src, dst FROM ({GRAPHS['word_next_doc'].sql})")
_add("edges_only_in_word_next_conv", lambda s, d: relational.edges_only_in(graphs.edges(s, d, "word_next_conv"), graphs.edges(s, d, "word_next_doc")), f"SELECT src, dst FROM ({GRAPHS['word_next_conv'].sql}) EXCEPT SELECT src, dst FROM ({GRAPHS['word_next_doc'].sql})")


def _sketched(e: DataFrame) -> DataFrame:
    sizes = e.groupBy("src").agg(F.count("*").alias("n"))
    exact = sizes.agg(F.count("*").alias("v"), F.expr("percentile(n, 0.5)").alias("m"))
    one = relational.sketches(e).crossJoin(exact)  # two single rows
    return one.select((F.abs(F.col("approx_sources") - F.col("v")) <= 0.05 * F.col("v")).alias("distinct_ok"), (F.abs(F.col("out_median") - F.col("m")) <= 0.1 * F.col("m")).alias("median_ok"), (F.length("target_sketch") < 1_000_000).alias("small"))


_add("sketches_doc_word", _on("doc_word", _sketched), "SELECT TRUE AS distinct_ok, TRUE AS median_ok, TRUE AS small")


def _sql_grid(s: SparkSession, d: str) -> DataFrame:
    sqlapi.register(s)
    return graphs.edges(s, d, "order_part").select("src", "dst", F.expr("grid_part_48(src, dst, 0)").alias("part"))


_add("sql_grid_part_order_part", _sql_grid, _sql("order_part", _grid_sql(48)))


def _ranks(e: DataFrame) -> DataFrame:
    new, _ = relational.pagerank_step(stateless.edge_hash(e, 16), relational.start_ranks(e))
    return new.select("v", F.round("rank", 12).alias("rank"))


_add(
    "pagerank_step_user_next", _on("user_next", _ranks),
    _sql("user_next", ", vs AS (SELECT src AS v FROM e UNION SELECT dst FROM e), n AS (SELECT count(*) AS n FROM vs), o AS (SELECT src, count(*) AS d FROM e GROUP BY src), g AS (SELECT dst AS v, sum((1 / n) / d) AS g FROM e JOIN o USING (src), n GROUP BY dst) SELECT v, round(0.15::DOUBLE / n + 0.85::DOUBLE * coalesce(g, 0), 12) AS rank FROM vs LEFT JOIN g USING (v), n"),
)
_add("pagerank_messages_user_next", _on("user_next", lambda e: relational.pagerank_step(stateless.edge_hash(e, 16), relational.start_ranks(e))[1]), _sql("user_next", f", {_PLACED} SELECT count(*) - count(DISTINCT v) AS gathered, count(*) - count(DISTINCT v) AS scattered FROM rep"))
