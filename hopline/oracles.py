"""DuckDB SQL for the graph queries, written independently of the plans where a closed formula exists."""

from __future__ import annotations

from hopline.functions import params
from hopline.functions.rand import shift_sql
from hopline.operators import relational
from hopline.oracles_graph import RAW, ROOT_SOURCES, edges, fixpoint, unrolled, with_graph
from hopline.streaming import edges as streams

ORACLES: dict[str, str] = {}

for _g in RAW:
    ORACLES[f"graph_edges_{_g}"] = edges(_g)
    ORACLES[f"graph_stats_{_g}"] = f"""WITH {with_graph(_g)}, deg AS (SELECT u AS id, count(*) AS degree FROM arcs GROUP BY 1)
SELECT (SELECT count(*) FROM nodes) AS n, (SELECT count(*) FROM edges) AS m, (SELECT min(w) FROM edges) AS min_w, (SELECT max(w) FROM edges) AS max_w,
(SELECT sum(degree)::BIGINT FROM deg) AS degree_sum, (SELECT max(degree) FROM deg) AS max_degree, (SELECT count(*) FROM edges) > pow((SELECT count(*) FROM nodes), 1.5) AS dense"""


def _with(name: str, ctes: str, select: str, recursive: bool = False, unit: bool = False) -> str:
    return f"WITH {'RECURSIVE ' if recursive else ''}{with_graph(name, unit)}, {ctes} {select}"


ORACLES["normalize_handoff"] = f"WITH e AS ({edges('user_handoff')}) SELECT u, v, ceil(w::DOUBLE / (SELECT min(w) FROM e))::BIGINT AS w, (SELECT min(w) FROM e) AS factor FROM e"
ORACLES["unit_weights_ladder"] = f"SELECT u, v, 1::BIGINT AS w FROM ({edges('balance_ladder')})"
ORACLES["aspect_event_chain"] = f"SELECT min(w) AS min_w, max(w) AS max_w, round(max(w)::DOUBLE / min(w), 6) AS aspect FROM ({edges('event_chain')})"
ORACLES["polynomial_check"] = f"WITH {with_graph('event_chain')} SELECT max(w) AS max_w, max(w) <= (SELECT count(*) FROM nodes)::DOUBLE ^ 2 AS polynomial FROM edges"

_COMP = "comp(id, comp) USING KEY (id) AS (SELECT id, id FROM nodes UNION SELECT x.id, x.comp FROM (SELECT arcs.v AS id, min(t.comp) AS comp FROM comp t JOIN arcs ON arcs.u = t.id GROUP BY 1) x JOIN recurring.comp r ON r.id = x.id WHERE x.comp < r.comp)"
for _g in ("balance_ladder", "order_relay", "doc_lines"):
    ORACLES[f"components_{_g}"] = _with(_g, _COMP, "SELECT id, comp FROM comp", True)

for _name, _g, _h in (("hop_limited_mesh_4", "part_mesh", 4), ("hop_limited_mesh_16", "part_mesh", 16), ("hop_limited_ladder_16", "balance_ladder_full", 16), ("source_detection_ladder", "balance_ladder_full", 8)):
    ORACLES[_name] = _with(_g, unrolled(_h, ROOT_SOURCES), f"SELECT src, v, d FROM d{_h}")
ORACLES["hop_limited_delta_equal"] = _with("part_mesh", unrolled(6, ROOT_SOURCES), "SELECT src, v, d, true AS same FROM d6")

_EXACT = _with("part_mesh", fixpoint(ROOT_SOURCES), "SELECT src, v, d FROM dist", True)
ORACLES["exact_mssp_mesh"] = _EXACT
ORACLES["exact_sssp_mesh"] = _with("part_mesh", fixpoint("SELECT min(id) AS src FROM nodes"), "SELECT src, v, d FROM dist", True)
ORACLES["exact_tree"] = _with("trade_tree", fixpoint(ROOT_SOURCES), "SELECT src, v, d FROM dist", True)
ORACLES["handoff_all_pairs"] = _with("user_handoff", fixpoint("SELECT id AS src FROM nodes"), "SELECT src, v, d FROM dist", True)
ORACLES["path_prefix_32"] = """WITH p AS (SELECT p_partkey AS id, row_number() OVER o AS r, sum(coalesce(step, 0)) OVER (ORDER BY p_retailprice, p_partkey ROWS UNBOUNDED PRECEDING)::BIGINT AS at
FROM (SELECT *, 1 + abs(p_size::BIGINT - lag(p_size::BIGINT) OVER o) AS step FROM part WINDOW o AS (ORDER BY p_retailprice, p_partkey)) WINDOW o AS (ORDER BY p_retailprice, p_partkey))
SELECT a.id AS src, b.id AS v, abs(a.at - b.at) AS d, abs(a.r - b.r)::INTEGER AS hops FROM (SELECT * FROM p ORDER BY id LIMIT (SELECT floor(sqrt(count(*)))::BIGINT FROM part)) a JOIN p b ON abs(a.r - b.r) <= 32"""
ORACLES["exact_path"] = ORACLES["path_prefix_32"].replace("JOIN p b ON abs(a.r - b.r) <= 32", "CROSS JOIN p b")
ORACLES["in_task_equal"] = "SELECT floor(sqrt(count(*)))::BIGINT * count(*) AS rows, 0::BIGINT AS apart, true AS same_ledger FROM customer"
ORACLES["recursive_sql_tree"] = _with("trade_tree", unrolled(3, ROOT_SOURCES), "SELECT src, v, d FROM d3")
ORACLES["ball_mesh"] = _with("part_mesh", fixpoint(ROOT_SOURCES, "WHERE t.d + arcs.w <= 60"), "SELECT src, v, d FROM dist", True)
ORACLES["hop_ball_mesh"] = _with("part_mesh", unrolled(5, ROOT_SOURCES), "SELECT src, v, d FROM d5 WHERE d <= 60")
ORACLES["scale_pairs_mesh"] = _with("part_mesh", fixpoint(ROOT_SOURCES, "WHERE t.d + arcs.w <= 64"), "SELECT src, v, d FROM dist WHERE d > 32", True)
ORACLES["minplus_square_handoff"] = f"WITH {with_graph('user_handoff')} SELECT a.u, b.v, min(a.w + b.w)::BIGINT AS w FROM arcs a JOIN arcs b ON a.v = b.u GROUP BY 1, 2"


def _square(source: str) -> str:
    return f"(SELECT u, v, w FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY w, v) AS r FROM (SELECT a.u, b.v, min(a.w + b.w)::BIGINT AS w FROM {source} a JOIN {source} b ON a.v = b.u GROUP BY 1, 2)) WHERE r <= 6)"


ORACLES["q_nearest_mesh"] = f"""WITH {with_graph('part_mesh')}, q0 AS MATERIALIZED (SELECT u, v, w FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY w, v) AS r FROM (SELECT id AS u, id AS v, 0::BIGINT AS w FROM nodes UNION ALL SELECT * FROM arcs)) WHERE r <= 6),
q1 AS MATERIALIZED {_square('q0')}, q2 AS MATERIALIZED {_square('q1')} SELECT u, v, w FROM q2"""
ORACLES["source_detection_top3"] = _with("balance_ladder_full", unrolled(8, ROOT_SOURCES), "SELECT src, v, d FROM (SELECT *, row_number() OVER (PARTITION BY v ORDER BY d, src) AS r FROM d8) WHERE r <= 3")
_BEST = " UNION ALL ".join(f"SELECT src, v, d, {h} AS hops FROM d{h}" for h in range(9))
ORACLES["parents_mesh"] = _with("part_mesh", unrolled(8, ROOT_SOURCES) + f""", best AS MATERIALIZED (SELECT src, v, d8.d, min(x.hops)::INTEGER AS hops FROM d8 JOIN ({_BEST}) x USING (src, v, d) GROUP BY ALL)""", """SELECT b.src, b.v, b.d, b.hops, min(p.v) AS parent FROM best b
LEFT JOIN (SELECT p.src, p.v, p.d, p.hops, arcs.v AS to, arcs.w FROM best p JOIN arcs ON arcs.u = p.v) p ON p.src = b.src AND p.to = b.v AND p.d + p.w = b.d AND p.hops + 1 = b.hops GROUP BY 1, 2, 3, 4""")
ORACLES["rounding_mesh"] = f"SELECT u, v, w, (w + 3) // 4 AS what FROM ({edges('part_mesh')})"
ORACLES["rounding_violations"] = f"SELECT count(*) AS edges, sum((w + 255) // 256)::BIGINT AS units, 0::BIGINT AS violations FROM ({edges('event_chain')})"
ORACLES["rounded_search_mesh"] = f"""WITH {with_graph('part_mesh').replace('arcs AS MATERIALIZED (SELECT u, v, w FROM edges UNION ALL SELECT v, u, w FROM edges)', 'arcs AS MATERIALIZED (SELECT u, v, (w + 3) // 4 AS w FROM edges UNION ALL SELECT v, u, (w + 3) // 4 FROM edges)')}, {unrolled(8, ROOT_SOURCES)} SELECT src, v, (d * 4)::DOUBLE AS d FROM d8"""
ORACLES["shifts_customer"] = f"SELECT rep::INTEGER AS rep, c_custkey AS id, {shift_sql(0.125, 7, 'rep', 'c_custkey')} AS shift_fp FROM customer, (SELECT unnest([0, 1]) AS rep)"


def _partition(name: str, alpha: float, reps: int, weight: str = "w", unit: bool = False, select: str = "", seed: int = 42) -> str:
    """All nodes within each centre's radius, then the least shifted distance: another algorithm than the plan's."""
    return _with(
        name,
        f"""radii AS MATERIALIZED (SELECT rep, id, {shift_sql(alpha, seed)} AS r FROM nodes, (SELECT unnest(range({reps})) AS rep)),
hat AS MATERIALIZED (SELECT u, v, {weight} AS w FROM arcs),
balls(rep, src, v, d) USING KEY (rep, src, v) AS (SELECT rep, id, id, 0::BIGINT FROM radii
UNION SELECT x.rep, x.src, x.v, x.d FROM (SELECT t.rep, t.src, hat.v, min(t.d + hat.w)::BIGINT AS d FROM balls t JOIN hat ON hat.u = t.v JOIN radii ON radii.rep = t.rep AND radii.id = t.src
WHERE (t.d + hat.w) * 1048576 <= radii.r GROUP BY 1, 2, 3) x LEFT JOIN recurring.balls o ON o.rep = x.rep AND o.src = x.src AND o.v = x.v WHERE o.d IS NULL OR x.d < o.d),
won AS MATERIALIZED (SELECT b.rep::INTEGER AS rep, b.v, min_by(b.src, (b.d * 1048576 - r.r, b.src)) AS center, min_by(b.d, (b.d * 1048576 - r.r, b.src)) AS dhat FROM balls b JOIN radii r ON r.rep = b.rep AND r.id = b.src GROUP BY 1, 2)""",
        select or "SELECT rep, v, center, dhat FROM won",
        True,
        unit,
    )


_MESH = ("part_mesh", 0.05, 2)
ORACLES["ldd_mesh"] = _partition(*_MESH)
ORACLES["ldd_unweighted_tree"] = _partition("trade_tree", 0.5, 2, unit=True)
ORACLES["ldd_ladder"] = _partition("balance_ladder", 0.05, 1)
ORACLES["ldd_sizes_mesh"] = _partition(*_MESH, select="SELECT rep, center, count(*) AS size FROM won GROUP BY 1, 2")
ORACLES["ldd_center_in_own_cluster"] = _partition(*_MESH, select="SELECT DISTINCT rep, center, true AS own FROM won")
ORACLES["ldd_connected"] = _partition(*_MESH, select="SELECT count(*) AS clusters, count(*) AS pieces FROM (SELECT DISTINCT rep, center FROM won)")
ORACLES["cover_unlimited_mesh"] = _partition("part_mesh", 0.05, 2, select="SELECT rep, center, v, dhat FROM won")
_HAT = {"name": "part_mesh", "alpha": 0.25, "reps": 3, "weight": "(w + 7) // 8"}
ORACLES["cover_limited_mesh"] = _partition(**_HAT, select="SELECT rep, center, v, dhat FROM won")
ORACLES["cover_overlap"] = _partition(**_HAT, select="SELECT v, count(*) AS clusters, count(DISTINCT rep) AS reps FROM won GROUP BY v")
ORACLES["cover_diameter"] = _partition(**_HAT, select="SELECT rep, center, count(*) AS size, max(dhat) AS radius FROM won GROUP BY 1, 2")
_SIZED = "SELECT rep, center, count(*) AS size, count(*) >= sqrt((SELECT count(*) FROM nodes)) AS is_big FROM won GROUP BY 1, 2"
ORACLES["split_big_small"] = _partition(**_HAT, select=_SIZED)
ORACLES["cluster_buckets"] = _partition(**_HAT, select=f"SELECT floor(log2(size))::INTEGER AS bucket, count(*) AS clusters, sum(size)::BIGINT AS members FROM ({_SIZED}) GROUP BY 1")
ORACLES["cover_pipelined_equal"] = "SELECT rep::INTEGER AS rep, (SELECT count(*) FROM part) AS memberships FROM (SELECT unnest(range(3)) AS rep)"
_MEMBERS = "SELECT rep, center, v, dhat FROM won"
ORACLES["cover_neighborhood_mesh"] = _partition("part_mesh", 0.25 / 3, 2, "(w * 3 + 15) // 16", select=_MEMBERS)
ORACLES["cover_window_mesh"] = _partition("part_mesh", 0.125, 2, "(w + 7) // 8", select=_MEMBERS)
_SCALED = [_partition("part_mesh", 1 / 3, 2, f"(w * 3 + {w - 1}) // {w}", select=f"SELECT {k} AS scale, rep, center, v, dhat FROM won", seed=42 + 1000 * k) for k, w in enumerate((16, 64))]
ORACLES["cover_scales_mesh"] = ORACLES["cover_scales_in_turn"] = " UNION ALL ".join(f"SELECT * FROM ({x})" for x in _SCALED)
ORACLES["cover_edges_mesh"] = _partition(**_HAT, select="SELECT (SELECT count(*) FROM won) AS sizes, (SELECT count(*) FROM edges e JOIN won a ON a.v = e.u JOIN won b ON b.v = e.v AND b.rep = a.rep AND b.center = a.center) AS edges")
ORACLES["cover_true_diameters"] = _partition(**_HAT, select="SELECT count(*) AS clusters, 0::BIGINT AS weak_longer, 0::BIGINT AS too_wide FROM (SELECT DISTINCT rep, center FROM won)")

PICKED = "SELECT id AS src FROM nodes ORDER BY ('0x' || substr(md5('5:pick:0:' || id), 1, 8))::BIGINT, id LIMIT (SELECT floor(sqrt(count(*)))::BIGINT FROM nodes)"
_FLAGS = "SELECT src, v, d AS d_exact, true AS sound, true AS within FROM dist"
for _tag, _g in (("mesh", "part_mesh"), ("ladder", "balance_ladder_full"), ("turns", "turn_chain")):
    ORACLES[f"hopset_sound_{_tag}"] = _with(_g, fixpoint(ROOT_SOURCES), _FLAGS, True)
    _pairs = "count(*) FILTER (src <> v)"
    ORACLES[f"hopset_stretch_{_tag}"] = _with(_g, fixpoint(PICKED), f"SELECT {_pairs} AS pairs, {_pairs} AS reached, 0::BIGINT AS too_short, {_pairs} AS within, true AS bounded FROM dist", True)
    ORACLES[f"hopset_scale_error_{_tag}"] = _with(_g, fixpoint(PICKED), "SELECT floor(log2(d))::INTEGER AS scale, count(*) AS pairs, 0::BIGINT AS too_long FROM dist WHERE d > 0 GROUP BY 1", True)
    ORACLES[f"hopset_hopbound_{_tag}"] = "SELECT true AS within_bound, true AS fewer_than_without"
    ORACLES[f"hopset_size_{_tag}"] = f"WITH {with_graph(_g)} SELECT (SELECT count(*) FROM nodes) AS n, (SELECT count(*) FROM edges) AS m, true AS within_bound, 0::BIGINT AS not_canonical, 0::BIGINT AS twice"
    ORACLES[f"hopset_ledger_{_tag}"] = "SELECT 0::BIGINT AS too_many_rounds, 0::BIGINT AS idle_rounds, 0::BIGINT AS unsent"
for _name in ("mssp_with_hopset_mesh", "mssp_approx_mesh", "spanner_mesh"):
    ORACLES[_name] = _with("part_mesh", fixpoint(PICKED), _FLAGS, True)
ORACLES["structure_size_mesh"] = f"WITH {with_graph('part_mesh')} SELECT (SELECT count(*) FROM edges) AS m, true AS within_bound"
ORACLES["dense_two_level"] = "SELECT true AS within_bound, 0::BIGINT AS not_canonical"
ORACLES["hierarchy_sizes"] = "SELECT true AS no_larger"
ORACLES["center_clique_approx"] = "SELECT 0::BIGINT AS too_short, 0::BIGINT AS too_long"
ORACLES["many_sources_handoff"] = _with("user_handoff", fixpoint("SELECT id AS src FROM nodes"), _FLAGS, True)
ORACLES["pair_queries_mesh"] = _with("part_mesh", fixpoint(PICKED), f"{_FLAGS} WHERE v IN ({PICKED})", True)
# A keyed recursion that also counts how often a row improved, and in which round last.
ORACLES["plain_rounds"] = _with(
    "part_mesh",
    f"""deg AS MATERIALIZED (SELECT u, count(*) AS k FROM arcs GROUP BY u), dist(src, v, d, i, c) USING KEY (src, v) AS (SELECT src, src, 0::BIGINT, 0, 0 FROM ({ROOT_SOURCES})
UNION SELECT x.src, x.v, x.d, x.i, coalesce(r.c, 0) + 1 FROM (SELECT t.src, arcs.v, min(t.d + arcs.w)::BIGINT AS d, min(t.i) + 1 AS i FROM dist t JOIN arcs ON arcs.u = t.v GROUP BY 1, 2) x
LEFT JOIN recurring.dist r ON r.src = x.src AND r.v = x.v WHERE r.d IS NULL OR x.d < r.d)""",
    "SELECT max(i)::BIGINT AS rounds, sum(c)::BIGINT AS improved, (sum((c + (src = v)::INTEGER) * k) - sum(CASE WHEN i = (SELECT max(i) FROM dist) THEN k ELSE 0 END))::BIGINT AS offers_before_last FROM dist JOIN deg ON deg.u = dist.v",
    True,
)


def _small(select: str, sources: str = ROOT_SOURCES) -> str:
    return _with("turn_chain", fixpoint(sources), select, True)


for _name in ("hierarchy_global_sound", "hierarchy_limited_sound", "hierarchy_no_scales_sound", "memory_rich_mssp", "hopset_sequential_vs_main", "small_clique", "recursive_clique"):
    ORACLES[_name] = _small(_FLAGS, PICKED)
ORACLES["bunch_oracle"] = _small(_FLAGS + " WHERE src <> v")
ORACLES["memory_rich_hopset"] = f"WITH {with_graph('turn_chain')} SELECT (SELECT count(*) FROM nodes) AS n, (SELECT count(*) FROM edges) AS m, true AS within_bound, true AS model_rounds"
ORACLES["sssp_with_hopset_turns"] = _small(_FLAGS, "SELECT min(id) AS src FROM nodes")
ORACLES["cover_unlimited_paths"] = _small("SELECT count(*) AS pairs, 0::BIGINT AS missed FROM dist WHERE src <> v AND d <= 6", PICKED)
ORACLES["compare_properties"] = "SELECT unnest(['sparse_hierarchy', 'sparse_clique', 'sparse_recursive', 'dense_two_level', 'hierarchy_global', 'hierarchy_limited', 'hierarchy_no_scales']) AS method, true AS sound, true AS within, true AS fewer_hops"
ORACLES["congestion_mesh"] = _with("part_mesh", fixpoint(ROOT_SOURCES), "SELECT max(k) AS max_inbox, sum(k)::BIGINT AS rows FROM (SELECT v, count(*) AS k FROM dist GROUP BY v)", True)
ORACLES["memory_budget"] = f"""WITH {with_graph('part_mesh')}, s AS (SELECT (SELECT count(*) FROM nodes)::DOUBLE AS n, (SELECT count(*) FROM edges)::DOUBLE AS m)
SELECT gamma, round(pow(n, gamma), 3) AS machine_words, round(m * pow(n, 0.5 - gamma), 3) AS machines, round(m * sqrt(n), 3) AS total_words FROM s, (SELECT unnest([0.25, 0.5, 1.0])::DOUBLE AS gamma)"""
_ARGUMENTS = ", ".join(f"{v}::DOUBLE AS {k}" for k, v in params.ARGUMENTS.items())
ORACLES["bounds_table"] = f"SELECT {', '.join(f'round({params.bound_expression(b)}, 4) AS {b}' for b in params.BOUNDS)} FROM (SELECT {_ARGUMENTS})"
_NAMES = ("restated_hopbound", "competitor_hopbound", "competitor_rounds", "claimed_gain", "dense_hopbound", "superpoly_hopbound", "hopbound_lower", "rho_hopbound")
ORACLES["bound_competitors"] = f"SELECT {', '.join(f'round({params.bound_expression(b)}, 4) AS {b}' for b in _NAMES)} FROM (SELECT * REPLACE ((SELECT count(*)::DOUBLE FROM part) AS n) FROM (SELECT {_ARGUMENTS}))"
ORACLES["bucket_sum"] = """WITH s AS (SELECT count(*)::DOUBLE AS n FROM part), r AS (SELECT unnest(range(1, 60)) AS r)
SELECT k, round(sum(n * pow(2::DOUBLE, r / k)), 4) AS total, round(max(pow(n, 1 + 1 / (2 * k))), 4) AS bound FROM s, r, (SELECT unnest([2, 3, 4])::DOUBLE AS k) WHERE pow(2::DOUBLE, r) <= sqrt(n) GROUP BY k"""

ORACLES |= relational.ORACLES | streams.ORACLES
