"""The graphs and the distance methods once more, as DuckDB SQL."""

from __future__ import annotations

_JUMP = "1 + abs(a.p_size::BIGINT - b.p_size::BIGINT)"

RAW = {
    "price_path": "SELECT p_partkey AS u, lead(p_partkey) OVER o AS v, 1 + abs(p_size::BIGINT - lead(p_size::BIGINT) OVER o) AS w FROM part WINDOW o AS (ORDER BY p_retailprice, p_partkey)",
    "part_mesh": f"""SELECT a.p_partkey AS u, b.p_partkey AS v, {_JUMP} AS w
FROM (SELECT *, row_number() OVER (ORDER BY p_retailprice, p_partkey) - 1 AS r, floor(sqrt(count(*) OVER ()))::BIGINT AS width FROM part) a
JOIN (SELECT *, row_number() OVER (ORDER BY p_retailprice, p_partkey) - 1 AS r FROM part) b ON (b.r = a.r + 1 AND a.r % a.width < a.width - 1) OR b.r = a.r + a.width""",
    "balance_ladder_full": """SELECT c_custkey AS u, lead(c_custkey) OVER o AS v, 1 + floor(abs(c_acctbal - lead(c_acctbal) OVER o))::BIGINT AS w FROM customer WINDOW o AS (ORDER BY c_acctbal, c_custkey)
UNION ALL SELECT c_custkey, lead(c_custkey) OVER o, 1 + floor(abs(c_acctbal - lead(c_acctbal) OVER o))::BIGINT FROM customer WINDOW o AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)""",
    "balance_ladder": """SELECT u, v, w FROM (SELECT c_custkey AS u, lead(c_custkey) OVER o AS v, 1 + floor(abs(c_acctbal - lead(c_acctbal) OVER o))::BIGINT AS w, c_nationkey + lead(c_nationkey) OVER o AS nn FROM customer WINDOW o AS (ORDER BY c_acctbal, c_custkey)) WHERE nn % 5 = 0
UNION ALL SELECT c_custkey, lead(c_custkey) OVER o, 1 + floor(abs(c_acctbal - lead(c_acctbal) OVER o))::BIGINT FROM customer WINDOW o AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)""",
    "event_chain": """SELECT event_id AS u, lead(event_id) OVER o AS v, 1 + (epoch_us(lead(ts) OVER o) - epoch_us(ts)) // 1000000 AS w FROM events WINDOW o AS (PARTITION BY user_id ORDER BY ts, event_id)
UNION ALL SELECT event_id, lead(event_id) OVER o, 1 + (epoch_us(lead(ts) OVER o) - epoch_us(ts)) // 1000000 FROM events WINDOW o AS (PARTITION BY event_type ORDER BY ts, event_id)""",
    "order_relay": """SELECT o_orderkey AS u, lead(o_orderkey) OVER o AS v, 1 + date_diff('day', o_orderdate::DATE, lead(o_orderdate::DATE) OVER o) AS w FROM orders WINDOW o AS (PARTITION BY o_custkey ORDER BY o_orderdate::DATE, o_orderkey)
UNION ALL SELECT o_orderkey, lead(o_orderkey) OVER o, 1 + date_diff('day', o_orderdate::DATE, lead(o_orderdate::DATE) OVER o) FROM orders JOIN customer ON c_custkey = o_custkey WINDOW o AS (PARTITION BY c_nationkey ORDER BY o_orderdate::DATE, o_orderkey)""",
    "user_handoff": "SELECT user_id AS u, lead(user_id) OVER o AS v, 1 + (epoch_us(lead(ts) OVER o) - epoch_us(ts)) // 1000000 AS w FROM events WINDOW o AS (ORDER BY ts, event_id)",
    "supply": "SELECT l_partkey AS u, l_suppkey + 10000000 AS v, 1 + floor(l_extendedprice / 1000)::BIGINT AS w FROM lineitem",
    "trade_tree": """SELECT n_regionkey::BIGINT AS u, (n_nationkey + 100)::BIGINT AS v, 1::BIGINT AS w FROM nation
UNION ALL SELECT c_nationkey + 100, c_custkey + 1000000, 1 FROM customer UNION ALL SELECT s_nationkey + 100, s_suppkey + 2000000000, 1 FROM supplier""",
    "embed_knn": """SELECT u, v, 1 + round(1000 * (1 - c))::BIGINT AS w FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY c DESC, v) AS r FROM (
SELECT a.vec_id AS u, b.vec_id AS v, list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) / (sqrt(list_dot_product(a.embedding::DOUBLE[], a.embedding::DOUBLE[])) * sqrt(list_dot_product(b.embedding::DOUBLE[], b.embedding::DOUBLE[]))) AS c
FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id)) WHERE r <= 5""",
    "page_links": """SELECT page_id AS u, ('0x' || substr(md5(unnest(regexp_extract_all(html, 'href="([^"]*)"', 1))), 1, 12))::BIGINT + 281474976710656 AS v, 1::BIGINT AS w FROM pages""",
    "doc_lines": """SELECT doc_id AS u, ('0x' || substr(md5(line), 1, 12))::BIGINT + 281474976710656 AS v, 1::BIGINT AS w FROM (SELECT doc_id, line, count(*) OVER (PARTITION BY line) AS k FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) > 20) WHERE k BETWEEN 2 AND 50""",
    "turn_chain": """SELECT conv_id * 100 + turn AS u, lead(conv_id * 100 + turn) OVER o AS v, 1 + length(text)::BIGINT // 100 AS w FROM conversations WINDOW o AS (PARTITION BY conv_id ORDER BY turn)
UNION ALL SELECT conv_id * 100 + turn, lead(conv_id * 100 + turn) OVER o, 1 + length(text)::BIGINT // 100 FROM conversations WINDOW o AS (PARTITION BY role, turn ORDER BY conv_id)""",
}
EXTRA_NODES = {
    "price_path": "SELECT p_partkey AS id FROM part",
    "part_mesh": "SELECT p_partkey AS id FROM part",
    "balance_ladder_full": "SELECT c_custkey AS id FROM customer",
    "balance_ladder": "SELECT c_custkey AS id FROM customer",
    "event_chain": "SELECT event_id AS id FROM events",
    "order_relay": "SELECT o_orderkey AS id FROM orders",
    "user_handoff": "SELECT DISTINCT user_id AS id FROM events",
    "embed_knn": "SELECT vec_id AS id FROM embeddings",
    "page_links": "SELECT page_id AS id FROM pages",
    "turn_chain": "SELECT conv_id * 100 + turn AS id FROM conversations",
}


def edges(name: str) -> str:
    return f"SELECT least(u, v)::BIGINT AS u, greatest(u, v)::BIGINT AS v, min(w)::BIGINT AS w FROM ({RAW[name]}) WHERE u <> v GROUP BY 1, 2"


def with_graph(name: str, unit: bool = False) -> str:
    """Common table expressions edges, arcs and nodes."""
    extra = f" UNION SELECT id::BIGINT FROM ({EXTRA_NODES[name]})" if name in EXTRA_NODES else ""
    e = edges(name)
    e = f"SELECT u, v, 1::BIGINT AS w FROM ({e})" if unit else e
    return f"""edges AS MATERIALIZED ({e}), arcs AS MATERIALIZED (SELECT u, v, w FROM edges UNION ALL SELECT v, u, w FROM edges),
nodes AS MATERIALIZED (SELECT u AS id FROM edges UNION SELECT v FROM edges{extra})"""


def unrolled(hops: int, sources: str, prune: str = "") -> str:
    """CTEs d0 .. d<hops> of (src, v, d): hop-limited distances, one round each."""
    parts = [f"d0 AS MATERIALIZED (SELECT src, src AS v, 0::BIGINT AS d FROM ({sources}))"]
    for i in range(1, hops + 1):
        parts.append(f"d{i} AS MATERIALIZED (SELECT src, v, min(d)::BIGINT AS d FROM (SELECT src, v, d FROM d{i - 1} UNION ALL SELECT src, arcs.v, d + w FROM d{i - 1} JOIN arcs ON arcs.u = d{i - 1}.v {prune}) GROUP BY 1, 2)")
    return ", ".join(parts)


def fixpoint(sources: str, limit: str = "") -> str:
    """CTE dist(src, v, d): exact distances by keyed recursion; only improvements go round again."""
    return f"""dist(src, v, d) USING KEY (src, v) AS (SELECT src, src AS v, 0::BIGINT FROM ({sources})
UNION SELECT x.src, x.v, x.d FROM (SELECT t.src, arcs.v, min(t.d + arcs.w)::BIGINT AS d FROM dist t JOIN arcs ON arcs.u = t.v {limit} GROUP BY 1, 2) x
LEFT JOIN recurring.dist r ON r.src = x.src AND r.v = x.v WHERE r.d IS NULL OR x.d < r.d)"""


ROOT_SOURCES = "SELECT id AS src FROM nodes ORDER BY id LIMIT (SELECT floor(sqrt(count(*)))::BIGINT FROM nodes)"
