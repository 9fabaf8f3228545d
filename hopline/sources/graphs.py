"""Graphs over the given tables. Each recipe gives edges (u, v, w) and nodes (id)."""

from __future__ import annotations

from collections.abc import Callable
from math import ceil

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hopline.functions.ranking import global_rank
from hopline.model import Graph, from_edges
from hopline.session import cut
from hopline.sources.tables import load

LINE_BASE = 1 << 48


def _next(df: DataFrame, by: list[str], order: list[str], node: str, keep: list[str]) -> DataFrame:
    """Each row with its successor within ``by``: u, v and the kept columns of both, suffixed _u and _v."""
    w = Window.partitionBy(*by).orderBy(*order)
    cols = [F.col(node).alias("u"), F.lead(node).over(w).alias("v")]
    for c in keep:
        cols += [F.col(c).alias(f"{c}_u"), F.lead(c).over(w).alias(f"{c}_v")]
    return df.select(*cols).where("v is not null")


def _next_global(df: DataFrame, order: list[str], node: str, keep: list[str], step: int = 1) -> DataFrame:
    """The same over the whole table, by rank instead of one window."""
    ranked = global_rank(df, order)
    a = ranked.select("rank", F.col(node).alias("u"), *[F.col(c).alias(f"{c}_u") for c in keep])
    b = ranked.select((F.col("rank") - step).alias("rank"), F.col(node).alias("v"), *[F.col(c).alias(f"{c}_v") for c in keep])
    return a.join(b, "rank")


def _parts(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "part").select("p_partkey", "p_retailprice", F.col("p_size").cast("long").alias("p_size"))


def _jump():
    return F.abs(F.col("p_size_u") - F.col("p_size_v")) + 1



def price_path(spark: SparkSession, d: str) -> Graph:
    part = _parts(spark, d)
    rows = _next_global(part, ["p_retailprice", "p_partkey"], "p_partkey", ["p_size"])
    return from_edges(rows.withColumn("w", _jump()), nodes=part.select(F.col("p_partkey").alias("id")))


def part_mesh(spark: SparkSession, d: str) -> Graph:
    """Row-major grid in price order, as wide as the root of the number of parts."""
    part = _parts(spark, d)
    width = int(part.count() ** 0.5)
    ranked = global_rank(part, ["p_retailprice", "p_partkey"])
    a = ranked.select("rank", F.col("p_partkey").alias("u"), F.col("p_size").alias("p_size_u")).withColumn("to", F.explode(F.array(F.when(F.col("rank") % width < width - 1, F.col("rank") + 1), F.col("rank") + width)))
    b = ranked.select(F.col("rank").alias("to"), F.col("p_partkey").alias("v"), F.col("p_size").alias("p_size_v"))
    return from_edges(a.join(b, "to").withColumn("w", _jump()), nodes=ranked.select(F.col("p_partkey").alias("id")))


def _balance(spark: SparkSession, d: str, linked: bool) -> Graph:
    c = load(spark, d, "customer").select("c_custkey", "c_acctbal", F.col("c_nationkey").cast("long").alias("nation"))
    overall = _next_global(c, ["c_acctbal", "c_custkey"], "c_custkey", ["c_acctbal", "nation"])
    if linked:
        overall = overall.where((F.col("nation_u") + F.col("nation_v")) % 5 == 0)
    within = _next(c, ["nation"], ["c_acctbal", "c_custkey"], "c_custkey", ["c_acctbal", "nation"])
    w = (F.floor(F.abs(F.col("c_acctbal_u") - F.col("c_acctbal_v"))) + 1).cast("long")
    return from_edges(overall.select(within.columns).unionByName(within).withColumn("w", w), nodes=c.select(F.col("c_custkey").alias("id")))


def balance_ladder_full(spark: SparkSession, d: str) -> Graph:
    return _balance(spark, d, False)


def balance_ladder(spark: SparkSession, d: str) -> Graph:
    return _balance(spark, d, True)


def _events(spark: SparkSession, d: str) -> DataFrame:
    micros = F.unix_micros(F.col("ts").cast("timestamp"))
    return load(spark, d, "events").select("event_id", "user_id", "event_type", micros.alias("t"))


def _seconds():
    return F.expr("(t_v - t_u) div 1000000 + 1")



def event_chain(spark: SparkSession, d: str) -> Graph:
    e = _events(spark, d)
    rows = _next(e, ["user_id"], ["t", "event_id"], "event_id", ["t"]).unionByName(_next(e, ["event_type"], ["t", "event_id"], "event_id", ["t"]))
    return from_edges(rows.withColumn("w", _seconds()), nodes=e.select(F.col("event_id").alias("id")))


def order_relay(spark: SparkSession, d: str) -> Graph:
    o = load(spark, d, "orders").select("o_orderkey", "o_custkey", F.datediff(F.col("o_orderdate").cast("date"), F.lit("1970-01-01").cast("date")).cast("long").alias("t"))
    o = o.join(load(spark, d, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey"), "o_custkey")
    rows = _next(o, ["o_custkey"], ["t", "o_orderkey"], "o_orderkey", ["t"]).unionByName(_next(o, ["c_nationkey"], ["t", "o_orderkey"], "o_orderkey", ["t"]))
    return from_edges(rows.withColumn("w", F.col("t_v") - F.col("t_u") + 1), nodes=o.select(F.col("o_orderkey").alias("id")))


def user_handoff(spark: SparkSession, d: str) -> Graph:
    e = _events(spark, d)
    rows = _next_global(e, ["t", "event_id"], "user_id", ["t"])
    return from_edges(rows.withColumn("w", _seconds()), nodes=e.select(F.col("user_id").alias("id")))


def supply(spark: SparkSession, d: str) -> Graph:
    li = load(spark, d, "lineitem")
    return from_edges(li.select(F.col("l_partkey").alias("u"), (F.col("l_suppkey") + 10_000_000).alias("v"), (F.floor(F.col("l_extendedprice") / 1000) + 1).cast("long").alias("w")))


def trade_tree(spark: SparkSession, d: str) -> Graph:
    """Regions from 0, nations from 100, customers from 1,000,000, suppliers from 2,000,000,000."""
    n, c, s = (load(spark, d, t) for t in ("nation", "customer", "supplier"))
    one = F.lit(1).cast("long").alias("w")
    rows = n.select(F.col("n_regionkey").cast("long").alias("u"), (F.col("n_nationkey") + 100).cast("long").alias("v"), one)
    rows = rows.unionByName(c.select((F.col("c_nationkey") + 100).cast("long").alias("u"), (F.col("c_custkey") + 1_000_000).alias("v"), one))
    return from_edges(rows.unionByName(s.select((F.col("s_nationkey") + 100).cast("long").alias("u"), (F.col("s_suppkey") + 2_000_000_000).alias("v"), one)))


def _matrix(table: pa.Table) -> np.ndarray:
    """The vectors of column ``e`` as rows."""
    many = pc.list_value_length(table["e"])
    if many.null_count or len(pc.unique(many)) > 1 or table["norm"].null_count or not np.all(np.isfinite(norm := table["norm"].to_numpy()) & (norm > 0)):
        raise ValueError("vectors must be finite, of one length and not zero")
    return table["e"].combine_chunks().flatten().to_numpy().reshape(len(table), -1)


def nearest_vectors(e: DataFrame, k: int, block: int = 16_384) -> DataFrame:
    """(ia, ib, cos): of each vector of ``e(vec_id, e, norm)`` the k others of greatest cosine, ties to the smaller id.

    A task holds two blocks of about ``block`` vectors. It finds the candidates by a product of matrices and decides between
    them by sums in the order of the components, whose rounding is that of the plain expression. Of equal vectors only the k + 1
    smallest ids can be among the nearest of any, so no more of them are compared."""
    blocks = max(1, ceil(e.count() / block))
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    own = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int")
    copies = e.withColumn("_copy", F.row_number().over(Window.partitionBy("e").orderBy("vec_id"))).where(F.col("_copy") <= k + 1).drop("_copy")
    left, right = e.withColumn("_a", own).withColumn("_b", every), copies.withColumn("_b", own).withColumn("_a", every)

    def run(one: pa.Table, other: pa.Table) -> pa.Table:
        found = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
        if len(one) and len(other):
            other = other.sort_by("vec_id")
            a, b = _matrix(one), _matrix(other)
            ia, ib, na, nb = (t[x].to_numpy() for x in ("vec_id", "norm") for t in (one, other))
            unit = np.ascontiguousarray((b / nb[:, None]).T)
            first, last = np.searchsorted(ib, ia), np.searchsorted(ib, ia, "right")
            step = max(1, 4_000_000 // len(b))
            for s in range(0, len(a), step):
                c = (a[s : s + step] / na[s : s + step, None]) @ unit
                for r in np.flatnonzero(last[s : s + step] > first[s : s + step]):
                    c[r, first[s + r] : last[s + r]] = -2.0
                least = np.partition(c, -k, axis=1)[:, -k] if len(b) > k else np.full(len(c), -1.5)
                row, col = np.nonzero(c >= np.maximum(least - 1e-12, -1.5)[:, None])
                row, dot = row + s, np.zeros(len(row))
                for x in range(a.shape[1]):
                    dot += a[row, x] * b[col, x]
                cos = dot / (na[row] * nb[col])
                order = np.lexsort((ib[col], -cos, row))
                row, col, cos = row[order], col[order], cos[order]
                near = np.arange(len(row)) - np.searchsorted(row, row) < k
                found.append((ia[row[near]], ib[col[near]], cos[near]))
        return pa.table(dict(zip(("ia", "ib", "cos"), map(np.concatenate, zip(*found, strict=True)), strict=True)))

    pair = left.groupBy("_a", "_b").cogroup(right.groupBy("_a", "_b")).applyInArrow(run, "ia long, ib long, cos double")
    order = Window.partitionBy("ia").orderBy(F.desc("cos"), "ib")
    return pair.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k).drop("place")


def embed_knn(spark: SparkSession, d: str, k: int = 5, block: int = 16_384) -> Graph:
    """The k nearest by cosine: every pair is compared, block against block."""
    e = load(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    e = e.withColumn("norm", F.sqrt(F.aggregate("e", F.lit(0.0), lambda a, x: a + x * x)))
    near = cut(nearest_vectors(e, k, block), "near")
    return from_edges(near.select(F.col("ia").alias("u"), F.col("ib").alias("v"), (F.round((1 - F.col("cos")) * 1000) + 1).cast("long").alias("w")), nodes=e.select(F.col("vec_id").alias("id")))


def _named(text) -> object:
    return F.conv(F.substring(F.md5(text), 1, 12), 16, 10).cast("long") + LINE_BASE


def page_links(spark: SparkSession, d: str) -> Graph:
    p = load(spark, d, "pages").select("page_id", F.explode(F.expr("regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)")).alias("href"))
    return from_edges(p.select(F.col("page_id").alias("u"), _named(F.col("href")).alias("v"), F.lit(1).cast("long").alias("w")), nodes=load(spark, d, "pages").select(F.col("page_id").alias("id")))


def doc_lines(spark: SparkSession, d: str) -> Graph:
    """Documents and lines of over 20 characters that occur 2 to 50 times."""
    line = load(spark, d, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where(F.length("line") > 20)
    shared = line.groupBy("line").agg(F.count("*").alias("k")).where("k between 2 and 50")
    return from_edges(line.join(shared, "line").select(F.col("doc_id").alias("u"), _named(F.col("line")).alias("v"), F.lit(1).cast("long").alias("w")))


def turn_chain(spark: SparkSession, d: str) -> Graph:
    t = load(spark, d, "conversations").select("conv_id", "turn", "role", (F.col("conv_id") * 100 + F.col("turn")).alias("node"), F.length("text").cast("long").alias("n"))
    after = _next(t, ["conv_id"], ["turn"], "node", ["n"])
    across = _next(t, ["role", "turn"], ["conv_id"], "node", ["n"])
    return from_edges(after.unionByName(across).withColumn("w", F.expr("n_u div 100 + 1")), nodes=t.select(F.col("node").alias("id")))


RECIPES: dict[str, Callable[..., Graph]] = {f.__name__: f for f in (price_path, part_mesh, balance_ladder_full, balance_ladder, event_chain, order_relay, user_handoff, supply, trade_tree, embed_knn, page_links, doc_lines, turn_chain)}
_HELD: dict[tuple, Graph] = {}


def graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """A recipe's graph, made once in a session."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _HELD:
        _HELD[key] = RECIPES[name](spark, sf_dir)
    return _HELD[key]
