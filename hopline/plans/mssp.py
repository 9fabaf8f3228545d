"""Queries: source detection, (1 + eps) distances from many sources, pairs; over the graph or graph and hopset."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hopline.functions.params import Budget
from hopline.model import Graph, augment
from hopline.plans.relax import hop_limited
from hopline.plans.rounds import Ledger


def guard(graph: Graph, sources: DataFrame, factor: float = 2.0, allow_many: bool = False) -> int:
    """Number of sources; more than O(sqrt n) need ``allow_many``."""
    s = sources.count()
    if not allow_many and s > factor * math.sqrt(max(1, graph.n)):
        raise ValueError(f"{s} sources, more than {factor} sqrt(n); pass allow_many=True")
    Budget().search(s, graph.n)
    return s


def source_detection(graph: Graph, sources: DataFrame, hops: int, top: int | None = None, allow_many: bool = False, ledger: Ledger | None = None, ends: DataFrame | None = None) -> DataFrame:
    """(src, v, d, hops): hop-limited distance of every node, or of ``ends`` (v) only, to every source, or to its ``top``
    nearest."""
    guard(graph, sources, allow_many=allow_many)
    dist = hop_limited(graph, sources, hops, ledger=ledger, phase="detection", ends=ends)
    if top is None:
        return dist
    order = Window.partitionBy("v").orderBy("d", "src")
    return dist.withColumn("place", F.row_number().over(order)).where(F.col("place") <= top).drop("place")


def approx(graph: Graph, sources: DataFrame, eps: float, hops: int | None = None, allow_many: bool = False, ends: DataFrame | None = None) -> DataFrame:
    """(1 + eps) distances from O(sqrt n) sources, to ``ends`` (v) only where given, through the dense two-level structure,
    whose edges are dropped; by default log^2 n / eps rounds."""
    from hopline.plans.baselines import dense_two_level

    aux = dense_two_level(graph, eps, seed=7)
    n = max(2, graph.n)
    rounds = hops or max(4, math.ceil(math.log2(n) ** 2 / eps))
    return source_detection(augment(graph, aux), sources, rounds, allow_many=allow_many, ends=ends)


def sssp(graph: Graph, source: int, eps: float, hopset: DataFrame | None = None, beta: int | None = None) -> DataFrame:
    one = graph.spark.createDataFrame([(source,)], "src long")
    return many(graph, hopset, one, beta) if hopset is not None else approx(graph, one, eps)


def many(graph: Graph, hopset: DataFrame, sources: DataFrame, beta: int, allow_many: bool = True, ledger: Ledger | None = None) -> DataFrame:
    """beta relaxations over graph and hopset for all sources together."""
    guard(graph, sources, allow_many=allow_many)
    return hop_limited(augment(graph, hopset), sources, beta, ledger=ledger, phase="query")


def pair(graph: Graph, hopset: DataFrame, pairs: DataFrame, beta: int) -> DataFrame:
    """(src, v, d) for the asked pairs that are within reach."""
    sources = pairs.select("src").distinct()
    return many(graph, hopset, sources, beta).join(pairs.select("src", "v"), ["src", "v"], "left_semi").select("src", "v", "d")
