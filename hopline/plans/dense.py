"""The memory-rich variant: cliques in small clusters, stars and a centre clique for large ones."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopline.functions.params import HopsetParams, bounds, check_gamma
from hopline.model import Graph, augment
from hopline.plans.hopset import HopsetResult, build as build_sparse
from hopline.plans.mssp import guard
from hopline.plans.relax import hop_limited
from hopline.plans.rounds import Ledger

MACHINES = 2000


def build(graph: Graph, params: HopsetParams, gamma: float = 0.5) -> HopsetResult:
    """Size about n^1.5 log n. Repetitions always share their rounds. A machine holds n^gamma words: gamma sets how many
    partitions states and arcs have, and a round of the model takes 1 / gamma of ours."""
    return build_sparse(within_memory(graph, gamma), params.but(small="clique"))


def within_memory(graph: Graph, gamma: float) -> Graph:
    """The graph in as many partitions as machines of n^gamma words need for m sqrt n words, up to ``MACHINES``."""
    machines = bounds("rich_machines", n=graph.n, m=graph.m, gamma=check_gamma(gamma))
    return Graph(graph.nodes, graph.edges, graph.in_task, least_partitions=max(1, min(MACHINES, math.ceil(machines))))


def rounds_in_model(ledger: Ledger, gamma: float) -> int:
    """Rounds of machines of n^gamma words: an aggregation over all of them takes 1 / gamma steps."""
    return math.ceil(ledger.rounds() / check_gamma(gamma))


def mssp(graph: Graph, hopset: DataFrame, sources: DataFrame, beta: int, gamma: float = 0.5) -> DataFrame:
    """Distances from O(sqrt n) sources; the state of a node lies in the partition of its arcs, so a round is one
    exchange of offers."""
    guard(graph, sources)
    union = augment(graph, hopset)
    return hop_limited(within_memory(union, gamma), sources, beta, phase="rich")


def memory_budget(graph: Graph, gammas: list[float]) -> DataFrame:
    """(gamma, machine_words, machines, total_words) for this graph."""
    n, m = graph.n, graph.m
    rows = [(float(check_gamma(g)), float(n) ** g, bounds("rich_machines", n=n, m=m, gamma=g), bounds("rich_memory", n=n, m=m)) for g in gammas]
    out = graph.spark.createDataFrame(rows, "gamma double, machine_words double, machines double, total_words double")
    return out.select("gamma", *[F.round(c, 3).alias(c) for c in ("machine_words", "machines", "total_words")])
