"""The sparse hopset, scale by scale.

For distances in (R, 2R] the graph with all smaller scales' edges is covered by clusters of hop-limited low diameter.
Clusters below n^mu nodes get a sparse local hopset; larger ones a star from their centre, and all large centres get
pairwise edges. Every search of a scale needs at most 2 beta + 1 hops, because smaller scales are reused. Each scale
is written before the next one starts, so a build can resume.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopline.functions.params import Budget, HopsetParams, bounds, cover_width, inner_eps
from hopline.model import HOPSET_SCHEMA, Graph, augment, components, induced
from hopline.plans import one_task
from hopline.plans.cover import clusters, limited_pairwise
from hopline.plans.local_hopset import at_centers, by_keys
from hopline.plans.relax import hop_limited, search
from hopline.plans.rounds import Ledger
from hopline.session import cut


@dataclass
class HopsetResult:
    edges: DataFrame
    params: HopsetParams
    beta: int
    graph: Graph
    ledger: Ledger
    clusters: list[DataFrame] = field(default_factory=list)

    @property
    def size(self) -> int:
        return self.edges.count()


def default_beta(n: int, params: HopsetParams) -> int:
    return params.beta or int(min(n, max(1, bounds("main_hopbound", n=n, k=params.k, eps=params.eps))))


def least_scale(beta: int) -> int:
    """The first kappa whose scale (2^kappa, 2^(kappa+1)] isn't settled by beta edges of weight one."""
    return max(0, math.floor(math.log2(max(beta, 1))))


def reach(graph: Graph, hops: int | None, ledger: Ledger | None = None) -> tuple[int, bool]:
    """Greatest distance from one node of each component by ``hops`` edges, and whether all nodes were reached."""
    roots = graph.roots if hasattr(graph, "roots") else components(graph).select(F.col("comp").alias("src")).distinct()
    dist = hop_limited(graph, roots, hops, ledger=ledger, phase="reach")
    row = dist.agg(F.max("d"), F.count("*")).first()
    return row[0] or 0, row[1] >= graph.n


def split_clusters(members: DataFrame, n: int, mu: float) -> DataFrame:
    return clusters(members, n**mu)


def stars(graph: Graph, members: DataFrame, big: DataFrame, hops: int | None, scope: str = "cluster", ledger: Ledger | None = None) -> DataFrame:
    """(rep, center, u, v, w): centre to every member of its large cluster. The length is that of a path of at most
    ``hops`` edges inside the cluster, or of the cluster's own tree where no such path exists."""
    inside = cut(members.join(big.select("rep", "center"), ["rep", "center"]).select("rep", "center", "v", "dtree"), "inside")
    keys = ["rep", "center"]
    start = big.select(*keys, F.col("center").alias("v"))
    arcs, rows = None, graph.in_task and inside.count()
    if scope == "cluster":
        own = cut(induced(graph, inside), "own")
        both = own.select(*keys, "u", "v", "w").unionByName(own.select(*keys, F.col("v").alias("u"), F.col("u").alias("v"), "w"))
        if graph.in_task and one_task.fits(2 * own.count(), rows):
            dist = search(both, start, keys, hops, 1, arc_keys=tuple(keys), phase="stars", ledger=ledger, nodes=graph.n, in_task=True)
        else:
            p = graph.partitions_for(own.count())
            arcs = both.repartition(p, "u").persist()
            dist = search(arcs, start, keys, hops, p, arc_keys=tuple(keys), phase="stars", ledger=ledger, nodes=graph.n)
    else:
        p = graph.partitions_for(big.count() * graph.n)
        dist = search(graph.arcs_in(p), start, keys, hops, p, phase="stars", ledger=ledger, nodes=graph.n)
    row = inside.where("v <> center").join(dist.select(*keys, "v", "d"), [*keys, "v"], "left")
    out = cut(row.select(*keys, F.least("center", "v").alias("u"), F.greatest("center", "v").alias("v"), F.coalesce(F.least("d", "dtree"), "dtree").alias("w")), "stars")
    if arcs is not None:
        arcs.unpersist()
    return out


def center_clique(graph: Graph, big: DataFrame, hops: int | None, radius: int | None = None, weights: str = "exact", eps: float = 0.1, clique_scope: str = "all", ledger: Ledger | None = None) -> DataFrame:
    """(u, v, w): edges between large clusters' centres within ``hops`` edges; auxiliary edges are not returned."""
    sources = cut(big.select(F.col("center").alias("src")).distinct(), "centres")
    ends = sources.select(F.col("src").alias("v"))
    if weights == "approx":
        from hopline.plans.mssp import approx

        dist = approx(graph, sources, eps, hops=hops, allow_many=True, ends=ends).where(F.lit(True) if radius is None else F.col("d") <= radius)
    else:
        dist = hop_limited(graph, sources, hops, radius=radius, ledger=ledger, phase="centres", ends=ends)
    pair = dist.where("src < v").select(F.col("src").alias("u"), "v", F.col("d").alias("w"))
    if clique_scope == "rep":
        a, b = (big.select("rep", F.col("center").alias(c)) for c in "uv")
        pair = pair.join(a, "u").join(b, ["rep", "v"]).select("u", "v", "w").distinct()
    return pair


def small_edges(graph: Graph, members: DataFrame, sized: DataFrame, params: HopsetParams, seed: int) -> DataFrame:
    """Local shortcut edges of the small clusters: one task a cluster, or by key columns where a cluster has more
    edges than a task should hold."""
    small = members.join(sized.where("not is_big").where("size > 1").select("rep", "center"), ["rep", "center"])
    own = cut(induced(graph, small), "induced")
    clique = params.small == "clique"
    size = sized.where("not is_big").select("rep", "center", "size")
    pairs = F.col("size").cast("double") * F.col("size") > params.local_edge_cap  # one task holds all distances of a cluster
    heavy = own.groupBy("rep", "center").agg(F.count("*").alias("e")).join(size, ["rep", "center"]).where((F.col("e") > params.local_edge_cap) | pairs).select("rep", "center")
    if heavy.isEmpty():
        return at_centers(own, params.k, seed, clique)
    light = at_centers(own.join(heavy, ["rep", "center"], "left_anti"), params.k, seed, clique)
    return light.unionByName(by_keys(own.join(heavy, ["rep", "center"], "left_semi"), params.k, seed, graph.partitions, clique))


def build(graph: Graph, params: HopsetParams, ledger: Ledger | None = None, max_scale: int | None = None) -> HopsetResult:
    """The hopset of all scales. ``params.segments``, ``beta``, ``ell``, ``reps`` and ``rate`` override constants of
    the theory, whose guarantee then has to be measured."""
    ledger = ledger or Ledger()
    given, graph = graph, graph.compact() if params.in_task else graph
    n, spark = graph.n, graph.spark
    beta = default_beta(n, params)
    hops = 2 * beta + 1
    Budget().cover(n, params.reps or 1)
    graph.roots = cut(components(graph).select(F.col("comp").alias("src")).distinct(), "roots")
    made: DataFrame | None = None
    kept_clusters = []
    kappa, farthest, all_reached = least_scale(beta), 0, False
    while max_scale is None or kappa <= max_scale:
        big_r, ledger.scale = 2**kappa, kappa
        union = augment(graph, made) if made is not None else graph
        union.roots = graph.roots
        if not all_reached:  # once all are reached, the first answer bounds every distance
            farthest, all_reached = reach(union, hops, ledger)
        if all_reached and big_r >= 2 * farthest:
            break
        if big_r > 2**62:
            raise OverflowError(f"scale {kappa} reached, but not all nodes within {hops} hops")
        width = cover_width(params, n, big_r)
        members = cut(limited_pairwise(union, width, params.ell or hops, params.eps0, params.reps, params.seed, params.rate, kappa, ledger=ledger), "members")
        sized = cut(split_clusters(members, n, params.mu), "clusters")
        kept_clusters.append(sized)
        if params.small == "recursive":
            from hopline.plans.baselines import recursive_small

            local = recursive_small(union, members, sized, params, kappa)
        else:
            local = small_edges(union, members, sized, params, params.seed + kappa)
        rows = local.select("u", "v", "w", "kind", "rep", "center")
        big = sized.where("is_big")
        if not big.isEmpty():
            star = stars(union, members, big, hops, params.scope, ledger)
            rows = rows.unionByName(star.select("u", "v", "w", F.lit("star").alias("kind"), "rep", "center"))
            pair = center_clique(union, big, hops, 4 * big_r, params.weights, inner_eps(params.eps, n), params.clique_scope, ledger)
            rows = rows.unionByName(pair.select("u", "v", "w", F.lit("clique").alias("kind"), F.lit(-1).alias("rep"), F.col("u").alias("center")))
        best = rows.groupBy("u", "v").agg(F.min(F.struct("w", "kind", "rep", "center")).alias("best"))
        part = cut(best.select("u", "v", "best.w", F.lit(kappa).alias("scale"), "best.kind", "best.rep", "best.center"), f"scale{kappa}")
        made = part if made is None else made.unionByName(part)
        union.release()
        kappa += 1
    ledger.scale = -1
    return HopsetResult(made if made is not None else spark.createDataFrame([], HOPSET_SCHEMA), params, beta, given, ledger, kept_clusters)


def build_sequential(graph: Graph, params: HopsetParams) -> HopsetResult:
    """The sequential form: no hop limits, exact distances, unlimited covers of radius rate 1/W; for small graphs."""
    given, graph = graph, graph.compact() if params.in_task else graph
    ledger, n = Ledger(), graph.n
    beta = default_beta(n, params)
    graph.roots = cut(components(graph).select(F.col("comp").alias("src")).distinct(), "roots")
    farthest, _ = reach(graph, None)
    made = None
    for kappa in range(least_scale(beta), max(least_scale(beta) + 1, math.ceil(math.log2(max(2, 2 * farthest))))):
        from hopline.plans.cover import neighborhood

        big_r = 2**kappa
        members = cut(neighborhood(graph, cover_width(params, n, big_r) / (params.rate or 1.0), params.reps, params.seed + kappa), "members")
        sized = cut(split_clusters(members, n, params.mu), "clusters")
        rows = small_edges(graph, members, sized, params, params.seed + kappa).select("u", "v", "w", "kind", "rep", "center")
        big = sized.where("is_big")
        if not big.isEmpty():
            star = stars(graph, members, big, None)
            rows = rows.unionByName(star.select("u", "v", "w", F.lit("star").alias("kind"), "rep", "center"))
            pair = center_clique(graph, big, None, 4 * big_r)
            rows = rows.unionByName(pair.select("u", "v", "w", F.lit("clique").alias("kind"), F.lit(-1).alias("rep"), F.col("u").alias("center")))
        best = rows.groupBy("u", "v").agg(F.min(F.struct("w", "kind", "rep", "center")).alias("best"))
        part = cut(best.select("u", "v", "best.w", F.lit(kappa).alias("scale"), "best.kind", "best.rep", "best.center"), f"scale{kappa}")
        made = part if made is None else made.unionByName(part)
    return HopsetResult(made, params, beta, given, ledger)
