"""The methods that the sparse hopset is compared with."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hopline.functions.params import HopsetParams, check_rho, inner_eps, levels
from hopline.functions.rand import chosen, u32
from hopline.model import HOPSET_SCHEMA, Graph, augment, components, induced
from hopline.plans import one_task
from hopline.plans.relax import exact, hop_bits, hop_limited, search
from hopline.plans.rounds import Ledger
from hopline.session import cut


def all_pairs(graph: Graph) -> DataFrame:
    """The n^2 table: every distance."""
    return exact(graph, graph.nodes.select(F.col("id").alias("src")))


def plain_relaxation(graph: Graph, sources: DataFrame, ledger: Ledger | None = None) -> DataFrame:
    """No hopset: as many rounds as shortest paths have hops."""
    return exact(graph, sources, ledger)


def _nearest_upper(graph: Graph, upper: DataFrame, hops: int | None, radius: int | None = None) -> DataFrame:
    """(v, cap, pivot): distance to the nearest node of ``upper`` and the smallest such node."""
    if graph.in_task and one_task.deals(2 * graph.m):
        return one_task.nearest(graph.edges, upper, hops, radius)
    dist = hop_limited(graph, upper.select(F.col("id").alias("src")), hops, radius=radius)
    best = dist.groupBy("v").agg(F.min(F.struct("d", "src")).alias("best"))
    return best.select("v", F.col("best.d").alias("cap"), F.col("best.src").alias("pivot"))


def _edges(rows: DataFrame, scale: int = 0) -> DataFrame:
    best = rows.where("a <> b").groupBy(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).agg(F.min(F.struct("d", "kind")).alias("best"))
    return best.select("u", "v", F.col("best.d").alias("w"), F.lit(scale).alias("scale"), "best.kind", F.lit(0).alias("rep"), F.col("u").alias("center"))


def _below_cap(graph: Graph, nodes: DataFrame, cap: DataFrame, hops: int | None, radius: int | None = None) -> DataFrame:
    """(src, cap, v, d, hops): nodes nearer to src than its cap and within ``radius``; the cap is a key of the search."""
    most = F.lit(2**40 if radius is None else radius + 1)
    caps = cap.select(F.col("v").alias("src"), "cap")
    start = nodes.select(F.col("id").alias("src"), F.col("id").alias("v")).join(caps, "src", "left").withColumn("cap", F.least(F.coalesce("cap", most), most))
    count = nodes.count()
    rows = count * graph.n
    if graph.in_task and one_task.deals(2 * graph.m):
        found = one_task.dealt(graph.edges, start.select("src", (F.col("cap") - 1).alias("_radius")), count, hops, hop_bits(hops, graph.n), many=graph.m)
        return found.join(start.select("src", "cap"), "src").select("src", "cap", "v", "d", "hops")
    p = graph.partitions_for(rows)
    return search(graph.arcs_in(p), start, ["src", "cap"], hops, p, radius=F.col("cap") - 1, phase="bunch", nodes=graph.n)


def _by_levels(graph: Graph, k: float, rho: float, seed: int, draw: int, hops: int | None, radius: int | None = None) -> DataFrame:
    """(a, b, d, kind): of every sampled level a node's bunch of nearer nodes and its pivot, the last level a clique."""
    level, n, out = graph.nodes, graph.n, None
    up = [chosen(max(float(n) ** (-(2**i) / k), float(n) ** -rho), seed, f"global{i}", F.lit(draw), F.col("id")) for i in range(levels(k))] if n else []
    if graph.in_task and one_task.deals(2 * graph.m):
        depth = F.lit(len(up))
        for i in reversed(range(len(up))):
            depth = F.when(up[i], depth).otherwise(F.lit(i))
        return one_task.levels(graph.edges, level.select("id", depth.cast("long").alias("level")), n, graph.m, hops, hop_bits(hops, n), radius)
    for i, drawn in enumerate(up):
        upper = cut(level.where(drawn), "level")
        if upper.isEmpty():
            break
        cap = cut(_nearest_upper(graph, upper, hops, radius), "caps")
        low = level.join(upper, "id", "left_anti")
        # Whoever lies on a path to a nearer node is nearer still, so searching below the source's cap loses none.
        back = _below_cap(graph, low, cap, hops, radius)
        mine = back.join(level.withColumnRenamed("id", "v"), "v", "left_semi")
        bunch = mine.select(F.col("src").alias("a"), F.col("v").alias("b"), "d", F.lit("bunch").alias("kind"))
        pivots = low.join(cap.withColumnRenamed("v", "id"), "id").select(F.col("id").alias("a"), F.col("pivot").alias("b"), F.col("cap").alias("d"), F.lit("pivot").alias("kind"))
        rows = cut(bunch.unionByName(pivots), "bunches")
        out = rows if out is None else out.unionByName(rows)
        level = upper
    top = hop_limited(graph, level.select(F.col("id").alias("src")), hops, radius=radius, ends=level.select(F.col("id").alias("v")))
    rows = top.select(F.col("src").alias("a"), F.col("v").alias("b"), "d", F.lit("top").alias("kind"))
    return rows if out is None else out.unionByName(rows)


class Scales:
    """The scales of a hop-limited construction: for each, the graph with all edges made so far, on rounded weights.

    At scale R weights are rounded up to units of eps' R / h, so a path of at most h edges and length in [R, 2R] is at
    most 1 + eps' too long; eps' shares eps out over the scales, whose errors compound. Edges longer than the scale's
    searches go are left out.
    """

    def __init__(self, graph: Graph, eps: float, hops: int):
        self.graph, self.hops, self.eps = graph, hops, inner_eps(eps, graph.n)
        self.made: DataFrame | None = None
        self.new: DataFrame | None = None  # made since the last union

    def __iter__(self):
        from hopline.plans.cover import eta, round_weights
        from hopline.plans.hopset import least_scale, reach

        graph, farthest, reached = self.graph, 0, False
        graph.roots = cut(components(graph).select(F.col("comp").alias("src")).distinct(), "roots")
        union = graph
        for kappa in range(least_scale(self.hops), 62):
            if self.new is not None:
                union, self.new = augment(union, self.new), None
            union.roots = graph.roots
            if not reached:
                farthest, reached = reach(union, self.hops)
            if reached and 2**kappa >= 2 * farthest:
                return
            unit = eta(2**kappa, self.hops, self.eps)
            radius = int(2 * 2**kappa * (1 + self.eps) / unit) + 1
            # No search of the scale goes further than the radius, so no path of it has a longer edge.
            short = round_weights(union, 2**kappa, self.hops, self.eps).where(F.col("what") <= radius)
            edges = short.select("u", "v", F.col("what").alias("w"))
            dealt = graph.in_task and one_task.deals(2 * union.m)  # the scale's one search reads them once
            rounded = Graph(graph.nodes, edges if dealt else cut(edges, "rounded"), graph.in_task)
            rounded.__dict__["n"] = graph.n
            if dealt:
                rounded.__dict__["m"] = union.m
            yield kappa, rounded, radius, unit
            rounded.release()

    def add(self, rows: DataFrame, kappa: int, unit) -> None:
        """Takes (a, b, d, kind) in units; an edge is never shorter than its path."""
        long = F.expr(f"(d * {unit.numerator} + {unit.denominator - 1}) div {unit.denominator}")
        self.put(cut(_edges(rows.withColumn("d", long), kappa), "scale"))

    def put(self, part: DataFrame) -> None:
        self.new = part if self.new is None else self.new.unionByName(part)
        self.made = part if self.made is None else self.made.unionByName(part)


def hierarchy_global(graph: Graph, k: float, eps: float = 1.0, rho: float = 0.5, seed: int = 42, hops: int | None = None, drop_scales: bool = False) -> DataFrame:
    """The general hierarchical hopset on the whole graph.

    ``hops=None``: the variant of constant hopbound and polynomial rounds, one run on exact distances without scales.
    With ``hops``: the efficient variant, scale by scale, every search limited to that many hops over the graph and the
    edges of smaller scales, (1 + eps') each; ``rho`` bounds from below how thin a level is sampled, and so the rows that
    a node holds in a round. ``drop_scales`` draws the same levels at every scale and keeps one edge a pair, which saves
    the factor log n in size.
    """
    check_rho(rho)
    if hops is None:
        return cut(_edges(_by_levels(graph, k, rho, seed, 0, None)), "hierarchy")
    scales = Scales(graph, eps, hops)
    for kappa, rounded, radius, unit in scales:
        scales.add(_by_levels(rounded, k, rho, seed, 0 if drop_scales else kappa, hops, radius), kappa, unit)
    out = scales.made if scales.made is not None else graph.spark.createDataFrame([], HOPSET_SCHEMA)
    if drop_scales:
        best = out.groupBy("u", "v").agg(F.min(F.struct("w", "kind", "scale")).alias("best"))
        out = best.select("u", "v", "best.w", F.lit(0).alias("scale"), "best.kind", F.lit(0).alias("rep"), F.col("u").alias("center"))
    return cut(out, "hierarchy")


def dense_two_level(graph: Graph, eps: float | None = None, seed: int = 42, hops: int | None = None) -> DataFrame:
    """The dense structure: a sample A of about sqrt n nodes; every node to all nodes nearer than its nearest A-node
    and to that node; all pairs of A. Size about n^1.5.

    Without ``eps`` the pairs of A have exact distances. With it they come scale by scale from searches of at most
    ``hops`` (default log n / eps) hops over the graph, the near edges and the pairs of smaller scales.
    """
    n = graph.n
    a = cut(graph.nodes.where(chosen(n**-0.5, seed, "dense", F.lit(0), F.col("id"))), "sample")
    if a.isEmpty():
        a = cut(graph.nodes.orderBy("id").limit(1), "sample")
    cap = cut(_nearest_upper(graph, a, None), "caps")
    bunch = _below_cap(graph, graph.nodes, cap, None)
    rows = bunch.where("src <> v").select(F.col("src").alias("a"), F.col("v").alias("b"), "d", F.lit("bunch").alias("kind"))
    near = cut(rows.unionByName(cap.select(F.col("v").alias("a"), F.col("pivot").alias("b"), F.col("cap").alias("d"), F.lit("pivot").alias("kind"))), "near")
    sources, ends = a.select(F.col("id").alias("src")), a.withColumnRenamed("id", "v")

    def pairs(dist: DataFrame) -> DataFrame:
        return dist.select(F.col("src").alias("a"), F.col("v").alias("b"), "d", F.lit("top").alias("kind"))

    if eps is None:
        return cut(_edges(near.unionByName(pairs(hop_limited(graph, sources, hops, ends=ends)))), "dense")
    scales = Scales(graph, eps, hops or max(4, math.ceil(math.log2(max(2, n)) / eps)))
    scales.put(cut(_edges(near), "near"))
    for kappa, rounded, radius, unit in scales:
        scales.add(pairs(hop_limited(rounded, sources, scales.hops, radius=radius, ends=ends)), kappa, unit)
    best = scales.made.groupBy("u", "v").agg(F.min(F.struct("w", "kind", "scale")).alias("best"))
    return cut(best.select("u", "v", "best.w", "best.scale", "best.kind", F.lit(0).alias("rep"), F.col("u").alias("center")), "dense")


def bunch_oracle(graph: Graph, k: int, seed: int = 42) -> tuple[DataFrame, DataFrame]:
    """Distance oracle of stretch 2k - 1: (bunches(v, x, d), pivots(level, v, pivot, d))."""
    level, n, bunches, pivots = graph.nodes, graph.n, None, None
    for i in range(k):
        nxt = cut(level.where(chosen(float(n) ** (-1 / k), seed, f"oracle{i}", F.lit(0), F.col("id"))), "level") if i < k - 1 else level.where(F.lit(False))
        near = cut(_nearest_upper(graph, level, None), "near")
        row = near.select(F.lit(i).alias("level"), "v", "pivot", F.col("cap").alias("d"))
        pivots = row if pivots is None else pivots.unionByName(row)
        cap = cut(_nearest_upper(graph, nxt, None), "caps") if i < k - 1 and not nxt.isEmpty() else None
        # x in A_i \ A_{i+1} grows its cluster: nodes v nearer to x than to A_{i+1}; closed along shortest paths to x.
        low = level.join(nxt, "id", "left_anti")
        count, below = low.count(), cap.select("v", "cap") if cap is not None else None
        if graph.in_task and one_task.deals(2 * graph.m):
            grow = one_task.dealt(graph.edges, low.select(F.col("id").alias("src"), F.lit(None).cast("long").alias("_radius")), count, None, hop_bits(None, graph.n), below, many=graph.m)
        else:
            p = graph.partitions_for(count * graph.n)
            grow = search(graph.arcs_in(p), low.select(F.col("id").alias("src"), F.col("id").alias("v")), ["src"], None, p, prune=below, phase="bunch", nodes=graph.n)
        rows = grow.select("v", F.col("src").alias("x"), "d")
        if cap is not None:
            rows = rows.join(cap.select("v", "cap"), "v", "left").where("cap is null or d < cap").drop("cap")
        bunches = rows if bunches is None else bunches.unionByName(rows)
        if cap is None:
            break
        level = nxt
    return cut(bunches, "bunches"), cut(pivots, "pivots")


def oracle_query(bunches: DataFrame, pivots: DataFrame, pairs: DataFrame, k: int) -> DataFrame:
    """(src, v, d): estimates within 2k - 1 of the distance, by alternating ends level by level."""
    best = None
    for i in range(k):
        a, b = ("src", "v") if i % 2 == 0 else ("v", "src")
        p = pivots.where(F.col("level") == i).select(F.col("v").alias(a), "pivot", F.col("d").alias("dp"))
        hit = pairs.join(p, a).join(bunches.select(F.col("v").alias(b), F.col("x").alias("pivot"), F.col("d").alias("db")), [b, "pivot"])
        rows = hit.select("src", "v", F.lit(i).alias("step"), (F.col("dp") + F.col("db")).alias("d"))
        best = rows if best is None else best.unionByName(rows)
    won = best.groupBy("src", "v").agg(F.min(F.struct("step", "d")).alias("first"))
    return won.select("src", "v", F.col("first.d").alias("d"))


def spanner(graph: Graph, k: int, seed: int = 42) -> DataFrame:
    """(u, v, w): a (2k - 1)-spanner by k - 1 phases of cluster sampling and a last joining of clusters."""
    n = graph.n
    member = cut(graph.nodes.select(F.col("id").alias("v"), F.col("id").alias("c")), "clusters")
    alive = cut(graph.edges.select("u", "v", "w"), "alive")
    kept = None

    def both(e: DataFrame) -> DataFrame:
        return e.select(F.col("u").alias("x"), F.col("v").alias("y"), "w").unionByName(e.select(F.col("v").alias("x"), F.col("u").alias("y"), "w"))

    def per_cluster(e: DataFrame, clusters: DataFrame) -> DataFrame:
        row = both(e).join(clusters.select(F.col("v").alias("y"), F.col("c").alias("cy")), "y")
        return row.groupBy("x", "cy").agg(F.min(F.struct("w", "y")).alias("e")).select("x", "cy", "e.w", "e.y")

    for i in range(1, k):
        picked = member.select("c").distinct().where(chosen(float(n) ** (-1 / k), seed, f"spanner{i}", F.lit(0), F.col("c")))
        picked = cut(picked.withColumn("in", F.lit(True)), "picked")
        best = per_cluster(alive, member).join(picked.withColumnRenamed("c", "cy"), "cy", "left")
        old = member.join(picked, "c", "left")
        loose = old.where("in is null").select(F.col("v").alias("x"))
        mine = cut(best.join(loose, "x"), "mine")
        near = mine.where("in").groupBy("x").agg(F.min(F.struct("w", "y", "cy")).alias("near"))
        joined = cut(mine.join(near, "x", "left"), "joined")
        # With a sampled neighbour: that edge and all lighter ones to other clusters; without: one to each cluster.
        add = joined.where("near is null or struct(w, y, cy) <= near")
        add = cut(add.select("x", "y", "w", "cy", F.col("near").isNull().alias("out")), "added")
        rows = add.select(F.least("x", "y").alias("u"), F.greatest("x", "y").alias("v"), "w")
        kept = rows if kept is None else kept.unionByName(rows)
        move = near.select(F.col("x").alias("v"), F.col("near.cy").alias("c"))
        member = cut(old.where("in").select("v", "c").unionByName(move), "clusters")
        gone = add.select("x", "cy").distinct()
        before = old.select(F.col("v").alias("y"), F.col("c").alias("cy"))
        dead = both(alive).join(before, "y").join(gone, ["x", "cy"], "left_semi").select(F.least("x", "y").alias("u"), F.greatest("x", "y").alias("v"))
        rest = alive.join(dead.distinct(), ["u", "v"], "left_anti")
        cu, cv = (member.select(F.col("v").alias(e), F.col("c").alias(f"c{e}")) for e in "uv")
        alive = cut(rest.join(cu, "u", "left").join(cv, "v", "left").where("cu is null or cv is null or cu <> cv").select("u", "v", "w"), "alive")
    last = per_cluster(alive, member).select(F.least("x", "y").alias("u"), F.greatest("x", "y").alias("v"), "w")
    return cut((last if kept is None else kept.unionByName(last)).distinct(), "spanner")


def small_clique(graph: Graph, params: HopsetParams):
    """Clique in small clusters with the sparse method's other parts."""
    from hopline.plans.hopset import build

    return build(graph, params.but(small="clique"))


def recursive_small(graph: Graph, members: DataFrame, sized: DataFrame, params: HopsetParams, kappa: int) -> DataFrame:
    """Recursion on small clusters, which the main method avoids: each is split around hubs, hubs get a clique and a star
    each, and every part is treated the same way, down to parts of a few nodes."""
    from hopline.plans.local_hopset import at_centers, recursive_edges

    small = members.join(sized.where("not is_big").where("size > 1").select("rep", "center"), ["rep", "center"])
    return at_centers(cut(induced(graph, small), "induced"), params.k, params.seed + kappa, make=recursive_edges)


def ball_growing_cover(graph: Graph, width: int, ell: int, growth: float = 0.5, seed: int = 42, max_phases: int = 200) -> DataFrame:
    """Members (rep 0) of the older cover: hash-ordered batches of centres grow balls in steps of ``width`` until the
    next ring is small against the ball; claimed nodes leave. Overlaps inside a batch go to the smaller draw."""
    steps = max(1, math.ceil(math.log(max(2, graph.n)) / math.log1p(growth)))
    left = cut(graph.nodes.select("id", u32(seed, "ball", F.lit(0), F.col("id")).alias("draw")), "left")
    out = None
    total = max(1, graph.n)
    for phase in range(max_phases):
        remain = left.count()
        if remain == 0:
            break
        share = min(1.0, 2.0 ** (phase + 1) / total)
        batch = left.where(F.col("draw") < int(share * 2**32)) if share < 1 else left
        if batch.isEmpty():
            continue
        e = graph.edges.join(left.select(F.col("id").alias("u")), "u", "left_semi").join(left.select(F.col("id").alias("v")), "v", "left_semi")
        rest = Graph(left.select("id"), cut(e.select("u", "v", "w"), "rest"))
        dist = cut(hop_limited(rest, batch.select(F.col("id").alias("src")), ell, radius=width * steps), "balls")
        rings = dist.groupBy("src", F.ceil(F.col("d") / width).cast("int").alias("ring")).agg(F.count("*").alias("k"))
        grid = rings.select("src").distinct().withColumn("ring", F.explode(F.sequence(F.lit(0), F.lit(steps))))
        upto = Window.partitionBy("src").orderBy("ring")
        run = grid.join(rings, ["src", "ring"], "left").withColumn("k", F.coalesce("k", F.lit(0))).withColumn("inside", F.sum("k").over(upto)).withColumn("next", F.lead("k", 1, 0).over(upto))
        stop = run.where(F.col("next") <= F.lit(growth) * F.col("inside")).groupBy("src").agg(F.min("ring").alias("stop"))
        held = dist.join(stop, "src").where(F.col("d") <= F.col("stop") * width)
        claimed = held.join(batch.select(F.col("id").alias("src"), "draw"), "src").groupBy("v").agg(F.min(F.struct("draw", "src", "d")).alias("best"))
        claimed = cut(claimed.select(F.lit(0).alias("scale"), F.lit(0).alias("rep"), F.col("best.src").alias("center"), "v", F.col("best.d").alias("dhat"), F.col("best.d").alias("dtree")), "claimed")
        rest.release()
        out = claimed if out is None else out.unionByName(claimed)
        left = cut(left.join(claimed.select(F.col("v").alias("id")), "id", "left_anti"), "left")
    if not left.isEmpty():
        raise RuntimeError(f"nodes without a cluster after {max_phases} phases")
    return out


def unlimited_cover(graph: Graph, width: float, reps: int, seed: int = 42, ledger: Ledger | None = None) -> DataFrame:
    """The cover without rounding: radii of rate 1/W on true weights, about W log n rounds."""
    from hopline.plans.cover import neighborhood

    return neighborhood(graph, width, reps, seed, ledger)


def rounded_search(graph: Graph, big_r: int, ell: int, eps0: float, sources: DataFrame) -> DataFrame:
    """Search from many sources on rounded weights, lengths recovered: (src, v, d) with d in [d, (1 + eps0) d]
    for pairs of at most ell hops in [R, 2R]."""
    from hopline.plans.cover import eta, round_weights

    unit = eta(big_r, ell, eps0)
    rounded = Graph(graph.nodes, round_weights(graph, big_r, ell, eps0).select("u", "v", F.col("what").alias("w")))
    dist = hop_limited(rounded, sources, ell)
    return dist.select("src", "v", (F.col("d") * unit.numerator / unit.denominator).alias("d"))
