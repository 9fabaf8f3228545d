"""The registry of graph queries: distances, covers, hopsets, baselines, measures. Surrounding operators join it
from their own modules."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hopline import model
from hopline.functions import params, rand
from hopline.functions.params import HopsetParams
from hopline.operators import relational
from hopline.plans import baselines, cover, dense, local_hopset, mssp, relax, verify
from hopline.plans import hopset as hopsets
from hopline.plans.rounds import Ledger
from hopline.session import cut
from hopline.sources import graphs
from hopline.sources.graphs import graph
from hopline.sources.tables import load
from hopline.streaming import edges as streams

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
_HELD: dict[tuple, object] = {}

#: Constants for test sizes: the theory's leave every small graph without a cluster.
TEST = HopsetParams(k=2, eps=0.5, beta=8, seed=42, reps=3, segments=8, ell=4, rate=1.0)
#: The whole graph that sweeps and comparisons of many builds run on.
SMALL = "turn_chain"
TINY = TEST.but(beta=4, ell=3, reps=3, segments=4)


def query(name: str) -> Callable[[Query], Query]:
    def put(f: Query) -> Query:
        QUERIES[name] = f
        return f

    return put


def held(spark: SparkSession, key: tuple, make: Callable[[], object]):
    """Results that several queries of a session share."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _HELD:
        _HELD[key] = make()
    return _HELD[key]


def root_sources(g: model.Graph) -> DataFrame:
    """The floor(sqrt n) smallest ids."""
    # The graph is held too, so that no other graph gets its id.
    return held(g.spark, ("roots", id(g)), lambda: (g, cut(g.nodes.orderBy("id").limit(int(g.n**0.5)).select(F.col("id").alias("src")), "sources")))[1]


def hash_sources(g: model.Graph) -> DataFrame:
    """As many nodes picked by hash, spread over the whole graph."""
    pick = rand.u32(5, "pick", F.lit(0), F.col("id"))
    return held(g.spark, ("picked", id(g)), lambda: (g, cut(g.nodes.orderBy(pick, "id").limit(int(g.n**0.5)).select(F.col("id").alias("src")), "sources")))[1]


def flags(exact: DataFrame, approx: DataFrame, factor: float) -> DataFrame:
    """(src, v, d_exact, sound, within): never shorter than the distance, and at most ``factor`` times as long."""
    got = approx.select("src", "v", F.col("d").alias("e"))
    return exact.join(got, ["src", "v"], "left").select("src", "v", F.col("d").alias("d_exact"), F.coalesce(F.col("e") >= F.col("d"), F.lit(False)).alias("sound"), F.coalesce(F.col("e") <= F.col("d") * factor, F.lit(False)).alias("within"))


def picked_truth(spark: SparkSession, d: str, name: str) -> DataFrame:
    g = graph(spark, d, name)
    return held(spark, ("picked truth", d, name), lambda: cut(relax.exact(g.compact(), hash_sources(g)), "truth"))


def truth(spark: SparkSession, d: str, name: str) -> DataFrame:
    g = graph(spark, d, name)
    return held(spark, ("truth", d, name), lambda: cut(relax.exact(g.compact(), root_sources(g)), "truth"))


for _name in graphs.RECIPES:
    QUERIES[f"graph_stats_{_name}"] = lambda s, d, g=_name: model.stats(graph(s, d, g))
    QUERIES[f"graph_edges_{_name}"] = lambda s, d, g=_name: graph(s, d, g).edges


@query("normalize_handoff")
def _(s, d):
    g, factor = model.normalize_weights(graph(s, d, "user_handoff"))
    return g.edges.withColumn("factor", F.lit(factor).cast("long"))


@query("unit_weights_ladder")
def _(s, d):
    return model.unweighted(graph(s, d, "balance_ladder")).edges


@query("aspect_event_chain")
def _(s, d):
    return model.aspect_ratio(graph(s, d, "event_chain"))


@query("aspect_reduced_event_chain")
def _(s, d):
    return model.reduce_aspect(graph(s, d, "event_chain"), 0.5, [1024, 65536])


@query("polynomial_check")
def _(s, d):
    return model.check_polynomial(graph(s, d, "event_chain"), 2)


for _name in ("balance_ladder", "order_relay", "doc_lines"):
    QUERIES[f"components_{_name}"] = lambda s, d, g=_name: model.components(graph(s, d, g).compact())


def _limited(name: str, hops: int, delta: bool = True) -> Query:
    def run(s, d):
        g = graph(s, d, name)
        return relax.hop_limited(g, root_sources(g), hops, delta).select("src", "v", "d")

    return run


QUERIES |= {"hop_limited_mesh_4": _limited("part_mesh", 4), "hop_limited_mesh_16": _limited("part_mesh", 16), "hop_limited_ladder_16": _limited("balance_ladder_full", 16), "source_detection_ladder": lambda s, d: mssp.source_detection(g := graph(s, d, "balance_ladder_full"), root_sources(g), 8).select("src", "v", "d")}


@query("hop_limited_delta_equal")
def _(s, d):
    a, b = (_limited("part_mesh", 6, delta)(s, d) for delta in (True, False))
    return a.join(b.withColumnRenamed("d", "e"), ["src", "v"], "full").select("src", "v", "d", (F.col("d").eqNullSafe(F.col("e"))).alias("same"))


@query("exact_mssp_mesh")
def _(s, d):
    return truth(s, d, "part_mesh").select("src", "v", "d")


@query("exact_sssp_mesh")
def _(s, d):
    g = graph(s, d, "part_mesh").compact()
    return relax.exact(g, g.nodes.orderBy("id").limit(1).select(F.col("id").alias("src"))).select("src", "v", "d")


@query("exact_tree")
def _(s, d):
    g = graph(s, d, "trade_tree")
    return relax.exact(g, root_sources(g)).select("src", "v", "d")


@query("path_prefix_32")
def _(s, d):
    g = graph(s, d, "price_path")
    return relax.hop_limited(g, root_sources(g), 32).select("src", "v", "d", "hops")


@query("exact_path")
def _(s, d):
    """About n rounds; the graph fits a task at the sizes given here, where rounds cost no job."""
    g = graph(s, d, "price_path").compact()
    return relax.exact(g, root_sources(g)).select("src", "v", "d", "hops")


@query("in_task_equal")
def _(s, d):
    """Distributed rounds and rounds in one task: rows that differ, rounds and offers of each."""
    g = graph(s, d, "balance_ladder_full")
    a, b = Ledger(), Ledger()
    x, y = relax.exact(g, hash_sources(g), a), relax.exact(g.compact(), hash_sources(g), b)
    apart = x.exceptAll(y).unionByName(y.exceptAll(x)).agg(F.count("*").alias("apart"))
    same = s.createDataFrame([(a.rounds() == b.rounds() and a.messages() == b.messages(),)], "same_ledger boolean")
    return x.agg(F.count("*").alias("rows")).join(apart).join(same)


@query("recursive_sql_tree")
def _(s, d):
    """Walks of at most three edges as recursive SQL; the least length of each pair."""
    g = graph(s, d, "trade_tree")
    g.arcs.createOrReplaceTempView("hop_arcs")
    root_sources(g).createOrReplaceTempView("hop_sources")
    return s.sql("""WITH RECURSIVE walk(src, v, d, h) AS (SELECT src, src, CAST(0 AS BIGINT), 0 FROM hop_sources
        UNION ALL SELECT walk.src, a.v, walk.d + a.w, walk.h + 1 FROM walk JOIN hop_arcs a ON a.u = walk.v WHERE walk.h < 3) SELECT src, v, min(d) AS d FROM walk GROUP BY src, v""")


@query("handoff_all_pairs")
def _(s, d):
    return baselines.all_pairs(graph(s, d, "user_handoff").compact()).select("src", "v", "d")


@query("ball_mesh")
def _(s, d):
    g = graph(s, d, "part_mesh")
    return relax.ball(g, root_sources(g), 60)


@query("hop_ball_mesh")
def _(s, d):
    g = graph(s, d, "part_mesh")
    return relax.ball(g, root_sources(g), 60, 5)


@query("scale_pairs_mesh")
def _(s, d):
    g = graph(s, d, "part_mesh")
    return relax.pairs_in_scale(g, root_sources(g), 32)


@query("minplus_square_handoff")
def _(s, d):
    g = graph(s, d, "user_handoff")
    return relax.minplus(g.arcs, g.arcs)


@query("q_nearest_mesh")
def _(s, d):
    return relax.q_nearest(graph(s, d, "part_mesh"), 6, 2)


@query("source_detection_top3")
def _(s, d):
    g = graph(s, d, "balance_ladder_full")
    return mssp.source_detection(g, root_sources(g), 8, top=3).select("src", "v", "d")


@query("parents_mesh")
def _(s, d):
    g = graph(s, d, "part_mesh")
    return relax.with_parents(g, relax.hop_limited(g, root_sources(g), 8)).select("src", "v", "d", "hops", "parent")


@query("rounding_mesh")
def _(s, d):
    return cover.round_weights(graph(s, d, "part_mesh"), 64, 8, 0.5)


@query("rounding_violations")
def _(s, d):
    g, unit = graph(s, d, "event_chain"), cover.eta(4096, 8, 0.5)
    e = cover.round_weights(g, 4096, 8, 0.5)
    bad = verify.rounding_inflation(e, unit.numerator, unit.denominator).agg(F.count("*").alias("violations"))
    return e.agg(F.count("*").alias("edges"), F.sum("what").alias("units")).join(bad)


@query("rounded_search_mesh")
def _(s, d):
    g = graph(s, d, "part_mesh")
    return baselines.rounded_search(g, 64, 8, 0.5, root_sources(g)).select("src", "v", F.round("d", 4).alias("d"))


@query("shifts_customer")
def _(s, d):
    return rand.shifts(graph(s, d, "balance_ladder_full").nodes, 0.125, 7, 2)


def parts(s, d, name: str = "part_mesh", alpha: float = 0.05, reps: int = 2, unit: bool = False) -> DataFrame:
    def make():
        g = graph(s, d, name)
        return cut(cover.partition(model.unweighted(g) if unit else g, alpha, 42, reps), "parts")

    return held(s, ("parts", d, name, alpha, reps, unit), make)


@query("ldd_mesh")
def _(s, d):
    return parts(s, d).select("rep", "v", "center", "dhat")


@query("ldd_unweighted_tree")
def _(s, d):
    return parts(s, d, "trade_tree", 0.5, 2, True).select("rep", "v", "center", "dhat")


@query("ldd_ladder")
def _(s, d):
    return parts(s, d, "balance_ladder", 0.05, 1).select("rep", "v", "center", "dhat")


@query("ldd_sizes_mesh")
def _(s, d):
    return parts(s, d).groupBy("rep", "center").agg(F.count("*").alias("size"))


@query("ldd_center_in_own_cluster")
def _(s, d):
    own = parts(s, d).where("v = center").select("rep", "center", F.lit(True).alias("own"))
    return parts(s, d).select("rep", "center").distinct().join(own, ["rep", "center"], "left").select("rep", "center", F.coalesce("own", F.lit(False)).alias("own"))


@query("ldd_connected")
def _(s, d):
    pieces = verify.connected_members(graph(s, d, "part_mesh"), parts(s, d))
    return pieces.agg(F.count("*").alias("clusters"), F.sum("pieces").alias("pieces"))


@query("padding_rate_mesh")
def _(s, d):
    g = graph(s, d, "part_mesh")
    return verify.padding_rate(parts(s, d), relax.ball(g, g.nodes.select(F.col("id").alias("src")), 6), 6, 0.05)


def mesh_cover(s, d) -> DataFrame:
    return held(s, ("cover", d), lambda: cut(cover.limited_pairwise(graph(s, d, "part_mesh").compact(), 32, 4, 1.0, 3, 42, 1.0), "cover"))


@query("cover_limited_mesh")
def _(s, d):
    return mesh_cover(s, d).select("rep", "center", "v", "dhat")


for _name, _together in (("cover_scales_mesh", True), ("cover_scales_in_turn", False)):
    QUERIES[_name] = lambda s, d, together=_together: cover.limited_pairwise_all(graph(s, d, "part_mesh"), [16, 64], 3, reps=2, rate=1.0, parallel_scales=together).select("scale", "rep", "center", "v", "dhat")


@query("cover_window_mesh")
def _(s, d):
    """Lengths in [W, 4 W]."""
    return cover.limited_pairwise(graph(s, d, "part_mesh"), 32, 4, reps=2, rate=1.0, window=4.0).select("rep", "center", "v", "dhat")


@query("cover_pipelined_equal")
def _(s, d):
    """One repetition after another, and all of them at a time."""
    g = graph(s, d, "part_mesh").compact()
    a, b = (cover.limited_pairwise(g, 32, 4, 1.0, 3, 42, 1.0, batch=x).select("rep", "v", "center", "dhat") for x in (1, None))
    return a.intersect(b).groupBy("rep").agg(F.count("*").alias("memberships"))


@query("cover_neighborhood_mesh")
def _(s, d):
    return cover.limited_neighborhood(graph(s, d, "part_mesh"), 16, 3, reps=2).select("rep", "center", "v", "dhat")


@query("cover_edges_mesh")
def _(s, d):
    return verify.cluster_edges(graph(s, d, "part_mesh"), mesh_cover(s, d))


@query("cover_true_diameters")
def _(s, d):
    """Strong and weak diameters: the weak one is no longer, and the strong one at most twice the tree's depth."""
    radius = verify.cluster_diameters(mesh_cover(s, d), "tree").select("rep", "center", "radius")
    both = verify.true_diameters(graph(s, d, "part_mesh").compact(), mesh_cover(s, d)).join(radius, ["rep", "center"])
    return both.agg(F.count("*").alias("clusters"), F.count_if(F.expr("weak > strong")).alias("weak_longer"), F.count_if(F.expr("strong > 2 * radius")).alias("too_wide"))


@query("cover_unlimited_paths")
def _(s, d):
    """The unlimited pairwise cover's own property: pairs of distance at most W, and those of them in no cluster of enough
    repetitions."""
    g = graph(s, d, SMALL).compact()
    members = cut(cover.neighborhood(g, 6.0, 24, seed=9), "members")
    near = relax.ball(g, hash_sources(g), 6).where("src <> v").select("src", "v")
    return verify.containment(members, near).agg(F.count("*").alias("pairs"), F.count_if(F.expr("not held")).alias("missed"))


@query("cover_overlap")
def _(s, d):
    return verify.overlap(mesh_cover(s, d))


@query("cover_contains_paths")
def _(s, d):
    g = graph(s, d, "part_mesh")
    near = relax.hop_limited(g, root_sources(g), 4, radius=32).where("src <> v and d >= 16")
    return verify.containment(mesh_cover(s, d), near).agg(F.count("*").alias("pairs"), F.sum(F.col("held").cast("long")).alias("held"))


@query("cover_contains_balls")
def _(s, d):
    g = graph(s, d, "part_mesh")
    balls = relax.ball(g, root_sources(g), 16, 4)
    return verify.ball_containment(mesh_cover(s, d), balls).agg(F.count("*").alias("balls"), F.sum(F.col("held").cast("long")).alias("held"))


@query("cover_diameter")
def _(s, d):
    return verify.cluster_diameters(mesh_cover(s, d), "rounded").select("rep", "center", "size", "radius")


@query("cover_ball_growing")
def _(s, d):
    return baselines.ball_growing_cover(graph(s, d, SMALL), 16, 8)


@query("cover_unlimited_mesh")
def _(s, d):
    return baselines.unlimited_cover(graph(s, d, "part_mesh"), 20.0, 2).select("rep", "center", "v", "dhat")


@query("split_big_small")
def _(s, d):
    return hopsets.split_clusters(mesh_cover(s, d), graph(s, d, "part_mesh").n, 0.5).select("rep", "center", "size", "is_big")


@query("cluster_buckets")
def _(s, d):
    return verify.buckets(hopsets.split_clusters(mesh_cover(s, d), graph(s, d, "part_mesh").n, 0.5))


def _own(s, d) -> DataFrame:
    def make():
        g, members = graph(s, d, "part_mesh"), mesh_cover(s, d)
        small = members.join(hopsets.split_clusters(members, g.n, 0.5).where("not is_big and size > 1").select("rep", "center"), ["rep", "center"])
        return cut(model.induced(g, small), "own")

    return held(s, ("own", d), make)


@query("local_hopset_edges")
def _(s, d):
    return local_hopset.by_keys(_own(s, d), 2, 42, graph(s, d, "part_mesh").partitions)


@query("local_hopset_udf_equal")
def _(s, d):
    a, b = local_hopset.at_centers(_own(s, d), 3, 42), local_hopset.by_keys(_own(s, d), 3, 42, graph(s, d, "part_mesh").partitions)
    return a.agg(F.count("*").alias("rows")).withColumn("same", F.lit(a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()))


@query("star_edges_mesh")
def _(s, d):
    g, members = graph(s, d, "part_mesh"), mesh_cover(s, d)
    big = hopsets.split_clusters(members, g.n, 0.5).where("is_big").select("rep", "center")
    return hopsets.stars(g, members, big, 17)


@query("center_clique_mesh")
def _(s, d):
    g, members = graph(s, d, "part_mesh"), mesh_cover(s, d)
    return hopsets.center_clique(g, hopsets.split_clusters(members, g.n, 0.5).where("is_big"), 12)


@query("center_clique_approx")
def _(s, d):
    """Centres' distances by the (1 + eps) search against exact ones."""
    g = graph(s, d, SMALL).compact()
    centers = hopsets.split_clusters(cover.limited_pairwise(g, 32, 4, 1.0, 1, 42, 1.0), g.n, 0.5)
    approx = hopsets.center_clique(g, centers, 40, weights="approx", eps=0.5)
    exact = hopsets.center_clique(g, centers, None).select(F.col("u").alias("src"), "v", F.col("w").alias("d"))
    return flags(exact, approx.select(F.col("u").alias("src"), "v", F.col("w").alias("d")), 1.5).agg(F.count_if(F.expr("not sound")).alias("too_short"), F.count_if(F.expr("not within")).alias("too_long"))


def built(s, d, name: str, p: HopsetParams = TEST) -> hopsets.HopsetResult:
    return held(s, ("hopset", d, name, p), lambda: hopsets.build(graph(s, d, name), p))


#: name of the query: graph and settings
BUILDS = {"mesh": ("part_mesh", TEST), "ladder": ("balance_ladder_full", TEST), "turns": (SMALL, TINY)}


def _hopset_queries(tag: str) -> None:
    name, p = BUILDS[tag]

    def at(s, d) -> tuple[hopsets.HopsetResult, DataFrame, DataFrame]:
        """The build, distances from picked sources, and lengths within 2 beta + 1 hops from the same ones."""
        b = built(s, d, name, p)
        g = b.graph.compact()
        got = held(s, ("within", d, tag), lambda: cut(mssp.many(g, b.edges, hash_sources(b.graph), 2 * b.beta + 1), "within"))
        return b, picked_truth(s, d, name), got

    def sound(s, d):
        b = built(s, d, name, p)
        g = b.graph.compact()
        t = held(s, ("root truth", d, name), lambda: cut(relax.exact(g, root_sources(b.graph)), "truth"))
        return flags(t, mssp.many(g, b.edges, root_sources(b.graph), 2 * b.beta + 1), 1 + p.eps)

    def stretch(s, d):
        b, t, got = at(s, d)
        return verify.stretch(t, got, p.eps).select("pairs", "reached", "too_short", "within", (F.col("max_stretch") <= 1 + p.eps).alias("bounded"))

    def scale_error(s, d):
        b, t, got = at(s, d)
        row = verify.compare(t, got).where("d_exact > 0").groupBy(F.floor(F.log2(F.col("d_exact").cast("double"))).cast("int").alias("scale"))
        return row.agg(F.count("*").alias("pairs"), F.count_if(F.coalesce(F.col("stretch") > 1 + p.eps, F.lit(True))).alias("too_long"))

    def hopbound(s, d):
        b, t, _ = at(s, d)
        g, most = b.graph.compact(), 2 * b.beta + 1
        after = verify.effective_hopbound(g, b.edges, hash_sources(b.graph), p.eps, t, most=most)
        before = verify.effective_hopbound(g, None, hash_sources(b.graph), p.eps, t, most=after) if after else None
        return s.createDataFrame([(after is not None and after <= most, before is None)], "within_bound boolean, fewer_than_without boolean")

    def size(s, d):
        b = built(s, d, name, p)
        g = b.graph
        bound = params.bounds("main_size", n=g.n, k=p.k)
        once = b.edges.groupBy("scale", "u", "v").agg(F.count("*").alias("k"))
        row = b.edges.agg((F.count("*") <= bound).alias("within_bound"), F.count_if(F.expr("u >= v")).alias("not_canonical"))
        return row.join(once.agg(F.count_if(F.expr("k > 1")).alias("twice"))).select(F.lit(g.n).cast("long").alias("n"), F.lit(g.m).cast("long").alias("m"), "*")

    def ledger(s, d):
        """Rounds of each phase against what bounds them: searches 2 beta + 1 at each scale, partitions the widest radius."""
        b = built(s, d, name, p)
        per = b.ledger.frame(s).groupBy("phase", "scale").agg(F.count("*").alias("rounds"), F.max("round").alias("last"), F.min("improved").alias("least"), F.min(F.col("messages") - F.col("improved")).alias("spare"))
        own = F.when(F.col("phase") == "partition", F.lit(2**31)).otherwise(2 * b.beta + 1)
        return per.agg(F.count_if(F.col("last") > own).alias("too_many_rounds"), F.count_if(F.expr("least <= 0")).alias("idle_rounds"), F.count_if(F.expr("spare < 0")).alias("unsent"))

    QUERIES[f"hopset_{tag}"] = lambda s, d: built(s, d, name, p).edges
    QUERIES.update({f"hopset_{what}_{tag}": f for what, f in (("size", size), ("sound", sound), ("stretch", stretch), ("scale_error", scale_error), ("hopbound", hopbound), ("ledger", ledger))})


for _tag in BUILDS:
    _hopset_queries(_tag)


@query("hopset_kinds_mesh")
def _(s, d):
    return verify.size_by_kind(built(s, d, "part_mesh").edges)


@query("hopset_rounds_mesh")
def _(s, d):
    return built(s, d, "part_mesh").ledger.frame(s).groupBy("phase").agg(F.count("*").alias("rounds"), F.sum("messages").alias("messages"), F.max("state_rows").alias("widest"))


@query("structure_size_mesh")
def _(s, d):
    """Rows of the stored structure, graph and hopset, against m + n^(1 + 1/2k) log n + n log^2 n."""
    b = built(s, d, "part_mesh")
    g = b.graph
    return s.createDataFrame([(g.m, g.m + b.size <= g.m + params.bounds("main_size", n=g.n, k=TEST.k))], "m long, within_bound boolean")


def _sweep(field: str, values: list) -> Query:
    """Size, effective hopbound, rounds and worst stretch for each value, over all pairs of the graph of conversation turns."""

    def run(s, d):
        g = graph(s, d, SMALL).compact()
        src, rows = g.nodes.select(F.col("id").alias("src")), []
        t = held(s, ("all truth", d, SMALL), lambda: cut(relax.exact(g, src), "truth"))
        for x in values:
            p = TINY.but(**{field: x})
            b = built(s, d, SMALL, p)
            got = verify.stretch(t, mssp.many(g, b.edges, src, 2 * b.beta + 1), p.eps).first()
            rows.append((field, float(x), b.size, verify.effective_hopbound(g, b.edges, src, p.eps, t), b.ledger.rounds(), b.ledger.messages(), got.too_short, got.max_stretch))
        return s.createDataFrame(rows, "parameter string, value double, edges long, hopbound int, rounds long, messages long, too_short long, max_stretch double")

    return run


QUERIES |= {"hopset_k_sweep": _sweep("k", [2, 3, 4, 7]), "hopset_eps_sweep": _sweep("eps", [0.25, 0.5, 1.0]), "hopset_mu_sweep": _sweep("mu", [0.3, 0.5, 0.7]), "hopset_beta_sweep": _sweep("beta", [4, 8, 16, 32]), "hopset_reps_sweep": _sweep("reps", [1, 3, 5])}


@query("hopset_sequential_vs_main")
def _(s, d):
    g = graph(s, d, SMALL)
    b = hopsets.build_sequential(g, TINY)
    return flags(picked_truth(s, d, SMALL), mssp.many(g.compact(), b.edges, hash_sources(g), 2 * TINY.beta + 1), 1 + TINY.eps)


def rich(s, d) -> hopsets.HopsetResult:
    return held(s, ("rich", d), lambda: dense.build(graph(s, d, SMALL), TINY))


@query("memory_rich_hopset")
def _(s, d):
    b = rich(s, d)
    bound = params.bounds("rich_size", n=b.graph.n)
    return s.createDataFrame([(b.graph.n, b.graph.m, b.size <= bound, dense.rounds_in_model(b.ledger, 0.5) >= b.ledger.rounds())], "n long, m long, within_bound boolean, model_rounds boolean")


@query("memory_rich_mssp")
def _(s, d):
    b = rich(s, d)
    return flags(picked_truth(s, d, SMALL), dense.mssp(b.graph.compact(), b.edges, hash_sources(b.graph), 2 * b.beta + 1), 1 + TINY.eps)


@query("memory_budget")
def _(s, d):
    return dense.memory_budget(graph(s, d, "part_mesh"), [0.25, 0.5, 1.0])


@query("mssp_with_hopset_mesh")
def _(s, d):
    """2 beta + 1 rounds, a fifth of the graph's depth, by distributed rounds from picked sources."""
    b = built(s, d, "part_mesh")
    return flags(picked_truth(s, d, "part_mesh"), mssp.many(b.graph, b.edges, hash_sources(b.graph), 2 * b.beta + 1), 1 + TEST.eps)


@query("sssp_with_hopset_turns")
def _(s, d):
    b = built(s, d, SMALL, TINY)
    source = b.graph.nodes.agg(F.min("id")).first()[0]
    one = s.createDataFrame([(source,)], "src long")
    return flags(relax.exact(b.graph.compact(), one), mssp.sssp(b.graph, source, TINY.eps, b.edges, 2 * b.beta + 1), 1 + TINY.eps)


@query("many_sources_handoff")
def _(s, d):
    """Every node a source, in the rounds of one query."""
    g = graph(s, d, "user_handoff")
    b = held(s, ("hopset", d, "user_handoff"), lambda: hopsets.build(g, TINY))
    src = g.nodes.select(F.col("id").alias("src"))
    return flags(relax.exact(g.compact(), src), mssp.many(g, b.edges, src, 2 * b.beta + 1), 1 + TINY.eps)


@query("pair_queries_mesh")
def _(s, d):
    """All pairs of picked sources."""
    b = built(s, d, "part_mesh")
    src = hash_sources(b.graph)
    pairs = src.crossJoin(F.broadcast(src.select(F.col("src").alias("v"))))  # sqrt n times sqrt n
    got = mssp.pair(b.graph.compact(), b.edges, pairs, 2 * b.beta + 1)
    return flags(picked_truth(s, d, "part_mesh").join(pairs, ["src", "v"]), got, 1 + TEST.eps)


@query("small_clique")
def _(s, d):
    g = graph(s, d, SMALL)
    b = held(s, ("hopset", d, SMALL, TINY.but(small="clique")), lambda: baselines.small_clique(g, TINY))
    return flags(picked_truth(s, d, SMALL), mssp.many(g.compact(), b.edges, hash_sources(g), 2 * b.beta + 1), 1 + TINY.eps)


@query("recursive_clique")
def _(s, d):
    g = graph(s, d, SMALL)
    b = built(s, d, SMALL, TINY.but(small="recursive"))
    return flags(picked_truth(s, d, SMALL), mssp.many(g.compact(), b.edges, hash_sources(g), 4 * b.beta + 2), 1 + TINY.eps)


def _dense_mesh(s, d) -> DataFrame:
    return held(s, ("dense", d), lambda: baselines.dense_two_level(graph(s, d, "part_mesh").compact(), 0.5))


@query("dense_two_level")
def _(s, d):
    """Its size against n^1.5 log n."""
    g, e = graph(s, d, "part_mesh"), _dense_mesh(s, d)
    return e.agg((F.count("*") <= F.lit(params.bounds("rich_size", n=g.n))).alias("within_bound"), F.count_if(F.expr("u >= v")).alias("not_canonical"))


@query("mssp_approx_mesh")
def _(s, d):
    """A quarter of the graph's depth in rounds, over the dense structure."""
    g = graph(s, d, "part_mesh").compact()
    return flags(picked_truth(s, d, "part_mesh"), relax.hop_limited(model.augment(g, _dense_mesh(s, d)), hash_sources(graph(s, d, "part_mesh")), 22), 1.5)


COMPETITORS = {"hierarchy_global": {"hops": None}, "hierarchy_limited": {"hops": 9, "eps": 0.5}, "hierarchy_no_scales": {"hops": 9, "eps": 0.5, "drop_scales": True}}


def competitor(s, d, name: str) -> DataFrame:
    return held(s, ("competitor", d, name), lambda: baselines.hierarchy_global(graph(s, d, SMALL).compact(), 3, **COMPETITORS[name]))


for _name in COMPETITORS:
    QUERIES[_name] = lambda s, d, name=_name: verify.size_by_kind(competitor(s, d, name))
    QUERIES[f"{_name}_sound"] = lambda s, d, name=_name: flags(picked_truth(s, d, SMALL), relax.hop_limited(model.augment(graph(s, d, SMALL).compact(), competitor(s, d, name)), hash_sources(graph(s, d, SMALL)), 19), 1.5)


@query("hierarchy_sizes")
def _(s, d):
    """The form without scales has no more edges than the one with them."""
    a, b = (competitor(s, d, x).count() for x in ("hierarchy_limited", "hierarchy_no_scales"))
    return s.createDataFrame([(b <= a,)], "no_larger boolean")


@query("bound_competitors")
def _(s, d):
    """Hopbounds and sizes of the methods at equal size, for this graph's n."""
    n = float(graph(s, d, "part_mesh").n)
    row = s.createDataFrame([tuple(float(x) for x in (params.ARGUMENTS | {"n": n}).values())], ", ".join(f"{k} double" for k in params.ARGUMENTS))
    names = ("restated_hopbound", "competitor_hopbound", "competitor_rounds", "claimed_gain", "dense_hopbound", "superpoly_hopbound", "hopbound_lower", "rho_hopbound")
    return row.select(*[F.round(F.expr(params.bound_expression(b)), 4).alias(b) for b in names])


@query("bunch_oracle")
def _(s, d):
    g = graph(s, d, SMALL)
    bunches, pivots = baselines.bunch_oracle(g.compact(), 2)
    t = relax.exact(g.compact(), root_sources(g)).where("src <> v").select("src", "v", "d")
    got = baselines.oracle_query(bunches, pivots, t.select("src", "v"), 2).withColumnRenamed("d", "e")
    return t.join(got, ["src", "v"], "left").select("src", "v", F.col("d").alias("d_exact"), (F.col("e") >= F.col("d")).alias("sound"), (F.col("e") <= 3 * F.col("d")).alias("within"))


@query("spanner_mesh")
def _(s, d):
    g = graph(s, d, "part_mesh")
    thin = model.Graph(g.nodes, baselines.spanner(g, 2), True)
    return flags(picked_truth(s, d, "part_mesh"), relax.exact(thin, hash_sources(g)), 3)


@query("plain_rounds")
def _(s, d):
    """Without a hopset: rounds, improved rows and offers until nothing improves, by distributed rounds."""
    g, ledger = graph(s, d, "part_mesh"), Ledger()
    baselines.plain_relaxation(g, root_sources(g), ledger)
    return s.createDataFrame([(ledger.rounds(), sum(r[4] for r in ledger.rows), ledger.messages())], "rounds long, improved long, offers_before_last long")


@query("congestion_mesh")
def _(s, d):
    return verify.congestion(truth(s, d, "part_mesh"))


def _compared(s, d) -> DataFrame:
    g = graph(s, d, SMALL)
    src, t, rows = hash_sources(g), picked_truth(s, d, SMALL), []

    def put(name: str, edges: DataFrame | None, ledger: Ledger | None) -> None:
        bound = verify.effective_hopbound(g.compact(), edges, src, TINY.eps, t)
        union = model.augment(g.compact(), edges) if edges is not None else g.compact()
        got = verify.stretch(t, relax.hop_limited(union, src, bound), TINY.eps).first()
        rows.append((name, edges.count() if edges is not None else 0, bound, ledger.rounds() if ledger else None, ledger.messages() if ledger else None, got.max_stretch, got.too_short))

    put("none", None, None)
    for small in ("hierarchy", "clique", "recursive"):
        b = built(s, d, SMALL, TINY.but(small=small))
        put(f"sparse_{small}", b.edges, b.ledger)
    put("dense_two_level", baselines.dense_two_level(g.compact(), 0.5), None)
    for name in COMPETITORS:
        put(name, competitor(s, d, name), None)
    return s.createDataFrame(rows, "method string, edges long, hopbound int, rounds long, messages long, max_stretch double, too_short long")


@query("compare_all")
def _(s, d):
    """Each method on the graph of conversation turns: size, effective hopbound, rounds and offers of the build, stretch."""
    return held(s, ("compared", d), lambda: cut(_compared(s, d), "compared"))


@query("compare_properties")
def _(s, d):
    """Of the same table what must hold: no method is too short or beyond 1 + eps, every hopset needs fewer hops than none,
    and the sparse one has fewer edges than the dense one's bound."""
    row = QUERIES["compare_all"](s, d)
    none = row.where("method = 'none'").select(F.col("hopbound").alias("plain"))
    return row.where("method <> 'none'").join(F.broadcast(none)).select("method", (F.col("too_short") == 0).alias("sound"), (F.col("max_stretch") <= 1 + TINY.eps).alias("within"), (F.col("hopbound") < F.col("plain")).alias("fewer_hops"))


@query("bounds_table")
def _(s, d):
    row = s.createDataFrame([tuple(float(x) for x in params.ARGUMENTS.values())], ", ".join(f"{k} double" for k in params.ARGUMENTS))
    return row.select(*[F.round(F.expr(params.bound_expression(b)), 4).alias(b) for b in params.BOUNDS])


@query("bucket_sum")
def _(s, d):
    """Sum over sizes 2^r < sqrt n of (n / 2^r) (2^r)^(1 + 1/k) beside n^(1 + 1/2k)."""
    n = F.col("n")
    parts = load(s, d, "part").agg(F.countDistinct("p_partkey").cast("double").alias("n"))
    r = s.range(1, 60).join(F.broadcast(parts)).where(F.pow(F.lit(2.0), F.col("id")) <= F.sqrt(n)).select("n", F.explode(F.array(*[F.lit(float(k)) for k in (2, 3, 4)])).alias("k"), "id")
    return r.groupBy("k").agg(F.round(F.sum(n * F.pow(F.lit(2.0), F.col("id") / F.col("k"))), 4).alias("total"), F.round(F.max(F.pow(n, 1 + 1 / (2 * F.col("k")))), 4).alias("bound"))


QUERIES |= relational.QUERIES | streams.QUERIES
