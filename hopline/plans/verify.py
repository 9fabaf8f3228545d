"""Measures and invariants: stretch, hopbound, soundness, sizes, cover properties, padding, rounding."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopline.functions.params import padding_bound
from hopline.model import Graph, augment, induced
from hopline.operators.components import connected_labels
from hopline.plans import one_task
from hopline.plans.relax import exact, hop_bits, hop_limited, search
from hopline.session import cut


def compare(truth: DataFrame, approx: DataFrame) -> DataFrame:
    """(src, v, d_exact, d_approx, stretch) for every pair that the truth reaches."""
    a = approx.select("src", "v", F.col("d").alias("d_approx"))
    row = truth.select("src", "v", F.col("d").alias("d_exact")).join(a, ["src", "v"], "left")
    ratio = F.when(F.col("d_exact") == 0, F.when(F.col("d_approx") == 0, 1.0)).otherwise(F.col("d_approx") / F.col("d_exact"))
    return row.withColumn("stretch", F.round(ratio, 6))


def stretch(truth: DataFrame, approx: DataFrame, eps: float) -> DataFrame:
    """One row: pairs, reached, too_short (must be 0), within, max and mean stretch, 95 % quantile."""
    row = compare(truth, approx).where("src <> v")
    return row.agg(
        F.count("*").alias("pairs"),
        F.count("d_approx").alias("reached"),
        F.sum((F.col("d_approx") < F.col("d_exact")).cast("long")).alias("too_short"),
        F.sum((F.col("stretch") <= 1 + eps).cast("long")).alias("within"),
        F.max("stretch").alias("max_stretch"),
        F.round(F.avg("stretch"), 6).alias("mean_stretch"),
        F.percentile("stretch", F.lit(0.95)).alias("q95"),
    )


def sound(graph: Graph, hopset: DataFrame) -> DataFrame:
    """Shortcut edges shorter than the true distance (must be none)."""
    sources = hopset.select(F.col("u").alias("src")).distinct()
    truth = exact(graph, sources).select(F.col("src").alias("u"), "v", F.col("d").alias("d_exact"))
    return hopset.join(truth, ["u", "v"], "left").where("d_exact is null or w < d_exact")


def effective_hopbound(graph: Graph, hopset: DataFrame | None, sources: DataFrame, eps: float, truth: DataFrame | None = None, most: int | None = None) -> int | None:
    """Least number of hops within which all pairs from ``sources`` are at most (1 + eps) d; None if ``most`` hops aren't
    enough. ``most`` defaults to the number of nodes, which no best path exceeds.

    The limit doubles until no pair is too long, then the gap is halved.
    """
    truth = (truth if truth is not None else exact(graph, sources)).select("src", "v", F.col("d").alias("d_exact")).persist()
    union = augment(graph, hopset) if hopset is not None else graph
    most = graph.n if most is None else most
    good = lambda h: hop_limited(union, sources, h).join(truth, ["src", "v"], "right").where(F.col("d").isNull() | (F.col("d") > F.col("d_exact") * (1 + eps))).isEmpty()
    lo, hi = 0, min(1, most)
    while not (found := good(hi)) and hi < most:
        lo, hi = hi, min(most, hi * 2)
    while found and hi - lo > 1:
        mid = (lo + hi) // 2
        lo, hi = (lo, mid) if good(mid) else (mid, hi)
    truth.unpersist()
    return hi if found else None


def size_by_kind(hopset: DataFrame) -> DataFrame:
    return hopset.groupBy("scale", "kind").agg(F.count("*").alias("edges"))


def scale_error(truth: DataFrame, approx: DataFrame) -> DataFrame:
    """(scale, pairs, max_stretch) by the power of two of the true distance."""
    row = compare(truth, approx).where("d_exact > 0")
    return row.groupBy(F.floor(F.log2(F.col("d_exact").cast("double"))).cast("int").alias("scale")).agg(F.count("*").alias("pairs"), F.max("stretch").alias("max_stretch"))


def overlap(members: DataFrame) -> DataFrame:
    """(v, clusters, reps): memberships of each node."""
    return members.groupBy("v").agg(F.count("*").alias("clusters"), F.countDistinct("rep").alias("reps"))


def containment(members: DataFrame, pairs: DataFrame) -> DataFrame:
    """``pairs(src, v)`` with whether some cluster holds both ends."""
    a, b = members.select("rep", "center", F.col("v").alias("src")), members.select("rep", "center", "v")
    held = pairs.join(a, "src").join(b, ["rep", "center", "v"]).select("src", "v").distinct().withColumn("held", F.lit(True))
    return pairs.select("src", "v").join(held, ["src", "v"], "left").withColumn("held", F.coalesce("held", F.lit(False)))


def ball_containment(members: DataFrame, balls: DataFrame) -> DataFrame:
    """(src, held): whether some cluster holds the whole of ``balls(src, v)`` around src."""
    size = balls.groupBy("src").agg(F.count("*").alias("n"))
    home = members.select("rep", "center", F.col("v").alias("src"))
    inside = balls.join(home, "src").join(members.select("rep", "center", "v"), ["rep", "center", "v"], "left_semi").groupBy("src", "rep", "center").agg(F.count("*").alias("k"))
    return size.join(inside.groupBy("src").agg(F.max("k").alias("k")), "src", "left").select("src", (F.coalesce("k", F.lit(0)) == F.col("n")).alias("held"))


def padding_rate(parts: DataFrame, balls: DataFrame, r: float, alpha: float) -> DataFrame:
    """One row: share of (repetition, node) whose ball of radius r lies in one cluster, beside exp(-2 r alpha)."""
    row = balls.join(parts.select("rep", "v", "center"), "v").groupBy("rep", "src").agg(F.countDistinct("center").alias("c"))
    return row.agg(F.round(F.avg((F.col("c") == 1).cast("double")), 6).alias("rate")).withColumn("bound", F.round(F.lit(padding_bound(r, alpha)), 6))


def cluster_diameters(members: DataFrame, kind: str = "tree") -> DataFrame:
    """(scale, rep, center, size, radius): greatest tree length ('tree', a path inside the cluster) or rounded
    length ('rounded') from the centre; a diameter is at most twice that."""
    column = "dtree" if kind == "tree" else "dhat"
    return members.groupBy("scale", "rep", "center").agg(F.count("*").alias("size"), F.max(column).alias("radius"))


def connected_members(graph: Graph, members: DataFrame) -> DataFrame:
    """(rep, center, pieces): components of the graph inside each cluster (must be one)."""
    named = members.select("rep", "center", "v", (F.col("rep").cast("long") * F.lit(2**44) + F.col("v")).alias("cls"))
    links = induced(graph, members).select(*[(F.col("rep").cast("long") * F.lit(2**44) + F.col(x)).alias(c) for x, c in (("u", "a"), ("v", "b"))])
    label = connected_labels(links)
    return named.join(label, "cls", "left").groupBy("rep", "center").agg(F.countDistinct(F.coalesce("comp", "cls")).alias("pieces"))


def cluster_edges(graph: Graph, members: DataFrame) -> DataFrame:
    """One row: sum of |C| and sum of |E(C)| over all clusters."""
    return members.agg(F.count("*").alias("sizes")).join(induced(graph, members).agg(F.count("*").alias("edges")))


def true_diameters(graph: Graph, members: DataFrame) -> DataFrame:
    """(rep, center, strong, weak): greatest distance of two members by paths inside the cluster, and by any path."""
    keys = ["rep", "center", "src"]
    own = cut(induced(graph, members), "own")
    both = own.unionByName(own.select("rep", "center", F.col("v").alias("u"), F.col("u").alias("v"), "w"))
    start = members.select("rep", "center", F.col("v").alias("src"), "v")
    rows = start.count()
    most = own.groupBy("rep", "center").agg(F.count("*").alias("k")).agg(F.max("k")).first()[0] or 0
    if graph.in_task and one_task.fits(2 * most, 0) and one_task.deals(2 * graph.m):
        lone = members.select("rep", "center", F.lit(0).cast("long").alias("strong"))
        strong = cut(one_task.widths(own, hop_bits(None, graph.n)).unionByName(lone).groupBy("rep", "center").agg(F.max("strong").alias("strong")), "strong")
        # Within a cluster no pair is further apart in the graph than inside: its own width bounds the searches.
        weak = one_task.spans(graph.edges, members.select("rep", "center", "v").join(strong, ["rep", "center"]), rows, hop_bits(None, graph.n), graph.m)
        return strong.join(weak, ["rep", "center"])
    p = graph.partitions_for(rows)
    arcs = both.repartition(p, "u").persist()
    inside = search(arcs, start, keys, None, p, arc_keys=("rep", "center"), nodes=graph.n)
    strong = inside.groupBy("rep", "center").agg(F.max("d").alias("strong"))
    a, b = members.select("rep", "center", F.col("v").alias("src")), members.select("rep", "center", "v")
    # Within a cluster no pair is further apart in the graph than inside, so a search up to the widest cluster sees all.
    widest = strong.agg(F.max("strong")).first()[0] or 0
    any_ = hop_limited(graph, graph.nodes.select(F.col("id").alias("src")), None, radius=widest)
    weak = any_.join(a, "src").join(b, ["rep", "center", "v"]).groupBy("rep", "center").agg(F.max("d").alias("weak"))
    arcs.unpersist()
    return strong.join(weak, ["rep", "center"])


def rounding_inflation(edges: DataFrame, unit_num: int, unit_den: int) -> DataFrame:
    """Edges whose rounded length isn't in [w, w + eta] (must be none)."""
    long = F.col("what") * F.lit(unit_num)
    return edges.where((long < F.col("w") * unit_den) | (long > F.col("w") * unit_den + unit_num))


def buckets(sized: DataFrame) -> DataFrame:
    """(bucket, clusters, members): clusters by power of two of their size."""
    return sized.groupBy(F.floor(F.log2(F.col("size").cast("double"))).cast("int").alias("bucket")).agg(F.count("*").alias("clusters"), F.sum("size").alias("members"))


def congestion(dist: DataFrame) -> DataFrame:
    """One row: the most rows that share a node, the inbox of the round model."""
    return dist.groupBy("v").agg(F.count("*").alias("inbox")).agg(F.max("inbox").alias("max_inbox"), F.sum("inbox").alias("rows"))


def worst(dist: DataFrame, truth: DataFrame, rows: int = 10) -> DataFrame:
    """The worst pairs by stretch, for reports."""
    return compare(truth, dist).orderBy(F.desc_nulls_last("stretch"), "src", "v").limit(rows)
