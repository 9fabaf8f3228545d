"""Weight rounding, the shifted low-diameter partition, and hop-limited covers made of its repetitions."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from hopline.functions.params import default_reps
from hopline.functions.rand import FRACTION, shifts
from hopline.model import Graph
from hopline.plans import one_task
from hopline.plans.rounds import Ledger, loop


def eta(big_r: int, ell: int, eps0: float) -> Fraction:
    """The unit that weights are rounded up to: eps0 R / ell."""
    return Fraction(eps0).limit_denominator(1000) * Fraction(big_r).limit_denominator(1000) / ell


def round_weights(graph: Graph, big_r: float, ell: int, eps0: float) -> DataFrame:
    """Edges with ``what``, the weight in whole units, rounded up."""
    unit = eta(big_r, ell, eps0)
    top = F.col("w") * F.lit(unit.denominator)
    return graph.edges.withColumn("what", F.floor((top + (unit.numerator - 1)) / F.lit(unit.numerator)).cast("long") if unit.numerator == 1 else F.expr(f"(w * {unit.denominator} + {unit.numerator - 1}) div {unit.numerator}"))


def recover(what, big_r: float, ell: int, eps0: float):
    """Length of a rounded path in the original unit."""
    unit = eta(big_r, ell, eps0)
    return what * F.lit(unit.numerator) / F.lit(unit.denominator)


def partition(graph: Graph, alpha: float, seed: int, reps: int, rounded: DataFrame | None = None, ledger: Ledger | None = None, first: int = 0) -> DataFrame:
    """(rep, v, center, dhat, dtree): every node joins the centre x of least d(v, x) - r_x.

    Only a node's best offer is forwarded, and an offer whose key is above 0 can't beat the node's own. All
    repetitions share the rounds, as key columns. Ties go to the smaller centre, then the shorter tree. Repetitions
    before ``first`` are left out.
    """
    return partitions(graph, {0: (alpha, seed, rounded)}, reps, ledger, first).drop("scale")


def partitions(graph: Graph, scales: dict[int, tuple], reps: int, ledger: Ledger | None = None, first: int = 0) -> DataFrame:
    """(scale, rep, v, center, dhat, dtree): the partitions of several scales, each with its rate, seed and rounded edges,
    in the same rounds: scale and repetition are key columns."""
    arcs = radii = None
    for scale, (alpha, seed, rounded) in scales.items():
        edges = rounded if rounded is not None else graph.edges.withColumn("what", F.col("w"))
        both = edges.select("u", "v", "w", "what").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"), "w", "what"))
        some = both.select(F.lit(scale).alias("scale"), F.col("u").alias("from"), F.col("v").alias("to"), "w", "what")
        start = shifts(graph.nodes, alpha, seed, reps).where(F.col("rep") >= first).select(F.lit(scale).alias("scale"), F.col("rep").cast("long").alias("rep"), F.col("id").alias("v"), (-F.col("shift_fp")).alias("key"))
        arcs, radii = (some, start) if arcs is None else (arcs.unionByName(some), radii.unionByName(start))
    if len(scales) == 1 and graph.in_task and (reps - first) * graph.n <= one_task.CELLS and one_task.deals(4 * graph.m):  # four columns of half the width an arc
        return one_task.partition(arcs, radii, reps - first, graph.n, graph.m, FRACTION, "partition", ledger).select(F.lit(next(iter(scales))).alias("scale"), F.col("rep").cast("int").alias("rep"), "v", "center", "dhat", "dtree")
    p = graph.partitions_for(len(scales) * (reps - first) * graph.n)
    arcs = arcs.repartition(p, "from").persist()
    zero, keys = F.lit(0).cast("long"), ["scale", "rep"]
    best = F.struct("key", F.col("v").alias("center"), zero.alias("dhat"), zero.alias("dtree"))
    start = radii.select(*keys, "v", best.alias("best"), F.lit(True).alias("fresh")).repartition(p, "v")

    def step(state: DataFrame, sent: Observation) -> DataFrame:
        front = state.where("fresh").select(*keys, F.col("v").alias("from"), "best").join(arcs, ["from", "scale"])
        offer = F.struct((F.col("best.key") + F.shiftleft("what", FRACTION)).alias("key"), F.col("best.center").alias("center"), (F.col("best.dhat") + F.col("what")).alias("dhat"), (F.col("best.dtree") + F.col("w")).alias("dtree"))
        offers = front.select(*keys, F.col("to").alias("v"), offer.alias("best"), F.lit(None).cast(state.schema["best"].dataType).alias("old")).where("best.key <= 0")
        offers = offers.observe(sent, F.count("*").alias("offers")).repartition(p, "v")  # the state stays where it is
        merged = state.select(*keys, "v", "best", F.col("best").alias("old")).unionByName(offers).groupBy(*keys, "v").agg(F.min("best").alias("best"), F.min("old").alias("old"))
        return merged.select(*keys, "v", "best", (F.col("best") < F.col("old")).alias("fresh"))

    state = loop(start, step, None, "partition", ledger)
    arcs.unpersist()
    return state.select("scale", F.col("rep").cast("int").alias("rep"), "v", "best.center", "best.dhat", "best.dtree")


def rate_of(ell: int, eps0: float, rate: float | None, window: float) -> float:
    """Rate of the radii: a path of at most ell edges and a length in [W, c W] has about c ell / eps0 rounded units."""
    return (0.5 if rate is None else rate) * eps0 / ell * 2 / window


def limited_pairwise(graph: Graph, width: float, ell: int, eps0: float = 1.0, reps: int | None = None, seed: int = 42, rate: float | None = None, scale: int = 0, batch: int | None = None, ledger: Ledger | None = None, window: float = 2.0) -> DataFrame:
    """Members of an ell-limited cover for lengths in [W, c W], c = ``window``: weights rounded at R = W, radii of rate
    eps0 / (c ell) in rounded units (``rate`` replaces the factor 1/2 of c = 2), repeated O(log n) times.

    ``batch`` runs so many repetitions at a time (the pipelined form); by default all share the rounds.
    """
    reps = reps or default_reps(graph.n)
    alpha = rate_of(ell, eps0, rate, window)
    rounded = round_weights(graph, width, ell, eps0)
    parts = [partition(graph, alpha, seed + 1000 * scale, reps, rounded, ledger)] if not batch or batch >= reps else []
    for first in range(0, reps if not parts else 0, batch or reps):
        parts.append(partition(graph, alpha, seed + 1000 * scale, min(reps, first + batch), rounded, ledger, first))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.select(F.lit(scale).alias("scale"), F.col("rep").cast("int").alias("rep"), "center", "v", "dhat", "dtree")


def limited_pairwise_all(graph: Graph, widths: list[int], ell: int, eps0: float = 1.0, reps: int | None = None, seed: int = 42, rate: float | None = None, window: float = 2.0, parallel_scales: bool = True, ledger: Ledger | None = None) -> DataFrame:
    """Covers for all lengths: one for each doubling of the width, all in the same rounds or one after another."""
    reps = reps or default_reps(graph.n)
    scales = {k: (rate_of(ell, eps0, rate, window), seed + 1000 * k, round_weights(graph, w, ell, eps0)) for k, w in enumerate(widths)}
    runs = [scales] if parallel_scales else [{k: v} for k, v in scales.items()]
    out = None
    for some in runs:
        part = partitions(graph, some, reps, ledger).select("scale", "rep", "center", "v", "dhat", "dtree")
        out = part if out is None else out.unionByName(part)
    return out


def limited_neighborhood(graph: Graph, width: float, ell: int, **settings) -> DataFrame:
    """The same clusters, read as a neighbourhood cover: a ball B^ell(v, W) lies in one cluster. The ball's diameter
    is twice its radius, so the rate is halved."""
    return limited_pairwise(graph, width, ell, rate=settings.pop("rate", 0.25), **settings)


def neighborhood(graph: Graph, width: float, reps: int | None = None, seed: int = 42, ledger: Ledger | None = None) -> DataFrame:
    """Unlimited cover: radii of rate 1/W on the weights themselves; needs about W log n rounds."""
    out = partition(graph, 1.0 / width, seed, reps or default_reps(graph.n), None, ledger)
    return out.select(F.lit(0).alias("scale"), F.col("rep").cast("int").alias("rep"), "center", "v", "dhat", "dtree")


def clusters(members: DataFrame, threshold: float) -> DataFrame:
    """(scale, rep, center, size, is_big)."""
    sized = members.groupBy("scale", "rep", "center").agg(F.count("*").alias("size"))
    return sized.withColumn("is_big", F.col("size") >= F.lit(float(threshold)))
