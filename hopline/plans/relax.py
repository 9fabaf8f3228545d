"""Distances by synchronous relaxation: from many sources at once, hop-limited, radius-limited, keyed by cluster.

A round joins the rows that improved in the round before with the arcs that leave their node and keeps the least
offer for each (key, node). State and arcs lie in the same partitions by node and stay there; only offers are
exchanged. Distance and hop count share one BIGINT (``d * 2^bits + hops``), so the minimum is a hash aggregate, the
least distance wins and the fewest hops break ties. After i rounds the state is exactly d^i.

Best paths are simple, so the hop limit or the number of nodes, whichever is less, gives the bits; where neither is
known there are HOP_BITS, and a search with more rounds fails. A distance that doesn't fit beside them fails as well.

Hubs. Nodes with more than ``HUB`` arcs have their arcs cut into slices by the other end, which lie in partitions of
their own; a hub's improved rows are copied to its slices. Offers to a hub are reduced slice by slice before they meet.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from hopline.model import Graph
from hopline.plans import one_task
from hopline.plans.rounds import Ledger, loop

HOP_BITS = 20
HUB, SLICES = 200_000, 64


def hop_bits(hops: int | None, nodes: int | None) -> int:
    """Bits that hold the hops of every offer of a search."""
    known = [x for x in (hops, nodes) if x is not None]
    return max(1, min(known).bit_length()) if known else HOP_BITS


def _longer(p: Column, w: Column, bits: int) -> Column:
    """The packed value one edge on."""
    fits = w < F.shiftright(F.lit(2**63 - 1) - p, bits)
    return F.when(fits, p + F.shiftleft(w, bits) + 1).otherwise(F.raise_error(F.lit("a distance exceeds the packed state")).cast("long"))


def _unpacked(state: DataFrame, keys: list[str], bits: int) -> DataFrame:
    return state.select(*keys, "v", F.shiftright("p", bits).alias("d"), (F.col("p").bitwiseAND((1 << bits) - 1)).cast("int").alias("hops"))


class Arcs:
    """Arcs (keys, u, v, w) of a search in three parts, which are one where no node is a hub."""

    def __init__(self, arcs: DataFrame, hubs: DataFrame | None = None, partitions: int = 1):
        self.plain, self.hubs, self.leaving, self.entering = arcs, None, None, None
        if hubs is not None:
            self.hubs = F.broadcast(hubs)
            out = arcs.join(self.hubs.withColumnRenamed("hub", "u"), "u", "left")
            cold = out.where("slices is null").drop("slices")
            into = cold.join(self.hubs.select(F.col("hub").alias("v"), F.lit(True).alias("into")), "v", "left")
            self.plain = into.where("into is null").select(arcs.columns).repartition(partitions, "u").persist()
            self.entering = into.where("into").select(arcs.columns).repartition(partitions, "u").persist()
            leaving = out.where("slices is not null").withColumn("slice", F.pmod(F.xxhash64("v"), "slices").cast("int"))
            self.leaving = leaving.drop("slices").repartition(partitions, "u", "slice").persist()

    def release(self) -> None:
        for part in (self.plain, self.leaving, self.entering) if self.hubs is not None else ():
            part.unpersist()

    def offers(self, front: DataFrame, keys: list[str], arc_keys: list[str], longer) -> DataFrame:
        """keys, v, p: what the rows ``front`` (keys, v, p) send along the arcs."""
        row = front.withColumnRenamed("v", "u")

        def sent(left: DataFrame, arcs: DataFrame, on: list[str]) -> DataFrame:
            return left.join(arcs.withColumnRenamed("v", "to"), on).select(*keys, F.col("u").alias("from"), F.col("to").alias("v"), longer(F.col("p"), F.col("w")).alias("p"))

        if self.hubs is None:
            return sent(row, self.plain, [*arc_keys, "u"]).drop("from")
        copies = row.join(self.hubs.withColumnRenamed("hub", "u"), "u").withColumn("slice", F.explode(F.sequence(F.lit(0), F.col("slices") - 1))).drop("slices")
        met = sent(row, self.entering, [*arc_keys, "u"]).groupBy(*keys, "v", F.pmod(F.xxhash64("from"), F.lit(SLICES)).alias("slice")).agg(F.min("p").alias("p"))
        return sent(row, self.plain, [*arc_keys, "u"]).drop("from").unionByName(sent(copies, self.leaving, [*arc_keys, "u", "slice"]).drop("from")).unionByName(met.drop("slice"))


def hubs_of(graph: Graph) -> DataFrame | None:
    """(hub, slices): nodes with more than HUB arcs, at most 2 m / HUB of them; None if there is none."""
    degree = graph.arcs.groupBy(F.col("u").alias("hub")).agg(F.count("*").alias("k")).where(F.col("k") > HUB)
    found = degree.select("hub", F.ceil(F.col("k") / HUB).cast("int").alias("slices"))
    return None if graph.m <= HUB or found.isEmpty() else found


def search(arcs: DataFrame | Arcs, seeds: DataFrame, keys: list[str], hops: int | None, partitions: int, radius: int | Column | None = None, arc_keys: tuple = (), delta: bool = True, phase: str = "search", ledger: Ledger | None = None, prune: DataFrame | None = None, nodes: int | None = None, in_task: bool = False) -> DataFrame:
    """``seeds``: keys and v at distance 0. ``arcs``: (u, v, w), with those of the keys that ``arc_keys`` names. ``prune``: (v,
    cap): offers to v must lie below the cap. ``nodes``: how many nodes the arcs join. ``in_task``: the caller has checked
    that arcs and state fit one task. Returns keys, v, d, hops."""
    bits = hop_bits(hops, nodes)
    if in_task and delta and hops != 0:
        caps = arcs.join(prune.select("v", F.col("cap").alias("_cap")), "v", "left") if prune is not None else arcs.withColumn("_cap", F.lit(None).cast("long"))
        limit = radius if isinstance(radius, Column) else F.lit(radius)
        return one_task.search(caps, seeds.select(*keys, "v", limit.cast("long").alias("_radius")), keys, list(arc_keys), hops, bits, phase, ledger)
    start = seeds.select(*keys, "v", F.lit(0).cast("long").alias("p"), F.lit(True).alias("fresh")).repartition(partitions, "v")
    out = arcs if isinstance(arcs, Arcs) else Arcs(arcs)

    def step(state: DataFrame, sent: Observation) -> DataFrame:
        front = (state.where("fresh") if delta else state).select(*keys, "v", "p")
        offers = out.offers(front, keys, list(arc_keys), lambda p, w: _longer(p, w, bits))
        if radius is not None:
            offers = offers.where(F.shiftright("p", bits) <= radius)
        if prune is not None:
            offers = offers.join(prune, "v", "left").where(F.col("cap").isNull() | (F.shiftright("p", bits) < F.col("cap"))).select(*keys, "v", "p")
        offers = offers.observe(sent, F.count("*").alias("offers")).repartition(partitions, "v")
        both = state.select(*keys, "v", "p", F.col("p").alias("old")).unionByName(offers.withColumn("old", F.lit(None).cast("long")))
        merged = both.groupBy(*keys, "v").agg(F.min("p").alias("p"), F.min("old").alias("old"))
        return merged.select(*keys, "v", "p", (F.col("old").isNull() | (F.col("p") < F.col("old"))).alias("fresh"))

    return _unpacked(start if hops == 0 else loop(start, step, hops, phase, ledger, most=(1 << bits) - 1 if hops is None and nodes is None else None), keys, bits)


def seeds(sources: DataFrame) -> DataFrame:
    return sources.select("src", F.col("src").alias("v"))


def hop_limited(graph: Graph, sources: DataFrame, hops: int | None, delta: bool = True, radius: int | None = None, ledger: Ledger | None = None, phase: str = "search", ends: DataFrame | None = None) -> DataFrame:
    """(src, v, d, hops): least length over paths of at most ``hops`` edges; all sources in the same rounds. ``ends`` (v): the
    only ends that are wanted."""
    count = sources.count()
    rows = count * graph.n
    if graph.in_task and ledger is None and delta and hops != 0 and one_task.deals(2 * graph.m):
        return one_task.dealt(graph.edges, sources.select("src", F.lit(radius).cast("long").alias("_radius")), count, hops, hop_bits(hops, graph.n), ends=ends, many=graph.m)
    of_ends = lambda out: out.join(ends, "v", "left_semi").select("src", "v", "d", "hops") if ends is not None else out
    if graph.in_task and one_task.fits(2 * graph.m, rows):
        return of_ends(search(graph.arcs, seeds(sources), ["src"], hops, 1, radius, phase=phase, ledger=ledger, nodes=graph.n, in_task=True))
    p = graph.partitions_for(rows)
    arcs = Arcs(graph.arcs_in(p), hubs_of(graph), p)
    out = search(arcs, seeds(sources), ["src"], hops, p, radius, delta=delta, phase=phase, ledger=ledger, nodes=graph.n)
    arcs.release()
    return of_ends(out)


def exact(graph: Graph, sources: DataFrame, ledger: Ledger | None = None) -> DataFrame:
    """Distances, by relaxing to the fixpoint."""
    return hop_limited(graph, sources, None, ledger=ledger, phase="exact")


def ball(graph: Graph, centers: DataFrame, r: int, hops: int | None = None) -> DataFrame:
    """(src, v, d): nodes within ``r`` of each centre, by at most ``hops`` edges."""
    return hop_limited(graph, centers, hops, radius=r).select("src", "v", "d")


def pairs_in_scale(graph: Graph, sources: DataFrame, big_r: int, hops: int | None = None) -> DataFrame:
    """Pairs whose (hop-limited) distance lies in (R, 2R]."""
    return hop_limited(graph, sources, hops, radius=2 * big_r).where(F.col("d") > big_r).select("src", "v", "d")


def minplus(a: DataFrame, b: DataFrame, keep: int | None = None) -> DataFrame:
    """(u, v, w): least of a(u, x) + b(x, v); with ``keep`` only the nearest ``keep`` columns of each row."""
    left, right = a.select("u", F.col("v").alias("x"), F.col("w").alias("wa")), b.select(F.col("u").alias("x"), "v", F.col("w").alias("wb"))
    out = left.join(right, "x").groupBy("u", "v").agg(F.min(F.col("wa") + F.col("wb")).alias("w"))
    return nearest(out, keep) if keep else out


def nearest(pairs: DataFrame, q: int) -> DataFrame:
    order = Window.partitionBy("u").orderBy("w", "v")
    return pairs.withColumn("place", F.row_number().over(order)).where(F.col("place") <= q).drop("place")


def q_nearest(graph: Graph, q: int, doublings: int) -> DataFrame:
    """(u, v, w): the q nearest nodes of each node (itself included) by at most 2^doublings edges, by filtered
    min-plus squaring."""
    own = graph.nodes.select(F.col("id").alias("u"), F.col("id").alias("v"), F.lit(0).cast("long").alias("w"))
    table = nearest(own.unionByName(graph.arcs.select("u", "v", "w")), q)
    for _ in range(doublings):
        table = minplus(table, table, q)
    return table


def with_parents(graph: Graph, dist: DataFrame) -> DataFrame:
    """Adds to (src, v, d, hops) the smallest node from which a best path arrives; null at the source."""
    near = dist.select("src", F.col("v").alias("u"), F.col("d").alias("du"), F.col("hops").alias("hu"))
    step = graph.arcs.join(near, "u").select("src", "v", (F.col("du") + F.col("w")).alias("d"), (F.col("hu") + 1).alias("hops"), "u")
    best = step.groupBy("src", "v", "d", "hops").agg(F.min("u").alias("parent"))
    return dist.join(best, ["src", "v", "d", "hops"], "left")
