"""The weighted undirected graph as two tables, and preparations on it."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property
from math import ceil

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopline.operators.components import connected_labels
from hopline.session import cut

EDGE_SCHEMA = "u long, v long, w long"
DIST_SCHEMA = "src long, v long, d long, hops int"
MEMBER_SCHEMA = "scale int, rep int, center long, v long, dhat long, dtree long"
HOPSET_SCHEMA = "u long, v long, w long, scale int, kind string, rep int, center long"
ROWS_PER_PARTITION, MOST_PER_PARTITION = 200_000, 2_000_000


@dataclass
class Graph:
    """``nodes(id)`` and canonical ``edges(u < v, w >= 1)``, one row for each pair."""

    nodes: DataFrame
    edges: DataFrame
    in_task: bool = False
    least_partitions: int = 1
    _held: dict = field(default_factory=dict, repr=False)

    @property
    def spark(self):
        return self.edges.sparkSession

    @cached_property
    def n(self) -> int:
        return self.nodes.count()

    @cached_property
    def m(self) -> int:
        return self.edges.count()

    @cached_property
    def partitions(self) -> int:
        """As many as the arcs fill."""
        return self.partitions_for(0)

    def partitions_for(self, rows: int) -> int:
        """As many as arcs and a state of ``rows`` rows fill: at most what the session asks for, but more where that many
        would hold more than MOST_PER_PARTITION rows each."""
        rows = max(rows, 2 * self.m)
        asked = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        return max(self.least_partitions, min(asked, ceil(rows / ROWS_PER_PARTITION)), ceil(rows / MOST_PER_PARTITION))

    @property
    def arcs(self) -> DataFrame:
        return self.arcs_in(self.partitions)

    def arcs_in(self, partitions: int) -> DataFrame:
        """Both directions, hash-partitioned by ``u`` and kept, so that no later round moves them again."""
        if partitions not in self._held:
            both = self.edges.select("u", "v", "w").unionByName(self.edges.select(F.col("v").alias("u"), F.col("u").alias("v"), "w"))
            self._held[partitions] = both.repartition(partitions, "u").persist(StorageLevel.MEMORY_AND_DISK)
        return self._held[partitions]

    def compact(self) -> Graph:
        """The same graph, searched in one task wherever arcs and state fit one."""
        out = Graph(self.nodes, self.edges, True)
        out.__dict__ |= {k: self.__dict__[k] for k in ("n", "m") if k in self.__dict__}
        return out

    def release(self) -> None:
        while self._held:
            self._held.popitem()[1].unpersist()


def validate(edges: DataFrame) -> None:
    """Raises on null ends or weights and on weights below one."""
    bad = edges.where("u is null or v is null or w is null or w < 1").limit(1).collect()
    if bad:
        raise ValueError(f"not an edge with a positive whole weight: {bad[0]}")


def from_edges(df: DataFrame, u: str = "u", v: str = "v", w: str = "w", nodes: DataFrame | None = None, keep: bool = True) -> Graph:
    """Canonical form: no loops, smaller end first, least weight among parallels. ``nodes`` adds isolated ones."""
    row = df.select(F.col(u).cast("long").alias("u"), F.col(v).cast("long").alias("v"), F.col(w).cast("long").alias("w"))
    validate(row)
    edges = row.where("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), "w").groupBy("u", "v").agg(F.min("w").alias("w"))
    edges = cut(edges, "edges") if keep else edges
    ends = row.select(F.explode(F.array("u", "v")).alias("id"))
    every = ends.unionByName(nodes.select(F.col("id").cast("long").alias("id"))) if nodes is not None else ends
    return Graph(cut(every.distinct(), "nodes") if keep else every.distinct(), edges)


def normalize_weights(graph: Graph) -> tuple[Graph, int]:
    """Divides by the least weight, rounding up; returns the factor. Lengths in the result times the factor are at
    least the true ones and exceed them by less than the factor for each hop."""
    least = graph.edges.agg(F.min("w")).first()[0] or 1
    return Graph(graph.nodes, graph.edges.withColumn("w", F.ceil(F.col("w") / F.lit(least)).cast("long"))), least


def unweighted(graph: Graph) -> Graph:
    return Graph(graph.nodes, graph.edges.withColumn("w", F.lit(1).cast("long")), graph.in_task)


def aspect_ratio(graph: Graph) -> DataFrame:
    """One row: least and greatest weight and their ratio."""
    return graph.edges.agg(F.min("w").alias("min_w"), F.max("w").alias("max_w")).withColumn("aspect", F.round(F.col("max_w") / F.col("min_w"), 6))


def check_polynomial(graph: Graph, c: float) -> DataFrame:
    """Whether every weight is at most n^c."""
    return graph.edges.agg(F.max("w").alias("max_w")).select("max_w", (F.col("max_w") <= F.lit(float(graph.n) ** c)).alias("polynomial"))


def reduce_aspect(graph: Graph, eps: float, scales: list[int]) -> DataFrame:
    """For each R: edges longer than 2R dropped, edges shorter than eps R / n contracted to their component.

    Rows (scale, u, v, w) over component representatives; weights inside one scale then differ by at most 2n / eps.
    """
    parts = []
    for big_r in scales:
        short = graph.edges.where(F.col("w") * graph.n < F.lit(eps * big_r))
        label = connected_labels(short.select(F.col("u").alias("a"), F.col("v").alias("b")))
        row = graph.edges.where(F.col("w") <= 2 * big_r)
        for end in ("u", "v"):
            row = row.join(label.select(F.col("cls").alias(end), F.col("comp").alias(f"c{end}")), end, "left").withColumn(end, F.coalesce(f"c{end}", end)).drop(f"c{end}")
        row = row.where("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), "w")
        parts.append(row.groupBy("u", "v").agg(F.min("w").alias("w")).select(F.lit(big_r).cast("long").alias("scale"), "u", "v", "w"))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def components(graph: Graph) -> DataFrame:
    """(id, comp): the smallest node of each node's component."""
    from hopline.plans import one_task

    if graph.in_task and one_task.deals(2 * graph.m):
        label = one_task.labels(graph.edges)
    else:
        label = connected_labels(graph.edges.select(F.col("u").alias("a"), F.col("v").alias("b"))).withColumnRenamed("cls", "id")
    return graph.nodes.join(label, "id", "left").select("id", F.coalesce("comp", "id").alias("comp"))


def augment(graph: Graph, hopset: DataFrame) -> Graph:
    """The graph with the shortcut edges added; the least weight of a pair wins."""
    both = graph.edges.select("u", "v", "w").unionByName(hopset.select("u", "v", "w")).groupBy("u", "v").agg(F.min("w").alias("w"))
    out = Graph(graph.nodes, cut(both, "union"), graph.in_task)
    out.__dict__["n"] = graph.n  # the nodes are the same
    return out


def induced(graph: Graph, members: DataFrame) -> DataFrame:
    """(rep, center, u, v, w): edges with both ends in one cluster."""
    left, right = (members.select("rep", "center", F.col("v").alias(end)) for end in ("u", "v"))
    return graph.edges.select("u", "v", "w").join(left, "u").join(right, ["rep", "center", "v"]).select("rep", "center", "u", "v", "w")


def stats(graph: Graph) -> DataFrame:
    """One row: n, m, sum and maximum of degrees, weights, and m against n^1.5."""
    degree = graph.edges.select(F.explode(F.array("u", "v")).alias("id")).groupBy("id").agg(F.count("*").alias("degree"))
    d = degree.agg(F.sum("degree").alias("degree_sum"), F.max("degree").alias("max_degree"))
    e = graph.edges.agg(F.count("*").alias("m"), F.min("w").alias("min_w"), F.max("w").alias("max_w"))
    return graph.nodes.agg(F.count("*").alias("n")).join(e).join(d).withColumn("dense", F.col("m") > F.pow(F.col("n").cast("double"), F.lit(1.5)))
