"""Connected components by minimum-label propagation with pointer jumping."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hopline.session import cut, discard


def connected_labels(links: DataFrame) -> DataFrame:
    """(cls, comp): for every end of ``links(a, b)`` the smallest end that it reaches.

    Each round lets every node take the least label among its neighbours' and then its label's own label, so paths
    of labels halve. Rounds go on until no label moves. The state is written to shared storage between rounds, the one
    before is deleted, and nothing but a flag reaches the driver. What each node hears from its neighbours is reduced by
    task first, so the hub of a star hears one label a task.
    """
    arcs = cut(links.select("a", "b").union(links.select("b", "a")).where("a <> b").distinct(), "arcs")
    state = cut(arcs.groupBy(F.col("a").alias("cls")).agg(F.least(F.min("b"), F.first("a")).alias("comp")), "labels")
    while True:
        near = arcs.join(state.withColumnRenamed("cls", "b"), "b").groupBy("a").agg(F.min("comp").alias("near"))
        hop = state.join(near.withColumnRenamed("a", "cls"), "cls").select("cls", F.col("comp").alias("old"), F.least("comp", "near").alias("comp"))
        jump = state.select(F.col("cls").alias("comp"), F.col("comp").alias("up"))
        fresh = cut(hop.join(jump, "comp", "left").select("cls", "old", F.least("comp", F.coalesce("up", "comp")).alias("comp")), "labels")
        moved = not fresh.where("old <> comp").isEmpty()
        discard(state)
        state = fresh.select("cls", "comp")
        if not moved:
            discard(arcs)
            return state
