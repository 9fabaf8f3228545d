"""Ranks over a whole table without sending it to one task."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hopline.session import cut


def global_rank(df: DataFrame, order: list[str], name: str = "rank") -> DataFrame:
    """Adds the position (from 0) of each row in the order of ``order``: range partitions are ranked on their own and
    shifted by the sizes of those before them. The range of a row is fixed by writing it down once."""
    ranged = df.repartitionByRange(*order).withColumn("_range", F.spark_partition_id())
    held = cut(ranged, "ranges")
    sizes = held.groupBy("_range").agg(F.count("*").alias("_n"))
    before = F.sum("_n").over(Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1))
    offsets = sizes.select("_range", F.coalesce(before, F.lit(0)).alias("_offset"))  # one row for each range
    inner = F.row_number().over(Window.partitionBy("_range").orderBy(*order)) - 1
    return held.join(F.broadcast(offsets), "_range").withColumn(name, (F.col("_offset") + inner).cast("long")).drop("_range", "_offset")
