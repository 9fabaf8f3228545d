"""Randomness as a function of (seed, tag, repetition, id), equal in every engine and on every partitioning."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

FRACTION = 20  # bits after the point of a fixed-point radius


def u32(seed: int, tag: str, rep: Column, node: Column) -> Column:
    """32 uniform bits: the first eight hex digits of an MD5."""
    text = F.concat_ws(":", F.lit(str(seed)), F.lit(tag), rep.cast("string"), node.cast("string"))
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def uniform(seed: int, tag: str, rep: Column, node: Column) -> Column:
    return (u32(seed, tag, rep, node) + F.lit(0.5)) / F.lit(float(2**32))


def chosen(probability: float | Column, seed: int, tag: str, rep: Column, node: Column) -> Column:
    """True with the given probability, as an integer comparison."""
    p = probability if isinstance(probability, Column) else F.lit(float(probability))
    return u32(seed, tag, rep, node) < F.floor(p * F.lit(float(2**32)))


def shifts(nodes: DataFrame, alpha: float, seed: int, reps: int) -> DataFrame:
    """(rep, id, shift_fp): exponential radii of rate ``alpha`` in fixed point, for every node and repetition."""
    row = nodes.select("id").withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))))
    radius = -F.ln(uniform(seed, "shift", F.col("rep"), F.col("id"))) / F.lit(float(alpha)) * F.lit(float(2**FRACTION))
    return row.select("rep", "id", F.round(radius).cast("long").alias("shift_fp"))


def shift_sql(alpha: float, seed: int, rep: str = "rep", node: str = "id") -> str:
    """The same radius for DuckDB."""
    bits = f"('0x' || substr(md5('{seed}:shift:' || {rep} || ':' || {node}), 1, 8))::BIGINT"
    return f"CAST(round(-ln(({bits} + 0.5::DOUBLE) / 4294967296::DOUBLE) / {float(alpha)}::DOUBLE * 1048576::DOUBLE) AS BIGINT)"
