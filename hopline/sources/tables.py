"""Reading and writing tables; the stored form of a graph with its hopset."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, fmt: str, path: str, schema: str | None = None, **options) -> DataFrame:
    """Parquet, CSV, JSON, ORC or text, with a stated schema."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write(df: DataFrame, fmt: str, path: str, mode: str = "overwrite", partition_by: list[str] | None = None, **options) -> None:
    writer = df.write.format(fmt).mode(mode).options(**options)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def register(spark: SparkSession, sf_dir: str, names: list[str] = TABLES) -> None:
    """The tables as temporary views, for SQL."""
    for name in names:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def save_hopset(hopset: DataFrame, path: str, mode: str = "overwrite") -> None:
    """One directory for each scale, so that scales can be added and read on their own."""
    hopset.repartition("scale", "u").write.mode(mode).partitionBy("scale").parquet(path)


def load_hopset(spark: SparkSession, path: str, scales: list[int] | None = None) -> DataFrame:
    df = spark.read.parquet(path)
    return df.where(df.scale.isin(scales)) if scales is not None else df


def save_bucketed(df: DataFrame, table: str, key: str = "u", buckets: int = 8) -> None:
    """A catalogue table bucketed and sorted by ``key``: later joins on it need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def load_bucketed(spark: SparkSession, table: str) -> DataFrame:
    return spark.table(table)
