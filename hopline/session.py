"""Session helpers: durable scratch space, lineage cuts, settings that are safe to change."""

from __future__ import annotations

import tempfile
import uuid
from contextlib import contextmanager

from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession

import hopline

# Worker functions travel with the task, so executors need no copy of the package.
cloudpickle.register_pickle_by_value(hopline)


def local_session(cpus: int | str = "*", memory: str = "20g", **conf: str) -> SparkSession:
    """A local session for tests and benchmarks; queries never depend on these settings."""
    settings = {
        "spark.sql.shuffle.partitions": "8",
        "spark.driver.memory": memory,
        "spark.sql.session.timeZone": "UTC",
        "spark.ui.enabled": "false",
        "spark.ui.showConsoleProgress": "false",
    } | conf
    spark = SparkSession.builder.master(f"local[{cpus}]").appName("hopline").config(map=settings).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def shared_dir(spark: SparkSession) -> str:
    """Folder that the driver and all executors see.

    The session's ``spark.checkpoint.dir`` comes first, then a checkpoint folder that was set by hand. Only a
    local master falls back to a temporary folder; on a cluster, whose machines share no such folder, this fails.
    """
    context = spark.sparkContext
    root = context.getConf().get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not root:
        local = context.master.startswith("local") and not context.master.startswith("local-cluster")
        if not local:
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = tempfile.mkdtemp(prefix="hopline-")
        context.setCheckpointDir(root)
    return root


def scratch_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"


def cut(df: DataFrame, tag: str = "step") -> DataFrame:
    """Write ``df`` to shared storage and read it back: ends the lineage and survives lost executors."""
    spark, path = df.sparkSession, scratch_path(df.sparkSession, tag)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Delete the files behind a table made by :func:`cut` once nothing reads it any more."""
    spark = df.sparkSession
    for name in df.inputFiles()[:1]:
        folder = spark._jvm.org.apache.hadoop.fs.Path(name).getParent()
        folder.getFileSystem(spark._jsc.hadoopConfiguration()).delete(folder, True)


def drop_checkpoint(df: DataFrame) -> None:
    """Delete the files of a frame made by ``checkpoint()`` once a later checkpoint has taken its place."""
    spark = df.sparkSession
    file = df._jdf.queryExecution().analyzed().rdd().getCheckpointFile()
    if file.isDefined():
        path = spark._jvm.org.apache.hadoop.fs.Path(file.get())
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def small_enough(df: DataFrame, max_rows: int) -> bool:
    """Whether ``df`` has at most ``max_rows`` rows; counts no more than one row beyond that and moves no columns."""
    return df.select().limit(max_rows + 1).count() <= max_rows


@contextmanager
def setting(spark: SparkSession, **conf: str):
    """Change runtime settings (dots written as double underscores) and put them back."""
    names = {k.replace("__", "."): v for k, v in conf.items()}
    before = {k: spark.conf.get(k, None) for k in names}
    try:
        for k, v in names.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


__all__ = ["cut", "discard", "drop_checkpoint", "local_session", "scratch_path", "setting", "shared_dir", "small_enough"]
