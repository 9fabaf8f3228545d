"""Events as a stream of edges, windowed counts, late rows, joins with static tables, and batch rebuilds.

Streams read the event table's folder as files and run with ``availableNow``, so a query ends with the whole table in
its sink; the same plans run unbounded with any other trigger. Sinks are Parquet in shared storage.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from hopline.model import Graph, components
from hopline.session import scratch_path
from hopline.sources.tables import load

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def event_stream(spark: SparkSession, sf_dir: str, rows_per_file: int | None = None) -> DataFrame:
    """The event table as an unbounded frame, its time column as a UTC timestamp."""
    static = load(spark, sf_dir, "events")
    path = scratch_path(spark, "feed")
    parts = static.select("event_id", "user_id", "event_type", "value", F.col("ts").cast("timestamp").alias("ts"))
    (parts.repartitionByRange(4, "ts") if rows_per_file is None else parts).write.parquet(path)
    return spark.readStream.schema(parts.schema).option("maxFilesPerTrigger", 4).parquet(path)


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream to the end of its input and returns what its sink holds."""
    spark, out = stream.sparkSession, scratch_path(stream.sparkSession, "sink")
    state = scratch_path(spark, "state")
    if mode == "complete":
        last = {}

        def keep(df: DataFrame, epoch: int) -> None:
            df.write.mode("overwrite").parquet(f"{out}/{epoch}")
            last["epoch"] = epoch

        stream.writeStream.outputMode("complete").foreachBatch(keep).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{out}/{last['epoch']}")
    stream.writeStream.format("parquet").outputMode(mode).option("checkpointLocation", state).option("path", out).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def _micros(c: str):
    return F.unix_micros(F.col(c))


def tumbling(spark: SparkSession, d: str) -> DataFrame:
    s = event_stream(spark, d).groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return drain(s, "complete").select(_micros("w.start").alias("start"), "event_type", "n")


def sliding(spark: SparkSession, d: str) -> DataFrame:
    s = event_stream(spark, d).groupBy(F.window("ts", "1 hour", "30 minutes").alias("w")).agg(F.count("*").alias("n"))
    return drain(s, "complete").select(_micros("w.start").alias("start"), "n")


def session(spark: SparkSession, d: str) -> DataFrame:
    s = event_stream(spark, d).groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return drain(s, "complete").select("user_id", _micros("w.start").alias("start"), "n")


def newest_first(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream of three micro-batches: the last quarter of the time span, the third, the first half. A
    watermark binds from the second batch after the one that moved it, so the first half is late."""
    events = load(spark, sf_dir, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"))
    lo, hi = events.agg(F.min(_micros("ts")), F.max(_micros("ts"))).first()
    path, middle, last = scratch_path(spark, "turns"), (lo + hi) // 2, (lo + 3 * hi) // 4
    for begin, end in ((last, hi + 1), (middle, last), (lo, middle)):
        events.where((_micros("ts") >= begin) & (_micros("ts") < end)).coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path)


def late_rows(spark: SparkSession, d: str) -> DataFrame:
    """Events by hour under a watermark of one hour: the late half comes after the watermark has passed and is dropped."""
    s = newest_first(spark, d).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    return drain(s).select(_micros("w.start").alias("start"), "n")


def dedup(spark: SparkSession, d: str) -> DataFrame:
    """Every event twice, in time order: repeats within the hour go."""
    s = event_stream(spark, d)
    return drain(s.unionByName(s).withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"))


def stream_join(spark: SparkSession, d: str) -> DataFrame:
    """Two streams: purchases and the clicks of the same user in the ten minutes before."""
    e = event_stream(spark, d)
    a = e.where("event_type = 'click'").select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("ts").alias("ta")).withWatermark("ta", "1 hour")
    b = e.where("event_type = 'purchase'").select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("ts").alias("tb")).withWatermark("tb", "1 hour")
    return drain(a.join(b, F.expr("ua = ub AND tb >= ta AND tb <= ta + INTERVAL 10 MINUTES")).select("a", "b"))


def rebuild(spark: SparkSession, d: str) -> DataFrame:
    """Edges of the event stream inserted batch by batch into a stored graph; at the end its components."""
    from hopline.model import from_edges

    held, state = {}, scratch_path(spark, "state")
    none = spark.createDataFrame([], "u long, v long, w long")

    def insert(batch: DataFrame, epoch: int) -> None:
        before = held.get("graph") or from_edges(none)
        held["graph"], _ = maintain(before, none, batch)

    stream = edge_stream(event_stream(spark, d))
    stream.writeStream.foreachBatch(insert).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    return components(held["graph"])


def static_join(spark: SparkSession, d: str) -> DataFrame:
    users = load(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_nationkey")
    return drain(event_stream(spark, d).join(users, "user_id").select("event_id", "c_nationkey"))


def edge_stream(events: DataFrame) -> DataFrame:
    """(u, v, w): consecutive events of a user, weight 1 + seconds; the last event of a user is the state."""

    def link(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(batches)).sort_values(["t", "event_id"])
        last = state.get if state.exists else (None, None)
        out = []
        for r in rows.itertuples(index=False):
            if last[0] is not None:
                out.append((last[0], r.event_id, 1 + (r.t - last[1]) // 1_000_000))
            last = (int(r.event_id), int(r.t))
        state.update(last)
        yield pd.DataFrame(out, columns=["u", "v", "w"])

    return events.select("event_id", "user_id", F.unix_micros("ts").alias("t")).groupBy("user_id").applyInPandasWithState(link, "u long, v long, w long", "event_id long, t long", "append", GroupStateTimeout.NoTimeout)


def edges(spark: SparkSession, d: str) -> DataFrame:
    return drain(edge_stream(event_stream(spark, d)))


def maintain(graph: Graph, hopset: DataFrame, inserted: DataFrame, removed: DataFrame | None = None) -> tuple[Graph, DataFrame]:
    """The graph after a batch of changes, and the shortcut edges that stay sound.

    Insertions keep every shortcut an upper bound that still is a path's length; its stretch must be measured again.
    Removals can leave shortcuts too short, so those of every touched component go, for a rebuild there.
    """
    from hopline.model import from_edges

    kept = graph.edges if removed is None else graph.edges.join(removed.select("u", "v"), ["u", "v"], "left_anti")
    after = from_edges(kept.unionByName(inserted.select("u", "v", "w")), nodes=graph.nodes)
    if removed is None:
        return after, hopset
    label = components(graph)
    touched = removed.select(F.explode(F.array("u", "v")).alias("id")).join(label, "id").select("comp").distinct()
    stale = label.join(touched, "comp", "left_semi").select(F.col("id").alias("u"))
    return after, hopset.join(stale, "u", "left_anti")


QUERIES |= {"op_stream_tumbling": tumbling, "op_stream_sliding": sliding, "op_stream_session": session, "op_stream_late_rows": late_rows, "op_stream_dedup": dedup, "op_stream_stream_join": stream_join, "op_stream_rebuild": rebuild, "op_stream_static_join": static_join, "op_stream_edges": edges}
_HOUR = 3_600_000_000
ORACLES |= {
    "op_stream_tumbling": f"SELECT epoch_us(ts) // {_HOUR} * {_HOUR} AS start, event_type, count(*) AS n FROM events GROUP BY ALL",
    "op_stream_sliding": f"SELECT s AS start, count(*) AS n FROM (SELECT unnest([epoch_us(ts) // {_HOUR // 2} * {_HOUR // 2}, epoch_us(ts) // {_HOUR // 2} * {_HOUR // 2} - {_HOUR // 2}]) AS s FROM events) GROUP BY s",
    "op_stream_session": "SELECT user_id, min(t) AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS g FROM (SELECT user_id, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 1800000000 THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, g",
    "op_stream_late_rows": f"""WITH e AS (SELECT epoch_us(ts) AS t FROM events), x AS (SELECT (min(t) + max(t)) // 2 AS middle, max(t) - {_HOUR} AS mark FROM e)
SELECT t // {_HOUR} * {_HOUR} AS start, count(*) AS n FROM e, x WHERE t >= middle AND t // {_HOUR} * {_HOUR} + {_HOUR} <= mark GROUP BY 1""",
    "op_stream_stream_join": "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND epoch_us(b.ts) - epoch_us(a.ts) BETWEEN 0 AND 600000000",
    "op_stream_rebuild": "SELECT event_id AS id, min(event_id) OVER (PARTITION BY user_id) AS comp FROM (SELECT event_id, user_id, count(*) OVER (PARTITION BY user_id) AS k FROM events) WHERE k > 1",
    "op_stream_dedup": "SELECT DISTINCT event_id, user_id FROM events",
    "op_stream_static_join": "SELECT event_id, c_nationkey FROM events JOIN customer ON user_id = c_custkey",
    "op_stream_edges": "SELECT u, v, w FROM (SELECT event_id AS u, lead(event_id) OVER o AS v, 1 + (epoch_us(lead(ts) OVER o) - epoch_us(ts)) // 1000000 AS w FROM events WINDOW o AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE v IS NOT NULL",
}
