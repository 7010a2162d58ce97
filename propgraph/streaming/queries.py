"""Streams of events as edges: windows, late data, duplicates, running degrees and graph upkeep."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType

from ..operators.algorithms import components
from ..operators.graph import PropertyGraph
from ..sources.shared import shared_path


def event_stream(spark: SparkSession, d: str, per_trigger: int = 1) -> DataFrame:
    """events replayed from their files, with a zoned event time `at`."""
    path = f"{d}/events.parquet"
    schema = spark.read.parquet(path).schema
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(f"{d}/events.parquet*")
    return rows.withColumn("at", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a stream over all that is there and returns its result, a table in shared storage.

    Each batch writes a folder of its own, so that a repeated batch leaves no row twice; of a complete
    result the last batch's folder is the whole."""
    spark = stream.sparkSession
    base = shared_path(spark, "stream")
    stream.sparkSession.createDataFrame([], stream.schema).write.parquet(f"{base}/rows/batch=-1")

    def keep(rows: DataFrame, batch: int) -> None:
        rows.write.mode("overwrite").parquet(f"{base}/rows/batch={batch}")

    q = stream.writeStream.foreachBatch(keep).outputMode(mode).trigger(availableNow=True)
    q.option("checkpointLocation", f"{base}/progress").start().awaitTermination()
    rows = spark.read.schema(StructType([*stream.schema.fields, StructField("batch", IntegerType())])).option("basePath", f"{base}/rows").parquet(f"{base}/rows")
    if mode == "complete":
        rows = rows.join(F.broadcast(rows.agg(F.max("batch").alias("batch"))), "batch")
    return rows.drop("batch")


def late_counts(stream: DataFrame, delay: str = "10 minutes", size: str = "1 hour") -> DataFrame:
    """begin, n: closed windows only, each given once; events later than the watermark allows aren't counted."""
    rows = stream.withWatermark("at", delay).groupBy(F.window("at", size).alias("w")).agg(F.count("*").alias("n"))
    return drained(rows, "append").select(F.col("w.start").cast("timestamp_ntz").alias("begin"), "n")


def _windowed(window) -> object:
    def run(spark: SparkSession, d: str) -> DataFrame:
        rows = event_stream(spark, d).withWatermark("at", "10 minutes").groupBy(window(F.col("at")).alias("w"), "event_type").agg(F.count("*").alias("n"))
        return drained(rows).select(F.col("w.start").cast("timestamp_ntz").alias("begin"), "event_type", "n")

    return run


def sessions(spark: SparkSession, d: str) -> DataFrame:
    rows = event_stream(spark, d).withWatermark("at", "10 minutes").groupBy(F.session_window("at", "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("n"))
    out = drained(rows).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("begin"), "n")
    return out


def dedup(spark: SparkSession, d: str) -> DataFrame:
    rows = event_stream(spark, d).withWatermark("at", "31 days").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")
    return drained(rows, "append")


def degree(spark: SparkSession, d: str) -> DataFrame:
    return drained(event_stream(spark, d).groupBy(F.col("user_id").alias("id")).agg(F.count("*").alias("degree")))


def upkeep(batches: list[DataFrame], labels: DataFrame | None = None) -> DataFrame:
    """Components after edge batches: each is taken in from the former labels, which stay valid as edges only come."""
    for new in batches:
        e = new.select("src", "dst")
        if labels is not None:
            e = e.unionByName(labels.select(F.col("id").alias("src"), F.col("component").alias("dst")))
        labels = components(PropertyGraph.from_edges(e))
    return labels


QUERIES = {
    "stream_tumbling": _windowed(lambda c: F.window(c, "1 hour")),
    "stream_sliding": _windowed(lambda c: F.window(c, "1 hour", "30 minutes")),
    "stream_session": sessions,
    "stream_dedup": dedup,
    "stream_degree": degree,
}
_N = "SELECT begin, event_type, count(*) AS n FROM ({}) q GROUP BY begin, event_type"
ORACLES = {
    "stream_tumbling": _N.format("SELECT date_trunc('hour', ts) AS begin, event_type FROM events"),
    "stream_sliding": _N.format("SELECT time_bucket(INTERVAL '30 minutes', ts) - o AS begin, event_type FROM events, (VALUES (INTERVAL '0 minutes'), (INTERVAL '30 minutes')) t(o)"),
    "stream_session": "SELECT user_id, min(ts) AS begin, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL '30 minutes' THEN 0 ELSE 1 END AS fresh FROM events) a) b GROUP BY user_id, s",
    "stream_dedup": "SELECT DISTINCT user_id, event_type FROM events",
    "stream_degree": "SELECT user_id AS id, count(*) AS degree FROM events GROUP BY user_id",
}
