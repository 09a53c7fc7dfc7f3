"""Event streams from files: windows, joins, first-seen links, running degrees. ``drain`` runs a stream over what is there."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..settle import shared_dir

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
LATENESS = "1 hour"


def source(spark: SparkSession, sf_dir: str, lateness: str = LATENESS, files: int = 100) -> DataFrame:
    """events.parquet as a stream with a watermark; ts is taken as UTC."""
    path = f"{sf_dir}/events.parquet"
    stream = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files).parquet(path if not path.endswith(".parquet") else f"{sf_dir}/event[s].parquet")
    return stream.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness)


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run over all input that is there, into files of the shared folder (append), or a table in memory (complete, update)."""
    spark, at = stream.sparkSession, f"{shared_dir(stream.sparkSession)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        stream.writeStream.format("parquet").option("path", f"{at}/out").option("checkpointLocation", f"{at}/state").outputMode("append").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{at}/out")
    name = f"drained_{uuid.uuid4().hex}"
    stream.writeStream.format("memory").queryName(name).option("checkpointLocation", f"{at}/state").outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.table(name)


def drain_sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Session windows, as ``windowed`` has them, over all input that is there, read from the state that the stream leaves in the shared folder.

    In complete mode the state holds every session, late rows included, so it is the result; a table in memory would
    bring as many rows to the driver as there are sessions.
    """
    spark, at = stream.sparkSession, f"{shared_dir(stream.sparkSession)}/stream-{uuid.uuid4().hex}"
    windowed(stream, "session", gap=gap).writeStream.format("noop").option("checkpointLocation", f"{at}/state").outputMode("complete").trigger(availableNow=True).start().awaitTermination()
    if not _batches(spark, f"{at}/state"):
        return spark.createDataFrame([], "start timestamp, end timestamp, user_id long, n long")
    w = F.col("value.session_window")
    return spark.read.format("statestore").load(f"{at}/state").select(w["start"].alias("start"), w["end"].alias("end"), F.col("value.user_id").alias("user_id"), F.col("value.count").alias("n"))


def _batches(spark: SparkSession, state: str) -> int:
    """Batches that a stream has ended."""
    at = spark._jvm.org.apache.hadoop.fs.Path(f"{state}/commits")
    fs = at.getFileSystem(spark._jsc.hadoopConfiguration())
    return len([f for f in fs.listStatus(at) if f.getPath().getName().isdigit()]) if fs.exists(at) else 0


def windowed(stream: DataFrame, kind: str = "tumbling", length: str = "1 day", slide: str = "6 hours", gap: str = "30 minutes") -> DataFrame:
    """(start, end, event_type, n): counts by tumbling or sliding window; by user for session windows."""
    if kind == "session":
        return stream.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n")
    w = F.window("ts", length) if kind == "tumbling" else F.window("ts", length, slide)
    return stream.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "event_type", "n")


def first_seen_links(stream: DataFrame) -> DataFrame:
    """(user_id, event_type) once each while the watermark holds them."""
    return stream.dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type", "ts")


def join_static(stream: DataFrame, rules: DataFrame) -> DataFrame:
    """Events as facts, by static rules (event_type, p, concept)."""
    return stream.join(F.broadcast(rules), "event_type").select("event_id", "p", "concept", "user_id")


def join_interval(stream: DataFrame, within: str = "1 hour") -> DataFrame:
    """(user_id, error_id, purchase_id): purchases within an hour after an error of the same user."""
    a = stream.where("event_type = 'error'").select("user_id", F.col("event_id").alias("error_id"), F.col("ts").alias("t1"))
    b = stream.where("event_type = 'purchase'").select(F.col("user_id").alias("u2"), F.col("event_id").alias("purchase_id"), F.col("ts").alias("t2"))
    return a.join(b, F.expr(f"user_id = u2 AND t2 >= t1 AND t2 <= t1 + INTERVAL {within}")).select("user_id", "error_id", "purchase_id")


def running_degree(stream: DataFrame) -> DataFrame:
    """(event_type, degree): distinct users of each kind so far; the state holds the users seen."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seen = set(state.get[0]) if state.exists else set()
        for b in batches:
            seen |= set(b["user_id"].dropna().astype(int).tolist())
        state.update((sorted(seen),))
        yield pd.DataFrame({"event_type": [key[0]], "degree": [len(seen)]})

    return stream.groupBy("event_type").applyInPandasWithState(step, "event_type string, degree long", "users array<long>", "update", GroupStateTimeout.NoTimeout)


def late_policy(spark: SparkSession, rows: DataFrame, lateness: str = LATENESS) -> DataFrame:
    """(policy, n) of (batch, ts) rows written as files in batch order: windows of a day with late rows dropped, and all rows kept."""
    at = f"{shared_dir(spark)}/late-{uuid.uuid4().hex}"
    for (b,) in sorted(rows.select("batch").distinct().collect()):
        rows.where(F.col("batch") == b).select("ts").coalesce(1).write.mode("append").parquet(f"{at}/in")
    stream = spark.readStream.schema("ts timestamp").option("maxFilesPerTrigger", 1).parquet(f"{at}/in").withWatermark("ts", lateness)
    kept = drain(stream.groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n")).select(F.col("window.start").alias("at"), "n"), "update")
    kept = kept.groupBy("at").agg(F.max("n").alias("n"))  # a window that two batches update is told twice, its last count is the largest
    return kept.agg(F.lit("dropped").alias("policy"), F.sum("n").alias("n")).unionByName(rows.agg(F.lit("kept").alias("policy"), F.count("*").alias("n")))
