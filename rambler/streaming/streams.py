"""Graphs and walk queries that arrive as streams. Every job runs to the end of what is there (availableNow) and stores its result."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from rambler.functions.store import shared_dir
from rambler.operators.graph import WalkGraph
from rambler.operators.walk import WalkConfig, random_walks
from rambler.plans.program import WeightProgram

LATE = "2 hours"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream, its time as event time with a watermark: rows later than that are dropped."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    # A pattern, as a stream takes a folder or a pattern, not a single file.
    return spark.readStream.schema(schema).parquet(f"{sf_dir}/events.parque[t]").withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", LATE)


def run(stream: DataFrame, mode: str, sink: Callable[[DataFrame, int, str], None] | None = None, schema: StructType | str | None = None) -> DataFrame:
    """Runs a stream to its end. complete: the last state replaces the ones before; append: batches are added, each in a folder of its own, so a repeated batch does no harm."""
    spark, base = stream.sparkSession, f"{shared_dir(stream.sparkSession)}/{uuid.uuid4().hex}"

    def store(batch: DataFrame, number: int) -> None:
        if sink:
            sink(batch, number, base)
        else:
            batch.write.mode("overwrite").parquet(f"{base}/out" if mode == "complete" else f"{base}/out/batch={number}")

    stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/log").trigger(availableNow=True).foreachBatch(store).start().awaitTermination()
    return read_batches(spark, f"{base}/out", schema or stream.schema)


def read_batches(spark: SparkSession, path: str, schema: StructType | str) -> DataFrame:
    """What a stream has stored; no rows if it had no batch."""
    there = spark._jvm.org.apache.hadoop.fs.Path(path)
    if not there.getFileSystem(spark._jsc.hadoopConfiguration()).exists(there):
        return spark.createDataFrame([], schema)
    return spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(path)  # the folders of batches are no column


def stream_node_stats(events: DataFrame, window: str = "1 day") -> DataFrame:
    """Tumbling count, sum and maximum of each user's new edges."""
    return events.groupBy(F.window("ts", window).alias("w"), "user_id").agg(F.count("*").alias("n"), F.sum("value").alias("total"), F.max("value").alias("top"))


def stream_sliding_edges(events: DataFrame) -> DataFrame:
    return events.groupBy(F.window("ts", "6 hours", "1 hour").alias("w")).agg(F.count("*").alias("n"))


def stream_session_users(events: DataFrame) -> DataFrame:
    return events.groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("n"))


def stream_dedup_edges(events: DataFrame) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(["event_id"])


def stream_interval_join(firsts: DataFrame, thens: DataFrame, within: str = "1 hour") -> DataFrame:
    """Edges (a, b) from an event of `firsts` to one of the same user in `thens`, after it but `within` at most. Both watermarks bound the state: rows too old to meet anything leave it."""
    a = firsts.select(F.col("user_id").alias("a_user"), F.col("event_id").alias("a"), F.col("ts").alias("a_ts"))
    b = thens.select(F.col("user_id").alias("b_user"), F.col("event_id").alias("b"), F.col("ts").alias("b_ts"))
    return a.join(b, F.expr(f"a_user = b_user and b_ts > a_ts and b_ts <= a_ts + interval {within}")).select("a", "b")


def transition_edges(events: DataFrame) -> DataFrame:
    """(event_id, user_id, came_from, event_type) for each event that follows another of its user, in the order of (ts, event_id).

    A batch is put behind the last event of each user so far (a row for each user, stored by batch, so a repeated batch does no harm);
    the window sorts and spills. Events not after their user's last one of earlier batches come too late and are left out."""
    spark, columns = events.sparkSession, ["user_id", "ts", "event_id", "event_type"]
    schema = "event_id long, user_id long, came_from string, event_type string"
    last_schema = events.select(*columns).schema

    def sink(batch: DataFrame, number: int, base: str) -> None:
        known = spark.read.schema(last_schema).parquet(f"{base}/last/{number - 1}") if number else spark.createDataFrame([], last_schema)
        fresh = batch.select(*columns).join(known.select("user_id", F.struct("ts", "event_id").alias("_seen")), "user_id", "left")
        fresh = fresh.where("_seen is null or struct(ts, event_id) > _seen").drop("_seen")
        rows = fresh.withColumn("new", F.lit(True)).unionByName(known.withColumn("new", F.lit(False)))
        line = Window.partitionBy("user_id").orderBy("ts", "event_id")
        rows.withColumn("came_from", F.lag("event_type").over(line)).where("new and came_from is not null").select("event_id", "user_id", "came_from", "event_type").write.mode("overwrite").parquet(f"{base}/out/batch={number}")
        newest = fresh.unionByName(known).groupBy("user_id").agg(F.max(F.struct("ts", "event_id", "event_type")).alias("m"))
        newest.select("user_id", "m.ts", "m.event_id", "m.event_type").write.mode("overwrite").parquet(f"{base}/last/{number}")

    return run(events, "append", sink, schema)


def serve_walk_queries(queries: DataFrame, graph: WalkGraph, program: WeightProgram, config: WalkConfig) -> DataFrame:
    """Starts (walk_id, start) arrive as rows; each batch walks the graph. A walk's draws depend on its id, so a replayed batch gives the same walks."""

    def sink(batch: DataFrame, number: int, base: str) -> None:
        random_walks(graph, program, batch, "keys", config).write.mode("overwrite").parquet(f"{base}/out/batch={number}")

    return run(queries, "append", sink, "walk_id long, step int, node long")
