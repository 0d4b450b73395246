"""Contiguous shards of near-equal bytes from global prefix sums of partition totals. DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import pick, written


def shard_by_bytes(docs: DataFrame, shards: int = 8) -> DataFrame:
    """(doc_id, size, text_crc32, shard, slot) of each row, in doc_id order.

    Rows (without their texts) are range-partitioned by doc_id and settled; each partition's byte and row totals are summed over
    the partitions before it (as many rows as there are partitions), so a row's global start is that offset plus the running sum
    in its own partition. A row goes to the shard in whose equal share of all bytes it starts; slot counts from 0 in the shard.

    Null text has size 1 and checksum 0. A null doc_id sorts first. Rows that share a doc_id stay neighbours in the order of the
    scan, also across a partition's end, so one hot id is split. An empty table gives no rows; further columns are ignored.
    """
    rows = pick(docs, "doc_id", "text").select("doc_id", (F.coalesce(F.octet_length("text"), F.lit(0)) + 1).cast("long").alias("size"), F.crc32(F.coalesce("text", F.lit("")).cast("binary")).alias("text_crc32"), F.monotonically_increasing_id().alias("row"))
    dealt = written(rows.repartitionByRange("doc_id", "row").withColumn("part", F.spark_partition_id()))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    totals = (
        dealt.groupBy("part").agg(F.sum("size").alias("bytes"), F.count("*").alias("n"))
        .select("part", F.coalesce(F.sum("bytes").over(before), F.lit(0)).alias("bytes_before"), F.coalesce(F.sum("n").over(before), F.lit(0)).alias("rows_before"), F.sum("bytes").over(Window.partitionBy()).alias("whole"))
    )
    inside = Window.partitionBy("part").orderBy("doc_id", "row")
    placed = dealt.join(F.broadcast(totals), "part").select(  # a row for each shuffle partition
        "doc_id", "size", "text_crc32", "whole",
        (F.col("bytes_before") + F.sum("size").over(inside) - F.col("size")).alias("start"),
        (F.col("rows_before") + F.row_number().over(inside) - 1).alias("rank"),
    ).select("doc_id", "size", "text_crc32", "rank", F.expr(f"cast(start * {shards} div whole as int)").alias("shard"))
    firsts = placed.groupBy("shard").agg(F.min("rank").alias("first"))
    return placed.join(F.broadcast(firsts), "shard").select("doc_id", "size", "text_crc32", "shard", (F.col("rank") - F.col("first")).alias("slot"))


def write_shards(docs: DataFrame, path: str, shards: int = 8) -> None:
    """Parquet folders shard=0 ... under `path`, rows joined to their shards by doc_id (which has to be unique here)."""
    placed = shard_by_bytes(docs, shards).select("doc_id", "shard", "slot")
    pick(docs, "doc_id", "text").join(placed, "doc_id").repartition("shard", (F.col("slot") / 100_000).cast("int")).sortWithinPartitions("slot").write.partitionBy("shard").parquet(path)
