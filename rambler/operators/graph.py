"""Graphs as tables: the indexed edge list, its statistics, and the chunked adjacency."""

from __future__ import annotations

import uuid
from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rambler.functions.store import settle, shared_dir

CHUNK = 4096
#: About so many edges meet in one bucket of packed lists; a node's list is in one.
BUCKET_EDGES = 250_000
#: Edges of a row of packed lists at most.
PACKED_EDGES = 4_000_000
#: Columns of packed lists and the types of their bytes; `nodes` has a node for each stretch of its edges in the row, `deg` the stretch's length.
PACKED = {"nodes": np.int64, "deg": np.int64, "dst": np.int64, "h": np.float64, "label": np.int32}


class InvalidGraph(ValueError):
    pass


@dataclass(frozen=True)
class WalkGraph:
    """edges: (src, idx, dst, h, label), idx being the edge's 0-based place in its source's list by (dst, label)."""

    edges: DataFrame
    kept: bool = False
    counted: bool = False  # steps shall tell how many candidates a plain sampler reads
    rows: DataFrame | None = None  # (src, dst, h, label) that merge to the edges by the sums of h

    @staticmethod
    def from_edges(df: DataFrame, src: str = "src", dst: str = "dst", h: str | None = "h", label: str | None = "label", directed: bool = True, combine: str = "sum", dealt: bool = False) -> WalkGraph:
        """Parallel edges (equal src, dst, label) merge; nodes are LONG, h DOUBLE (1 without a column), label INT (0 without). `dealt`: by src first, one
        shuffle in place of two, for edges of which few merge."""
        cols = [F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"), (F.col(h).cast("double") if h in df.columns else F.lit(1.0)).alias("h"), (F.col(label).cast("int") if label in df.columns else F.lit(0)).alias("label")]
        raw = df.select(*cols)
        if not directed:
            raw = raw.union(raw.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "h", "label"))
        merged = (raw.repartition("src") if dealt else raw).groupBy("src", "dst", "label").agg(getattr(F, combine)("h").alias("h"))
        return WalkGraph(index_edges(merged), rows=raw if combine == "sum" else None)

    def listed(self) -> WalkGraph:
        """The same graph, kept as packed lists alone: rows are merged, ordered and packed after one shuffle, and edges and statistics are read out of the lists."""
        if self.rows is None:
            return self.stored()
        buckets = _buckets(self.rows.sparkSession, self.rows.count())
        dealt = self.rows.withColumn("bucket", bucket_of("src", buckets)).repartition(buckets, "bucket")
        packed = _kept_lists(dealt.mapInArrow(_merge_and_pack, _PACKED_ROW), buckets)
        out = WalkGraph(packed.groupBy("bucket").applyInArrow(_unpack, "src long, idx int, dst long, h double, label int"), True, self.counted)
        stretches = packed.mapInArrow(_stretch_stats, "src long, deg long, h_max double, h_min double, h_sum double")
        stats = stretches.groupBy("src").agg(*[getattr(F, f)(c).alias(c) for c, f in (("deg", "sum"), ("h_max", "max"), ("h_min", "min"), ("h_sum", "sum"))])
        vars(out).update(packed=packed, buckets=buckets, node_stats=settle(stats))
        return out

    def stored(self) -> WalkGraph:
        """The same graph, computed once and kept in the shared folder; its statistics and pairs are stored too, by their first use."""
        return WalkGraph(settle(self.edges), True, self.counted)

    def _once(self, df: DataFrame) -> DataFrame:
        return settle(df) if self.kept else df

    @cached_property
    def node_stats(self) -> DataFrame:
        return self._once(node_stats(self.edges))

    @cached_property
    def largest(self) -> tuple[int, int]:
        """(nodes, greatest degree) of a stored graph."""
        return tuple(self.node_stats.agg(F.count("*"), F.coalesce(F.max("deg"), F.lit(0))).first())

    @cached_property
    def size(self) -> int:
        """Edges of a stored graph."""
        return self.node_stats.agg(F.coalesce(F.sum("deg"), F.lit(0))).first()[0]

    @cached_property
    def label_stats(self) -> DataFrame:
        return self._once(self.edges.groupBy("src", "label").agg(F.count("*").alias("n"), F.max("h").alias("h_max"), F.sum("h").alias("h_sum")))

    @cached_property
    def pairs(self) -> DataFrame:
        """Distinct (src, dst), for edge-existence tests."""
        return self._once(self.edges.select("src", "dst").distinct())

    @cached_property
    def buckets(self) -> int:
        return _buckets(self.edges.sparkSession, self.size)

    @cached_property
    def packed(self) -> DataFrame:
        """(bucket, part, and PACKED as bytes) of a stored graph: lists in their order, dealt by `bucket_of`. A bucketed table: rows that
        come to the lists are shuffled to them, the lists stay where they are."""
        dealt = self.edges.withColumn("bucket", bucket_of("src", self.buckets)).groupBy("bucket")
        return _kept_lists(dealt.applyInArrow(_pack, _PACKED_ROW), self.buckets)

    def chunks(self, size: int = CHUNK) -> DataFrame:
        return adjacency_chunks(self.edges, size)

    def validate(self) -> WalkGraph:
        """An action: raises if an edge has a null end, or an h that is null, negative or not finite."""
        bad = self.edges.where("src is null or dst is null or h is null or h < 0 or isnan(h) or h = double('infinity')").limit(1).collect()
        if bad:
            raise InvalidGraph(f"invalid edge {bad[0]}")
        return self

    def reversed(self) -> WalkGraph:
        return WalkGraph(index_edges(self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "label", "h")))

    def with_weights(self, h) -> WalkGraph:
        return WalkGraph(self.edges.withColumn("h", h))


def index_edges(edges: DataFrame) -> DataFrame:
    at = Window.partitionBy("src").orderBy("dst", "label")
    return edges.select("src", (F.row_number().over(at) - 1).cast("int").alias("idx"), "dst", "h", "label")


def bucket_of(node: str, buckets: int, *salt: str):
    return F.pmod(F.xxhash64(node, *salt), F.lit(buckets)).cast("int")


def _buckets(spark: SparkSession, edges: int) -> int:
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    return max(1, min(2 * parts, edges // (BUCKET_EDGES // 10)), edges // BUCKET_EDGES)


_PACKED_ROW = "bucket int, part int, " + ", ".join(f"{c} binary" for c in PACKED)


def _kept_lists(packed: DataFrame, buckets: int) -> DataFrame:
    spark, name = packed.sparkSession, uuid.uuid4().hex
    packed.write.bucketBy(buckets, "bucket").option("path", f"{shared_dir(spark).rstrip('/')}/{name}").saveAsTable(f"lists_{name}")
    return spark.table(f"lists_{name}")


def _pack(edges: pa.Table) -> pa.Table:
    src, idx = edges.column("src").to_numpy(), edges.column("idx").to_numpy()
    order = np.lexsort((idx, src))
    return _packed_rows(edges.column("bucket")[0].as_py(), src[order], *(edges.column(c).to_numpy()[order] for c in ("dst", "h", "label")))


def _packed_rows(bucket: int, src: np.ndarray, *more: np.ndarray) -> pa.Table:
    """The rows of a bucket, from its edges (src, dst, h, label) in the order of their lists."""
    more, rows = [x.astype(PACKED[c], copy=False) for c, x in zip(("dst", "h", "label"), more)], {c: [] for c in PACKED}
    for a in range(0, len(src), PACKED_EDGES):
        here = slice(a, a + PACKED_EDGES)
        at = np.flatnonzero(np.diff(src[here], prepend=~src[a]))
        for c, x in zip(PACKED, (src[here][at], np.diff(np.append(at, len(src[here]))).astype(np.int64), *(x[here] for x in more))):
            rows[c].append(x.tobytes())
    n = len(rows["dst"])
    return pa.table({"bucket": pa.array([bucket] * n, pa.int32()), "part": pa.array(range(n), pa.int32())} | {c: pa.array(x, pa.binary()) for c, x in rows.items()})


def _merge_and_pack(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Whole buckets of rows to packed lists; equal (src, dst, label) merge by the sum of their h, of which nulls don't count."""
    if not (batches := [b for b in batches if b.num_rows]):
        return
    rows = pa.Table.from_batches(batches)
    order = np.lexsort([rows.column(c).to_numpy() for c in ("label", "dst", "src", "bucket")])
    bucket, src, dst, h, label = (rows.column(c).to_numpy()[order] for c in ("bucket", "src", "dst", "h", "label"))
    first = np.flatnonzero(np.logical_or.reduce([np.diff(x, prepend=~x[:1]) != 0 for x in (src, dst, label)]))
    if len(first) < len(src):
        null = np.asarray(rows.column("h").is_null())[order]
        h = np.where(np.logical_and.reduceat(null, first), np.nan, np.add.reduceat(np.where(null, 0.0, h), first))
        bucket, src, dst, label = bucket[first], src[first], dst[first], label[first]
    ends = [*np.flatnonzero(np.diff(bucket)) + 1, len(bucket)]
    for a, b in zip([0, *ends], ends):
        yield from _packed_rows(int(bucket[a]), *(x[a:b] for x in (src, dst, h, label))).to_batches()


def unpacked(rows: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(src, dst, h, label) of a bucket's packed rows."""
    order = np.argsort(rows.column("part").to_numpy())
    parts = {c: [np.frombuffer(rows.column(c)[int(k)].as_buffer(), t) for k in order] for c, t in PACKED.items()}
    nodes, deg, *more = (np.concatenate([np.zeros(0, PACKED[c]), *x]) for c, x in parts.items())
    return np.repeat(nodes, deg), *more


def _unpack(rows: pa.Table) -> pa.Table:
    src, dst, h, label = unpacked(rows)
    begin = np.flatnonzero(np.diff(src, prepend=~src[:1]))
    idx = np.arange(len(src)) - np.repeat(begin, np.diff(np.append(begin, len(src))))
    return pa.table({"src": src, "idx": idx.astype(np.int32), "dst": dst, "h": h, "label": label})


def _stretch_stats(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Statistics of each stretch of a node's edges in a packed row."""
    for batch in batches:
        for k in range(batch.num_rows):
            nodes, deg, h = (np.frombuffer(batch.column(c)[k].as_buffer(), PACKED[c]) for c in ("nodes", "deg", "h"))
            begin = np.cumsum(deg) - deg
            columns = nodes, deg, *(f.reduceat(h, begin) for f in (np.maximum, np.minimum, np.add))
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in columns], ["src", "deg", "h_max", "h_min", "h_sum"])


def node_stats(edges: DataFrame) -> DataFrame:
    """One hash aggregate: everything that bounds, estimates and proposals need."""
    return edges.groupBy("src").agg(F.count("*").alias("deg"), F.max("h").alias("h_max"), F.min("h").alias("h_min"), F.sum("h").alias("h_sum"))


def adjacency_chunks(edges: DataFrame, size: int = CHUNK) -> DataFrame:
    """(src, chunk, dst[], h[], label[]): at most `size` edges a row, so a hub never makes one giant row."""
    grouped = edges.groupBy("src", F.floor(F.col("idx") / size).cast("int").alias("chunk")).agg(F.array_sort(F.collect_list(F.struct("idx", "dst", "h", "label"))).alias("e"))
    return grouped.select("src", "chunk", F.col("e.dst").alias("dst"), F.col("e.h").alias("h"), F.col("e.label").alias("label"))


def rank_ids(df: DataFrame, *keys: str, name: str = "id") -> DataFrame:
    """`df` with its 0-based rank in the order of `keys`, without a global window: a range partition, its rows counted from the totals of those before it."""
    dealt = settle(df.repartitionByRange(*keys).withColumn("_part", F.spark_partition_id()))
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    starts = dealt.groupBy("_part").agg(F.count("*").alias("_n")).select("_part", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    inside = Window.partitionBy("_part").orderBy(*keys)
    return dealt.join(F.broadcast(starts), "_part").withColumn(name, (F.col("_before") + F.row_number().over(inside) - 1).cast("long")).drop("_part", "_before")


def write_graph(graph: WalkGraph, table: str, buckets: int = 64) -> None:
    """Edges bucketed by source and sorted by (src, idx): later joins on the source don't shuffle them."""
    graph.edges.write.bucketBy(buckets, "src").sortBy("src", "idx").mode("overwrite").saveAsTable(table)


def read_graph(spark: SparkSession, table: str) -> WalkGraph:
    return WalkGraph(spark.table(table))
