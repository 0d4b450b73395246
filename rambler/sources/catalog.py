"""Graphs derived from the given tables, and edge-weight schemes."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rambler.functions import rng
from rambler.operators.graph import WalkGraph, node_stats, rank_ids

#: Typed node ids are code * 2^40 + key.
PART, SUPPLIER, CUSTOMER, ORDER, NATION, REGION, SEGMENT, DOCUMENT, SOURCE, LANG, PAGE, LINK, TURN = range(1, 14)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def typed(code: int, column: str) -> Column:
    return F.col(column).cast("long") + F.lit(code << 40)


def _both_ways(df: DataFrame, *keep: str) -> DataFrame:
    return df.unionByName(df.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *keep))


def co_purchase(spark, d):
    """G1: parts bought in one order; weight: quantity of the source's lines."""
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    a = lines.select("l_orderkey", F.col("l_partkey").alias("src"), F.col("l_quantity").alias("h"))
    b = lines.select("l_orderkey", F.col("l_partkey").alias("dst"))
    return a.join(b, "l_orderkey").where("src <> dst").select("src", "dst", "h")


def supplier_part(spark, d):
    """G2: suppliers and parts, both ways; weight: quantity."""
    return _both_ways(table(spark, d, "lineitem").select(typed(SUPPLIER, "l_suppkey").alias("src"), typed(PART, "l_partkey").alias("dst"), F.col("l_quantity").alias("h")), "h")


def customer_part(spark, d):
    """G3: customers and the parts they bought, both ways; weight: quantity."""
    lines = table(spark, d, "lineitem").join(table(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return _both_ways(lines.select(typed(CUSTOMER, "o_custkey").alias("src"), typed(PART, "l_partkey").alias("dst"), F.col("l_quantity").alias("h")), "h")


def hubs(spark, d):
    """G4: segments and nations with their customers, both ways; weight: positive balance plus 1."""
    customers = table(spark, d, "customer").select("c_custkey", "c_nationkey", "c_mktsegment", (F.greatest("c_acctbal", F.lit(0.0)) + 1).alias("h"))
    segments = rank_ids(customers.select("c_mktsegment").distinct(), "c_mktsegment")
    by_segment = customers.join(segments, "c_mktsegment").select(typed(SEGMENT, "id").alias("src"), typed(CUSTOMER, "c_custkey").alias("dst"), "h")
    by_nation = customers.select(typed(NATION, "c_nationkey").alias("src"), typed(CUSTOMER, "c_custkey").alias("dst"), "h")
    return _both_ways(by_segment.unionByName(by_nation), "h")


def word_tokens(spark, d) -> DataFrame:
    """(doc_id, pos, token): blank-delimited lower-cased tokens of each text."""
    return table(spark, d, "documents").select("doc_id", F.posexplode(_words()).alias("pos", "token"))


def _words() -> Column:
    return F.filter(F.split(F.lower("text"), r"[ \n]+"), lambda w: w != "")


def word_dictionary(spark, d) -> DataFrame:
    return rank_ids(word_tokens(spark, d).select("token").distinct(), "token")


def word_adjacency(spark, d):
    """G5: token to next token; weight: number of places. Power-law degrees and dead ends."""
    ids = word_dictionary(spark, d)
    words = table(spark, d, "documents").select(_words().alias("w"))
    pairs = words.select(F.explode(F.arrays_zip(F.slice("w", 1, F.greatest(F.size("w") - 1, F.lit(0))).alias("a"), F.slice("w", 2, F.greatest(F.size("w") - 1, F.lit(0))).alias("b"))).alias("p"))
    counted = pairs.groupBy(F.col("p.a").alias("a"), F.col("p.b").alias("b")).agg(F.count("*").cast("double").alias("h"))
    return counted.join(ids.select(F.col("token").alias("a"), F.col("id").alias("src")), "a").join(ids.select(F.col("token").alias("b"), F.col("id").alias("dst")), "b").select("src", "dst", "h")


def next_user(spark, d):
    """G6: user of an event to the user of the next one; weight: the event's value. Ranks instead of a global window."""
    ranked = rank_ids(table(spark, d, "events").select("ts", "event_id", "user_id", "value"), "ts", "event_id", name="at")
    after = ranked.select((F.col("at") - 1).alias("at"), F.col("user_id").alias("dst"))
    return ranked.join(after, "at").where("user_id <> dst").select(F.col("user_id").alias("src"), "dst", F.col("value").alias("h"))


def page_links(spark, d):
    """G7: pages and the targets of their links, both ways; weight: occurrences."""
    links = table(spark, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), 1)).alias("target"))
    ids = rank_ids(links.select("target").distinct(), "target")
    return _both_ways(links.join(ids, "target").select(typed(PAGE, "page_id").alias("src"), typed(LINK, "id").alias("dst"), F.lit(1.0).alias("h")), "h")


def nearest_vectors(spark, d, k: int = 10, block: int = 512):
    """G8: each vector's k nearest by cosine; weight: the cosine, 0 at least. Blocks of queries meet blocks of vectors; a block pair keeps k a query, and the best k of those are merged."""
    vectors = table(spark, d, "embeddings").select("vec_id", "embedding")
    blocks = vectors.withColumn("block", F.expr(f"cast(vec_id div {block} as int)")).groupBy("block").agg(F.collect_list("vec_id").alias("ids"), F.flatten(F.collect_list("embedding")).alias("x"))
    pairs = blocks.select(F.col("ids").alias("a"), F.col("x").alias("x")).crossJoin(blocks.select(F.col("ids").alias("b"), F.col("x").alias("y")))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                a, x, b, y = (np.asarray(batch.column(c)[i].values.to_numpy(zero_copy_only=False)) for c in range(4))
                x, y = (v.astype(float).reshape(len(n), -1) for v, n in ((x, a), (y, b)))
                x, y = (v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-300) for v in (x, y))
                cosine = np.where(a[:, None] == b[None], -np.inf, x @ y.T)
                order = np.lexsort((np.broadcast_to(b, cosine.shape), -cosine), axis=1)[:, :k]
                src, dst, c = np.repeat(a, order.shape[1]), b[order].ravel(), np.take_along_axis(cosine, order, 1).ravel()
                keep = np.isfinite(c)
                yield pa.RecordBatch.from_arrays([pa.array(src[keep]), pa.array(dst[keep]), pa.array(c[keep])], ["src", "dst", "cosine"])

    best = pairs.repartition(8 * spark.sparkContext.defaultParallelism).mapInArrow(run, "src long, dst long, cosine double")
    top = best.groupBy("src").agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("cosine")).alias("far"), "dst"))), 1, k).alias("t"))
    return top.select("src", F.explode("t").alias("t")).select("src", F.col("t.dst").alias("dst"), F.greatest(-F.col("t.far"), F.lit(0.0)).alias("h"))


def nation_trade(spark, d):
    """G9: customer's nation to supplier's nation; weight: extended price."""
    lines = table(spark, d, "lineitem").join(table(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    lines = lines.join(table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(table(spark, d, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    return lines.select(F.col("c_nationkey").cast("long").alias("src"), F.col("s_nationkey").cast("long").alias("dst"), F.col("l_extendedprice").alias("h"))


def typed_star(spark, d):
    """G10: region, nation, customer, order, part, supplier; labels 0 to 4; weight 1, or quantity on labels 3 and 4."""
    one = F.lit(1.0).alias("h")
    lines = table(spark, d, "lineitem")
    parts = [
        table(spark, d, "nation").select(typed(REGION, "n_regionkey").alias("src"), typed(NATION, "n_nationkey").alias("dst"), one, F.lit(0).alias("label")),
        table(spark, d, "customer").select(typed(NATION, "c_nationkey").alias("src"), typed(CUSTOMER, "c_custkey").alias("dst"), one, F.lit(1).alias("label")),
        table(spark, d, "orders").select(typed(CUSTOMER, "o_custkey").alias("src"), typed(ORDER, "o_orderkey").alias("dst"), one, F.lit(2).alias("label")),
        lines.select(typed(ORDER, "l_orderkey").alias("src"), typed(PART, "l_partkey").alias("dst"), F.col("l_quantity").alias("h"), F.lit(3).alias("label")),
        lines.select(typed(PART, "l_partkey").alias("src"), typed(SUPPLIER, "l_suppkey").alias("dst"), F.col("l_quantity").alias("h"), F.lit(4).alias("label")),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def document_facets(spark, d):
    """G11: documents to their source (label 0) and language (label 1)."""
    docs = table(spark, d, "documents").select("doc_id", "source", "lang")
    sources, langs = (rank_ids(docs.select(c).where(F.col(c).isNotNull()).distinct(), c) for c in ("source", "lang"))
    a = docs.join(sources, "source").select(typed(DOCUMENT, "doc_id").alias("src"), typed(SOURCE, "id").alias("dst"), F.lit(1.0).alias("h"), F.lit(0).alias("label"))
    b = docs.join(langs, "lang").select(typed(DOCUMENT, "doc_id").alias("src"), typed(LANG, "id").alias("dst"), F.lit(1.0).alias("h"), F.lit(1).alias("label"))
    return a.unionByName(b)


GRAPHS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "g1": co_purchase, "g2": supplier_part, "g3": customer_part, "g4": hubs, "g5": word_adjacency, "g6": next_user,
    "g7": page_links, "g8": nearest_vectors, "g9": nation_trade, "g10": typed_star, "g11": document_facets,
}


#: Graphs of lines, whose edges hardly repeat and whose weights are whole numbers (their sums don't depend on the order).
FEW_PARALLEL = ("g1", "g2", "g3")


def load_graph(spark: SparkSession, sf_dir: str, name: str, weights: str = "natural", alpha: float | None = None, seed: int = 42, labels: bool = False) -> WalkGraph:
    """One of the graphs, with natural, uniform, pareto, degree, int8 or unit weights; labels=True draws labels 0 to 4 for graphs without their own."""
    graph = WalkGraph.from_edges(GRAPHS[name](spark, sf_dir), dealt=name in FEW_PARALLEL)
    if weights != "natural":
        graph = apply_weights(graph, weights, alpha, seed)
    if labels:
        graph = WalkGraph(graph.edges.withColumn("label", F.floor(edge_uniform(seed, rng.LABEL) * 5).cast("int")))
    return graph


def edge_uniform(seed: int, tag: int) -> Column:
    """A uniform for each edge: the source is the walk of the counter, the destination the item, its high half the step."""
    return rng.uniform(seed, "src", "shiftrightunsigned(dst, 32)", tag, "dst")


def listed(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(src, dst, label) of the graph's edges, dealt by src: all that drawn weights depend on."""
    raw = GRAPHS[name](spark, sf_dir)
    label = F.col("label").cast("int") if "label" in raw.columns else F.lit(0)
    return raw.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), label.alias("label")).repartition("src").distinct()


def with_edge_uniform(edges: DataFrame, name: str, tag: int, seed: int = 42) -> DataFrame:
    """`edge_uniform` as a column of a large table."""
    edges = rng.with_states(edges, ("_e1", "_e2"), seed, tag, F.col("src"), F.shiftrightunsigned("dst", 32))
    return rng.with_uniform(edges, name, ("_e1", "_e2"), F.col("dst")).drop("_e1", "_e2")


def apply_weights(graph: WalkGraph, scheme: str, alpha: float | None = None, seed: int = 42) -> WalkGraph:
    if scheme == "unit":
        return graph.with_weights(F.lit(1.0))
    if scheme in ("uniform", "pareto"):
        drawn = with_edge_uniform(graph.edges, "_u", rng.WEIGHT, seed)
        h = F.lit(1.0) + 4 * F.col("_u") if scheme == "uniform" else F.pow("_u", F.lit(-1.0 / alpha)) - 1
        return WalkGraph(drawn.withColumn("h", h).drop("_u"))
    if scheme == "degree":
        degree = node_stats(graph.edges).select(F.col("src").alias("dst"), F.col("deg"))
        edges = graph.edges.join(degree, "dst", "left").withColumn("h", F.greatest(F.coalesce("deg", F.lit(0)), F.lit(1)).cast("double"))
        return WalkGraph(edges.select("src", "idx", "dst", "h", "label"))
    if scheme == "int8":
        top = graph.edges.agg(F.max("h").alias("top"))
        edges = graph.edges.crossJoin(F.broadcast(top))  # a single row
        return WalkGraph(edges.withColumn("h", F.round(F.col("h") * 127 / F.col("top")).cast("tinyint").cast("double")).select("src", "idx", "dst", "h", "label"))
    raise ValueError(f"unknown weights {scheme}")
