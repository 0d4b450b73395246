"""Operators around the walks: sources and sinks, joins, aggregates and windows over graphs and walks."""

from __future__ import annotations

import time
import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rambler import oracles as O
from rambler.functions.store import settle, shared_dir
from rambler.operators import samplers as S
from rambler.operators.graph import read_graph, write_graph
from rambler.operators.walk import WalkConfig, forget_copies, one_per_node, placed, profile_ratio, random_walks, walk_cost, walk_log
from rambler.queries import MODELS, QUERIES, query
from rambler.sources.catalog import apply_weights, load_graph, table

W = "w AS MATERIALIZED (" + O.walk("g9", "node2vec_w") + ")"
_E = lambda g: f"e AS MATERIALIZED ({O.edges(g)})"


def walks(s, d, graph="g9", steps=5) -> DataFrame:
    return settle(random_walks(load_graph(s, d, graph).stored(), MODELS["node2vec_w"], sampler="keys", config=WalkConfig(steps=steps, mode="replicated")))


def edges(s, d, g="g9") -> DataFrame:
    return load_graph(s, d, g).edges


# Sources and sinks ------------------------------------------------------------------------------------------------------
@query("scan_edges_parquet", "SELECT l_suppkey AS src, l_partkey AS dst FROM lineitem WHERE l_quantity > 30")
def scan_edges(s, d):
    """Typed scan: only the columns named are read, and the filter reaches the files."""
    return s.read.schema("l_suppkey long, l_partkey long, l_quantity double").parquet(f"{d}/lineitem.parquet").where("l_quantity > 30").select(F.col("l_suppkey").alias("src"), F.col("l_partkey").alias("dst"))


@query("roundtrip_formats", f"WITH {_E('g9')} SELECT f AS format, src, dst, round(h, 6) AS h, label FROM e, (VALUES ('csv'), ('json'), ('orc'), ('parquet')) v(f)")
def roundtrip(s, d):
    """An edge list written and read again in four formats."""
    e, out = edges(s, d).select("src", "dst", F.round("h", 6).alias("h"), "label"), None
    for f in ("csv", "json", "orc", "parquet"):
        path = f"{shared_dir(s)}/{uuid.uuid4().hex}"
        e.write.format(f).save(path)
        back = s.read.format(f).schema(e.schema).load(path).select(F.lit(f).alias("format"), "*")
        out = back if out is None else out.unionByName(back)
    return out


@query("edge_list_text", f"WITH {_E('g9')} SELECT src, dst FROM e")
def edge_list_text(s, d):
    """Whitespace-separated edge list, comment lines skipped."""
    path = f"{shared_dir(s)}/{uuid.uuid4().hex}"
    edges(s, d).select(F.concat_ws(" ", "src", "dst")).write.text(path)
    return s.read.text(path).where("not value like '#%'").select(F.split("value", r"\s+").alias("p")).select(F.col("p")[0].cast("long").alias("src"), F.col("p")[1].cast("long").alias("dst"))


@query("bucketed_store", f"WITH {_E('g9')} SELECT src, idx, dst, round(h, 6) AS h, label FROM e")
def bucketed_store(s, d):
    """Edges in buckets by source, read again: a join on the source needs no shuffle of them."""
    name = f"edges_{uuid.uuid4().hex}"
    write_graph(load_graph(s, d, "g9"), name, 8)
    back = settle(read_graph(s, name).edges.withColumn("h", F.round("h", 6)))
    s.sql(f"DROP TABLE {name}")
    return back


@query("walk_sink", f"WITH {W} SELECT walk_id, step, node FROM w")
def walk_sink(s, d):
    """Walks appended step by step to a table partitioned by step."""
    path = f"{shared_dir(s)}/{uuid.uuid4().hex}"
    walks(s, d).write.partitionBy("step").mode("append").parquet(path)
    return s.read.schema("walk_id long, node long, step int").parquet(path)


# Joins ------------------------------------------------------------------------------------------------------------------
_START = "SELECT src AS walk_id, 0 AS step, NULL::BIGINT AS prev, src AS cur FROM g"


def _starts(g):
    return g.node_stats.select(F.col("src").alias("walk_id"), F.lit(0).alias("step"), F.lit(None).cast("long").alias("prev"), F.col("src").alias("cur"))


@query("step_candidates", f"WITH {O.with_graph('g9')}, s AS ({_START}) SELECT walk_id, dst, round(w, 6) AS w FROM ({O.candidates('s', 'node2vec_w')}) WHERE w > 0")
def step_candidates(s, d):
    g = load_graph(s, d, "g9").stored()
    return S.candidates(_starts(g), g, MODELS["node2vec_w"]).select("walk_id", "dst", F.round("w", 6).alias("w"))


@query("stats_broadcast", f"WITH {O.with_graph('g4')} SELECT src AS walk_id, deg AS deg_cur, round(h_max, 6) AS h_max FROM g")
def stats_broadcast(s, d):
    g = load_graph(s, d, "g4").stored()
    return S.attach_stats(_starts(g), g, False).select("walk_id", "deg_cur", F.round("h_max", 6).alias("h_max"))


@query("proposal_lookup", f"WITH {O.with_graph('g3')} SELECT g.src AS walk_id, t AS trial, e.dst FROM g, unnest(range(4)) x(t) JOIN e ON e.src = g.src AND e.idx = least(floor({O.rng.duck_uniform(42, 'g.src', '0', O.rng.SLOT, 't')} * deg), deg - 1)")
def proposal_lookup(s, d):
    """Rejection's read: the proposed edges alone, by (src, idx)."""
    g = load_graph(s, d, "g3").stored()
    ready = S.attach_stats(_starts(g), g, False)
    return S.proposals(ready, g, MODELS["static"], 42, 0, 4).select("walk_id", F.col("trial").cast("long").alias("trial"), "dst")


_PAIRS = "SELECT DISTINCT a.src AS prev, a.dst AS cur, b.dst FROM e a JOIN e b ON a.dst = b.src"


@query("linked_left", f"WITH {_E('g9')}, t AS ({_PAIRS}) SELECT prev, cur, t.dst, p.src IS NOT NULL AS linked FROM t LEFT JOIN (SELECT DISTINCT src, dst FROM e) p ON prev = p.src AND t.dst = p.dst")
def linked_left(s, d):
    g = load_graph(s, d, "g9").stored()
    return S.linked_flag(_two_hops(g), g).select("prev", "cur", "dst", "linked")


def _two_hops(g):
    a, b = g.edges.select(F.col("src").alias("prev"), F.col("dst").alias("cur")), g.edges.select(F.col("src").alias("cur"), "dst")
    return a.join(b, "cur").distinct()


@query("linked_semi", f"WITH {_E('g9')}, t AS ({_PAIRS}) SELECT prev, cur, dst FROM t WHERE EXISTS (SELECT 1 FROM e WHERE e.src = prev AND e.dst = t.dst)")
def linked_semi(s, d):
    g = load_graph(s, d, "g9").stored()
    return _two_hops(g).join(g.pairs.withColumnRenamed("src", "prev"), ["prev", "dst"], "left_semi").select("prev", "cur", "dst")


@query("dead_ends_anti", f"WITH {_E('g10')} SELECT DISTINCT dst AS node FROM e WHERE dst NOT IN (SELECT src FROM e)")
def dead_ends(s, d):
    e = settle(edges(s, d, "g10"))
    return e.select(F.col("dst").alias("node")).distinct().join(e.select(F.col("src").alias("node")).distinct(), "node", "left_anti")


@query("its_range_lookup", f"""WITH {O.with_graph('g9')} SELECT src AS walk_id, dst FROM (SELECT *, sum(h) OVER (PARTITION BY src ORDER BY idx) AS hi, sum(h) OVER (PARTITION BY src ORDER BY idx) - h AS lo, sum(h) OVER (PARTITION BY src) AS whole FROM e)
WHERE lo <= {O.rng.duck_uniform(42, 'src', '0', O.rng.PICK, '0')} * whole AND {O.rng.duck_uniform(42, 'src', '0', O.rng.PICK, '0')} * whole < hi""")
def its_range_lookup(s, d):
    g = load_graph(s, d, "g9").stored()
    return S.inverse_step(_starts(g), g, MODELS["static"], 42).select("walk_id", F.col("next").alias("dst"))


@query("asof_last_order", "SELECT event_id, max(o_orderdate) AS last_at, arg_max(o_orderkey, (o_orderdate, o_orderkey)) AS o_orderkey FROM events JOIN orders ON o_custkey = user_id AND o_orderdate <= ts GROUP BY event_id")
def asof_last_order(s, d):
    """As-of join: the user's last order at or before each event. Both sides meet in one sorted stream for each key, never in pairs."""
    orders = table(s, d, "orders").select(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("t"), F.lit(None).cast("long").alias("event_id"), "o_orderkey", F.lit(0).alias("side"))
    events = table(s, d, "events").select(F.col("user_id").alias("k"), F.col("ts").alias("t"), "event_id", F.lit(None).cast("long").alias("o_orderkey"), F.lit(1).alias("side"))
    before = Window.partitionBy("k").orderBy("t", "side", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("side") == 0, F.struct("t", "o_orderkey")), ignorenulls=True).over(before)
    return events.unionByName(orders).withColumn("l", last).where("side = 1 and l is not null").select("event_id", F.col("l.t").alias("last_at"), F.col("l.o_orderkey").alias("o_orderkey"))


@query("interval_colocation", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
def interval_colocation(s, d):
    """Events of one user at most ten minutes apart, by buckets of ten minutes."""
    e = table(s, d, "events").select("event_id", "user_id", "ts", F.expr("unix_seconds(cast(ts as timestamp)) div 600").alias("bucket"))
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("t"), F.explode(F.array("bucket", F.col("bucket") + 1)).alias("bucket"))
    return a.join(e.withColumnRenamed("event_id", "b"), ["user_id", "bucket"]).where("ts > t and ts <= t + interval 10 minutes").select("a", "b")


@query("reciprocity_outer", f"WITH {_E('g6')} SELECT coalesce(a.src, b.dst) AS src, coalesce(a.dst, b.src) AS dst, a.src IS NOT NULL AS forth, b.src IS NOT NULL AS back FROM e a FULL JOIN e b ON a.src = b.dst AND a.dst = b.src")
def reciprocity_outer(s, d):
    e = settle(edges(s, d, "g6").select("src", "dst"))
    back = e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit(True).alias("b"))
    return e.withColumn("f", F.lit(True)).join(back, ["src", "dst"], "full").select("src", "dst", F.coalesce("f", F.lit(False)).alias("forth"), F.coalesce("b", F.lit(False)).alias("back"))


@query("filter_starts_quality", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1 AND toxic = 0)")
def filter_starts(s, d):
    return table(s, d, "documents").select("doc_id").join(table(s, d, "labels").where("quality = 1 and toxic = 0"), "doc_id", "left_semi")


query("temporal_edges_before", "SELECT l_suppkey AS src, l_partkey AS dst, l_shipdate AS at FROM lineitem WHERE l_shipdate < TIMESTAMP '1996-06-01'")(
    lambda s, d: table(s, d, "lineitem").where("l_shipdate < timestamp '1996-06-01'").select(F.col("l_suppkey").alias("src"), F.col("l_partkey").alias("dst"), F.col("l_shipdate").alias("at")))
query("label_pruned_edges", f"WITH {_E('g10')} SELECT src, dst FROM e WHERE label = 2")(lambda s, d: edges(s, d, "g10").where("label = 2").select("src", "dst"))
query("events_k_edges", "SELECT user_id AS src, props->>'$.k' AS k, count(*) AS n FROM events GROUP BY 1, 2")(lambda s, d: table(s, d, "events").groupBy(F.col("user_id").alias("src"), F.get_json_object("props", "$.k").alias("k")).agg(F.count("*").alias("n")))

# Aggregates, windows and sets over walks --------------------------------------------------------------------------------
query("visits", f"WITH {W} SELECT node, count(*) AS n FROM w GROUP BY node")(lambda s, d: walks(s, d).groupBy("node").agg(F.count("*").alias("n")))
query("top_visited", f"WITH {W} SELECT node, count(*) AS n FROM w GROUP BY node ORDER BY n DESC, node LIMIT 10")(lambda s, d: walks(s, d).groupBy("node").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "node").limit(10))
query("distinct_reached", f"WITH {W} SELECT walk_id, count(DISTINCT node) AS n FROM w GROUP BY walk_id")(lambda s, d: walks(s, d).groupBy("walk_id").agg(F.countDistinct("node").alias("n")))
query("approx_reached", None)(lambda s, d: walks(s, d).groupBy("walk_id").agg(F.approx_count_distinct("node").alias("n")))
_R = "SELECT n_regionkey AS region, node, step FROM w JOIN nation ON node = n_nationkey"


def _regions(s, d):
    return walks(s, d).join(table(s, d, "nation").select(F.col("n_nationkey").cast("long").alias("node"), F.col("n_regionkey").alias("region")), "node")


query("visits_rollup", f"WITH {W} SELECT region, node, count(*) AS n FROM ({_R}) GROUP BY ROLLUP (region, node)")(lambda s, d: _regions(s, d).rollup("region", "node").agg(F.count("*").alias("n")))
query("visits_cube", f"WITH {W} SELECT region, step, count(*) AS n FROM ({_R}) GROUP BY CUBE (region, step)")(lambda s, d: _regions(s, d).cube("region", "step").agg(F.count("*").alias("n")))
query("visits_grouping_sets", f"WITH {W} SELECT region, step, count(*) AS n FROM ({_R}) GROUP BY GROUPING SETS ((region), (step), ())")(
    lambda s, d: _regions(s, d).groupingSets([[F.col("region")], [F.col("step")], []], F.col("region"), F.col("step")).agg(F.count("*").alias("n")))
query("visits_pivot", f"WITH {W} SELECT region, count(*) FILTER (step = 0) AS s0, count(*) FILTER (step = 1) AS s1, count(*) FILTER (step = 2) AS s2 FROM ({_R}) GROUP BY region")(
    lambda s, d: _regions(s, d).groupBy("region").pivot("step", [0, 1, 2]).agg(F.count(F.lit(1))).select("region", *[F.coalesce(F.col(str(k)), F.lit(0)).alias(f"s{k}") for k in range(3)]))
query("visit_percentiles", f"WITH {W} SELECT quantile_cont(n, 0.5) AS p50, quantile_cont(n, 0.9) AS p90 FROM (SELECT node, count(*)::DOUBLE AS n FROM w GROUP BY node)")(
    lambda s, d: walks(s, d).groupBy("node").agg(F.count("*").cast("double").alias("n")).agg(F.percentile("n", 0.5).alias("p50"), F.percentile("n", 0.9).alias("p90")))
query("topk_neighbors", f"SELECT src, dst, r FROM (SELECT src, dst, CAST(row_number() OVER (PARTITION BY src ORDER BY h DESC, dst) AS INTEGER) AS r FROM ({O.edges('g3')})) WHERE r <= 3")(
    lambda s, d: edges(s, d, "g3").withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("h"), "dst"))).where("r <= 3").select("src", "dst", "r"))
query("prefix_weights", f"SELECT src, idx, sum(h) OVER (PARTITION BY src ORDER BY idx) AS acc FROM ({O.edges('g3')})")(
    lambda s, d: edges(s, d, "g3").select("src", "idx", F.sum("h").over(Window.partitionBy("src").orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)).alias("acc")))
query("walk_bigrams", f"WITH {W} SELECT a, node AS b, count(*) AS n FROM (SELECT lag(node) OVER (PARTITION BY walk_id ORDER BY step) AS a, node FROM w) WHERE a IS NOT NULL GROUP BY 1, 2")(
    lambda s, d: walks(s, d).select(F.lag("node").over(Window.partitionBy("walk_id").orderBy("step")).alias("a"), F.col("node").alias("b")).where("a is not null").groupBy("a", "b").agg(F.count("*").alias("n")))
query("walk_context_pairs", f"WITH {W} SELECT x.node AS center, y.node AS context, count(*) AS n FROM w x JOIN w y ON x.walk_id = y.walk_id AND x.step <> y.step AND abs(x.step - y.step) <= 2 GROUP BY 1, 2")(
    lambda s, d: context_pairs(walks(s, d)))


def context_pairs(w: DataFrame, reach: int = 2) -> DataFrame:
    """Pairs of nodes at most `reach` steps apart, from a frame of the walk itself (no self-join)."""
    around = F.collect_list(F.struct("step", "node")).over(Window.partitionBy("walk_id").orderBy("step").rowsBetween(-reach, reach))
    return w.withColumn("near", around).select(F.col("node").alias("center"), "step", F.explode("near").alias("c")).where("c.step <> step").groupBy("center", F.col("c.node").alias("context")).agg(F.count("*").alias("n"))


query("value_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events")(
    lambda s, d: table(s, d, "events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.rint(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000).cast("long")).rangeBetween(-3600, 0)).alias("n")))
_FORTH, _BACK = "SELECT src, dst FROM e", "SELECT dst AS src, src AS dst FROM e"
for _name, _op in (("edges_union_reverse", "UNION"), ("edges_intersect_reciprocal", "INTERSECT"), ("edges_except_reverse", "EXCEPT")):

    @query(_name, f"WITH {_E('g6')} {_FORTH} {_op} {_BACK}")
    def _sets(s, d, how=_op):
        e = settle(edges(s, d, "g6").select("src", "dst"))
        back = e.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
        return e.union(back).distinct() if how == "UNION" else e.intersect(back) if how == "INTERSECT" else e.subtract(back)


# Measures and experiments -----------------------------------------------------------------------------------------------
def counters(s, d, graphs, samplers, weights=(("natural", None),), model="node2vec_w", also=(), **options) -> DataFrame:
    """Mean reads and draws of a step of long walks from every node, and the share of rejection, by graph, sampler and weights: what the ablations turn on.
    `also`: (samplers, model) of further walks, which get a column `model`. Each graph is made once, and what was sent of it is freed."""
    out = None
    for graph in graphs:
        base = load_graph(s, d, graph).stored() if len(weights) > 1 else None  # drawn weights depend on an edge's ends alone
        for scheme, alpha in weights:
            g = (load_graph(s, d, graph, scheme, alpha) if base is None else apply_weights(base, scheme, alpha)).stored()
            for names, of in ((samplers, model), *also):
                for sampler in names:
                    log = walk_log(g, MODELS[of], None, sampler, WalkConfig(mode="replicated", sampler_options=options))
                    row = log.agg(F.count("*").alias("steps"), F.round(F.avg("reads"), 6).alias("reads"), F.round(F.avg("draws"), 6).alias("draws"), F.round(F.avg((F.col("mode") == "rejection").cast("int")), 6).alias("rejection"))
                    row = row.select(F.lit(graph).alias("graph"), F.lit(scheme).alias("weights"), F.lit(alpha).cast("double").alias("alpha"), F.lit(sampler).alias("sampler"), "*", *([F.lit(of).alias("model")] if also else []))
                    row = settle(row)
                    out = row if out is None else out.unionByName(row)
            forget_copies(g)
    return out


ALPHA = tuple(("pareto", a) for a in (1.0, 2.0, 4.0))
SOCIAL = ("g1", "g2", "g5")
query("x1_four_samplers")(
    lambda s, d: counters(s, d, (*SOCIAL, "g8"), ("inverse", "alias", "rejection_exact", "prefix"), also=((("inverse", "alias", "rejection_bound", "prefix"), "node2vec_u"),)))
WORKLOADS = ("node2vec_w", "node2vec_u", "metapath_w", "metapath_u", "sorank_w")
BASELINES = ("inverse", "alias", "prefix", "rejection_exact", "adaptive")
#: Seconds after which a run is marked as out of time.
TIME_LIMIT = 600.0


@query("x2_main_table")
def x2_main_table(s, d):
    """Run times of five workloads by all baselines and by selection, and how many times faster selection is; with the geometric mean and
    the maximum over all workloads (workload 'all')."""
    rows = []
    for graph in ("g1", "g2"):
        g = load_graph(s, d, graph, "uniform", labels=True).stored()
        random_walks(g, MODELS["static"], None, "keys", WalkConfig(mode="replicated", steps=1)).count()  # workers copy the graph: not in any baseline's time
        for workload in WORKLOADS:
            for sampler in BASELINES:
                began = time.perf_counter()
                steps = random_walks(g, MODELS[workload], None, sampler, WalkConfig(mode="replicated")).where("step > 0").count()
                rows.append((graph, workload, sampler, steps, time.perf_counter() - began))
        forget_copies(g)
    runs = s.createDataFrame(rows, "graph string, workload string, sampler string, steps long, seconds double")
    own = runs.where("sampler = 'adaptive'").select("graph", "workload", F.col("seconds").alias("own"))  # a row for each run above
    out = runs.join(own, ["graph", "workload"]).select("graph", "workload", "sampler", "steps", "seconds", (F.col("seconds") / F.col("own")).alias("speedup"), (F.col("seconds") > TIME_LIMIT).alias("out_of_time")).withColumn("largest", F.col("speedup"))
    whole = out.groupBy("graph", "sampler").agg(F.sum("steps").alias("steps"), F.sum("seconds").alias("seconds"), F.exp(F.avg(F.log("speedup"))).alias("speedup"), F.max("out_of_time").alias("out_of_time"), F.max("speedup").alias("largest"))
    return out.unionByName(whole.withColumn("workload", F.lit("all")))


query("x6_weight_variation")(lambda s, d: QUERIES["weight_cv_hist"](s, d))
query("x10_selection_ratio")(lambda s, d: QUERIES["selection_ratio_alpha"](s, d))


@query("x11_overhead")
def x11_overhead(s, d):
    """Seconds of profiling and of preprocessing beside those of the walks, and the profiled cost ratio, by graph."""
    rows = []
    for graph in ("g1", "g2", "g3"):
        g = load_graph(s, d, graph, "uniform").stored()
        began = time.perf_counter()
        ratio = profile_ratio(g, MODELS["node2vec_w"]).first()["ratio"]
        profiled = time.perf_counter()
        g.node_stats.count()
        ready = time.perf_counter()
        random_walks(g, MODELS["node2vec_w"], None, "adaptive", WalkConfig(mode="replicated", sampler_options={"ratio": ratio})).count()
        rows.append((graph, ratio, profiled - began, ready - profiled, time.perf_counter() - ready))
    table = s.createDataFrame(rows, "graph string, ratio double, profile double, preprocess double, walks double")
    return table.withColumn("share", (F.col("profile") + F.col("preprocess")) / (F.col("profile") + F.col("preprocess") + F.col("walks")))


query("x3_power_law")(lambda s, d: counters(s, d, SOCIAL, ("rejection_exact", "prefix", "adaptive"), ALPHA))
query("x4_degree_weights")(lambda s, d: counters(s, d, SOCIAL, ("rejection_exact", "prefix", "adaptive"), (("degree", None),)))
query("x5_skew_sensitivity")(lambda s, d: counters(s, d, ("g1", "g5"), ("rejection_bound", "jump"), ALPHA))
query("x7_selection_ablation")(lambda s, d: counters(s, d, SOCIAL, ("adaptive", "rejection_bound", "keys", "prefix"), (("uniform", None), ("pareto", 1.0))))
query("x8_kernel_ablation")(lambda s, d: counters(s, d, ("g1", "g5"), ("prefix", "keys", "jump", "rejection_exact", "rejection_bound"), (("uniform", None), ("pareto", 1.0))))
query("x14_low_precision")(lambda s, d: counters(s, d, ("g3",), ("prefix", "adaptive"), (("int8", None),)))


@query("x9_selectors")
def x9_selectors(s, d):
    """Random, degree, cost and hindsight selection on the graphs with hubs."""
    out = None
    for kind in ("random", "degree", "cost", "exact", "rejection", "reservoir"):
        part = counters(s, d, ("g4", "g5"), ("adaptive",), (("uniform", None),), kind=kind, threshold=100).withColumn("selector", F.lit(kind))
        out = part if out is None else out.unionByName(part)
    return out


@query("x12_scale_out")
def x12_scale_out(s, d):
    """Walks of every node by 1, 2, 4 and 8 workers: the slowest worker's seconds of walking, all workers' CPU seconds, how many times faster than one worker; and apart from these the slowest copy of the graph."""
    g, out = load_graph(s, d, "g1", "uniform").stored(), None
    settle(walk_cost(g, MODELS["node2vec_w"], None, "adaptive", WalkConfig(steps=2, partitions=8)))  # starts the workers
    for parts in (1, 2, 4, 8):
        part = walk_cost(g, MODELS["node2vec_w"], None, "adaptive", WalkConfig(partitions=parts)).agg(F.sum("steps").alias("steps"), F.max("wall_seconds").alias("seconds"), F.sum("cpu_seconds").alias("cpu_seconds"), F.max("copy_seconds").alias("copy_seconds"))
        part = settle(part.select(F.lit(parts).alias("workers"), "*"))  # one run at a time
        out = part if out is None else out.unionByName(part)
    alone = out.where("workers = 1").select(F.col("seconds").alias("alone"))  # one row
    return out.join(F.broadcast(alone)).select("workers", "steps", "seconds", "cpu_seconds", "copy_seconds", (F.col("alone") / F.col("seconds")).alias("speedup"))


@query("x13_cpu_cost")
def x13_cpu_cost(s, d):
    """CPU seconds that a million steps cost by each sampler: what stands in for energy where no meter can be read."""
    g, out = load_graph(s, d, "g3", "uniform").stored(), None
    settle(walk_cost(g, MODELS["node2vec_w"], None, "keys", WalkConfig(steps=2)))  # starts the workers
    for sampler in ("inverse", "prefix", "keys", "jump", "jump_shared", "rejection_exact", "rejection_bound", "adaptive"):
        part = walk_cost(g, MODELS["node2vec_w"], None, sampler, WalkConfig()).agg(F.sum("steps").alias("steps"), F.sum("cpu_seconds").alias("cpu_seconds"), F.max("wall_seconds").alias("seconds"))
        part = settle(part.select(F.lit(sampler).alias("sampler"), "*", (F.col("cpu_seconds") / F.col("steps") * 1e6).alias("cpu_seconds_per_million")))  # one run at a time
        out = part if out is None else out.unionByName(part)
    return out


@query("x12_placement")
def x12_placement(s, d):
    """Rows a worker gets under hash and range placement of the starts."""
    starts = settle(one_per_node(load_graph(s, d, "g1")))
    out = None
    for how in ("hash", "range"):
        part = placed(starts, 4, how).groupBy(F.spark_partition_id().alias("part")).agg(F.count("*").alias("n")).withColumn("how", F.lit(how))
        out = part if out is None else out.unionByName(part)
    return out
