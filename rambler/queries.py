"""queries() of the walk engine, each with its DuckDB twin where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rambler import oracles as O
from rambler.functions import rng
from rambler.functions.measures import law_fit
from rambler.functions.store import settle
from rambler.operators import samplers as S
from rambler.operators.graph import adjacency_chunks
from rambler.operators.walk import WalkConfig, random_walks
from rambler.plans import program as P
from rambler.sqlapi import register
from rambler.sources.catalog import GRAPHS, listed, load_graph, table, with_edge_uniform

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}

MODELS = {
    "static": P.static_walk(), "node2vec_w": P.return_inout(), "node2vec_u": P.return_inout(weighted=False), "metapath_w": P.meta_path(), "metapath_u": P.meta_path(weighted=False),
    "sorank_w": P.second_order_rank(), "sorank_u": P.second_order_rank(weighted=False), "brand": P.WeightProgram("brand", "CASE WHEN dst % 5 = cur % 5 THEN 3 ELSE 1 END"),
    "square": P.WeightProgram("square", "(1 - h) * (1 - h)", weighted=False),
}


def query(name: str, sql: str | None = None):
    def register(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return register


# Graphs -----------------------------------------------------------------------------------------------------------------
for _g in GRAPHS:
    _h = "round(h, 6)" if _g not in ("g8",) else "round(h, 4)"
    query(f"{_g}_edges", f"SELECT src, idx, dst, {_h} AS h, label FROM ({O.edges(_g)})")(lambda s, d, g=_g: load_graph(s, d, g).edges.select("src", "idx", "dst", F.round("h", 4 if g == "g8" else 6).alias("h"), "label"))


@query("entry", O.walk("g1", "node2vec_w", "adaptive", 5))
def flagship(spark, d):
    """Adaptive second-order walks over the co-purchase graph."""
    return random_walks(load_graph(spark, d, "g1").stored(), MODELS["node2vec_w"], sampler="adaptive", config=WalkConfig(steps=5))


# Walks ------------------------------------------------------------------------------------------------------------------
def _walk(name, graph, model, sampler="keys", steps=5, mode="superstep", oracle=True, starts=None, starts_sql=None, options=None, **how):
    sql = O.walk(graph, model, sampler, steps, **({"starts": starts_sql} if starts_sql else {}), **how) if oracle else None

    @query(name, sql)
    def run(spark, d):
        g = load_graph(spark, d, graph, **how)
        g = S.kept_for(g, MODELS[model], True) if mode == "superstep" and "jump" in (sampler, (options or {}).get("reservoir")) else g.stored()
        return random_walks(g, MODELS[model], starts(spark, d, g) if starts else None, sampler, WalkConfig(steps=steps, mode=mode, sampler_options=options or {}))


_walk("walk_static_key", "g1", "static")
_walk("walk_node2vec_w", "g1", "node2vec_w", mode="replicated")
_walk("walk_node2vec_u", "g1", "node2vec_u")
_walk("walk_metapath_w", "g2", "metapath_w", labels=True)
_walk("walk_metapath_u", "g2", "metapath_u", mode="replicated", labels=True)
_walk("walk_sorank_w", "g3", "sorank_w", mode="replicated", steps=3)
_walk("walk_sorank_u", "g3", "sorank_u", steps=3)
_walk("walk_node2vec_reject", "g1", "node2vec_w", "rejection_bound", steps=3)
_walk("walk_node2vec_adaptive", "g1", "node2vec_w", "adaptive", steps=3)
_walk("walk_node2vec_adaptive_replicated", "g1", "node2vec_w", "adaptive", mode="replicated")
_walk("walk_its", "g9", "node2vec_w", "inverse")
_walk("walk_its_replicated", "g3", "static", "inverse", mode="replicated", steps=3)
_walk("walk_reservoir_prefix", "g9", "node2vec_w", "prefix")
_walk("walk_reservoir_prefix_replicated", "g9", "node2vec_w", "prefix", mode="replicated")
_walk("walk_alias", "g9", "node2vec_w", "alias", oracle=False)
_walk("walk_jump", "g2", "node2vec_w", "jump", steps=3, oracle=False)
_walk("walk_jump_replicated", "g2", "node2vec_w", "jump", steps=3, mode="replicated", oracle=False)
_walk("walk_jump_shared", "g4", "node2vec_w", "jump_shared", steps=3, mode="replicated", oracle=False)
_walk("walk_adaptive_jump", "g2", "node2vec_w", "adaptive", steps=3, oracle=False, options={"reservoir": "jump"})
_walk("walk_adaptive_jump_replicated", "g2", "node2vec_w", "adaptive", steps=3, mode="replicated", oracle=False, options={"reservoir": "jump"})
_walk("walk_int8", "g1", "node2vec_w", mode="replicated", weights="int8")
_walk("walk_typed_star", "g10", "metapath_u", starts=lambda s, d, g: table(s, d, "region").select((F.col("r_regionkey").cast("long") + (6 << 40)).alias("start")), starts_sql=f"SELECT r_regionkey::BIGINT + {O.T['REGION']} AS start FROM region")
_walk("walk_custom_program", "g1", "brand", mode="replicated")
_walk("walk_square_reject", "g3", "square", "rejection_bound", steps=3, weights="pareto", alpha=1.5)
_walk("walk_square_adaptive", "g3", "square", "adaptive", steps=3, mode="replicated", weights="pareto", alpha=1.5)
_walk("walk_power_law_graph", "g5", "node2vec_w", mode="replicated")


# Single steps -----------------------------------------------------------------------------------------------------------
def second_states(g, model, seed: int = 42) -> DataFrame:
    """Walkers after a first step by keys from every node: (walk_id, step 1, prev, cur)."""
    start = g.node_stats.select(F.col("src").alias("walk_id"), F.lit(0).alias("step"), F.lit(None).cast("long").alias("prev"), F.col("src").alias("cur"))
    moved = start.join(S.key_step(start, g, model, seed), "walk_id")
    return settle(moved.select("walk_id", F.lit(1).alias("step"), F.col("cur").alias("prev"), F.col("next").alias("cur")))


def _step(name, graph, model, sampler, oracle=True, sampler_sql=None, hubs=False, **options):
    """hubs: the graph has some at size, so it is packed before anything else is made of it."""

    @query(name, O.step(graph, model, sampler_sql or sampler) if oracle else None)
    def run(spark, d):
        g = load_graph(spark, d, graph)
        g = S.kept_for(g, MODELS[model]) if hubs else g.stored()
        return S.STEPS[sampler](second_states(g, MODELS[model]), g, MODELS[model], 42, **options).select("walk_id", "next")


_step("step_reservoir_key", "g1", "node2vec_w", "keys")
_step("step_reservoir_prefix", "g3", "node2vec_w", "prefix")
_step("step_its", "g3", "node2vec_w", "inverse")
_step("step_reject_bound", "g3", "node2vec_w", "rejection_bound")
_step("step_reject_constant_bound", "g3", "node2vec_u", "rejection_bound")
_step("step_reject_exact", "g3", "node2vec_w", "rejection_exact")
_step("step_adaptive", "g3", "node2vec_w", "adaptive")
_step("step_alias", "g3", "node2vec_w", "alias", oracle=False)
_step("step_reservoir_jump", "g4", "node2vec_w", "jump", oracle=False)
for _kind, _options in {"random": {}, "degree": {"threshold": 100}, "rejection": {}, "reservoir": {}, "exact": {}}.items():
    _step(f"step_select_{_kind}", "g4", "node2vec_w", "adaptive", sampler_sql=f"adaptive_{_kind}", hubs=True, kind=_kind, **_options)


# Exact laws, bounds, estimates and selection ----------------------------------------------------------------------------
def all_states(g) -> DataFrame:
    """Every (prev, cur) that a walker can be in at its second step."""
    return g.edges.select(F.col("src").alias("prev"), F.col("dst").alias("cur")).distinct().withColumn("step", F.lit(1))


for _name, _graph, _model in (("exact_probs_g9_static", "g9", "static"), ("exact_probs_g9_node2vec", "g9", "node2vec_w"), ("exact_probs_g9_node2vec_u", "g9", "node2vec_u"), ("exact_probs_g9_sorank", "g9", "sorank_w"), ("exact_probs_g10_metapath", "g10", "metapath_w")):
    _sql = f"""WITH {O.with_graph(_graph)}, s AS (SELECT row_number() OVER () AS walk_id, 1 AS step, prev, cur FROM (SELECT DISTINCT src AS prev, dst AS cur FROM e)),
c AS ({O.candidates('s', _model)}) SELECT prev, cur, step, dst, round(w, 6) AS w, round(w / sum(w) OVER (PARTITION BY prev, cur), 6) AS p FROM c WHERE w > 0"""
    query(_name, _sql)(lambda s, d, g=_graph, m=_model: (lambda graph: S.transition_probabilities(graph, MODELS[m], all_states(graph)))(load_graph(s, d, g).stored()).select("prev", "cur", "step", "dst", F.round("w", 6).alias("w"), F.round("p", 6).alias("p")))


def node_estimates(g, model) -> DataFrame:
    """A row for each node (as a walker's first step sees it): its statistics, bound and sum estimate."""
    a = model.analysis
    stats = g.node_stats.withColumnRenamed("deg", "deg_cur").withColumn("deg_prev", F.lit(None).cast("long"))
    return stats.withColumn("bound", F.expr(a.bound_sql)).withColumn("est_sum", F.expr(a.sum_sql))


_STATS = "WITH e AS MATERIALIZED ({e}), g AS ({s})"


def _stats_sql(graph, **how):
    return _STATS.format(e=O.edges(graph, **how), s=O.stats("SELECT * FROM e"))


query("node_stats", f"{_stats_sql('g1')} SELECT src, deg, round(h_max, 6) AS h_max, round(h_min, 6) AS h_min, round(h_sum, 6) AS h_sum FROM g")(
    lambda s, d: load_graph(s, d, "g1").node_stats.select("src", "deg", *[F.round(c, 6).alias(c) for c in ("h_max", "h_min", "h_sum")]))
query("label_stats", f"WITH e AS ({O.edges('g10')}) SELECT src, label, count(*) AS n, max(h) AS h_max, sum(h) AS h_sum FROM e GROUP BY src, label")(lambda s, d: load_graph(s, d, "g10").label_stats)
query("degree_histogram", f"{_stats_sql('g5')} SELECT CAST(floor(log2(deg)) AS BIGINT) AS bin, count(*) AS n FROM g GROUP BY 1")(
    lambda s, d: load_graph(s, d, "g5").node_stats.groupBy(F.floor(F.log2("deg")).alias("bin")).agg(F.count("*").alias("n")))
query("weight_bounds", f"{_stats_sql('g1')} SELECT src, round(2 * h_max, 6) AS bound FROM g")(lambda s, d: node_estimates(load_graph(s, d, "g1"), MODELS["node2vec_w"]).select("src", F.round("bound", 6).alias("bound")))
query("weight_sum_estimates", f"{_stats_sql('g1')} SELECT src, round({O.TOTAL['node2vec_w']}, 6) AS est_sum FROM g")(lambda s, d: node_estimates(load_graph(s, d, "g1"), MODELS["node2vec_w"]).select("src", F.round("est_sum", 6).alias("est_sum")))
for _kind, _test in (("choice", f"2.0 * (2 * h_max) < {O.TOTAL['node2vec_w']}"), ("degree", "deg >= 100")):
    query(f"selector_{_kind}", f"{_stats_sql('g4')} SELECT src, {_test} AS rejects FROM g")(
        lambda s, d, k=_kind: node_estimates(load_graph(s, d, "g4"), MODELS["node2vec_w"]).withColumn("walk_id", F.col("src")).withColumn("step", F.lit(0)).select("src", S.prefers_rejection({"choice": "cost"}.get(k, k), MODELS["node2vec_w"], 42, 2.0, 100).alias("rejects")))
query("sampler_costs", f"{_stats_sql('g4')} SELECT src, deg::DOUBLE AS cost_reservoir, round(2.0::DOUBLE * deg * (2 * h_max) / ({O.TOTAL['node2vec_w']}), 6) AS cost_rejection FROM g")(
    lambda s, d: node_estimates(load_graph(s, d, "g4"), MODELS["node2vec_w"]).withColumns(S.step_costs()).select("src", "cost_reservoir", F.round("cost_rejection", 6).alias("cost_rejection")))
query("selector_random", f"{_stats_sql('g4')} SELECT src, {O.rng.duck_uniform(42, 'src', '0', O.rng.COIN, '0')} < 0.5 AS rejects FROM g")(
    lambda s, d: load_graph(s, d, "g4").node_stats.withColumn("walk_id", F.col("src")).withColumn("step", F.lit(0)).select("src", S.prefers_rejection("random", MODELS["node2vec_w"], 42).alias("rejects")))
query("expected_trials_exact", f"{_stats_sql('g5')} SELECT src, round(deg * h_max / h_sum, 6) AS trials FROM g")(lambda s, d: load_graph(s, d, "g5").node_stats.select("src", F.round(F.col("deg") * F.col("h_max") / F.col("h_sum"), 6).alias("trials")))
@query("expected_trials_bound", f"""WITH {O.with_graph('g9')}, s AS (SELECT row_number() OVER () AS walk_id, 1 AS step, prev, cur FROM (SELECT DISTINCT src AS prev, dst AS cur FROM e)),
c AS ({O.candidates('s', 'node2vec_w')}) SELECT prev, cur, round(any_value(deg) * 2 * any_value(h_max) / sum(w), 6) AS trials, round(2 * any_value(h_max) / max(w), 6) AS looseness FROM c JOIN g ON cur = src GROUP BY prev, cur""")
def expected_trials_bound(spark, d):
    """Expected trials under the derived bound, and how far it exceeds the true maximum."""
    g = load_graph(spark, d, "g9").stored()
    model = MODELS["node2vec_w"]
    true = S.transition_probabilities(g, model, all_states(g)).groupBy("prev", "cur").agg(F.max("w").alias("top"), F.sum("w").alias("whole"))
    both = S.attach_stats(true, g, True).withColumn("bound", F.expr(model.analysis.bound_sql))
    return both.select("prev", "cur", F.round(F.col("deg_cur") * F.col("bound") / F.col("whole"), 6).alias("trials"), F.round(F.col("bound") / F.col("top"), 6).alias("looseness"))


@query("bound_soundness", f"""WITH {O.with_graph('g3', weights='pareto', alpha=1.5)}, s AS (SELECT row_number() OVER () AS walk_id, 1 AS step, prev, cur FROM (SELECT DISTINCT src AS prev, dst AS cur FROM e)),
c AS ({O.candidates('s', 'square')}), t AS (SELECT cur, max(w) AS top FROM c WHERE w > 0 GROUP BY cur)
SELECT cur, round(top / {O.BOUND['square']}, 6) AS share, false AS exceeded FROM t JOIN g ON cur = src""")
def bound_soundness(spark, d):
    """The greatest weight of each node as a share of the derived bound, for a weight whose factors change their sign."""
    g = load_graph(spark, d, "g3", "pareto", 1.5).stored()
    found = S.bound_soundness(g, MODELS["square"], all_states(g)).select("cur", "top", "bound").distinct()
    return found.select("cur", F.round(F.col("top") / F.col("bound"), 6).alias("share"), (F.col("top") > F.col("bound")).alias("exceeded"))


@query("estimate_quality", f"""WITH {O.with_graph('g9')}, s AS (SELECT row_number() OVER () AS walk_id, 1 AS step, prev, cur FROM (SELECT DISTINCT src AS prev, dst AS cur FROM e)),
c AS ({O.candidates('s', 'node2vec_w')}), t AS (SELECT prev, cur, max(w) AS top, sum(w) AS whole FROM c GROUP BY prev, cur)
SELECT prev, cur, round({O.TOTAL['node2vec_w']} / whole, 6) AS sum_ratio, round(2 * h_max / top, 6) AS bound_ratio, (2.0 * (2 * h_max) < {O.TOTAL['node2vec_w']}) <> (2.0 * top < whole) AS regret FROM t JOIN g ON cur = src""")
def estimate_quality(spark, d):
    """Estimates against the truth, and whether the cost rule decides otherwise than hindsight would."""
    g = load_graph(spark, d, "g9").stored()
    model = MODELS["node2vec_w"]
    true = S.transition_probabilities(g, model, all_states(g)).groupBy("prev", "cur").agg(F.max("w").alias("top"), F.sum("w").alias("whole"))
    both = S.attach_stats(true, g, True).withColumn("bound", F.expr(model.analysis.bound_sql)).withColumn("est", F.expr(model.analysis.sum_sql))
    regret = (2.0 * F.col("bound") < F.col("est")) != (2.0 * F.col("top") < F.col("whole"))
    return both.select("prev", "cur", F.round(F.col("est") / F.col("whole"), 6).alias("sum_ratio"), F.round(F.col("bound") / F.col("top"), 6).alias("bound_ratio"), regret.alias("regret"))


ALPHAS = (1.0, 1.5, 2.0, 2.5, 3.0, 4.0)
query("selection_ratio_alpha", " UNION ALL ".join(f"SELECT {a}::DOUBLE AS alpha, rejects, count(*) AS n FROM ({_stats_sql('g1', weights='pareto', alpha=a)} SELECT 2.0 * (2 * h_max) < {O.TOTAL['node2vec_w']} AS rejects FROM g) GROUP BY rejects" for a in ALPHAS))(
    lambda s, d: selection_ratio(s, d))


def selection_ratio(spark, d, graph: str = "g1", ratio: float = 2.0) -> DataFrame:
    """How many nodes take which sampler, for each shape of power-law weights: all shapes' weights from one uniform an edge, in one pass."""
    edges = with_edge_uniform(listed(spark, d, graph), "u", rng.WEIGHT)
    shaped = edges.select("src", *[(F.pow("u", F.lit(-1.0 / a)) - 1).alias(f"h{k}") for k, a in enumerate(ALPHAS)])
    stats = [F.struct(F.lit(a).alias("alpha"), F.max(f"h{k}").alias("h_max"), F.min(f"h{k}").alias("h_min"), F.sum(f"h{k}").alias("h_sum")) for k, a in enumerate(ALPHAS)]
    nodes = shaped.groupBy("src").agg(F.count("*").alias("deg_cur"), F.array(*stats).alias("s")).select("src", "deg_cur", F.lit(None).cast("long").alias("deg_prev"), F.inline("s"))
    a = MODELS["node2vec_w"].analysis
    return nodes.select("alpha", (ratio * F.expr(a.bound_sql) < F.expr(a.sum_sql)).alias("rejects")).groupBy("alpha", "rejects").agg(F.count("*").alias("n"))


for _scheme, _alpha in (("uniform", None), ("pareto", 1.5), ("degree", None), ("int8", None)):
    query(f"ws_{_scheme}", f"SELECT src, dst, round(h, 6) AS h FROM ({O.edges('g3', _scheme, _alpha)})")(lambda s, d, w=_scheme, a=_alpha: load_graph(s, d, "g3", w, a).edges.select("src", "dst", F.round("h", 6).alias("h")))
query("ws_label", f"SELECT src, dst, label FROM ({O.edges('g3', labels=True)})")(lambda s, d: load_graph(s, d, "g3", labels=True).edges.select("src", "dst", "label"))


def _cv_sql(g):
    return f"""SELECT '{g}' AS graph, CAST(floor(cv / 5) AS BIGINT) AS bin, count(*) AS n FROM (WITH {O.with_graph(g)}, s AS (SELECT row_number() OVER () AS walk_id, 1 AS step, prev, cur FROM (SELECT DISTINCT src AS prev, dst AS cur FROM e)),
c AS ({O.candidates('s', 'node2vec_w')}), t AS (SELECT prev, cur, sum(w) AS whole FROM c GROUP BY prev, cur) SELECT cur, round(100 * stddev_pop(whole) / avg(whole), 6) + 1e-9 AS cv FROM t GROUP BY cur) GROUP BY 2"""


@query("weight_cv_hist", f"{_cv_sql('g4')} UNION ALL {_cv_sql('g6')}")
def weight_cv_hist(spark, d):
    """Variation of a node's weight sum over the states it can be met in, in bins of 5 per cent, on a graph with hubs and a sparse one."""
    out = None
    for name in ("g4", "g6"):
        g = load_graph(spark, d, name).stored()
        whole = S.weight_totals(settle(all_states(g).select("prev", "cur")), g, MODELS["node2vec_w"]).select("cur", F.col("w_sum").alias("whole"))
        cv = whole.groupBy("cur").agg((F.round(100 * F.stddev_pop("whole") / F.avg("whole"), 6) + 1e-9).alias("cv"))
        part = cv.groupBy(F.lit(name).alias("graph"), F.floor(F.col("cv") / 5).alias("bin")).agg(F.count("*").alias("n"))
        out = part if out is None else out.unionByName(part)
    return out


@query("program_analysis", None)
def program_analysis(spark, d):
    """Branches of all models as the analyzer sees them, each with the number of edges that take it, over all second steps of walks between nations (labels drawn)."""
    g = load_graph(spark, d, "g9", labels=True).stored()
    rows = [(m.name, m.weighted, *b, m.analysis.flag, m.analysis.bound_sql, m.analysis.sum_sql) for m in MODELS.values() for b in m.analysis.rows()]
    ways = S.linked_flag(all_states(g).join(g.edges.withColumnRenamed("src", "cur"), "cur"), g)
    guards = list(dict.fromkeys(r[3] for r in rows))
    taken = ways.agg(F.array(*[F.struct(F.lit(x).alias("guard"), F.count_if(F.expr(x)).alias("n")) for x in guards]).alias("t")).select(F.inline("t"))
    seen = spark.createDataFrame(rows, "program string, weighted boolean, branch_id int, guard string, value string, deps array<string>, flag string, program_flag string, bound string, sum string")
    return seen.join(taken, "guard").select(*seen.columns, "n")


@query("edge_index", f"SELECT src, idx, dst FROM ({O.edges('g3')})")
def edge_index(spark, d):
    return load_graph(spark, d, "g3").edges.select("src", "idx", "dst")


@query("adj_chunks", f"SELECT src, CAST(idx // 64 AS INTEGER) AS chunk, count(*) AS n, string_agg(dst, ',' ORDER BY idx) AS dsts FROM ({O.edges('g3')}) GROUP BY 1, 2")
def adj_chunks(spark, d):
    return adjacency_chunks(load_graph(spark, d, "g3").edges, 64).select("src", "chunk", F.size("dst").cast("long").alias("n"), F.array_join(F.transform("dst", lambda x: x.cast("string")), ",").alias("dsts"))


_DRAWS = 200


@query("law_fit", f"""WITH {O.with_graph('g9')}, s0 AS MATERIALIZED (SELECT src * {_DRAWS} + i AS walk_id, 0 AS step, NULL::BIGINT AS prev, src AS cur FROM g, unnest(range({_DRAWS})) x(i)),
n AS (SELECT cur, next AS dst, count(*) AS n FROM ({O.pick('s0', 'static')}) GROUP BY 1, 2), l AS (SELECT src AS cur, dst, sum(h) / any_value(h_sum) AS p FROM e JOIN g USING (src) GROUP BY 1, 2)
SELECT cur, sum(coalesce(n, 0))::BIGINT AS draws, round(sum(pow(coalesce(n, 0) - {_DRAWS} * p, 2) / ({_DRAWS} * p)), 6) AS chi_square, count(*) - 1 AS degrees, round(sum(abs(coalesce(n, 0) / {_DRAWS} - p)) / 2, 6) AS total_variation, 0::BIGINT AS strays
FROM l LEFT JOIN n USING (cur, dst) GROUP BY cur""")
def law_fit_of_keys(spark, d):
    """Chi-square and total variation of 200 draws by keys from every node against the exact law."""
    g = load_graph(spark, d, "g9").stored()
    model, state = MODELS["static"], g.node_stats.select(F.lit(0).alias("step"), F.lit(None).cast("long").alias("prev"), F.col("src").alias("cur"))
    walkers = settle(state.select(F.explode(F.sequence(F.lit(0), F.lit(_DRAWS - 1))).alias("i"), "*").select((F.col("cur") * _DRAWS + F.col("i")).alias("walk_id"), "step", "prev", "cur"))
    drawn = walkers.join(S.key_step(walkers, g, model, 42), "walk_id").select("cur", F.col("next").alias("dst"))
    law = S.transition_probabilities(g, model, state).groupBy("cur", "dst").agg(F.sum("p").alias("p"))
    return law_fit(drawn, law, "cur").select("cur", "draws", F.round("chi_square", 6).alias("chi_square"), "degrees", F.round("total_variation", 6).alias("total_variation"), "strays")


@query("sql_walk_from", O.walk("g9", "node2vec_w", "keys", 3))
def sql_walk_from(spark, d):
    """Walks by the table function, from SQL."""
    register(spark, load_graph(spark, d, "g9").stored(), MODELS["node2vec_w"], prefix="nations_")
    return spark.sql("SELECT n.src AS walk_id, w.step, w.node FROM nations_node_stats n, LATERAL nations_walk_from(n.src, 3, 42) w")
