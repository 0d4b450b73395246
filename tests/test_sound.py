"""Bounds that hold for any sign, walks without broadcasts, and what is computed once."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from rambler.operators import samplers as S
from rambler.operators.graph import WalkGraph
from rambler.operators.walk import REPLICATED, WalkConfig, profile_ratio, random_walks
from rambler.plans.program import WeightProgram, return_inout

SQUARE = WeightProgram("square", "(1 - h) * (1 - h)", weighted=False)


def graph(spark, rows):
    return WalkGraph.from_edges(spark.createDataFrame(rows, "src long, dst long, h double")).stored()


@pytest.mark.parametrize("mode", ["replicated", "superstep"])
@pytest.mark.parametrize("sampler", ["keys", "rejection_bound", "adaptive"])
def test_law_of_a_weight_whose_factors_change_sign(spark, sampler, mode):
    """Edges of h = 0 and 5 have weights 1 and 16: the bound has to cover the product of the two lows."""
    g = graph(spark, [(0, 1, 0.0), (0, 2, 5.0)])
    starts = spark.range(4000).select(F.col("id").alias("walk_id"), F.lit(0).cast("long").alias("start"))
    rows = random_walks(g, SQUARE, starts, sampler, WalkConfig(steps=1, mode=mode, sampler_options={"ratio": 0.1} if sampler == "adaptive" else {})).where("step = 1")
    n = dict(rows.groupBy("node").count().collect())
    assert sum(n.values()) == 4000
    want = {1: 4000 / 17, 2: 4000 * 16 / 17}
    assert sum((n.get(k, 0) - v) ** 2 / v for k, v in want.items()) < 15.1  # chi-square, 1 degree, 1e-4


def test_bounds_hold_on_random_expressions(spark):
    """Every bound that is derived is at least the greatest weight, whatever the signs; what can't be bounded says so."""
    rng = np.random.default_rng(3)
    texts = ["(1 - h) * (2 - h)", "(h - 3) * (1 - h) + 20", "(h - 2) / deg_cur", "(1 - h) * (1 - h) * (2 - h) + 90", "greatest(1 - h, h - 2)", "(3 - h) / (1 + h)", "-2 * (h - 4)", "exp(1 - h)", "sqrt(h) * (2 - h)", "(h - 1) / (0 - 2)"]
    for text in texts:
        program = WeightProgram("t", text, weighted=False)
        for _ in range(40):
            h = rng.uniform(0, 5, 4) if rng.random() < 0.8 else np.array([0.0, rng.uniform(0, 5)])
            env = {"h_min": h.min(), "h_max": h.max(), "h_sum": h.sum(), "deg_cur": float(len(h))}
            top = max(float(program.full.evaluate({"h": x, "deg_cur": float(len(h))})) for x in h)
            assert float(program.analysis.bound.evaluate(env)) >= top - 1e-9, text
    for text in ("1 / h", "1 / (h - 2)", "ln(h)", "sqrt(h - 1)", "h % 2"):
        analysis = WeightProgram("t", text, weighted=False).analysis
        assert analysis.bound is None and analysis.warnings
    found = S.bound_soundness(graph(spark, [(0, 1, 0.0), (0, 2, 5.0), (1, 0, 0.5)]), SQUARE, spark.createDataFrame([(9, 0, 1), (9, 1, 1)], "prev long, cur long, step int"))
    assert found.where("top > bound").count() == 0 and found.count() == 2


def test_supersteps_without_broadcasts(spark):
    """All samplers run where statistics and pairs outgrow a broadcast, and give the walks that they give with broadcasts."""
    g = graph(spark, [(a, b, 1.0 + (a * b) % 3) for a in range(8) for b in range(8) if a != b and (a + b) % 3])
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    for sampler in sorted(REPLICATED):
        walk = lambda: sorted(map(tuple, random_walks(g, return_inout(), None, sampler, WalkConfig(steps=2, mode="superstep")).collect()))  # noqa: B023, E731
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        try:
            alone = walk()
        finally:
            spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
        assert alone and (sampler not in ("keys", "adaptive") or alone == walk()), sampler


def test_statistics_and_pairs_are_computed_once(spark):
    g = graph(spark, [(0, 1, 1.0), (1, 0, 2.0), (1, 2, 1.0)])
    for table in (g.node_stats, g.pairs, g.label_stats):
        plan = table._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in plan and "Scan parquet" in plan
    walkers = spark.createDataFrame([(0, 1, 0, 1)], "walk_id long, step int, prev long, cur long")
    plan = S.key_step(walkers, g, return_inout(), 42)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Scan parquet") == 2  # edges and pairs, once each


def test_profiled_ratio(spark):
    g = graph(spark, [(a, b, 1.0) for a in range(30) for b in range(30) if a != b])
    row = profile_ratio(g, return_inout()).collect()
    assert len(row) == 1 and row[0].ratio > 0 and row[0].trial_ns > 0
    assert profile_ratio(g, WeightProgram("t", "1 / h")).count() == 0
