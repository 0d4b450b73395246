"""Walkers at hubs take their steps at the lists: the choices of all candidates, without a row for any of them."""

import pytest
from pyspark.sql import functions as F

from rambler.functions.store import settle
from rambler.operators import lists, walk
from rambler.operators import samplers as S
from rambler.operators.graph import WalkGraph
from rambler.operators.walk import WalkConfig, walk_log
from rambler.queries import MODELS


def at_hub(spark, n, walkers):
    """A hub of n neighbours, some of whom are neighbours of each other, and walkers that come to it, two of them from its heaviest edges."""
    rows = [(0, k, float(1 + k % 7)) for k in range(1, n + 1)] + [(0, 5, 90.0), (0, 9, 90.0)] + [(k, 0, 1.0) for k in range(1, walkers + 1)] + [(k, k + 1, 2.0) for k in range(1, walkers + 1)] + [(5, 9, 1.0), (9, 5, 1.0)]
    g = WalkGraph.from_edges(spark.createDataFrame(rows, "src long, dst long, h double")).stored()
    come = spark.range(1, walkers + 1).select(F.col("id").alias("walk_id"), F.lit(1).alias("step"), F.col("id").alias("prev"), F.lit(0).cast("long").alias("cur"))
    return g, settle(come.unionByName(spark.sql("SELECT 10000L + id AS walk_id, 1 AS step, 0L AS prev, id AS cur FROM range(1, 40)")))


def test_keys_at_a_hub_are_drawn_at_its_list(spark, monkeypatch):
    """Before, walkers whom the greatest uniforms didn't serve had a row for each candidate, and the others told what they drew as their reads."""
    g, walkers = at_hub(spark, 9000, 300)
    monkeypatch.setattr(lists, "CROWD", 100)
    rows = lambda df: sorted(map(tuple, df.select("walk_id", "next", "reads", "draws").collect()))
    got = S.key_step(walkers, g, MODELS["node2vec_w"], 42)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "CoGroups" in plan and "SortMergeJoin" not in plan.split("CoGroups")[0]
    assert rows(got) == rows(S.all_keys_step(walkers, g, MODELS["node2vec_w"], 42)) and got.count() == 339


def test_packed_lists_stay_where_they_are(spark):
    g, _ = at_hub(spark, 30, 10)
    plan = spark.range(3).selectExpr("cast(id as int) AS bucket").groupBy("bucket").cogroup(g.packed.groupBy("bucket")).applyInArrow(lambda a, b: b.select(["bucket"]), "bucket int")
    assert plan._jdf.queryExecution().executedPlan().toString().count("Exchange") == 1


@pytest.mark.parametrize("kind", ["degree", "rejection", "exact", "random"])
def test_selection_on_graphs_with_hubs_takes_its_steps_at_the_lists(spark, monkeypatch, kind):
    """Before, trials and keys were rows that met all pairs of the graph."""
    g, walkers = at_hub(spark, 60, 30)
    ask = lambda: sorted(map(tuple, S.adaptive_step(walkers, g, MODELS["node2vec_w"], 42, kind, threshold=40, trials=2).select("walk_id", "next").collect()))
    monkeypatch.setattr(S, "HUB", 50)
    got = ask()
    assert "pairs" not in g.__dict__
    monkeypatch.setattr(S, "HUB", 10**9)
    assert got == ask() and len(got) == 60


def test_adaptive_walks_with_jumps_count_the_same_in_both_modes(spark):
    """Before, supersteps left out the failed trials of walkers that go on to the reservoir, and trials met all pairs of the graph."""
    g, _ = at_hub(spark, 40, 30)
    options = {"reservoir": "jump", "kind": "degree", "threshold": 20}
    both = [sorted(map(tuple, walk_log(g, MODELS["node2vec_w"], None, "adaptive", WalkConfig(steps=3, mode=m, trials=1, rounds=1, sampler_options=options)).select("walk_id", "step", "node", "reads", "draws").collect())) for m in ("superstep", "replicated")]
    assert both[0] == both[1] and len(both[0]) > 60 and "pairs" not in g.__dict__


@pytest.mark.parametrize("sampler", ["keys", "prefix", "adaptive"])
def test_logged_walks_of_large_graphs_are_those_of_the_replicated_mode(spark, monkeypatch, sampler):
    """Before, each step of a graph too large to replicate had a row for every candidate, and met all pairs."""
    g, _ = at_hub(spark, 40, 30)
    ask = lambda: sorted(map(tuple, walk_log(g, MODELS["node2vec_w"], None, sampler, WalkConfig(steps=2, mode="replicated")).select("walk_id", "step", "node", "reads", "draws").collect()))
    want = ask()
    monkeypatch.setattr(S, "LIST_EDGES", 10)
    monkeypatch.setattr(walk, "REPLICATED_EDGES", 10)
    assert ask() == want and "pairs" not in g.__dict__ and "packed" in g.__dict__
