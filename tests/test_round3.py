"""What larger tables showed: frames over fractions of a second, graphs too large to replicate, and hubs."""

from datetime import datetime, timedelta

import numpy as np
import pytest
from pyspark.sql import functions as F

from rambler import stream_queries, surround  # noqa: F401  (register their queries)
from rambler.functions import rng
from rambler.functions.store import settle
from rambler.operators import samplers as S
from rambler.operators import walk
from rambler.operators.graph import WalkGraph
from rambler.operators.walk import WalkConfig, random_walks
from rambler.queries import MODELS, QUERIES
from rambler.sources import catalog


def put(spark, sf, name, rows, schema):
    spark.createDataFrame(rows, schema).coalesce(1).write.mode("overwrite").parquet(f"{sf}/{name}.parquet")


def test_frame_rounds_seconds_as_its_sql_does(spark, tmp_path):
    """Half a second goes to the even second, as DuckDB casts doubles; a floor gives other frames."""
    start = datetime(2024, 1, 1)
    at = [0.4, 0.5, 1.5, 3600.4, 3600.5, 3601.4, 3601.6, 7203.5]
    put(spark, tmp_path, "events", [(i, 7, start + timedelta(seconds=t)) for i, t in enumerate(at)], "event_id long, user_id long, ts timestamp")
    second = [round(t) for t in at]
    want = {i: sum(a - 3600 <= b <= a for b in second) for i, a in enumerate(second)}
    assert {r.event_id: r.n for r in QUERIES["value_range_frame"](spark, str(tmp_path)).collect()} == want


def small_graph(spark, n=12, stored=True):
    rows = [(a, (a * k + 1) % n, float(1 + (a * k) % 5), 0) for a in range(n) for k in (1, 3, 4)]
    g = WalkGraph.from_edges(spark.createDataFrame(rows, "src long, dst long, h double, label int"))
    return g.stored() if stored else g


@pytest.mark.parametrize("sampler", ["keys", "adaptive"])
def test_graphs_too_large_to_replicate_are_walked_all_the_same(spark, monkeypatch, sampler):
    g = small_graph(spark)
    ask = lambda: sorted(map(tuple, random_walks(g, MODELS["node2vec_w"], None, sampler, WalkConfig(steps=5, mode="replicated")).collect()))
    small = ask()
    monkeypatch.setattr(walk, "REPLICATED_EDGES", 10)
    assert ask() == small and len(small) == 12 * 6


@pytest.mark.parametrize("model", ["node2vec_w", "node2vec_u", "static", "brand"])
def test_weight_totals_equal_those_of_all_candidates(spark, monkeypatch, model):
    monkeypatch.setattr(S, "LONG", 1)
    g, program = small_graph(spark), MODELS[model]
    assert S.splits(program)
    states = g.edges.select(F.col("src").alias("prev"), F.col("dst").alias("cur")).distinct().withColumns({"step": F.lit(1), "walk_id": F.col("prev") * 100 + F.col("cur")})
    want = {(r.prev, r.cur): (r.a, r.b) for r in S.candidates(states, g, program).groupBy("prev", "cur").agg(F.sum("w").alias("a"), F.max("w").alias("b")).collect()}
    got = {(r.prev, r.cur): (r.w_sum, r.w_max) for r in S.weight_totals(settle(states.select("prev", "cur")), g, program).collect()}
    assert {k: v[0] for k, v in got.items()} == pytest.approx({k: v[0] for k, v in want.items()})
    assert all(v[1] in (None, want[k][1]) for k, v in got.items()) and any(v[1] for v in got.values())
    assert {r.walk_id: r.w_max for r in S.true_weights(settle(states), g, program).collect()} == {a * 100 + b: v[1] for (a, b), v in want.items()}


def test_programs_that_see_more_of_the_previous_node_do_not_split():
    assert not S.splits(MODELS["sorank_w"]) and not S.splits(MODELS["metapath_w"])


def test_the_least_keys_of_a_hub_are_found_without_drawing_all(spark, monkeypatch):
    """A list of 9,000 neighbours: the same choices as by all keys, most walkers served by the greatest uniforms."""
    n = 9000
    rows = [(0, k, float(1 + k % 7)) for k in range(1, n + 1)] + [(k, 0, 1.0) for k in range(1, 301)] + [(k, k + 1, 2.0) for k in range(1, 301)]
    g = WalkGraph.from_edges(spark.createDataFrame(rows, "src long, dst long, h double")).stored()
    walkers = settle(spark.range(1, 301).select(F.col("id").alias("walk_id"), F.lit(1).alias("step"), F.col("id").alias("prev"), F.lit(0).cast("long").alias("cur")))
    program = MODELS["node2vec_w"]
    want = {r.walk_id: r.next for r in S.all_keys_step(walkers, g, program, 42).collect()}
    served, rest = S.hub_step(walkers, g, program, 42)
    assert served.count() > 280 and served.count() + rest.count() == 300 and served.agg(F.max("reads")).first()[0] < 200
    got = {r.walk_id: r.next for r in S.key_step(walkers, g, program, 42).collect()}
    assert got == want and len(want) == 300


def test_words_of_the_greatest_uniforms():
    state = rng.states(42, np.arange(20) + (3 << 40), np.ones(20, int), rng.KEY)
    size = np.array([8192, 30_001] * 10)
    owner, item = rng.high_items(state, size, 8)
    want = {(k, int(i)) for k in range(20) for i in np.flatnonzero(rng.uniforms((np.repeat(state[0][k], size[k]), np.repeat(state[1][k], size[k])), np.arange(size[k])) >= 1 - 2.0**-8)}
    assert set(zip(owner.tolist(), item.tolist())) == want and len(owner) == len(want)


def test_selection_ratio_reads_the_edges_once(spark, tmp_path):
    """One scan pair of the lines for all shapes (there were six), and the same uniforms as `edge_uniform` gives."""
    put(spark, tmp_path, "lineitem", [(o, (o * k) % 11, 1.0 + k) for o in range(40) for k in (1, 2, 5)], "l_orderkey long, l_partkey long, l_quantity double")
    got = QUERIES["selection_ratio_alpha"](spark, str(tmp_path))
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("parquet") == 2
    g = catalog.load_graph(spark, str(tmp_path), "g1")
    assert [r[0] for r in got.groupBy("alpha").agg(F.sum("n")).select("sum(n)").collect()] == [g.node_stats.count()] * 6
    edges = catalog.with_edge_uniform(g.edges.withColumn("dst", F.col("dst") + (5 << 40)), "u", rng.WEIGHT)
    assert edges.where(F.col("u") == catalog.edge_uniform(42, rng.WEIGHT)).count() == g.edges.count() > 0


def test_program_analysis_counts_the_edges_of_each_branch(spark, tmp_path):
    put(spark, tmp_path, "customer", [(n, n) for n in range(6)], "c_custkey long, c_nationkey int")
    put(spark, tmp_path, "supplier", [(n, n) for n in range(6)], "s_suppkey long, s_nationkey int")
    put(spark, tmp_path, "orders", [(n, n) for n in range(6)], "o_orderkey long, o_custkey long")
    pairs = {(n, (n + k) % 6) for n in range(6) for k in (1, 2)} | {(1, 0)}
    put(spark, tmp_path, "lineitem", [(a, b, 1.0) for a, b in pairs], "l_orderkey long, l_suppkey long, l_extendedprice double")
    ways = [(p, c, x) for p, c in pairs for y, x in pairs if y == c]
    got = {(r.program, r.weighted, r.branch_id): r.n for r in QUERIES["program_analysis"](spark, str(tmp_path)).collect()}
    back, linked = sum(p == x for p, _, x in ways), sum(p != x and (p, x) in pairs for p, _, x in ways)
    assert len(got) == 26 and back and linked
    for weighted in (True, False):
        assert [got["return_inout", weighted, k] for k in range(3)] == [back, linked, len(ways) - back - linked]
    assert got["static", True, 0] == len(ways) and sum(got["meta_path", True, k] for k in range(6)) == len(ways)
    assert got["brand", True, 0] == sum(x % 5 == c % 5 for _, c, x in ways)


def test_hubs_of_the_replicated_mode_take_the_edges_that_all_keys_give(monkeypatch):
    n = 9000
    src = np.concatenate([np.zeros(n, int), np.arange(1, 301), np.arange(1, 301)])
    dst = np.concatenate([np.arange(1, n + 1), np.zeros(300, int), np.arange(2, 302)])
    h = np.concatenate([np.where(np.arange(n) % 100 == 0, 500.0, 1 + np.arange(n) % 3), np.ones(600)])
    csr, program = walk.Csr(src, dst, h, np.zeros(len(src), int)), MODELS["node2vec_w"]
    who = np.arange(1, 301)
    state = who, np.zeros(300, np.int64), who, csr.at(who), 1
    want = walk.advance(csr, program, "keys", WalkConfig(), *state)[0]
    assert (walk.advance(csr, program, "keys", WalkConfig(), *state, counted=False)[0] == want).all()
    served = walk._hub_keys(csr, program, 42, *state)
    assert (served >= 0).sum() > 270 and (served[served >= 0] == want[served >= 0]).all()
