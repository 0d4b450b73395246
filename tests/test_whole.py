"""Queries against brute force over whole tables: nothing is left out by a prefix or a choice of ids."""

import re
from collections import Counter
from datetime import datetime, timedelta

import pytest

from rambler import stream_queries, surround  # noqa: F401  (register their queries)
from rambler.operators.graph import WalkGraph
from rambler.operators.walk import WalkConfig, random_walks
from rambler.queries import MODELS, QUERIES
from rambler.sources.catalog import load_graph


@pytest.fixture(scope="module")
def sf(spark, tmp_path_factory):
    """Checkpoints go to a folder of their own."""
    spark.sparkContext.setCheckpointDir(str(tmp_path_factory.mktemp("checkpoints")))
    return tmp_path_factory.mktemp("tables")


def put(spark, sf, name, rows, schema):
    spark.createDataFrame(rows, schema).coalesce(1).write.mode("overwrite").parquet(f"{sf}/{name}.parquet")


def test_word_graph_holds_pairs_beyond_any_prefix(spark, sf):
    texts = [" ".join(f"w{(i * i) % 37}" for i in range(400)) + "\n\nTail  tail end", "a b\na b", "one", "", None]
    put(spark, sf, "documents", list(enumerate(texts)), "doc_id long, text string")
    split = [[w for w in re.split(r"[ \n]+", (t or "").lower()) if w] for t in texts]
    ids = {w: i for i, w in enumerate(sorted({w for ws in split for w in ws}))}
    pairs = Counter((ids[a], ids[b]) for ws in split for a, b in zip(ws, ws[1:]))
    got = {(r.src, r.dst): r.h for r in QUERIES["g5_edges"](spark, str(sf)).collect()}
    assert got == pairs and (ids["tail"], ids["end"]) in got
    degrees = Counter(a for a, _ in pairs)
    histogram = {r.bin: r.n for r in QUERIES["degree_histogram"](spark, str(sf)).collect()}
    assert histogram == Counter(n.bit_length() - 1 for n in degrees.values())
    trials = {r.src: r.trials for r in QUERIES["expected_trials_exact"](spark, str(sf)).collect()}
    for a, n in degrees.items():
        mine = [h for (s, _), h in pairs.items() if s == a]
        assert trials[a] == pytest.approx(n * max(mine) / sum(mine), abs=1e-6)
    walked = QUERIES["walk_power_law_graph"](spark, str(sf)).collect()
    steps = {(r.walk_id, r.step): r.node for r in walked}
    assert {r.walk_id for r in walked} == set(degrees)
    assert all((steps[w, k - 1], node) in pairs for (w, k), node in steps.items() if k)


def test_every_user_of_the_stream_gets_a_walk(spark, sf):
    start = datetime(2024, 1, 1)
    rows = [(i, (i * 7) % 11 if i < 100 else 11 + i % 13, start + timedelta(minutes=i), 1.0 + i % 5) for i in range(150)]
    put(spark, sf, "events", rows, "event_id long, user_id long, ts timestamp, value double")
    users = {u for _, u, _, _ in rows}
    got = sorted(map(tuple, QUERIES["stream_walk_queries"](spark, str(sf)).collect()))
    assert {w for w, k, node in got if k == 0 and w == node} == users == {w for w, _, _ in got}
    graph = load_graph(spark, str(sf), "g6").stored()
    starts = spark.createDataFrame([(u,) for u in users], "start long")
    assert got == sorted(map(tuple, random_walks(graph, MODELS["node2vec_w"], starts, "keys", WalkConfig(steps=3, mode="replicated")).collect()))


def test_links_of_every_two_hop_state(spark, sf):
    nations = 9
    put(spark, sf, "customer", [(n, n) for n in range(nations)], "c_custkey long, c_nationkey int")
    put(spark, sf, "supplier", [(n, n) for n in range(nations)], "s_suppkey long, s_nationkey int")
    put(spark, sf, "orders", [(n, n) for n in range(nations)], "o_orderkey long, o_custkey long")
    pairs = {(n, (n * k + 1) % nations) for n in range(nations) for k in (1, 3)}
    put(spark, sf, "lineitem", [(a, b, 1.0) for a, b in pairs], "l_orderkey long, l_suppkey long, l_extendedprice double")
    want = {(a, b, c): (a, c) in pairs for a, b in pairs for x, c in pairs if x == b}
    assert len({a for a, _, _ in want}) == nations and set(want.values()) == {True, False}
    got = QUERIES["linked_left"](spark, str(sf)).collect()
    assert len(got) == len(want) and {(r.prev, r.cur, r.dst): r.linked for r in got} == want
    semi = sorted(map(tuple, QUERIES["linked_semi"](spark, str(sf)).collect()))
    assert semi == sorted(k for k, linked in want.items() if linked)


def test_experiments_walk_all_steps_on_the_planned_graphs(spark, sf, monkeypatch):
    rows = [(n, (n * k + 1) % 9, float(n + k), 0) for n in range(9) for k in (1, 3)]
    small = WalkGraph.from_edges(spark.createDataFrame(rows, "src long, dst long, h double, label int")).stored()
    monkeypatch.setattr(surround, "load_graph", lambda *_: small)
    plan = {"x1_four_samplers": "g1 g2 g5 g8", "x3_power_law": "g1 g2 g5", "x4_degree_weights": "g1 g2 g5", "x5_skew_sensitivity": "g1 g5", "x7_selection_ablation": "g1 g2 g5", "x8_kernel_ablation": "g1 g5", "x14_low_precision": "g3"}
    for name in ("x1_four_samplers", "x5_skew_sensitivity"):
        got = QUERIES[name](spark, str(sf)).collect()
        assert {r.steps for r in got} == {9 * 80}, name
        assert {r.graph for r in got} == set(plan[name].split())
        if name == "x1_four_samplers":
            assert {r.sampler for r in got if r.model == "node2vec_w"} == {"inverse", "alias", "rejection_exact", "prefix"}
    asked, walked = [], []
    monkeypatch.setattr(surround, "load_graph", lambda s, d, name, *_: asked.append(name) or small)
    monkeypatch.setattr(surround, "walk_log", lambda g, m, starts, sampler, config: walked.append(config.steps) or spark.range(1).selectExpr("1 AS reads", "1 AS draws", "'x' AS mode"))
    for name in plan:
        asked.clear()
        QUERIES[name](spark, str(sf))
        assert set(asked) == set(plan[name].split()) and set(walked) == {80}


def test_alias_gives_the_same_walks_in_both_modes(spark):
    rows = [(n, (n * k + 1) % 9, float(n * k % 5), 0) for n in range(9) for k in (1, 2, 3, 5)]
    g = WalkGraph.from_edges(spark.createDataFrame(rows, "src long, dst long, h double, label int")).stored()
    walks = [sorted(map(tuple, random_walks(g, MODELS["node2vec_w"], None, "alias", WalkConfig(steps=4, mode=m)).collect())) for m in ("superstep", "replicated")]
    assert walks[0] == walks[1]
