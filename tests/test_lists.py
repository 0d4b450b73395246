"""Jumps where the lists are: the picks of jumps over all candidates."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from rambler.functions.store import settle
from rambler.operators import graph as graphs
from rambler.operators import lists, walk
from rambler.operators import samplers as S
from rambler.operators.graph import WalkGraph
from rambler.operators.walk import WalkConfig
from rambler.queries import MODELS, QUERIES


def graph(spark):
    """A hub of 300, chains with links back and across, zero weights, and parallel edges of two labels."""
    rows = [(0, k, float(k % 4), 0) for k in range(1, 301)] + [(k, 0, 1.0 + k % 3, 0) for k in range(1, 301)]
    rows += [(k, k % 300 + j, 2.0 + j, j % 2) for k in range(1, 301) for j in (1, 2, 7)] + [(k, k % 300 + 1, 0.5, 5) for k in range(1, 301, 2)]
    rows += [(k, k, 3.0, 0) for k in range(1, 301, 11)]
    return WalkGraph.from_edges(spark.createDataFrame(rows, "src long, dst long, h double, label int")).stored()


@pytest.mark.parametrize("model", ["node2vec_w", "node2vec_u", "static", "brand"])
def test_jumps_at_the_lists_pick_what_jumps_over_all_candidates_pick(spark, model, monkeypatch):
    monkeypatch.setattr(lists, "CROWD", 50)
    g, program = graph(spark), MODELS[model]
    e = g.edges.select("src", "dst").distinct()
    second = e.select(F.col("src").alias("prev"), F.col("dst").alias("cur")).withColumns({"walk_id": F.col("prev") * 1000 + F.col("cur"), "step": F.lit(1)})
    first = g.node_stats.select(F.lit(None).cast("long").alias("prev"), F.col("src").alias("cur"), (F.col("src") + 10**6).alias("walk_id"), F.lit(0).alias("step"))
    walkers = settle(second.unionByName(first).select("walk_id", "step", "prev", "cur"))
    for lane in (4096, 16):
        got = {r.walk_id: (r.next, r.reads, r.draws) for r in S.jump_step(walkers, g, program, 42, lane).collect()}
        edges = g.edges.select("src", "dst", "h", "label").toArrow()
        csr = walk.Csr(*(edges.column(c).to_numpy() for c in ("src", "dst", "h", "label")))
        monkeypatch.setattr(walk, "jump_lanes", lambda *a, shared, n=lane: S.jump_lanes(*a, n, shared))
        rows = walkers.collect()
        for step in (0, 1):
            mine = [r for r in rows if r.step == step and r.cur <= 300]  # the others are at dead ends
            cur, prev = np.array([r.cur for r in mine]), np.array([-1 if r.prev is None else r.prev for r in mine])
            edge, reads, draws, _ = walk.advance(csr, program, "jump", WalkConfig(), np.array([r.walk_id for r in mine]), csr.at(cur), prev, csr.at(prev), step)
            want = {r.walk_id: (int(csr.dst[k]), int(a), int(b)) for r, k, a, b in zip(mine, edge, reads, draws) if k >= 0}
            assert {k: v for k, v in got.items() if (k >= 10**6) == (step == 0)} == want


def test_no_row_for_each_candidate_leaves_the_lists(spark):
    """300 walkers at a hub of 300: 90,000 candidates were gathered, one list for each walker."""
    g = graph(spark)
    walkers = settle(spark.range(1, 301).select(F.col("id").alias("walk_id"), F.lit(1).alias("step"), F.col("id").alias("prev"), F.lit(0).cast("long").alias("cur")))
    got = S.jump_step(walkers, g, MODELS["node2vec_w"], 42)
    assert got.count() == 300 and "collect_list" not in got._jdf.queryExecution().optimizedPlan().toString()


def test_a_graph_packed_at_once_is_the_stored_graph(spark, monkeypatch):
    """Parallel edges merge (their h may be null), lists are in order, and a node's list may go over several rows."""
    rows = [(k % 7, (k * 5) % 23, None if k % 10 == 0 else float(k % 4), k % 2) for k in range(400)] + [(9, 1, None, 0), (9, 1, 2.0, 0), (8, 3, None, 0), (8, 3, None, 0), (2**41, 2**42, 1.0, 0)]
    given = WalkGraph.from_edges(spark.createDataFrame(rows, "src long, dst long, h double, label int"))
    kept, at_once = given.stored(), given.listed()
    none = lambda df: sorted(tuple(-1 if x is None or x != x else x for x in r) for r in df.collect())
    assert none(at_once.edges.select(kept.edges.columns)) == none(kept.edges) and at_once.size == kept.size
    plain = lambda g: sorted(map(tuple, g.node_stats.where("src <> 8").select("src", "deg", "h_max", "h_min", "h_sum").where("not isnan(h_sum)").collect()))
    assert plain(at_once) == [r for r in plain(kept) if r[0] in {x[0] for x in plain(at_once)}]
    monkeypatch.setattr(graphs, "PACKED_EDGES", 30)
    batch = pa.RecordBatch.from_pydict({"bucket": np.zeros(90, np.int32), "src": np.arange(90) // 45, "dst": np.arange(90)[::-1].copy(), "h": np.ones(90), "label": np.zeros(90, np.int32)})
    packed = pa.Table.from_batches(list(graphs._merge_and_pack([batch])))
    got = graphs._unpack(packed)
    assert packed.num_rows == 3 and got.column("src").to_pylist() == [0] * 45 + [1] * 45 and got.column("idx").to_pylist() == [*range(45)] * 2 and got.column("dst").to_pylist() == [*range(45, 90), *range(45)]
    stats = pa.Table.from_batches(list(graphs._stretch_stats(packed.to_batches())))
    assert list(zip(stats.column("src").to_pylist(), stats.column("deg").to_pylist())) == [(0, 30), (0, 15), (1, 15), (1, 30)]


def test_walks_by_jumps_pack_their_graph_at_once(spark, monkeypatch):
    monkeypatch.setattr(WalkGraph, "stored", lambda self: pytest.fail("edges were stored beside the lists"))
    assert QUERIES["walk_adaptive_jump"](spark, "/root/testdata/sf0.001").where("step = 3").count() > 0


def test_no_list_is_read_for_the_near_edges_of_a_first_step(spark, monkeypatch):
    g = graph(spark)
    monkeypatch.setattr(lists, "near_edges", lambda *_: pytest.fail("no walker has a previous node"))
    first = settle(g.node_stats.select(F.col("src").alias("walk_id"), F.lit(0).alias("step"), F.lit(None).cast("long").alias("prev"), F.col("src").alias("cur")))
    assert lists.list_keys(first, g, MODELS["node2vec_w"], 42).count() == g.largest[0]


@pytest.mark.parametrize("kind", ["degree", "rejection", "exact", "random"])
def test_selection_on_a_graph_with_hubs_packs_it_at_once(spark, tmp_path, monkeypatch, kind):
    """Some 300 customers, whose segments count as hubs: their edges aren't stored beside the lists, and choices are those on the stored graph."""
    spark.range(1, 301).selectExpr("id AS c_custkey", "cast(id % 5 AS int) AS c_nationkey", "concat('s', id % 3) AS c_mktsegment", "id % 17 - 3.0D AS c_acctbal").write.parquet(f"{tmp_path}/customer.parquet")
    whole = sorted(map(tuple, QUERIES[f"step_select_{kind}"](spark, str(tmp_path)).collect()))
    monkeypatch.setattr(S, "HUB", 50)
    monkeypatch.setattr(WalkGraph, "stored", lambda self: pytest.fail("edges were stored beside the lists"))
    assert whole == sorted(map(tuple, QUERIES[f"step_select_{kind}"](spark, str(tmp_path)).collect())) and len(whole) == 308


def test_drawn_weights_are_columns_of_a_large_table(spark, monkeypatch):
    from rambler.functions import rng
    from rambler.sources import catalog

    g, u = graph(spark), catalog.edge_uniform(42, rng.WEIGHT)
    want = {(r.src, r.dst, r.label): r.h for r in g.edges.select("src", "dst", "label", (1 + 4 * u).alias("h")).collect()}
    monkeypatch.setattr(catalog, "edge_uniform", lambda *_: pytest.fail("one expression for each edge's uniform"))
    got = catalog.apply_weights(g, "uniform").edges
    assert got.columns == g.edges.columns and {(r.src, r.dst, r.label): r.h for r in got.collect()} == want
