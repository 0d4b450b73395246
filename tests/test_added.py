"""Streams in append mode, transition edges over several files, the fit of draws to a law, walks from SQL, selection with jumps, and the link test."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from rambler.functions.measures import law_fit
from rambler.operators.graph import WalkGraph
from rambler.operators.walk import Csr, WalkConfig, random_walks, walk_cost
from rambler.plans import program as P
from rambler.sqlapi import register
from rambler.streaming import streams as T

SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double"


def files(spark, tmp_path, *batches):
    """A stream that reads the given batches one after another."""
    for k, rows in enumerate(batches):
        table = spark.createDataFrame(rows, "event_id long, ts string, user_id long, event_type string, value double").withColumn("ts", F.col("ts").cast("timestamp"))
        table.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    return spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in")).withWatermark("ts", T.LATE)


def test_append_drops_late_rows_and_keeps_closed_windows(spark, tmp_path):
    day1 = [(1, "2024-01-01 10:00:00", 7, "view", 1.0), (2, "2024-01-01 11:00:00", 7, "view", 2.0)]
    day2 = [(3, "2024-01-02 12:00:00", 7, "view", 4.0)]
    more = [(6, "2024-01-02 12:30:00", 7, "view", 32.0)]  # Spark tests lateness by the watermark of the batch before
    late = [(4, "2024-01-01 12:00:00", 7, "view", 8.0), (5, "2024-01-02 13:00:00", 7, "view", 16.0)]
    got = T.run(T.stream_node_stats(files(spark, tmp_path, day1, day2, more, late)), "append").collect()
    assert [(r.n, r.total) for r in got] == [(2, 3.0)]  # event 4 comes after its window has closed; the second day is still open


def test_transitions_over_batches(spark, tmp_path):
    one = [(1, "2024-01-01 10:00:00", 7, "view", 1.0), (2, "2024-01-01 10:00:00", 7, "click", 1.0), (3, "2024-01-01 09:00:00", 8, "view", 1.0)]
    two = [(4, "2024-01-01 10:05:00", 7, "purchase", 1.0), (5, "2024-01-01 09:30:00", 7, "late", 1.0), (6, "2024-01-01 09:30:00", 8, "view", 1.0)]
    got = {tuple(r) for r in T.transition_edges(files(spark, tmp_path, one, two)).select("event_id", "user_id", "came_from", "event_type").collect()}
    assert got == {(2, 7, "view", "click"), (4, 7, "click", "purchase"), (6, 8, "view", "view")}


def test_law_fit(spark):
    law = spark.createDataFrame([(0, 1, 0.5), (0, 2, 0.5), (1, 1, 1.0)], "cur long, dst long, p double")
    seen = spark.createDataFrame([(0, 1)] * 3 + [(0, 2)] + [(2, 9)], "cur long, dst long")
    got = {r.cur: (r.draws, r.chi_square, r.degrees, r.total_variation, r.strays) for r in law_fit(seen, law, "cur").collect()}
    assert got == {0: (4, 1.0, 1, 0.25, 0), 1: (0, 0.0, 0, None, 0), 2: (1, 0.0, -1, 0.5, 1)}


EDGES = [(a, b, 1.0 + (a * b) % 5, 0) for a in range(8) for b in range(8) if a != b]


def test_sql_walks_and_selection_with_jumps(spark):
    g = WalkGraph.from_edges(spark.createDataFrame(EDGES, "src long, dst long, h double, label int")).stored()
    rows = lambda df: {tuple(r) for r in df.select("walk_id", "step", "node").collect()}
    register(spark, g, P.return_inout(), prefix="t_")
    by_sql = spark.sql("SELECT s.src AS walk_id, w.* FROM t_node_stats s, LATERAL t_walk_from(s.src, 4, 42) w")
    assert rows(by_sql) == rows(random_walks(g, P.return_inout(), None, "keys", WalkConfig(steps=4)))
    assert spark.sql("SELECT * FROM t_walk_from(CAST(NULL AS BIGINT), 4, 42)").count() == 0
    both = [rows(random_walks(g, P.return_inout(), None, "adaptive", WalkConfig(steps=2, mode=m, sampler_options={"reservoir": "jump", "ratio": 9.0}))) for m in ("superstep", "replicated")]
    assert both[0] == both[1] and len(both[0]) == 24
    cost = walk_cost(g, P.return_inout(), None, "adaptive", WalkConfig(steps=4, partitions=2)).agg(F.sum("steps")).first()[0]
    assert cost == 40  # the starts count too


@pytest.mark.parametrize("n", [1, 40])
def test_links_are_exact(n):
    gen = np.random.default_rng(n)
    src, dst = gen.integers(0, n, 5 * n), gen.integers(0, n, 5 * n)
    csr = Csr(src, dst, np.ones(5 * n), np.zeros(5 * n, int))
    there = set(zip(src.tolist(), dst.tolist()))
    a, b = np.repeat(csr.names, len(csr.names)), np.tile(np.arange(len(csr.names)), len(csr.names))
    assert csr.linked(csr.at(a), b).tolist() == [(int(x), int(csr.names[y])) in there for x, y in zip(a, b)]
