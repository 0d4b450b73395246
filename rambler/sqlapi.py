"""Walks from SQL: views of a graph, and a table function that walks from a node."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from rambler.operators.graph import WalkGraph
from rambler.operators.walk import Csr, WalkConfig, advance
from rambler.plans.program import WeightProgram

#: Edges up to which walk_from takes a graph along with its code (some 28 bytes each).
FUNCTION_EDGES = 1_000_000


def register(spark: SparkSession, graph: WalkGraph, program: WeightProgram, sampler: str = "keys", prefix: str = "") -> None:
    """Temporary views {prefix}edges and {prefix}node_stats, and {prefix}walk_from(start, steps, seed), a table function of (step, node).

    SELECT s.id, w.* FROM starts s, LATERAL walk_from(s.id, 5, 42) w: the walk is the one that random_walks makes with walk_id = start.
    A null argument gives no rows; a start without edges gives itself. Graphs above FUNCTION_EDGES get no table function: an error says so."""
    graph.edges.createOrReplaceTempView(f"{prefix}edges")
    graph.node_stats.createOrReplaceTempView(f"{prefix}node_stats")
    if (n := graph.edges.count()) > FUNCTION_EDGES:
        raise ValueError(f"{n} edges are too many for a table function; use random_walks")
    table = graph.edges.select("src", "dst", "h", "label").toArrow()
    arrays = tuple(table.column(c).to_numpy() for c in ("src", "dst", "h", "label"))
    program.full, program.analysis  # parsed once, here  # noqa: B018

    class WalkFrom:
        def __init__(self):
            self.csr = Csr(*arrays)

        def eval(self, start: int, steps: int, seed: int) -> Iterator[tuple[int, int]]:
            if start is None or steps is None or seed is None:
                return
            walk, cur, prev, prev_row = np.array([start]), np.array([start]), np.array([-1]), np.array([-1])
            config = WalkConfig(seed=seed)
            yield 0, int(cur[0])
            for k in range(min(steps, program.depth or steps)):
                row = self.csr.at(cur)
                if row[0] < 0:
                    return
                edge, *_ = advance(self.csr, program, sampler, config, walk, row, prev, prev_row, k)
                if edge[0] < 0:
                    return
                prev, prev_row, cur = cur, row, self.csr.ends(edge)
                yield k + 1, int(cur[0])

    spark.udtf.register(f"{prefix}walk_from", udtf(WalkFrom, returnType="step: int, node: bigint"))
