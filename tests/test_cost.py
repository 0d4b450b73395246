"""What walks cost on graphs too large to replicate."""

import pytest

from rambler.operators import walk
from rambler.operators.graph import WalkGraph
from rambler.operators.walk import WalkConfig, walk_cost
from rambler.queries import MODELS


@pytest.mark.parametrize("sampler", ["keys", "adaptive", "jump_shared"])
def test_walks_of_graphs_too_large_to_replicate_have_a_cost(spark, monkeypatch, sampler):
    """Both modes count the same steps; such graphs were refused."""
    rows = [(a, (a * k + 1) % 12, float(1 + (a * k) % 5)) for a in range(12) for k in (1, 3, 4)]
    g = WalkGraph.from_edges(spark.createDataFrame(rows, "src long, dst long, h double")).stored()
    ask = lambda: walk_cost(g, MODELS["node2vec_w"], None, sampler, WalkConfig(steps=2, partitions=3)).collect()
    small = ask()
    monkeypatch.setattr(walk, "REPLICATED_EDGES", 10)
    large, before = ask(), spark.conf.get("spark.sql.shuffle.partitions")
    assert len(large) == 1 and large[0].steps == sum(r.steps for r in small) == 12 * 3
    assert large[0].cpu_seconds > 0 and large[0].wall_seconds > 0 and before == spark.conf.get("spark.sql.shuffle.partitions") == "4"
