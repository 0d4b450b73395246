"""Laws, modes and edge cases of the walk engine on hand-checkable graphs."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from rambler.functions import rng
from rambler.operators import samplers as S
from rambler.operators.graph import InvalidGraph, WalkGraph, rank_ids
from rambler.operators.walk import Csr, WalkConfig, advance, random_walks
from rambler.plans import program as P

LIST = [(0, 1, 3.0, 0), (0, 2, 2.0, 1), (0, 3, 4.0, 0), (0, 4, 1.0, 1)]
LAW = np.array([0.3, 0.2, 0.4, 0.1])


def graph(spark, rows=LIST):
    return WalkGraph.from_edges(spark.createDataFrame(rows, "src long, dst long, h double, label int"))


def chi_square(counts, law):
    want = law * counts.sum()
    return float(((counts - want) ** 2 / want).sum())


def csr_counts(rows, program, sampler, n=120_000, **options):
    csr = Csr(*(np.array(c) for c in zip(*[(a, b, float(h), x) for a, b, h, x in rows])))
    config = WalkConfig(sampler_options=options)
    row, none = np.zeros(n, np.int64), np.full(n, -1, np.int64)
    edge, reads, draws, by_trial = advance(csr, program, sampler, config, np.arange(n), row, none, none, 0)
    return np.bincount(csr.dst[edge[edge >= 0]], minlength=5)[1:], reads, draws, by_trial


@pytest.mark.parametrize("sampler", ["keys", "prefix", "inverse", "rejection_bound", "rejection_exact", "adaptive"])
def test_law_in_numpy(sampler):
    counts, *_ = csr_counts(LIST, P.static_walk(), sampler)
    assert chi_square(counts, LAW) < 21.1  # 1e-4 at three degrees of freedom


def test_jump_and_alias_laws():
    w = np.array([3.0, 2.0, 4.0, 1.0])
    gen = np.random.default_rng(0)
    jumped = np.bincount([S.jump_pick(w, lambda k, lane: gen.random())[0] for _ in range(40_000)], minlength=4)
    assert chi_square(jumped, LAW) < 21.1
    own, other = S.alias_tables(w, np.array([0]))
    slot, coin = gen.integers(0, 4, 100_000), gen.random(100_000)
    assert chi_square(np.bincount(np.where(coin < own[slot], slot, other[slot]), minlength=4), LAW) < 21.1


def test_alias_tables_of_many_lists_give_every_weight():
    """What the slots give each item is its weight's share: random, equal, single, huge and tiny ones, thousands of lists at once."""
    gen = np.random.default_rng(5)
    lists = [gen.pareto(1, n) + 1e-3 for n in gen.integers(1, 60, 2000)] + [np.ones(7), np.full(3, 0.1), np.array([2.0]), np.array([1e-300, 1e300, 1.0]), np.array([1.0, 1e-12]), gen.random(5000)]
    w, size = np.concatenate(lists), np.array([len(x) for x in lists])
    first = np.cumsum(size) - size
    own, other = S.alias_tables(w, first)
    which = np.repeat(np.arange(len(lists)), size)
    assert ((own >= 0) & (own <= 1)).all() and (which[other] == which).all()
    given = (own + np.bincount(other, 1 - own, len(w))) / size[which]
    want = np.concatenate([x / x.max() / (x / x.max()).sum() for x in lists])
    assert np.allclose(given, want, rtol=0, atol=1e-9)
    assert (S.running_sums(w, first) == np.concatenate([np.cumsum(x) for x in lists])).all()
    assert len(S.alias_picks(np.empty(0), np.empty(0, np.int64), (np.empty(0, np.uint64),) * 2)) == 0


def test_jump_saves_draws_on_long_lists():
    gen = np.random.default_rng(1)
    draws = np.mean([S.jump_pick(np.ones(1024), lambda k, lane: gen.random())[2] for _ in range(300)])
    assert 12 < draws < 19  # 15.1 expected


def test_an_unconditional_jump_key_would_be_wrong():
    gen, w, counts = np.random.default_rng(2), [3.0, 2.0, 4.0, 1.0], np.zeros(4)
    for _ in range(20_000):
        best, at, acc, threshold = math.log(gen.random()) / w[0], 0, 0.0, 0.0
        threshold = math.log(gen.random()) / best
        for i in range(1, 4):
            acc += w[i]
            if acc >= threshold:
                best, at, acc = math.log(gen.random()) / w[i], i, 0.0
                threshold = math.log(gen.random()) / best
        counts[at] += 1
    assert chi_square(counts, LAW) > 1000


def test_trials_follow_the_bound():
    """Mean trials are degree * bound / sum, and the law doesn't depend on the bound."""
    csr = Csr(*(np.array(c) for c in zip(*[(a, b, h, x) for a, b, h, x in LIST])))
    from rambler.operators.walk import _rejected

    n = 60_000
    for factor in (1, 2, 10):
        none = np.full(n, -1, np.int64)
        edge, trials = _rejected(csr, P.static_walk(), 7, np.full(n, 4.0 * factor), 400, np.arange(n), np.zeros(n, np.int64), none, none, 0)
        assert trials.mean() == pytest.approx(1.6 * factor, rel=0.03)
        assert chi_square(np.bincount(csr.dst[edge], minlength=5)[1:], LAW) < 21.1
    edge, _ = _rejected(csr, P.static_walk(), 7, np.full(n, 2.0), 400, np.arange(n), np.zeros(n, np.int64), none, none, 0)
    assert chi_square(np.bincount(csr.dst[edge], minlength=5)[1:], LAW) > 500  # below the maximum it must fail


def test_uniforms_agree_and_are_uniform(spark):
    rows = [(w, s, i) for w in (0, 5, 2**40 + 3) for s in (0, 7) for i in range(50)]
    df = spark.createDataFrame(rows, "walk_id long, step int, i long")
    a, b = rng.state_columns(42, rng.KEY)
    got = rng.with_uniform(df.withColumn("s1", a).withColumn("s2", b), "u", ("s1", "s2"), F.col("i")).withColumn("v", rng.uniform(42, "walk_id", "step", rng.KEY, "i")).collect()
    for r in got:
        want = float(rng.uniforms(rng.states(42, np.array([r.walk_id]), np.array([r.step]), rng.KEY), np.array([r.i]))[0])
        assert r.u == r.v == want
    u = np.sort(rng.uniforms(rng.states(1, np.repeat(np.arange(300), 300), np.zeros(90_000), rng.KEY), np.tile(np.arange(300), 300)))
    assert np.abs(u - (np.arange(90_000) + 0.5) / 90_000).max() * 300 < 1.95


def test_second_order_laws(spark):
    g = graph(spark, [(1, 0, 1.0, 0), (0, 1, 1.0, 0), (0, 2, 1.0, 0), (0, 3, 1.0, 0), (1, 2, 1.0, 0)])
    state = spark.createDataFrame([(1, 0, 1)], "prev long, cur long, step int")
    p = {r.dst: r.p for r in S.transition_probabilities(g, P.return_inout(), state).collect()}
    assert p == pytest.approx({1: 1 / 7, 2: 2 / 7, 3: 4 / 7})
    p = {r.dst: r.p for r in S.transition_probabilities(g, P.second_order_rank(), state).collect()}
    assert p == pytest.approx({1: 0.8 / 2.7, 2: 1.1 / 2.7, 3: 0.8 / 2.7})


def test_meta_path_and_dead_ends(spark):
    g = graph(spark, [(0, 1, 1.0, 0), (0, 2, 1.0, 1), (1, 3, 1.0, 1), (2, 3, 1.0, 0), (3, 0, 1.0, 4)])
    start = spark.createDataFrame([(0,)], "start long")
    for mode in ("superstep", "replicated"):
        walk = lambda schema: [r.node for r in random_walks(g, P.meta_path(schema), start, "keys", WalkConfig(steps=5, mode=mode)).orderBy("step").collect()]  # noqa: B023, E731
        assert walk((0, 1)) == [0, 1, 3]
        assert walk((0, 2)) == [0, 1]


@pytest.mark.parametrize("sampler", ["keys", "prefix", "inverse", "rejection_bound", "rejection_exact", "jump", "alias", "adaptive"])
def test_zero_weights_extremes_and_unknown_starts(spark, sampler):
    g = graph(spark, [(0, 1, 0.0, 0), (0, 2, 0.0, 0), (1, 2, 1.0, 0), (5, 6, 1e-300, 0), (5, 7, 1.0, 0), (5, 8, 1e300, 0)])
    start = spark.createDataFrame([(0,), (1,), (2,), (5,), (99,)], "start long")
    got = sorted(map(tuple, random_walks(g, P.static_walk(), start, sampler, WalkConfig(steps=3, mode="superstep")).collect()))
    assert got == [(0, 0, 0), (1, 0, 1), (1, 1, 2), (2, 0, 2), (5, 0, 5), (5, 1, 8), (99, 0, 99)]


@pytest.mark.parametrize("sampler", ["keys", "inverse", "prefix", "rejection_bound", "adaptive", "jump"])
def test_modes_agree(spark, sampler):
    gen = np.random.default_rng(4)
    rows = [(int(a), int(b), float(h), 0) for a, b, h in zip(gen.integers(0, 40, 400), gen.integers(0, 40, 400), gen.integers(1, 9, 400))]
    g = graph(spark, rows).stored()
    both = [sorted(map(tuple, random_walks(g, P.return_inout(), None, sampler, WalkConfig(steps=3, mode=m)).collect())) for m in ("superstep", "replicated")]
    assert both[0] == both[1]


def test_validation_and_merging(spark):
    for h in (-1.0, None, float("nan"), float("inf")):
        with pytest.raises(InvalidGraph):
            graph(spark, [(0, 1, h, 0)]).validate()
    assert [(r.dst, r.h) for r in graph(spark, [(0, 1, 1.0, 0), (0, 1, 2.0, 0)]).validate().edges.collect()] == [(1, 3.0)]
    assert random_walks(graph(spark, []), P.static_walk(), None, "keys", WalkConfig(steps=2, mode="superstep")).count() == 0
    assert sorted(r.id for r in rank_ids(spark.createDataFrame([(x,) for x in "dbca"], "k string"), "k").collect()) == [0, 1, 2, 3]


def test_analysis():
    a = P.return_inout(weighted=False).analysis
    assert (a.flag, a.bound.value) == ("RUN", 2.0) and len(a.branches) == 3
    a = P.return_inout().analysis
    assert a.flag == "STEP" and a.bound.evaluate({"h_max": 3.0}) == 6.0 and a.total.evaluate({"h_sum": 6.0}) == pytest.approx(7.0)
    assert P.return_inout(1.0, 0.5, False).analysis.bound.value == 2.0
    assert P.meta_path().analysis.total.evaluate({"h_sum": 4.0}) == 2.0
    bad = P.WeightProgram("x", "rand() * h").analysis
    assert bad.bound is None and "reservoir" in bad.warnings[0]
    assert P.WeightProgram("y", "3 / (1 + h)", weighted=False).analysis.bound.evaluate({"h_min": 0.5, "h_max": 2.0}) == 2.0


def test_key_step_plan_has_no_sort_of_candidates(spark):
    g = graph(spark).stored()
    walkers = spark.createDataFrame([(0, 0, None, 0)], "walk_id long, step int, prev long, cur long")
    plan = S.key_step(walkers, g, P.static_walk(), 1)._jdf.queryExecution().executedPlan().toString()
    assert "Window" not in plan and "SortAggregate" not in plan
