"""What walkers of the replicated mode share gives the choices that all candidates give."""

import numpy as np
import pyarrow as pa
import pytest

from rambler.functions import rng
from rambler.operators import plain
from rambler.operators.graph import WalkGraph
from rambler.operators.walk import Csr, WalkConfig, _batch, _over_all, advance, forget_copies, random_walks
from rambler.plans.program import WeightProgram
from rambler.queries import MODELS
from rambler.sources.catalog import apply_weights, load_graph


def lists(n=160, weights=lambda r, k: r.integers(1, 50, k).astype(float)):
    """Lists of 1 to n neighbours with parallel edges of two labels, loops, and edges back and across."""
    r = np.random.default_rng(5)
    src = np.concatenate([np.full(k, k) for k in range(1, n)] + [np.arange(1, n)] * 2)
    dst = np.concatenate([r.integers(0, n, len(src) - 2 * n + 2), np.arange(1, n) % 7 + 1, np.arange(1, n)])
    label = r.integers(0, 2, len(src))
    src, dst, label = np.unique(np.stack([src, dst, label]), axis=1)
    order = r.permutation(len(src))
    return Csr(src[order], dst[order], weights(r, len(src)), label[order])


def states(csr):
    edge = np.arange(len(csr.to))[csr.row_of[csr.to] >= 0]
    prev_row = np.repeat(np.arange(len(csr.nodes)), csr.deg)[edge]
    row = csr.row_of[csr.to[edge]]
    prev = csr.nodes[prev_row]
    return np.arange(len(row)) * 3 + (1 << 40), row, prev, prev_row


def as_over_all(csr, program, how, walk, row, prev, prev_row):
    kept, csr.plain = csr.plain, lambda *_: None
    try:
        return _over_all(csr, program, 42, how, walk, row, prev, prev_row, 1)
    finally:
        csr.plain = kept


@pytest.mark.parametrize("how", ["keys", "prefix", "inverse", "jump", "alias"])
@pytest.mark.parametrize("model", ["node2vec_w", "node2vec_u", "static", "brand"])
def test_the_same_choices_reads_and_draws(how, model, monkeypatch):
    monkeypatch.setattr(plain, "BLOCK", 700)
    for weights in (lambda r, k: r.integers(1, 50, k).astype(float), lambda r, k: r.random(k) ** -1.0 - 1 + 1e-9):
        csr = lists(weights=weights)
        at = states(csr)
        assert csr.plain(MODELS[model], at[3]) is not None
        want = as_over_all(csr, MODELS[model], how, *at)
        edge, reads, draws, _ = advance(csr, MODELS[model], how, WalkConfig(), *at, 1)
        assert (edge == want[0]).all() and (reads == want[1]).all() and (draws == want[2]).all()


@pytest.mark.parametrize("model", ["node2vec_w", "node2vec_u"])
def test_the_greatest_weight_is_that_of_the_list(model):
    csr = lists()
    walk, row, prev, prev_row = at = states(csr)
    got = advance(csr, MODELS[model], "rejection_exact", WalkConfig(), *at, 1)
    csr.plain = lambda *_: None
    assert all((a == b).all() for a, b in zip(got, advance(csr, MODELS[model], "rejection_exact", WalkConfig(), *at, 1)))


def test_zero_weights_and_programs_that_do_not_split_take_all_candidates():
    zero = lists(weights=lambda r, k: r.integers(0, 3, k).astype(float))
    at = states(zero)
    assert zero.plain(MODELS["node2vec_w"], at[3]) is None
    edge, reads, _, _ = advance(zero, MODELS["node2vec_w"], "keys", WalkConfig(), *at, 1)
    assert (zero.h[edge[edge >= 0]] > 0).all() and (reads <= zero.deg[at[1]]).all() and (reads < zero.deg[at[1]]).any()
    assert lists().plain(MODELS["sorank_w"], at[3]) is None
    hidden = WeightProgram("hidden", "CASE WHEN linked THEN 0 ELSE 1 END", order=2)
    assert lists().plain(hidden, at[3]) is None


def test_words_of_32_bits_give_the_numbers_of_64():
    def mixed(x):
        for _ in range(2):
            x = ((x ^ (x >> 16)) * rng.MULTIPLIER) & rng.MASK
        return x ^ (x >> 16)

    walk, step = [-5, 7, (3 << 40) + 9, 2**62], [0, 1, 79, 5]
    got = rng.uniforms(state := rng.states(42, np.array(walk), np.array(step), rng.JUMP), np.arange(4) << 20)
    for k in range(4):
        words = []
        for salt, s in zip(rng.SALTS, state):
            x = salt
            for v in (42, walk[k] & rng.MASK, (walk[k] >> 32) & rng.MASK, step[k], rng.JUMP):
                x = mixed(x ^ v)
            assert s.dtype == np.uint32 and int(s[k]) == x
            words.append(mixed(x ^ ((k << 20) & rng.MASK)))
        assert got[k] == (words[0] * 1048576.0 + (words[1] >> 12) + 0.5) / 2.0**52


def test_a_stored_graph_is_sent_once_for_all_its_walks(spark):
    """Each walk read the edges through the driver and sent them again."""
    g = WalkGraph.from_edges(spark.createDataFrame([(k, (k * j + 1) % 20, float(1 + k * j % 5)) for k in range(20) for j in (1, 3, 4)], "src long, dst long, h double")).stored()
    rows = [sorted(map(tuple, random_walks(g, MODELS["node2vec_w"], None, how, WalkConfig(steps=3, mode="replicated")).collect())) for how in ("keys", "prefix", "keys")]
    sent = vars(g)["copies"]
    random_walks(g, MODELS["node2vec_u"], None, "inverse", WalkConfig(steps=3, mode="replicated")).count()
    assert vars(g)["copies"] is sent and rows[0] == rows[2] != rows[1]
    forget_copies(g)
    assert rows[0] == sorted(map(tuple, random_walks(g, MODELS["node2vec_w"], None, "keys", WalkConfig(steps=3, mode="replicated")).collect()))


def test_drawn_weights_of_a_stored_graph_are_those_of_a_loaded_one(spark):
    d = "/root/testdata/sf0.001"
    of = lambda g: sorted(map(tuple, g.edges.select("src", "dst", "h", "label", "idx").collect()))
    assert of(apply_weights(load_graph(spark, d, "g6").stored(), "pareto", 2.0)) == of(load_graph(spark, d, "g6", "pareto", 2.0))


def test_modes_of_a_log_are_taken_from_two_words(monkeypatch):
    """A string was made in numpy for each step."""
    made = []
    monkeypatch.setattr("rambler.operators.walk.np.where", lambda *a: made.append(a) or np.zeros(3))
    n = np.arange(3)
    got = _batch(n, 1, n, n, n, np.array([True, False, True]), True)
    assert got.column("mode").to_pylist() == ["rejection", "reservoir", "rejection"] and not made
    assert _batch(n, 0, n, n, n, n > 5, True).column("mode").to_pylist() == [None] * 3


def test_a_worker_makes_its_copy_once_for_all_its_tasks(spark):
    """Each task made its own, as the table of copies went along with the function."""
    g = WalkGraph.from_edges(spark.createDataFrame([(k, (k * j + 1) % 20, float(1 + k * j % 5)) for k in range(20) for j in (1, 3, 4)], "src long, dst long, h double")).stored()
    random_walks(g, MODELS["node2vec_w"], None, "keys", WalkConfig(steps=3, mode="replicated", partitions=8)).count()
    token = g.copies[1]

    def kept(batches):
        from rambler.operators import walk

        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([int(token in walk._GRAPHS)] * b.num_rows, pa.int32())], ["n"])

    assert spark.range(0, 8, 1, 8).mapInArrow(kept, "n int").groupBy().sum().first()[0] > 0


def test_a_graph_passes_the_driver_in_parts(spark, monkeypatch):
    """All edges were in the driver's heap at once."""
    g = WalkGraph.from_edges(spark.createDataFrame([(k, (k * j + 1) % 20, float(1 + k * j % 5)) for k in range(20) for j in (1, 3, 4)], "src long, dst long, h double")).stored()
    walks = lambda: sorted(map(tuple, random_walks(g, MODELS["node2vec_w"], None, "keys", WalkConfig(steps=3, mode="replicated")).collect()))
    want, whole = walks(), len(g.copies[0].value[0])
    forget_copies(g)
    monkeypatch.setattr("rambler.operators.walk.READ_EDGES", 7)
    assert walks() == want and len(g.copies[0].value[0]) == whole
