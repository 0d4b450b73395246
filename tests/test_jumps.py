"""The law of the jumps that all lanes make at once."""

import numpy as np

from rambler.functions import rng
from rambler.operators.samplers import jump_lanes


def test_lanes_jump_at_once_by_the_law():
    w0, n = np.array([3.0, 2.0, 0.0, 4.0, 1.0]), 60_000
    owner, idx = np.repeat(np.arange(n), 5), np.tile(np.arange(5), n)
    for lane in (4096, 2):
        out, _, draws = jump_lanes(np.tile(w0, n), owner, idx, rng.states(1, np.arange(n), np.zeros(n, int), rng.JUMP), n, lane)
        assert (out // 5 == np.arange(n)).all() and (draws >= 2).all()
        got, want = np.bincount(out % 5, minlength=5), w0 / w0.sum() * n
        assert got[2] == 0 and ((got - want)[w0 > 0] ** 2 / want[w0 > 0]).sum() < 21.1  # 3 degrees, 1e-4
    out, _, draws = jump_lanes(np.array([0.0, 0.0, 1e-300, 1.0, 1e300]), np.array([0, 0, 1, 1, 1]), np.array([0, 1, 0, 1, 2]), rng.states(1, np.arange(2), np.zeros(2, int), rng.JUMP), 2)
    assert out.tolist() == [-1, 4] and draws[0] == 0


def test_lanes_share_one_maximum_by_the_same_law():
    """Lanes against one best key keep the law, and land less often than lanes that each climb by themselves."""
    w0, n = np.array([3.0, 2.0, 0.0, 4.0, 1.0, 0.5, 2.5, 1e-6]), 60_000
    owner, idx = np.repeat(np.arange(n), 8), np.tile(np.arange(8), n)
    state = rng.states(7, np.arange(n), np.zeros(n, int), rng.JUMP)
    for lane in (4096, 2):
        out, key, draws = jump_lanes(np.tile(w0, n), owner, idx, state, n, lane, shared=True)
        assert (out // 8 == np.arange(n)).all() and (key < 0).all()
        got, want, big = np.bincount(out % 8, minlength=8), w0 / w0.sum() * n, w0 > 0.1
        assert got[2] == 0 and ((got - want)[big] ** 2 / want[big]).sum() < 25.7  # 5 degrees, 1e-4
    alone = jump_lanes(np.tile(w0, n), owner, idx, state, n, 2)[2]
    assert draws.mean() < alone.mean()
    one, other = (jump_lanes(np.tile(w0, 50), owner[:400], idx[:400], state, 50, 4096, s)[0] for s in (True, False))
    assert (one == other).all()  # with one lane there is nothing to share
