"""Operators on training data: cases where less than the whole text or model counted."""

import numpy as np

from rambler.llm import lm, winnow


def test_short_texts_keep_enough_fingerprints():
    """Any 23 shared code points give a common hash, and a text of 60 has several."""
    rng = np.random.default_rng(5)
    draw = lambda letters, n: "".join(rng.choice(list(letters), n))
    for _ in range(50):
        common = draw("abcdefgh", 16 + 8 - 1)
        a, b = (draw(x, rng.integers(0, 40)) + common + draw(y, 30) for x, y in (("ijkl", "mnop"), ("qrst", "uvwx")))
        assert set(winnow.winnow(a)[0]) & set(winnow.winnow(b)[0])
        assert len(winnow.winnow(draw("abcdefgh", 60))[0]) >= 5


def test_every_context_has_its_own_table(spark):
    context = np.arange(40_000) * 419
    counts = spark.createDataFrame([(c << 8 | 65, 1 + c % 3) for c in context.tolist()], "key long, n long")
    got, values, roots = lm.train_bytes(counts)
    assert set(context.tolist()) == {c for c in got.tolist() if c < lm.OTHER}
    assert len(values) == len(got) and sum(counts.sum() for _, _, counts in roots) == (1 + context % 3).sum()
