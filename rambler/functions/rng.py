"""Counter-based uniforms: a draw depends on (seed, walk, step, tag, item) alone.

Retries, repartitioning and the mode of execution don't change a draw, and the same numbers come from Spark columns, numpy and
DuckDB SQL. Two independently salted 32-bit words are folded over the counters; together they give 52 bits of a double in (0, 1).
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Fixed values of the generator: mask, multiplier of the mixer, and the two salts.
MASK, MULTIPLIER, SALTS = 0xFFFFFFFF, 73244475, (608135816, 2242054355)
#: Tags keep the draws of a step apart.
KEY, PICK, SLOT, HEIGHT, COIN, JUMP, WEIGHT, LABEL = range(1, 9)


# numpy ------------------------------------------------------------------------------------------------------------------
def mix(x: np.ndarray) -> np.ndarray:
    """Words of 32 bits to words of 32 bits; products wrap at 32 bits by themselves."""
    k, s = np.uint32(MULTIPLIER), np.uint32(16)
    x = (x ^ (x >> s)).astype(np.uint32, copy=False)
    x *= k
    x ^= x >> s
    x *= k
    x ^= x >> s
    return x


def states(seed: int, walk, step, tag: int) -> tuple[np.ndarray, np.ndarray]:
    walk = np.asarray(walk).astype(np.int64)
    counters = np.uint32(seed & MASK), walk.astype(np.uint32), (walk >> 32).astype(np.uint32), np.asarray(step).astype(np.int64).astype(np.uint32), np.uint32(tag)
    out = []
    for salt in SALTS:
        x = np.full(walk.shape, salt, np.uint32)
        for v in counters:
            x = mix(x ^ v)
        out.append(x)
    return out[0], out[1]


def uniforms(state: tuple[np.ndarray, np.ndarray], item) -> np.ndarray:
    item = np.asarray(item).astype(np.uint32)
    a, b = (mix(s ^ item) for s in state)
    out = a.astype(np.float64)
    out *= 1048576.0
    out += b >> np.uint32(12)
    out += 0.5
    out *= 1 / 4503599627370496.0  # a power of two
    return out


# The greatest uniforms of a walker's step, without drawing all of them ---------------------------------------------------------
#: Exponents for which `crest` is kept: it has 2^(32 - j) words, so 84 MB in all.
CREST = (8, 10, 12)


def unmix(y: np.ndarray) -> np.ndarray:
    """The word that `mix` takes to y: each of its rounds can be undone."""
    k, s = np.uint32(pow(MULTIPLIER, -1, 1 << 32)), np.uint32(16)
    y = (y ^ (y >> s)) * k
    y = (y ^ (y >> s)) * k
    return y ^ (y >> s)


@lru_cache(maxsize=None)
def crest(j: int) -> np.ndarray:
    """All words, in order, that `mix` takes to one of the 2^(32 - j) greatest; a uniform of any other word is below 1 - 2^-j."""
    parts = [unmix(np.arange(a, a + (1 << 20), dtype=np.uint64).astype(np.uint32)) for a in range((1 << 32) - (1 << (32 - j)), 1 << 32, 1 << 20)]
    out = np.concatenate(parts)
    out.sort()
    return out


def high_items(state: tuple[np.ndarray, np.ndarray], size: np.ndarray, j: int) -> tuple[np.ndarray, np.ndarray]:
    """(owner, item) of all items below `size` whose uniform may be 1 - 2^-j or more. Items of one walker differ in low bits alone, so
    their words are one stretch of the crest."""
    words = crest(j)
    bits = np.ceil(np.log2(np.maximum(size, 2))).astype(np.uint64)
    low = state[0].astype(np.uint64) >> bits << bits
    begin, end = np.searchsorted(words, low.astype(np.uint32)), np.searchsorted(words, (low + (np.uint64(1) << bits) - np.uint64(1)).astype(np.uint32), side="right")
    n = end - begin
    owner = np.repeat(np.arange(len(n)), n)
    item = (words[np.arange(len(owner)) - np.repeat(np.cumsum(n) - n, n) + begin[owner]] ^ state[0][owner]).astype(np.int64)
    keep = item < size[owner]
    return owner[keep], item[keep]


# Spark ------------------------------------------------------------------------------------------------------------------
def _mixed(x: str, xor: str, shift: str) -> str:
    """SQL of the mixer over a cheap expression (it is repeated)."""
    step = lambda y: f"(({xor.format(y, shift.format(y, 16))} * {MULTIPLIER}) & {MASK})"
    y = step(step(x))
    return xor.format(y, shift.format(y, 16))


_SPARK = _mixed("(s ^ v)", "({} ^ {})", "shiftright({}, {})")
_DUCK = _mixed("xor(s, v)", "xor({}, {})", "({} >> {})")


def state_columns(seed: int, tag: int, walk: str = "walk_id", step: str = "step") -> tuple[Column, Column]:
    """Folded states of a walker's step; once per walker, so the fold may be a higher-order function."""
    counters = f"array({seed & MASK}L, {walk} & {MASK}L, shiftrightunsigned({walk}, 32), cast({step} as bigint), {tag}L)"
    return tuple(F.expr(f"aggregate({counters}, {salt}L, (s, v) -> {_SPARK})") for salt in SALTS)


def with_uniform(df: DataFrame, name: str, state: tuple[str, str], item: Column) -> DataFrame:
    """Adds the uniform of (state, item) in plain arithmetic, one projection for each round, all inside code generation."""
    t = (f"_{name}1", f"_{name}2")
    mask, k = F.lit(MASK).cast("long"), F.lit(MULTIPLIER).cast("long")
    df = df.withColumns({c: F.col(s).bitwiseXOR(item.cast("long").bitwiseAND(mask)) for c, s in zip(t, state)})
    for _ in range(2):
        df = df.withColumns({c: (F.col(c).bitwiseXOR(F.shiftright(c, 16)) * k).bitwiseAND(mask) for c in t})
    df = df.withColumns({c: F.col(c).bitwiseXOR(F.shiftright(c, 16)) for c in t})
    return df.withColumn(name, (F.col(t[0]) * F.lit(1048576.0) + F.shiftright(t[1], 12) + F.lit(0.5)) / F.lit(4503599627370496.0)).drop(*t)


def with_states(df: DataFrame, names: tuple[str, str], seed: int, tag: int, walk: Column, step: Column) -> DataFrame:
    """Adds the folded states of `states` in plain arithmetic too, for tables with a walk or step of its own in every row."""
    mask, k = F.lit(MASK).cast("long"), F.lit(MULTIPLIER).cast("long")
    begun = [int(mix(np.array([salt ^ (seed & MASK)], np.uint32))[0]) for salt in SALTS]
    df = df.withColumns({c: F.lit(x).cast("long") for c, x in zip(names, begun)})
    for counter in (walk.bitwiseAND(mask), F.shiftrightunsigned(walk, 32), step.cast("long"), F.lit(tag).cast("long")):
        df = df.withColumns({c: F.col(c).bitwiseXOR(counter) for c in names})
        for _ in range(2):
            df = df.withColumns({c: (F.col(c).bitwiseXOR(F.shiftright(c, 16)) * k).bitwiseAND(mask) for c in names})
        df = df.withColumns({c: F.col(c).bitwiseXOR(F.shiftright(c, 16)) for c in names})
    return df


def uniform(seed: int, walk: str, step: str, tag: int, item: str) -> Column:
    """The same number as one expression, for use away from hot paths."""
    a, b = (f"aggregate(array({seed & MASK}L, ({walk}) & {MASK}L, shiftrightunsigned({walk}, 32), cast({step} as bigint), {tag}L, cast({item} as bigint) & {MASK}L), {salt}L, (s, v) -> {_SPARK})" for salt in SALTS)
    return F.expr(f"({a} * 1048576D + shiftright({b}, 12) + 0.5D) / 4503599627370496D")


# DuckDB -----------------------------------------------------------------------------------------------------------------
def duck_uniform(seed: int, walk: str, step: str, tag: int, item: str) -> str:
    a, b = (f"list_reduce([{salt}::BIGINT, {seed & MASK}, ({walk})::BIGINT & {MASK}, ({walk})::BIGINT >> 32, ({step})::BIGINT, {tag}, ({item})::BIGINT & {MASK}], lambda s, v: {_DUCK})" for salt in SALTS)
    return f"(({a} * 1048576::DOUBLE + ({b} >> 12) + 0.5::DOUBLE) / 4503599627370496::DOUBLE)"
