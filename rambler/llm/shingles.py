"""Distinct word-shingle hashes of many texts at once, in numpy."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

from .common import byte_texts

_RNG = np.random.Generator(np.random.PCG64(20240229))
_LETTER = _RNG.integers(0, 2**63, 256, np.uint64) * np.uint64(2) + np.uint64(1)
_WORD = _RNG.integers(0, 2**63, 64, np.uint64) * np.uint64(2) + np.uint64(1)
_BASE = np.uint64(0x9E3779B97F4A7C13)
_BLANK = np.zeros(256, bool)
#: Bytes of text hashed at once (a longer text by itself); numpy holds some 80 bytes for each.
CHUNK = 250_000
_BLANK[[9, 10, 11, 12, 13, 32]] = True


def mix(x: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
        x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
        return x ^ (x >> np.uint64(33))


def word_hashes(raws: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the lower-cased (A-Z) words of all texts, and where each text's words begin (one entry more)."""
    joined = b"\n".join(raws).lower() + b"\n"
    codes = np.frombuffer(joined, np.uint8)
    blank = _BLANK[codes]
    before = np.concatenate([[True], blank[:-1]])
    starts = np.flatnonzero(~blank & before)
    ends = np.flatnonzero(blank & ~before)
    edges = np.cumsum([0, *(len(r) + 1 for r in raws)])
    if not len(starts):
        return np.zeros(0, np.uint64), np.zeros(len(raws) + 1, np.int64)
    lengths = ends - starts
    with np.errstate(over="ignore"):
        power = np.concatenate([[np.uint64(1)], np.cumprod(np.full(int(lengths.max()), _BASE))])
        inside = np.flatnonzero(~blank)
        first = np.concatenate([[0], np.cumsum(lengths)[:-1]])
        place = np.arange(len(inside)) - np.repeat(first, lengths)
        words = mix(np.add.reduceat(_LETTER[codes[inside]] * power[place], first) + lengths.astype(np.uint64))
    return words, np.searchsorted(starts, edges)


def shingle_sets(raws: list[bytes], k: int = 5) -> Iterator[np.ndarray]:
    """For each text its distinct shingles' hashes, rising; of fewer than k words, the whole sequence as one; without words, none."""
    at = 0
    while at < len(raws):
        end, size = at, 0
        while end < len(raws) and (end == at or size + len(raws[end]) < CHUNK):
            size += len(raws[end]) + 1
            end += 1
        words, bounds = word_hashes(raws[at:end])
        with np.errstate(over="ignore"):
            grams = sum((words[i : len(words) - k + 1 + i] * _WORD[i] for i in range(1, k)), words[: len(words) - k + 1] * _WORD[0]) if len(words) >= k else np.zeros(0, np.uint64)
            grams = mix(grams)
            for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
                if b - a >= k:
                    yield np.unique(grams[a : b - k + 1])
                elif b > a:
                    yield mix(np.array([(words[a:b] * _WORD[8 : 8 + b - a]).sum() + np.uint64(b - a)], np.uint64))
                else:
                    yield np.zeros(0, np.uint64)
        at = end


def column_sets(column: pa.Array, k: int = 5) -> Iterator[np.ndarray]:
    """shingle_sets of a text column, of which few texts are held beside the batch at a time."""
    for at in range(0, len(column), 128):
        yield from shingle_sets(byte_texts(column.slice(at, 128)), k)
