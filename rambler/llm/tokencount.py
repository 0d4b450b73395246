"""Exact token counts at every prefix, by dynamic programming over the last token.

Of a pre-token's prefix of i bytes the encoding ends in exactly one token t such that the encoding of the first i - len(t) bytes,
followed by t, is stable: merging the bytes of its last token and of t gives these two tokens back. So count(i) = count(i -
len(t)) + 1, and the ids of no prefix are ever made. Stability of a pair of tokens is remembered.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import bpe
from .common import byte_texts, per_worker, pick


class PrefixCounter:
    """Counts for prefixes of texts. A worker keeps one for each vocabulary."""

    def __init__(self, path: str):
        self.bpe = bpe.Bpe(path)
        self.width = max(map(len, self.bpe.ranks))
        self._stable: dict[tuple[int, int], bool] = {}
        self._totals: dict[bytes, int] = {}
        self._last: dict[str, int] = {}
        self._bytes = {i: t for t, i in self.bpe.ranks.items()}

    def _fits(self, left: int, right: int) -> bool:
        key = (left, right)
        if (known := self._stable.get(key)) is None:
            if len(self._stable) > 1_500_000:
                self._stable.clear()
            known = self._stable[key] = self.bpe.piece_ids(self._bytes[left] + self._bytes[right]) == [left, right]
        return known

    def piece(self, raw: bytes) -> list[int]:
        """Token counts of raw[:0], raw[:1] ... raw of one pre-token."""
        rank, stable, counts, last = self.bpe.ranks.get, self._stable.get, [0], [-1]
        for end in range(1, len(raw) + 1):
            if (token := rank(raw[:end])) is not None:
                counts.append(1)
                last.append(token)
                continue
            for start in range(max(1, end - self.width), end):
                if (token := rank(raw[start:end])) is not None:
                    before = last[start]
                    if (fits := stable((before, token))) is None:
                        fits = self._fits(before, token)
                    if fits:
                        counts.append(counts[start] + 1)
                        last.append(token)
                        break
        return counts

    def prefixes(self, text: str) -> np.ndarray:
        """counts[i]: tokens of the first i bytes of `text`, encoded by themselves; counts[-1]: of the whole text.

        Where i falls inside a character, its first bytes are taken as they are."""
        out, total = [np.zeros(1, np.int64)], 0
        parts = text.split(bpe.SPECIAL)
        for k, part in enumerate(parts):
            own = self._plain(part)
            out.append(own[1:] + total)
            if k + 1 < len(parts):
                # A special string that isn't whole yet is plain text, joined to what stands before it.
                started = self._plain(part + bpe.SPECIAL[:-1])[len(own) :]
                out.append(np.append(started, own[-1] + 1) + total)
                total += 1
            total += int(own[-1])
        return np.concatenate(out)

    def _plain(self, text: str) -> np.ndarray:
        """Counts at every prefix of a text without a special string. A prefix has the text's pre-tokens up to its end, but for two cases:
        a run of white space is one pre-token where it ends the prefix, though its last character goes with what follows in the text;
        and an apostrophe with a part of its ending is two."""
        out, total = [np.zeros(1, np.int64)], 0
        pretokens = self.bpe.pretokens(text)
        for k, p in enumerate(pretokens):
            own = self.piece(p.encode())
            counts = np.array(own[1:])
            if p in ("'re", "'ve", "'ll"):
                counts[1] = 2
            if k and pretokens[k - 1].isspace() and p[0].isspace():  # p begins with the last character of the run
                counts[len(p[0].encode()) - 1] = self.piece((pretokens[k - 1] + p[0]).encode())[-1] - last
            out.append(counts + total)
            last = own[-1]
            total += last
        return np.concatenate(out)

    def cut(self, text: str, budget: int) -> str:
        """The longest prefix, in whole characters, of at most `budget` tokens."""
        raw, counts = text.encode(), self.prefixes(text)
        end = bisect_right(counts.tolist(), budget) - 1 if (np.diff(counts) >= 0).all() else int(np.flatnonzero(counts <= budget)[-1])
        return raw[:end].decode("utf-8", "ignore")

    def _chunk(self, raw: bytes) -> int:
        """Sum of the pre-tokens' last counts, each pre-token's table being worked out once."""
        total, known = 0, self._last
        for p in self.bpe.pretokens(raw.decode("utf-8", "replace")):
            if (n := known.get(p)) is None:
                n = self.piece(p.encode())[-1]
                if len(known) < bpe.CACHE_ENTRIES:
                    known[p] = n
            total += n
        return total

    def total(self, raw: bytes) -> int:
        """The count of the whole text: the last entry of its chunks' prefix tables, remembered by chunk."""
        if not raw:
            return 0
        if b"<|endoftext|>" in raw:
            parts = raw.split(b"<|endoftext|>")
            return len(parts) - 1 + sum(map(self.total, parts))
        if (parts := self.bpe.chunks(raw)) is None or not parts[0] or not parts[-1] or parts[-1] == b"\n":
            return self._chunk(raw)
        known, first = self._totals, self._chunk(parts[0])
        del parts[0]
        found = list(map(known.get, parts))
        if None not in found:
            return first + sum(found)
        for i, n in enumerate(found):
            if n is None:
                p = parts[i]
                found[i] = n = self._chunk(p if p[:1] == b"\n" else b" " + p)
                if len(known) < bpe.CACHE_ENTRIES:
                    known[p] = n
        return first + sum(found)


def counter(path: str) -> PrefixCounter:
    return per_worker(f"counter {path}", lambda: PrefixCounter(path))


def count_tokens(docs: DataFrame, limit: int = 512, vocab: str | None = None) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) of each row: one pass, no shuffle.

    Null text counts as empty: 0 bytes, 0 tokens. Special strings count as one token, as the library does by default. Repeated
    rows and null doc_id give a row each; an empty table gives none; further columns are ignored.
    """
    path = vocab or bpe.default_vocab()

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = counter(path).total
        for batch in batches:
            raws = byte_texts(batch.column(1))
            n = np.fromiter(map(count, raws), np.int64, len(raws))
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(np.fromiter(map(len, raws), np.int64, len(raws))), pa.array(n), pa.array(n > limit)], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return pick(docs, "doc_id", "text").mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")


def prefix_counts(docs: DataFrame, vocab: str | None = None) -> DataFrame:
    """(doc_id, counts array<long>): the count at every byte prefix of each text, from which any truncation or budget question is read off."""
    path = vocab or bpe.default_vocab()

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = counter(path).prefixes
        for batch in batches:
            for doc, raw in zip(batch.column(0).to_pylist(), byte_texts(batch.column(1))):
                yield pa.RecordBatch.from_arrays([pa.array([doc], pa.int64()), pa.array([table(raw.decode("utf-8", "replace")).tolist()], pa.list_(pa.int64()))], ["doc_id", "counts"])

    return pick(docs, "doc_id", "text").mapInArrow(run, "doc_id long, counts array<long>")
