"""Byte-level BPE over a fixed public vocabulary: ids of whole texts through a cache of space-delimited chunks.

A single space between two non-blank characters always begins a new pre-token, and so does a line feed between two of them; the
ids of a text are thus those of its chunks, joined. Each distinct chunk is encoded once by a worker. Texts with other white
space (runs, tabs, no-break spaces ...) take the plain path over the whole text.
"""

from __future__ import annotations

import json
from itertools import chain

import numpy as np
import regex

from .common import per_worker

#: Fixed values of the public vocabulary: its pre-token pattern and the string of its special token.
PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
SPECIAL = "<|endoftext|>"
#: Byte sequences whose presence beside a space or line feed moves a boundary.
_ODD = (b"  ", b" \n", b"\n ", b"\n\n", b"\t", b"\r", b"\x0b", b"\x0c", b"\x1c", b"\x1d", b"\x1e", b"\x1f", b"\xc2\x85", b"\xc2\xa0", b"\xe1\x9a\x80", b"\xe2\x80", b"\xe2\x81\x9f", b"\xe3\x80\x80")
#: Above this code point (Latin, IPA), letters and digits are told apart by the tokenizer library itself.
_PLAIN_MAX = "ʯ"
#: Chunks that a worker remembers: about 250 bytes each, so 50 MB. Only speed depends on it.
CACHE_ENTRIES = 200_000


def default_vocab() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def _byte_of_char() -> dict[str, int]:
    """The usual printable stand-ins of byte-level vocabularies: printable bytes stand for themselves, the others for 256, 257 ..."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in set(shown)]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}


class Bpe:
    """Ids, counts and prefix counts of texts under one vocabulary file."""

    def __init__(self, path: str):
        import tiktoken

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        to_byte = _byte_of_char()
        special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.ranks = {bytes(to_byte[c] for c in token): i for token, i in spec["model"]["vocab"].items() if token not in special}
        self.special_id = special[SPECIAL]
        self.path = path
        self._fast = tiktoken.Encoding("public", pat_str=PATTERN, mergeable_ranks=self.ranks, special_tokens={})
        self.piece_ids = self._fast._encode_single_piece
        self._raw = self._fast._core_bpe.encode_ordinary
        self.lengths = np.zeros(max(self.special_id, *self.ranks.values()) + 1, np.int64)
        for token, i in self.ranks.items():
            self.lengths[i] = len(token)
        self.split = regex.compile(PATTERN).findall
        self._library = None
        self._chunks: dict[bytes, bytes] = {}

    def pretokens(self, text: str) -> list[str]:
        """Pre-tokens of a text that holds no special string."""
        if text.isascii() or max(text) <= _PLAIN_MAX:
            return self.split(text)
        if self._library is None:
            from tokenizers import Tokenizer

            self._library = Tokenizer.from_file(self.path)
        return [text[a:b] for _, (a, b) in self._library.pre_tokenizer.pre_tokenize_str(text)]

    def _encode_chunk(self, chunk: str) -> bytes:
        return np.fromiter(chain.from_iterable(self.piece_ids(p.encode()) for p in self.pretokens(chunk)), "<u4").tobytes()

    def chunks(self, raw: bytes) -> list[bytes] | None:
        """The chunks of a text whose white space is plain, each but the first with its leading space or line feed; else None."""
        if any(odd in raw for odd in _ODD):
            return None
        parts = raw.replace(b"\n", b" \n").split(b" ")
        return parts

    def encode(self, raw: bytes) -> bytes:
        """Ids of a text as little-endian unsigned 32-bit integers, its special strings as the special id."""
        if b"<|endoftext|>" in raw:
            return np.array([self.special_id], "<u4").tobytes().join(self.encode(p) for p in raw.split(b"<|endoftext|>"))
        if not raw:
            return b""
        if (parts := self.chunks(raw)) is None or not parts[0] or not parts[-1] or parts[-1] == b"\n":
            return self._encode_chunk(raw.decode("utf-8", "replace"))
        first = self._encode_chunk(parts[0].decode("utf-8", "replace"))
        del parts[0]
        return first + b"".join(self._cached(parts))

    def _cached(self, parts: list[bytes]) -> list[bytes]:
        """Ids of each chunk. Those that the cache lacks are encoded in one call and told apart by the byte lengths of their tokens."""
        known = self._chunks
        out = list(map(known.get, parts))
        if None not in out:
            return out
        at = [i for i, ids in enumerate(out) if ids is None]
        new = [p if p[:1] == b"\n" else b" " + p for p in (parts[i] for i in at)]
        text = b"".join(new).decode("utf-8", "replace")
        if not text.isascii() and max(text) > _PLAIN_MAX:
            found = [self._encode_chunk(p.decode("utf-8", "replace")) for p in new]
        else:
            ids = np.array(self._raw(text), "<u4")
            ends = np.searchsorted(np.cumsum(self.lengths[ids]), np.cumsum(list(map(len, new)))) + 1
            packed, cuts = ids.tobytes(), (ends * 4).tolist()
            found = [packed[a:b] for a, b in zip([0, *cuts], cuts)]
        for i, ids in zip(at, found):
            out[i] = ids
        if len(known) < CACHE_ENTRIES:  # the frequent chunks come early; later ones are encoded where they stand
            known.update(zip((parts[i] for i in at), found))
        return out


def load(path: str) -> Bpe:
    """One for each worker process, of the latest vocabulary."""
    return per_worker(f"bpe {path}", lambda: Bpe(path))
