"""Packing of whole documents into token windows by Karmarkar-Karp multiway differencing.

One pass without a shuffle: every task tokenizes its documents, cuts full windows off the long ones, gathers the remainders into
batches of about `batch_windows` windows, and packs each batch. Memory is bounded by a batch, whatever the table's size.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from . import bpe
from .common import byte_texts, give_back, pick

#: Texts held as bytes beside their batch, and bytes of token ids that a task gathers before it hands them on.
TEXTS, HANDED = 128, 4_000_000
SCHEMA = "doc_id long, start long, length long, token_ids binary, doc_tokens long, sequence_id long, offset long"


def differencing(sizes: list[int], windows: int) -> list[list[int]]:
    """Parts of near-equal sum: indices of `sizes` in at most `windows` lists.

    Every item starts as a partial partition with one loaded part. The two partitions of widest spread merge, the fullest parts of
    one meeting the emptiest of the other, until one partition is left. Parts that are still empty aren't stored.
    """
    if not sizes:
        return []
    trees: list = list(range(len(sizes)))  # an item, or a pair of trees
    heap = [(-s, i, [(s, i)]) for i, s in enumerate(sizes)]
    heapq.heapify(heap)
    serial = len(sizes)
    while len(heap) > 1:
        _, _, a = heapq.heappop(heap)
        _, _, b = heapq.heappop(heap)  # both by falling sum
        if (shared := len(a) + len(b) - windows) <= 0:
            parts = a + b
        else:
            keep, rising = len(a) - shared, b[::-1]
            parts = a[:keep] + rising[shared:]
            for (x, p), (y, q) in zip(a[keep:], rising[:shared]):
                trees.append((p, q))
                parts.append((x + y, len(trees) - 1))
        parts.sort(reverse=True)
        spread = parts[0][0] - (parts[-1][0] if len(parts) == windows else 0)
        heapq.heappush(heap, (-spread, serial, parts))
        serial += 1
    out = []
    for _, root in heap[0][2]:
        items, todo = [], [root]
        while todo:
            node = trees[todo.pop()]
            if isinstance(node, tuple):
                todo.extend(node)
            else:
                items.append(node)
        out.append(items)
    return out


def pack(sizes: list[int], capacity: int) -> list[list[int]]:
    """Differencing into the fewest windows that the sum allows; while a part exceeds the capacity, into more of them."""
    windows = -(-sum(sizes) // capacity)
    while True:
        parts = differencing(sizes, windows)
        worst = max((sum(sizes[i] for i in p) for p in parts), default=0)
        if worst <= capacity:
            return parts
        windows += max(1, min(len(sizes) - windows, windows * (worst - capacity) // (8 * capacity)))


def _packer(vocab: str, capacity: int, end_id: int, piece: int, batch_windows: int):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, end = bpe.load(vocab), np.array([end_id], "<u4").tobytes()
        sequence = TaskContext.get().partitionId() << 40
        held: list[tuple] = []  # (doc_id, start, ids, doc_tokens) of remainders
        load = size = 0
        rows: list[tuple] = []

        def settle():
            nonlocal sequence, load, size
            for part in pack([len(r[2]) // 4 for r in held], capacity):
                offset = 0
                for i in part:
                    doc, start, ids, n = held[i]
                    rows.append((doc, start, len(ids) // 4, ids, n, sequence, offset))
                    offset += len(ids) // 4
                    size += len(ids) + 200  # a row costs more than its ids
                sequence += 1
            held.clear()
            load = 0

        def flush():
            nonlocal size
            out = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.int64(), pa.int64(), pa.int64()))], ["doc_id", "start", "length", "token_ids", "doc_tokens", "sequence_id", "offset"])
            rows.clear()
            size = 0
            return out

        def few():
            for batch in batches:
                for at in range(0, batch.num_rows, TEXTS):
                    yield from zip(batch.column(0).slice(at, TEXTS).to_pylist(), byte_texts(batch.column(1).slice(at, TEXTS)))
                give_back()

        for doc, raw in few():
            ids = encoder.encode(raw) + end
            n = len(ids) // 4
            full = n - n % capacity
            for start in range(0, full, capacity):
                rows.append((doc, start, capacity, ids[4 * start : 4 * (start + capacity)], n, sequence, 0))
                sequence += 1
                size += 4 * capacity
                if size >= HANDED:
                    yield flush()
            for start in range(full, n, piece):  # small pieces balance; a window's worth is never cut
                held.append((doc, start, ids[4 * start : 4 * (start + piece)], n))
            load += n - full
            if load >= batch_windows * capacity:
                settle()
            if size >= HANDED:
                yield flush()
        settle()
        if rows:
            yield flush()

    return run


def pack_documents(docs: DataFrame, max_tokens: int = 2048, vocab: str | None = None, end_id: int = 1, piece_tokens: int = 512, batch_windows: int = 128) -> DataFrame:
    """Pieces (doc_id, start, length, token_ids, doc_tokens, sequence_id, offset) of all documents; token_ids: little-endian unsigned 32-bit.

    A document's ids and `end_id` follow each other; full windows are cut off first, the rest into pieces of at
    most `piece_tokens`. Each sequence holds whole
    pieces, gapless from offset 0. Null or empty text: the end id alone. Repeated rows are packed as often as they occur, null
    doc_id too. An empty table gives no rows. Further columns are ignored. sequence_id is unique, not dense.
    """
    return pick(docs, "doc_id", "text").mapInArrow(_packer(vocab or bpe.default_vocab(), max_tokens, end_id, piece_tokens, batch_windows), SCHEMA)
