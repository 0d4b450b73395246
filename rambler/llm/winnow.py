"""Winnowed document fingerprints with positions, and the likeness of fingerprints."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import pick

#: Fixed odd multipliers of the rolling hash (its doubling steps and its last mix).
_STEPS = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5, 0x85EBCA77C2B2AE63, 0xFF51AFD7ED558CCD)]
_MIX = np.uint64(0xD6E8FEB86659FD93)


def gram_hashes(codes: np.ndarray, k: int) -> np.ndarray:
    """32-bit hashes of all runs of k code points (k a power of two), by doubling; of the whole text if it is shorter."""
    with np.errstate(over="ignore"):
        if len(codes) < k:
            h = np.uint64(len(codes))
            for c in codes.tolist():
                h = (h ^ np.uint64(c + 1)) * _STEPS[0]
            h = np.array([h], np.uint64) if len(codes) else np.zeros(0, np.uint64)
        else:
            h, width = (codes.astype(np.uint64) + np.uint64(1)) * _MIX, 1
            while width < k:
                h = h[:-width] * _STEPS[width.bit_length() % 6] + (h[width:] ^ (h[width:] >> np.uint64(29)))
                width *= 2
        h = (h ^ (h >> np.uint64(32))) * _MIX
        return (h >> np.uint64(32)).astype(np.uint32)


def winnow(text: str, k: int = 16, window: int = 8) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, positions): the least hash of each window of `window` k-grams, the rightmost of equal ones, each place once.

    Any run of at least window + k - 1 code points that two texts share yields a common hash. Shorter texts yield one hash at
    least; an empty text none."""
    h = gram_hashes(np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4"), k)
    n = len(h)
    if not n:
        return h, np.zeros(0, np.int64)
    # The hash above, the distance from the end below: one minimum gives the least hash and, of equal ones, the rightmost.
    low = (h.astype(np.uint64) << np.uint64(32)) | np.arange(n, 0, -1, dtype=np.uint64)
    w, width = min(window, n), 1
    while width * 2 <= w:
        low = np.minimum(low[:-width], low[width:])
        width *= 2
    if w > width:
        low = np.minimum(low[: n - w + 1], low[w - width :])
    chosen = low[np.concatenate([[True], low[1:] != low[:-1]])]
    chosen = np.unique(chosen) if len(chosen) < 2 else chosen
    at = n - (chosen & np.uint64(0xFFFFFFFF)).astype(np.int64)
    return (chosen >> np.uint64(32)).astype(np.uint32), at


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    """Jaccard likeness of two sets of hashes (sorted, distinct); 1 for two empty ones."""
    if not len(a) and not len(b):
        return 1.0
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / (len(a) + len(b) - both)


def shown(hashes: np.ndarray) -> str:
    """The distinct hashes, sorted, eight hexadecimal digits each."""
    return hashes.astype(">u4").tobytes().hex()


def fingerprints(docs: DataFrame, k: int = 16, window: int = 8) -> DataFrame:
    """(doc_id, hashes array<long>, positions array<long>) of each row; null text counts as empty and has none. One pass, no shuffle."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [winnow(t or "", k, window) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([h.astype(np.int64) for h, _ in found], pa.list_(pa.int64())), pa.array([p for _, p in found], pa.list_(pa.int64()))], ["doc_id", "hashes", "positions"])

    return pick(docs, "doc_id", "text").mapInArrow(run, "doc_id long, hashes array<long>, positions array<long>")


def edited_fingerprints(docs: DataFrame, k: int = 16, window: int = 8, ranges: int | None = None) -> DataFrame:
    """Each row beside its edited text, whose last third comes from the head of the next document by falling doc_id.

    (doc_id, n_chars, edited_text, fingerprint, edited_fingerprint, near_edited, near_next). The ids are cut into ranges at exact
    ids of the table; a row that ends a range goes to both sides, so each range has its own last neighbour, and texts are
    shuffled once. After the last document comes the first. Null text counts as empty. A null doc_id is the lowest; rows that
    share a doc_id stand in the order of their texts' hashes. A single row is its own neighbour. An empty table gives no rows.
    """
    rows = pick(docs, "doc_id", "text").select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("doc_id", F.lit(-(2**63))).cast("long").alias("id"), F.coalesce("text", F.lit("")).alias("text"))
    spark = docs.sparkSession
    ranges = ranges or 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    cuts, top, bottom = rows.agg(F.percentile_approx("id", [i / ranges for i in range(1, ranges)], 50_000) if ranges > 1 else F.array().cast("array<long>"), F.max("id"), F.min("id")).first()
    cuts = sorted({c for c in cuts or [] if c != top})
    # Range r holds ids in (cuts[r-1], cuts[r]]; its last row by falling id is followed by the id cuts[r-1], and in range 0 by the top.
    first = F.array(*[F.lit(c) for c in cuts]).cast("array<long>")
    own = F.expr(f"{len(cuts)}") if not cuts else F.size(F.filter(first, lambda c: c < F.col("id")))
    own = own.cast("int")
    extra = F.when(F.array_contains(first, F.col("id")), F.array(own, own + 1)).otherwise(F.array(own)) if cuts else F.array(own)
    extra = F.when(F.col("id") == top, F.concat(extra, F.array(F.lit(-1)))).otherwise(extra)
    dealt = rows.withColumn("r", F.explode(extra)).withColumn("guest", F.col("r") != own).withColumn("r", F.when(F.col("r") < 0, 0).otherwise(F.col("r")))
    # A guest is the head of what follows: of the rows of that id, the one that comes first; it stands after the range's own rows.
    sorted_rows = dealt.withColumn("tie", F.xxhash64("text")).repartition(F.col("r")).sortWithinPartitions("r", "guest", F.desc("id"), "tie").select("r", "guest", "doc_id", "text")
    alone = top == bottom

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def emit(row, following):
            doc, text, mine = row
            n, next_text = len(text), following[1]
            m = n // 3
            edited = text[: n - m] + next_text[:m]
            changed = np.unique(winnow(edited, k, window)[0])
            return doc, n, edited, shown(mine), shown(changed), likeness(mine, changed), likeness(mine, following[2])

        def flush(out):
            types = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64())
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), types)], ["doc_id", "n_chars", "edited_text", "fingerprint", "edited_fingerprint", "near_edited", "near_next"])

        held, at, out, size, start, closed = None, None, [], 0, None, False
        for batch in batches:
            for r, guest, doc, text in zip(*(batch.column(i).to_pylist() for i in range(4))):
                if r != at:
                    if held is not None and not closed:  # a range without guest: all rows of the table share one id
                        out.append(emit(held, start))
                    held, at, start, closed = None, r, None, False
                if closed:
                    continue
                row = (doc, text, np.unique(winnow(text, k, window)[0]))
                if guest and alone:
                    continue
                if held is not None:
                    out.append(emit(held, row))
                    size += len(text)
                start = start or row
                held, closed = row, guest
                if size > 8_000_000:
                    yield flush(out)
                    out, size = [], 0
        if held is not None and not closed:
            out.append(emit(held, start))
        if out:
            yield flush(out)

    return sorted_rows.mapInArrow(run, "doc_id long, n_chars long, edited_text string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")
