"""Reversible removal of lines that many documents share: exact reference counts behind sharded cuckoo filters.

State, all of it stored: a table of (h1, h2, n), the 128-bit hash of a line's key and the number of documents that hold it; and a
cuckoo filter for each shard of the keys at or over the threshold. Inserting documents adds to the counts, deleting takes away, so
any sequence of both ends where a fresh count would; keys that cross the threshold on the way enter their shard's filter or leave
it. A filter answers most lines alone; every hit is checked against the exact keys.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import byte_texts, per_worker, pick, without, written

BLANKS = b" \t\n\x0b\x0c\r"
#: Droppable keys that are broadcast at most (16 bytes each, as one array); with more, the lines that pass the filters meet them in a join.
BROADCAST_KEYS = 1_000_000
#: Bytes of filters that are broadcast at most; beyond, all lines meet the keys in the join.
FILTER_BYTES = 64 << 20
#: Keys to a shard, when the shards of a new store are numbered.
SHARD_KEYS = 250_000
COUNT_SCHEMA = "h1 long, h2 long, n long"


class CuckooFilter:
    """16-bit tags in buckets of four; two candidate buckets for each key. No false negatives for what was inserted and not deleted."""

    SLOTS = 4

    def __init__(self, expected: int):
        self.mask = (1 << max(4, int(np.ceil(np.log2(max(1, expected) / 0.85 / self.SLOTS))))) - 1
        self.table = np.zeros((self.mask + 1, self.SLOTS), np.uint16)
        self.stash: list[tuple[int, int]] = []  # (bucket, tag) that found no room; still answered
        self._seed = 1

    def dump(self) -> bytes:
        return np.array([self.mask, self._seed, len(self.stash), *(x for pair in self.stash for x in pair)], "<i8").tobytes() + self.table.astype("<u2").tobytes()

    @staticmethod
    def load(raw: bytes) -> CuckooFilter:
        out = CuckooFilter(0)
        out.mask, out._seed, n = np.frombuffer(raw, "<i8", 3).tolist()
        out.stash = list(map(tuple, np.frombuffer(raw, "<i8", 2 * n, 24).reshape(-1, 2).tolist()))
        out.table = np.frombuffer(raw, "<u2", offset=24 + 16 * n).reshape(-1, CuckooFilter.SLOTS).astype(np.uint16)
        return out

    def room(self) -> int:
        """Keys that still go in before the table is nine tenths full."""
        return int(0.9 * self.table.size) - int(np.count_nonzero(self.table)) - len(self.stash)

    @staticmethod
    def _tag(h: np.ndarray) -> np.ndarray:
        return ((h >> np.uint64(48)) | np.uint64(1)).astype(np.uint16)

    def _other(self, bucket, tag):
        """The partner bucket: the same formula leads back."""
        return (bucket ^ (tag * 0x5BD1E995)) & self.mask

    def insert(self, key: int) -> None:
        tag = ((key >> 48) | 1) & 0xFFFF
        at = key & self.mask
        for bucket in (at, self._other(at, tag)):
            if (free := np.flatnonzero(self.table[bucket] == 0)).size:
                self.table[bucket, free[0]] = tag
                return
        for _ in range(200):
            self._seed = (self._seed * 1103515245 + 12345) & 0x7FFFFFFF
            slot = (self._seed >> 16) % self.SLOTS
            tag, self.table[at, slot] = int(self.table[at, slot]), tag
            at = self._other(at, tag)
            if (free := np.flatnonzero(self.table[at] == 0)).size:
                self.table[at, free[0]] = tag
                return
        self.stash.append((at, tag))

    def delete(self, key: int) -> bool:
        tag = ((key >> 48) | 1) & 0xFFFF
        at = key & self.mask
        for bucket in (at, self._other(at, tag)):
            if (held := np.flatnonzero(self.table[bucket] == tag)).size:
                self.table[bucket, held[0]] = 0
                return True
            if (bucket, tag) in self.stash:
                self.stash.remove((bucket, tag))
                return True
        return False

    def contains(self, keys: np.ndarray) -> np.ndarray:
        tag = self._tag(keys)
        at = (keys & np.uint64(self.mask)).astype(np.int64)
        wide = tag.astype(np.int64)
        other = (at ^ (wide * 0x5BD1E995)) & self.mask
        found = (self.table[at] == tag[:, None]).any(1) | (self.table[other] == tag[:, None]).any(1)
        for bucket, t in self.stash:
            found |= (wide == t) & ((at == bucket) | (other == bucket))
        return found


def owners(keys: np.ndarray, shards: int) -> np.ndarray:
    """The shard of each key (pairs of int64); shards: a power of two."""
    return keys[:, 1] & (shards - 1)


class ShardedFilter:
    """One cuckoo filter for each shard of the keys, the shard being given by h2; and the exact keys behind them, in one sorted array."""

    def __init__(self, keys: np.ndarray, shards: int = 16, filters: dict[int, bytes] | None = None):
        """filters: stored ones by shard; without them they are made from the keys."""
        self.shards = shards
        self.exact = np.unique(np.ascontiguousarray(keys, np.int64).reshape(-1, 2).view("V16").ravel())
        self.changed: dict[tuple[int, int], bool] = {}  # keys added or removed since
        if filters is not None:
            self.filters = [CuckooFilter.load(filters[k]) if k in filters else CuckooFilter(0) for k in range(shards)]
            return
        self.filters, owner = [], owners(keys, shards)
        for k in range(shards):
            mine = keys[owner == k, 0].astype(np.uint64)
            f = CuckooFilter(len(mine))
            for key in mine.tolist():
                f.insert(key)
            self.filters.append(f)

    def _held(self, hashes: np.ndarray) -> np.ndarray:
        if not len(hashes):
            return np.zeros(0, bool)
        mine = np.ascontiguousarray(hashes, np.int64).view("V16").ravel()
        at = np.minimum(np.searchsorted(self.exact, mine), max(0, len(self.exact) - 1))
        out = self.exact[at] == mine if len(self.exact) else np.zeros(len(mine), bool)
        if self.changed:
            out = np.array([self.changed.get(tuple(h), o) for h, o in zip(hashes.tolist(), out.tolist())], bool)
        return out

    def add(self, key: tuple[int, int]) -> None:
        if not self._held(np.array([key], np.int64))[0]:
            self.changed[key] = True
            self.filters[key[1] & (self.shards - 1)].insert(key[0] & (2**64 - 1))

    def remove(self, key: tuple[int, int]) -> None:
        if self._held(np.array([key], np.int64))[0]:
            self.changed[key] = False
            self.filters[key[1] & (self.shards - 1)].delete(key[0] & (2**64 - 1))

    def passes(self, hashes: np.ndarray) -> np.ndarray:
        """Which of the lines (int64 pairs) their shard's filter lets through: all that are held, and a few others."""
        out, owner = np.zeros(len(hashes), bool), owners(hashes, self.shards)
        for k, f in enumerate(self.filters):
            if (mine := np.flatnonzero(owner == k)).size:
                out[mine] = f.contains(hashes[mine, 0].astype(np.uint64))
        return out

    def drops(self, hashes: np.ndarray) -> np.ndarray:
        """Which of the lines are held: the shard's filter first, then the exact keys for what passes."""
        out = self.passes(hashes)
        at = np.flatnonzero(out)
        out[at] = self._held(hashes[at])
        return out


def line_hashes(raw: bytes) -> tuple[list[bytes], np.ndarray, np.ndarray]:
    """Lines of a text, the hashes of their keys as int64 pairs, and which keys are empty."""
    lines = raw.split(b"\n")
    keys = [x.strip(BLANKS) for x in raw.lower().split(b"\n")]  # of bytes, lower() changes A-Z alone
    digest = xxhash.xxh3_128_digest
    return lines, np.frombuffer(b"".join(map(digest, keys)), "<i8").reshape(-1, 2), np.fromiter(map(len, keys), np.int64, len(keys)) == 0


def _counts(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    def out(parts: list[np.ndarray]) -> pa.RecordBatch:
        keys, n = np.unique(np.concatenate(parts), return_counts=True)
        pairs = keys.view("<i8").reshape(-1, 2)
        return pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1]), pa.array(n.astype(np.int64))], ["h1", "h2", "n"])

    held, size = [], 0
    for batch in batches:
        for raw in byte_texts(batch.column(0)):
            _, hashes, empty = line_hashes(raw)
            own = np.unique(np.ascontiguousarray(hashes[~empty]).view("V16").ravel())
            held.append(own)
            size += len(own)
            if size > 500_000:
                yield out(held)
                held, size = [], 0
    if size:
        yield out(held)


def line_counts(docs: DataFrame) -> DataFrame:
    """(h1, h2, n): documents (rows) that hold each non-empty key, once each."""
    return pick(docs, "text").mapInArrow(_counts, COUNT_SCHEMA).groupBy("h1", "h2").agg(F.sum("n").alias("n"))


def _turn(key, old, turned) -> pa.Table:
    """A shard's filter after keys that left (add is false) and came; null if it has to be made anew, being too small."""
    shard = (old if old.num_rows else turned).column("shard")[0].as_py()
    add = turned.column("add").to_numpy(zero_copy_only=False).astype(bool) if turned.num_rows else np.zeros(0, bool)
    keys = turned.column("h1").to_numpy().astype(np.uint64) if turned.num_rows else np.zeros(0, np.uint64)
    f = CuckooFilter.load(old.column("filter")[0].as_py()) if old.num_rows else CuckooFilter(2 * len(keys))
    for k in keys[~add].tolist():
        f.delete(k)
    raw = None
    if f.room() >= add.sum():
        for k in keys[add].tolist():
            f.insert(k)
        raw = f.dump()
    return pa.table({"shard": pa.array([shard], pa.int32()), "filter": pa.array([raw], pa.binary())})


class LineStore:
    """Reference counts of line keys and the filters of the droppable ones, kept as stored tables that every insertion or deletion replaces."""

    FILTERS = "shard int, filter binary"

    def __init__(self, spark: SparkSession, min_docs: int = 10, state: DataFrame | None = None, filters: DataFrame | None = None, shards: int | None = None):
        self.min_docs, self.shards = min_docs, shards
        self.state = state if state is not None else spark.createDataFrame([], COUNT_SCHEMA)
        self.filters = filters if filters is not None else spark.createDataFrame([], self.FILTERS)

    def insert(self, docs: DataFrame) -> LineStore:
        return self._merge(line_counts(docs))

    def delete(self, docs: DataFrame) -> LineStore:
        """Takes documents out that were inserted before (their texts as they were then)."""
        return self._merge(line_counts(docs).withColumn("n", -F.col("n")))

    def _merge(self, change: DataFrame) -> LineStore:
        both = self.state.withColumn("was", F.col("n")).unionByName(change.withColumn("was", F.lit(0).cast("long")))
        merged = written(both.groupBy("h1", "h2").agg(F.sum("n").alias("n"), F.sum("was").alias("was")))
        state = merged.where("n > 0").select("h1", "h2", "n")
        over, before = F.col("n") >= self.min_docs, F.col("was") >= self.min_docs
        shards = self.shards or 1 << max(4, (merged.where(over).count() // SHARD_KEYS).bit_length())
        shard = F.pmod("h2", F.lit(shards)).cast("int").alias("shard")
        turned = merged.where(over != before).select(shard, "h1", over.alias("add"))
        filters = written(self.filters.groupBy("shard").cogroup(turned.groupBy("shard")).applyInArrow(_turn, self.FILTERS))
        if filters.where("filter is null").count():  # outgrown: these shards are made from their exact keys
            small = filters.where("filter is null").select("shard")
            keys = state.where(over).select(shard, "h1", F.lit(True).alias("add")).join(F.broadcast(small), "shard")
            none = change.sparkSession.createDataFrame([], self.FILTERS)
            filters = written(filters.where("filter is not null").unionByName(none.groupBy("shard").cogroup(keys.groupBy("shard")).applyInArrow(_turn, self.FILTERS)))
        return LineStore(change.sparkSession, self.min_docs, state, filters, shards)

    def droppable(self) -> DataFrame:
        return self.state.where(F.col("n") >= self.min_docs).select("h1", "h2")

    def apply(self, docs: DataFrame, broadcast_keys: int = BROADCAST_KEYS, filter_bytes: int = FILTER_BYTES) -> DataFrame:
        size = self.filters.agg(F.coalesce(F.sum(F.octet_length("filter")), F.lit(0))).first()[0]
        filters = {r["shard"]: bytes(r["filter"]) for r in self.filters.collect()} if size <= filter_bytes else None
        return drop_lines(docs, self.droppable(), broadcast_keys, filters, self.shards or 16)


def drop_lines(docs: DataFrame, keys: DataFrame, broadcast_keys: int = BROADCAST_KEYS, filters: dict[int, bytes] | None = None, shards: int = 16) -> DataFrame:
    """`docs` with their lines of the given keys (h1, h2) left out: column text replaced, n_lines and n_dropped added.

    filters: the keys' cuckoo filters by shard. Up to `broadcast_keys` keys go to all tasks and texts stay where they are; beyond,
    those of each document's keys that pass the filters meet the table in a shuffle, and come back to it by doc_id (rows that share
    a doc_id share the found keys, which changes nothing for them)."""
    docs = without(docs, "n_lines", "n_dropped")
    names = docs.columns
    fields = ", ".join(f"_{i} {t}" for i, (_, t) in enumerate(docs.dtypes))
    at = names.index("text")
    numbered = docs.toDF(*[f"_{i}" for i in range(len(names))])
    token, filtered = uuid.uuid4().hex, filters is not None
    few = keys.limit(broadcast_keys + 1).count() <= broadcast_keys
    if few:
        held = keys.toArrow()
        shared = docs.sparkSession.sparkContext.broadcast((np.stack([held.column(c).to_numpy() for c in ("h1", "h2")], 1), shards, filters))
    else:
        shared = docs.sparkSession.sparkContext.broadcast((np.zeros((0, 2), np.int64), shards, filters))
        own = pick(docs, "doc_id", "text").select("doc_id", "text")

        def keyed(batches):
            for batch in batches:
                for doc, raw in zip(batch.column(0).to_pylist(), byte_texts(batch.column(1))):
                    _, hashes, empty = line_hashes(raw)
                    pairs = np.unique(np.ascontiguousarray(hashes[~empty]).view("V16").ravel()).view("<i8").reshape(-1, 2)
                    if filtered:
                        pairs = pairs[per_worker(token, lambda: ShardedFilter(*shared.value)).passes(pairs)]
                    yield pa.RecordBatch.from_arrays([pa.array([doc] * len(pairs), pa.int64()), pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], ["doc", "h1", "h2"])

        found = own.mapInArrow(keyed, "doc long, h1 long, h2 long").join(keys, ["h1", "h2"]).groupBy("doc").agg(F.flatten(F.collect_set(F.array("h1", "h2"))).alias("found"))
        numbered = numbered.join(found, numbered[f"_{names.index('doc_id')}"].eqNullSafe(found.doc), "left").drop("doc")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if few:
            shard = per_worker(token, lambda: ShardedFilter(*shared.value))
        for batch in batches:
            parts = [line_hashes(raw) for raw in byte_texts(batch.column(at))]
            if few:
                gone = shard.drops(np.concatenate([h for _, h, _ in parts])) if parts else np.zeros(0, bool)
            else:
                gone = np.concatenate([[tuple(p) in held for p in h.tolist()] for (_, h, _), f in zip(parts, batch.column(len(names)).to_pylist()) for held in [set(zip(f[::2], f[1::2])) if f else ()]]).astype(bool) if parts else np.zeros(0, bool)
            texts, dropped, start = [], [], 0
            for lines, hashes, empty in parts:
                out = gone[start : start + len(lines)] & ~empty
                start += len(lines)
                n = int(out.sum())
                texts.append(b"\n".join(x for x, o in zip(lines, out.tolist()) if not o) if n else b"\n".join(lines))
                dropped.append(n)
            columns = [batch.column(i) for i in range(len(names))]
            columns[at] = pa.array(texts, pa.binary()).cast(pa.string())
            columns += [pa.array([len(p[0]) for p in parts], pa.int64()), pa.array(dropped, pa.int64())]
            yield pa.RecordBatch.from_arrays(columns, [f"_{i}" for i in range(len(names))] + ["n_lines", "n_dropped"])

    result = numbered.mapInArrow(run, f"{fields}, n_lines long, n_dropped long")
    return result.toDF(*names, *["n_lines", "n_dropped"])


def dedup_lines(docs: DataFrame, min_docs: int = 10, broadcast_keys: int = BROADCAST_KEYS) -> DataFrame:
    """All columns of `docs`, text without the lines whose key stands in at least `min_docs` documents, n_lines (before), n_dropped.

    A key is the line stripped of ASCII blanks, A-Z lower-cased; lines of empty key stay. A document is a row: repeated rows count
    as often as they occur. Null or empty text is one empty line and becomes or stays empty. An empty table gives no rows. Every
    other column is passed through, but one named n_lines or n_dropped (in any case) gives way to the new one.
    """
    return LineStore(docs.sparkSession, min_docs).insert(docs).apply(docs, broadcast_keys)
