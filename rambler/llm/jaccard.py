"""Exact n-gram Jaccard join that skips work through relations between sets.

Equal sets are one node. Index lists are skipped by blocks: a list's entries stand by (size, position), so that for a probing set
every block of one size ends where position rules the rest out, and the list ends where size does. Answers are derived instead of
computed anew: each node is compared with one highly similar node, its head, and what is kept of that comparison (which shingles of
the head it holds, and which others) gives the exact overlap of any two nodes of one head without their texts. Such pairs never
become rows: blocks of a group meet in a task, which returns links between classes alone, one at most for each node.

The remaining pairs come from prefix lists (the shingles of which a similar set must hold one), common shingles last. Sets with many
common shingles carry a bitmap of parities: two bitmaps differ in no more bits than the sets in shingles, so a pair whose bitmaps
differ in too many is ruled out for certain. Pairs that survive are compared on their whole sets. What is returned are the classes,
so copies are never expanded into pairs.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import give_back, per_worker, pick, small_batches, written
from .components import components
from .decontam import small
from .shingles import column_sets, mix

#: Least hashes kept of a set to find its head by; shingles in more sets than COMMON stand last in the order of the prefixes, by count.
LEAST, COMMON = 16, 8
#: Members of a head that meet in one task, from either side; text bytes to a bucket of the index.
BLOCK, BUCKET_BYTES = 2_048, 4_000_000
#: Bits of the parity bitmaps, and the least share of common shingles (one of so many) of a set that has one.
BITS, CROWDED = 512, 20
#: Hashes that a task gathers before it sends them on.
GATHERED = 400_000
#: Common shingles that tasks are given at most; with more, only the commonest count as common. The order may be any: the join stays exact.
COMMON_KEYS = 8_000_000
NO_ID = 2**63 - 1


def _node(own: np.ndarray) -> int:
    """64-bit identity of a set (of sorted distinct hashes)."""
    with np.errstate(over="ignore"):
        turned = mix(own + np.arange(len(own), dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
        return int(mix(np.array([turned.sum() + np.uint64(len(own))], np.uint64)).view(np.int64)[0])


def _summaries(k: int, common, token: str):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            nodes, sizes, ranks, least = [], [], [], []
            for own in column_sets(batch.column(1), k):
                nodes.append(_node(own) if len(own) else None)
                sizes.append(len(own))
                low = own[: -(-35 * len(own) // 100)]
                ranks.append(1000 * int(_late(low, *_known(common, token))[0].sum()) // max(1, len(low)))
                least.append(own[:LEAST].view(np.int64))
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(nodes, pa.int64()), pa.array(sizes, pa.int64()), pa.array(ranks, pa.int64()), pa.array(least, pa.list_(pa.int64()))], ["doc_id", "node", "n", "rank", "least"])

    return run


def _overlap(a: np.ndarray, b: np.ndarray) -> int:
    return len(np.intersect1d(a, b, assume_unique=True))


def _compare(k: int, percent: int, keep: bool):
    """Rows (a, salt, b, text), a group's own text first (b null): yields the pairs (a, b) that are linked.

    keep: yields (a, b, linked, n, kept, more) of every pair of which b holds half its shingles from a at least; kept: a bit for each
    shingle of a, more: b's other shingles."""
    types = (pa.int64(), pa.int64(), *((pa.bool_(), pa.int32(), pa.binary(), pa.binary()) if keep else ()))
    names = ["a", "b", "linked", "n", "kept", "more"][: len(types)]

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group, own = None, None
        for batch in batches:
            out, size = [], 0
            a, salt, b = (batch.column(i).to_pylist() for i in range(3))
            for x, s, y, other in zip(a, salt, b, column_sets(batch.column(3), k)):
                if y is None:
                    if (x, s) != group or own is None or _node(other) == x:
                        group, own = (x, s), other
                elif own is not None and (x, s) == group and _node(other) == y:
                    held = np.isin(own, other, assume_unique=True) if keep else None
                    both = int(held.sum()) if keep else _overlap(own, other)
                    linked = 100 * both >= percent * (len(own) + len(other) - both)
                    if keep and 2 * both >= len(other):
                        out.append((x, y, linked, len(other), np.packbits(held).tobytes(), np.setdiff1d(other, own, assume_unique=True).tobytes()))
                        size += len(out[-1][4]) + len(out[-1][5])
                    elif linked:
                        out.append((x, y))
                if size > 4_000_000:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), types)], names)
                    out, size = [], 0
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), types)], names)
        give_back()

    return run


def _derived(percent: int):
    """(a, b) links among the members of one head in blocks i and j, from what each keeps of the head. Members that aren't linked to
    the head meet all others; the linked ones are one class, so no two of them meet."""

    def run(key, table):
        b, n, at, side = (table.column(c).to_numpy() for c in ("b", "n", "at", "side"))
        across = key[1].as_py() != key[2].as_py()
        kept = table.column("kept").to_pylist()
        width = -(-len(kept[0]) // 8) * 8
        bits = np.frombuffer(b"".join(x.ljust(width, b"\0") for x in kept), np.uint64).reshape(len(b), -1)
        more = [np.frombuffer(x, np.uint64) for x in table.column("more").to_pylist()]
        extra = np.array([len(x) for x in more])
        every, owner = np.concatenate(more), np.repeat(np.arange(len(b)), extra)
        order = np.argsort(every, kind="stable")
        every, owner = every[order], owner[order]
        label, found = np.arange(len(b)), []
        label[side == 1] = -1  # linked to the head, so one class
        for x in np.flatnonzero(side == 0).tolist():
            rest = np.flatnonzero((label != label[x]) & ((side == 1) | (np.arange(len(b)) > x)) & ((at != at[x]) if across else True))
            if not len(rest):
                continue
            both = np.bitwise_count(bits[rest] & bits[x]).sum(1, dtype=np.int64)
            whole = n[rest].astype(np.int64) + int(n[x])
            near = (100 + percent) * (both + np.minimum(extra[rest], extra[x])) >= percent * whole
            rest, both, whole = rest[near], both[near], whole[near]
            if len(rest) and extra[x]:
                lo, hi = np.searchsorted(every, more[x], "left"), np.searchsorted(every, more[x], "right")
                shared = np.bincount(np.concatenate([owner[i:j] for i, j in zip(lo.tolist(), hi.tolist())]), minlength=len(b))
                both = both + shared[rest]
            for y in rest[(100 + percent) * both >= percent * whole].tolist():
                if label[y] != label[x]:
                    found.append((int(b[x]), int(b[y])))
                    label[label == label[y]] = label[x]
        return pa.table({"a": pa.array([p[0] for p in found], pa.int64()), "b": pa.array([p[1] for p in found], pa.int64())})

    return run


def _group_links(compared: DataFrame, percent: int) -> DataFrame:
    """Links (a, b) among nodes that were compared with the same head. Members are dealt in blocks, and every block of unlinked
    members meets every block of the group once, so that no task grows with the group."""
    blocks = lambda c: F.greatest(F.ceil(F.sum(c.cast("int")) / BLOCK), F.lit(1)).cast("int")
    groups = compared.groupBy("a").agg(F.count("*").alias("m"), F.sum((~F.col("linked")).cast("int")).alias("u"), blocks(~F.col("linked")).alias("ub"), blocks(F.col("linked")).alias("lb"))
    rows = compared.join(groups.where("u > 0 and m > 1").select("a", "m", "ub", "lb"), "a")
    rows = rows.withColumns({"side": F.col("linked").cast("int"), "at": F.expr("cast(if(linked, ub + pmod(xxhash64(b), lb), pmod(xxhash64(b), ub)) as int)")})
    meets = F.expr(f"""CASE WHEN m <= {BLOCK} THEN array(struct(0 as i, 0 as j)) WHEN linked THEN transform(sequence(0, ub - 1), i -> struct(i as i, at as j))
        ELSE concat(transform(sequence(0, ub - 1), i -> struct(least(i, at) as i, greatest(i, at) as j)), transform(sequence(ub, ub + lb - 1), j -> struct(at as i, j as j))) END""")
    dealt = rows.select("a", F.explode(meets).alias("t"), "b", "n", "at", "side", "kept", "more").select("a", "t.i", "t.j", "at", "side", "b", "n", "kept", "more")
    return dealt.groupBy("a", "i", "j").applyInArrow(_derived(percent), "a long, b long")


def _verified(docs: DataFrame, nodes: DataFrame, pairs: DataFrame, k: int, percent: int, keep: bool = False) -> DataFrame:
    """Those of the (stored) pairs (a, b) whose whole sets are similar enough. Each text travels once for each group it is compared in; large groups are salted."""
    sizes = pairs.groupBy("a").agg(F.count("*").alias("m"))
    salted = pairs.join(sizes, "a").select("a", "b", F.pmod("b", F.ceil(F.col("m") / 500)).alias("salt"))
    wanted = salted.select(F.col("b").alias("node"), "a", "salt", "b").union(
        sizes.select(F.col("a").alias("node"), "a", F.explode(F.sequence(F.lit(0).cast("long"), F.ceil(F.col("m") / 500) - 1)).alias("salt"), F.lit(None).cast("long").alias("b"))
    )
    asked = written(wanted.join(nodes.select("node", "rep"), "node").select("rep", "a", "salt", "b"))
    texts = pick(docs, "doc_id", "text").select(F.coalesce("doc_id", F.lit(NO_ID)).cast("long").alias("rep"), "text")
    dealt = texts.join(small(asked, 64), "rep").select("a", "salt", "b", "text").repartition("a", "salt").sortWithinPartitions("a", "salt", F.asc_nulls_first("b"))
    return dealt.mapInArrow(_compare(k, percent, keep), "a long, b long" + ", linked boolean, n int, kept binary, more binary" * keep)


def _common_counts(k: int, buckets: int, common=None, token: str = ""):
    """Counts of the lower 35 % of each set's hashes, as sorted blobs by bucket (48 bits of each hash).

    Given what is common among those: counts of the other hashes, in the sets of which a tenth is common. Only such sets have
    prefixes that reach far into what they share with many."""

    def blobs(parts: list[np.ndarray]):
        keys, n = np.unique(np.concatenate(parts) >> np.uint64(16), return_counts=True)
        used, first = np.unique((keys >> np.uint64(16)) * np.uint64(buckets) >> np.uint64(32), return_index=True)
        raw = keys.astype("<u8").view(np.uint8).reshape(-1, 8)
        rows = [(j, raw[a:b, :6].tobytes(), n[a:b].astype("<u4").tobytes()) for j, a, b in zip(used.tolist(), first.tolist(), [*first[1:].tolist(), len(keys)])]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.binary(), pa.binary()))], ["bucket", "keys", "n"])

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for batch in batches:
            for own in column_sets(batch.column(0), k):
                if len(own):
                    cut = -(-35 * len(own) // 100)
                    part = own[:cut]
                    if common is not None:
                        part = own[cut:] if 10 * _late(own[:cut], *_known(common, token))[0].sum() >= cut else own[:0]
                    if len(part):
                        held.append(part)
                        size += len(part)
                if size > GATHERED:
                    yield blobs(held)
                    held, size = [], 0
        if size:
            yield blobs(held)
        del held
        give_back()

    return run


def _known(common, token: str) -> tuple[np.ndarray, np.ndarray]:
    """The broadcast common shingles and their counts, once in each worker."""
    return per_worker(token, lambda: common.value)


def _late(own: np.ndarray, often: np.ndarray, times: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which hashes are common, and the counts of those."""
    if not len(often):
        return np.zeros(len(own), bool), times
    short = (own >> np.uint64(16)).astype(np.int64)
    at = np.minimum(np.searchsorted(often, short), len(often) - 1)
    late = often[at] == short
    return late, times[at[late]]


def _wide(raw: bytes, width: int) -> np.ndarray:
    out = np.zeros((len(raw) // width, 8), np.uint8)
    out[:, :width] = np.frombuffer(raw, np.uint8).reshape(-1, width)
    return out.view("<u8").ravel()


def _commonest(key, table):
    keys = np.concatenate([_wide(x, 6) for x in table.column("keys").to_pylist()])
    n = np.concatenate([np.frombuffer(x, "<u4") for x in table.column("n").to_pylist()])
    order = np.argsort(keys, kind="stable")
    keys, n = keys[order], n[order]
    first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    sums = np.add.reduceat(n.astype(np.int64), first)
    often = sums > COMMON
    out = pa.table({"key": pa.array(keys[first][often].astype(np.int64)), "n": pa.array(sums[often])})
    del keys, n, order, first, sums
    give_back()
    return out


_POST = "bucket int, h binary, doc binary, node binary, comp binary, head binary, n binary, pos binary, has binary, bits binary"


def _parities(own: np.ndarray) -> np.ndarray:
    return np.packbits((np.bincount((own >> np.uint64(16)).astype(np.int64) % BITS, minlength=BITS) & 1).astype(bool))


def _postings(k: int, percent: int, buckets: int, common, token: str):
    """Prefix postings as blobs by bucket: of each posting its hash, position and document, the latter by its place in the blob's table."""
    names = ["bucket", "h", "doc", "node", "comp", "head", "n", "pos", "has", "bits"]

    def blobs(hashes, nodes, comps, heads, sizes, bits):
        h = np.concatenate(hashes)
        lengths = [len(x) for x in hashes]
        doc = np.repeat(np.arange(len(hashes)), lengths)
        pos = np.arange(len(h)) - np.repeat(np.cumsum([0, *lengths[:-1]]), lengths)
        bucket = ((h >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32)).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        used, first = np.unique(bucket[order], return_index=True)
        nodes, comps, heads, sizes = np.array(nodes, np.int64), np.array(comps, np.int64), np.array(heads, np.int64), np.array(sizes, np.int32)
        has = np.array([x is not None for x in bits])
        rows = []
        for j, start, end in zip(used.tolist(), first.tolist(), [*first[1:].tolist(), len(h)]):
            mine = order[start:end]
            own, place = np.unique(doc[mine], return_inverse=True)
            rows.append((j, h[mine].astype("<u8").tobytes(), place.astype("<u2").tobytes(), nodes[own].tobytes(), comps[own].tobytes(), heads[own].tobytes(), sizes[own].tobytes(), pos[mine].astype("<u4").tobytes(), has[own].tobytes(), b"".join(bits[i].tobytes() for i in own[has[own]].tolist())))
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), *[pa.binary()] * 9))], names)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        often, times = _known(common, token)
        held, size = ([], [], [], [], [], []), 0
        for batch in batches:
            for own, node, comp, head in zip(column_sets(batch.column(0), k), *(batch.column(i).to_pylist() for i in (1, 2, 3))):
                if not len(own) or _node(own) != node:
                    continue  # a row that shares its id with the node's
                need = len(own) - -(-percent * len(own) // 100) + 1
                late, counts = _late(own, often, times)
                bits = _parities(own) if CROWDED * late.sum() >= len(own) else None
                if len(counts) and late.any():
                    own = np.concatenate([own[~late], own[late][np.argsort(counts, kind="stable")]])
                for x, y in zip(held, (own[:need].copy(), node, comp, head, len(own), bits)):
                    x.append(y)
                size += need
                if size > GATHERED or len(held[0]) >= 60_000:
                    yield blobs(*held)
                    held, size = ([], [], [], [], [], []), 0
        if size:
            yield blobs(*held)
        del held
        give_back()

    return run


class _Lists:
    """Entries of index lists in the order (list, size, position). A block: the entries of one list and size."""

    def __init__(self, lists: np.ndarray, n: np.ndarray, pos: np.ndarray, own: np.ndarray):
        order = np.lexsort((pos, n, lists))
        self.own, self.n, self.pos = own[order], n[order], pos[order]
        self.key = lists[order] << 32 | self.n
        self.first = np.flatnonzero(np.concatenate([[True], self.key[1:] != self.key[:-1]])) if len(own) else np.zeros(0, np.int64)
        self.block = self.key[self.first]
        self.end = np.append(self.first[1:], len(own))
        self.place = (np.repeat(np.arange(len(self.first)), self.end - self.first) << 32) | self.pos if len(own) else self.key


def _met(probes: _Lists, lists: _Lists, percent: int, strict: bool, limit: int = 500_000) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs (own number of the probe, own number of the entry) that size and position leave, in bounded stretches. Entries are as
    large as the probe at least (larger, if strict); lists that are probed by themselves give each pair once."""
    if not len(probes.own) or not len(lists.own):
        return
    same = probes is lists
    active = np.arange(len(probes.own))
    block = np.searchsorted(lists.block, probes.key + strict)
    while len(active):
        inside = block[active] < len(lists.block)
        active = active[inside]
        at = lists.block[block[active]]
        n, own = at & 0xFFFFFFFF, probes.n[active]
        need = -(-percent * (n + own) // (100 + percent))
        # The list ends with the sizes; a probe ends where its own position leaves too little, as more is needed of larger sets.
        on = (at >> 32 == probes.key[active] >> 32) & (100 * own >= percent * n) & (own - probes.pos[active] >= need)
        active, n, need = active[on], n[on], need[on]
        if not len(active):
            return
        # Within the block, what lies behind the last useful position is skipped unseen.
        stop = np.searchsorted(lists.place, (block[active] << 32) | np.maximum(n - need, 0), "right")
        start = np.maximum(lists.first[block[active]], active + 1) if same else lists.first[block[active]]
        many = np.maximum(stop - start, 0)
        some = np.flatnonzero(many)
        if len(some):
            cut = np.cumsum(many[some])
            for part in np.split(some, np.flatnonzero(np.diff((cut - many[some]) // limit)) + 1):
                m = many[part]
                yield np.repeat(probes.own[active[part]], m), lists.own[np.repeat(start[part] - np.cumsum(m) + m, m) + np.arange(m.sum())]
        block[active] += 1


def _candidates(percent: int):
    def run(key, table):
        columns, maps, mapped = ([], [], [], [], [], [], []), [np.zeros((0, BITS // 64), np.uint64)], 0
        for row in table.to_pylist():
            place, has = np.frombuffer(row["doc"], "<u2"), np.frombuffer(row["has"], bool)
            maps.append(np.frombuffer(row["bits"], np.uint64).reshape(-1, BITS // 64))
            slot = np.where(has, np.cumsum(has) - 1 + mapped, -1)
            mapped += len(maps[-1])
            found = (np.frombuffer(row["h"], "<u8"), *(np.frombuffer(row[c], "<i8")[place] for c in ("node", "comp", "head")), np.frombuffer(row["n"], "<i4")[place].astype(np.int64), np.frombuffer(row["pos"], "<u4").astype(np.int64), slot[place])
            for x, y in zip(columns, found):
                x.append(y)
        h, node, comp, head, n, pos, slot = (np.concatenate(x) for x in columns)
        maps = np.concatenate(maps)
        lists = np.unique(h, return_inverse=True)[1].astype(np.int64)
        length = np.bincount(lists)

        def largest(group):
            """Whether an entry belongs to the largest part of its list by `group`, and that part's size."""
            order = np.lexsort((group, lists))
            first = np.flatnonzero(np.concatenate([[True], (lists[order][1:] != lists[order][:-1]) | (group[order][1:] != group[order][:-1])]))
            run = np.diff(np.append(first, len(order)))
            top = np.zeros(len(length), np.int64)
            np.maximum.at(top, lists[order[first]], run)
            chosen = np.flatnonzero(run == top[lists[order[first]]])
            chosen = chosen[np.unique(lists[order[first[chosen]]], return_index=True)[1]]
            mark = np.zeros(len(order), bool)
            mark[order] = np.repeat(np.isin(np.arange(len(first)), chosen), run)
            return mark, top

        # No pair is left inside a class, nor among the members of a head. Of each list, the larger of such parts isn't paired with itself.
        (by_comp, c), (by_head, d) = largest(comp), largest(head)
        part = np.where((c >= d)[lists], by_comp, by_head)
        alive = (length > np.maximum(c, d))[lists]
        big, other = np.flatnonzero(part & alive), np.flatnonzero(~part & alive)
        big, other = (_Lists(lists[x], n[x], pos[x], x) for x in (big, other))
        found, held, size = [], [], 0

        def settle():
            nonlocal size
            if held:
                pairs = np.concatenate(held)
                pairs.sort(axis=1)
                found.append(np.unique(np.ascontiguousarray(pairs).view("i8,i8").ravel()))
                held.clear()
                size = 0

        for probes, entries, strict in ((other, other, False), (other, big, False), (big, other, True)):
            for i, j in _met(probes, entries, percent, strict):
                good = (comp[i] != comp[j]) & (head[i] != head[j]) & (node[i] != head[j]) & (head[i] != node[j])
                i, j = i[good], j[good]
                good = np.ones(len(i), bool)
                for at in np.array_split(mine := np.flatnonzero((slot[i] >= 0) & (slot[j] >= 0)), len(mine) // 25_000 + 1):
                    differ = np.bitwise_count(maps[slot[i[at]]] ^ maps[slot[j[at]]]).sum(1, dtype=np.int64)
                    whole = n[i[at]] + n[j[at]]
                    good[at] = differ <= whole - 2 * -(-percent * whole // (100 + percent))
                if good.any():
                    held.append(np.stack([node[i[good]], node[j[good]]], 1))
                    size += len(held[-1])
                    if size > GATHERED // 4:
                        settle()
        settle()
        pairs = np.unique(np.concatenate(found)) if found else np.zeros(0, "i8,i8")
        del columns, maps, found, h, node, comp, head, n, pos, slot, lists, big, other, part, alive, table
        give_back()
        return pa.table({"a": pa.array(pairs["f0"]), "b": pa.array(pairs["f1"])})

    return run


def jaccard_classes(docs: DataFrame, k: int = 5, percent: int = 75) -> DataFrame:
    """(doc_id, n_shingles, component_id) of each row: its set's size and the least doc_id that links reach from it.

    Two rows are linked if 100 * intersection >= percent * union of their sets of distinct k-word shingles. Null, empty and blank
    texts have no set and stay alone. Repeated rows are linked with each other. A null doc_id counts as the largest; a class of
    null ids alone has a null component_id. An empty table gives no rows; further columns are ignored. Sets are told apart by 64
    bits of a hash, shingles too.
    """
    with small_batches(docs.sparkSession):
        return _classes(docs, k, percent)


def _classes(docs: DataFrame, k: int, percent: int) -> DataFrame:
    spark = docs.sparkSession
    token = uuid.uuid4().hex
    blobs, texts = "bucket int, keys binary, n binary", pick(docs, "text")
    volume = texts.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = max(8, int(spark.conf.get("spark.sql.shuffle.partitions")), -(-volume // BUCKET_BYTES))

    def commonest(counts):
        """What is broadcast of stored counts: COMMON_KEYS rows of 16 bytes at most."""
        floor = COMMON
        while counts.where(F.col("n") > floor).count() > COMMON_KEYS:
            floor *= 4
        table = counts.where(F.col("n") > floor).orderBy("key").toArrow()
        return spark.sparkContext.broadcast((table.column("key").to_numpy(), table.column("n").to_numpy()))

    low = written(texts.mapInArrow(_common_counts(k, buckets), blobs).groupBy("bucket").applyInArrow(_commonest, "key long, n long"))
    often = commonest(low)
    sets = written(pick(docs, "doc_id", "text").mapInArrow(_summaries(k, often, f"{token}-low"), "doc_id long, node long, n long, rank long, least array<long>"))
    nodes = written(sets.where("node is not null").groupBy("node").agg(F.min(F.coalesce("doc_id", F.lit(NO_ID))).alias("rep"), F.first("n").alias("n"), F.first("rank").alias("rank"), F.first("least").alias("least")))

    # Heads: in each list of a least hash, the member with the largest share of common shingles, as the source of many edited copies
    # is; a member is compared with the head it meets most often.
    lists = nodes.select("node", "n", "rank", F.explode("least").alias("h"))
    lengths = lists.groupBy("h").agg(F.count("*").alias("m")).where("m > 1").select("h")
    named = written(lists.join(lengths, "h").withColumn("band", F.floor(F.log(100 / percent, F.col("n")))).select("h", "band", "node", "rank"))
    heads = written(named.groupBy("h", "band").agg(F.max(F.struct("rank", (-F.col("node")).alias("back"))).alias("x"), F.count("*").alias("m")).where("m > 1").select("h", "band", (-F.col("x.back")).alias("a")))
    votes = named.join(heads, ["h", "band"]).where("node <> a").groupBy("node", "a").agg(F.count("*").alias("v"))
    best = written(votes.groupBy("node").agg(F.max(F.struct("v", "a")).alias("x")).select(F.col("x.a").alias("a"), F.col("node").alias("b")))
    compared = written(_verified(docs, nodes, best, k, percent, keep=True))
    links = compared.where("linked").select("a", "b").union(written(_group_links(compared, percent)))
    classes = written(components(links))

    # Exact round over nodes of different classes.
    more_counts = texts.mapInArrow(_common_counts(k, buckets, often, f"{token}-low"), blobs).groupBy("bucket").applyInArrow(_commonest, "key long, n long")
    common = commonest(written(low.unionByName(more_counts).groupBy("key").agg(F.sum("n").alias("n"))))
    asked = compared.select(F.col("b").alias("node"), F.col("a").alias("head"))
    labelled = written(nodes.join(classes, "node", "left").join(asked, "node", "left").select("rep", "node", F.coalesce("comp", "node").alias("comp"), F.coalesce("head", "node").alias("head")))
    whole = pick(docs, "doc_id", "text").select(F.coalesce("doc_id", F.lit(NO_ID)).cast("long").alias("rep"), "text")
    posted = whole.join(small(labelled, 64), "rep").select("text", "node", "comp", "head").mapInArrow(_postings(k, percent, buckets, common, token), _POST)
    pairs = written(posted.groupBy("bucket").applyInArrow(_candidates(percent), "a long, b long").distinct())
    more = written(_verified(docs, nodes, pairs, k, percent))
    final = components(links.union(more))

    member = nodes.join(final, "node", "left").select("node", "rep", F.coalesce("comp", "node").alias("comp"))
    least = member.groupBy("comp").agg(F.min("rep").alias("least"))
    named = member.join(least, "comp").select("node", "least")
    return sets.drop("least", "rank").join(named, "node", "left").select("doc_id", F.col("n").alias("n_shingles"), F.nullif(F.coalesce("least", "doc_id"), F.lit(NO_ID)).alias("component_id"))
