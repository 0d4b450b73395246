"""Steps where the lists are: walkers come to their node's list, which every walker there reads in place.

For programs that split (`samplers.splits`): all walkers at a node share its plain weights and their running sums, and each brings along
its few near edges, which lead back or to neighbours of its previous node. No list is copied for a walker, and the lists themselves are
packed and bucketed once (`WalkGraph.packed`), so what is shuffled is a row for each walker, whatever the lists' lengths."""

from __future__ import annotations

from collections.abc import Callable
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rambler.functions import rng
from rambler.functions.store import settle
from rambler.plans.program import WeightProgram

from .graph import WalkGraph, bucket_of, unpacked

#: Walkers at one node beyond so many are dealt over several buckets, each with the list.
CROWD = 16_384
#: A previous node that no edge's destination equals, and that isn't null (-1 in numpy).
ELSEWHERE = -(2**63)
#: Lists of at least so many neighbours are hubs to the key sampler, which draws their greatest keys alone.
HUB = 8192
#: Expected number of keys among those drawn that beat all others; a walker for whom none does, exp(-SURE) of them, looks at more of its list.
SURE = 6.0


class Lists:
    """The lists of a bucket in arrays, each in its own order; from packed rows, or from edges."""

    def __init__(self, rows: pa.Table):
        if "nodes" in rows.column_names:
            src, self.dst, self.h, self.label = unpacked(rows)
        else:
            src, idx, self.dst, self.h, self.label = (rows.column(c).to_numpy() for c in ("src", "idx", "dst", "h", "label"))
            order = np.lexsort((idx, src))
            order = order[(np.diff(src[order], prepend=-1) != 0) | (np.diff(idx[order], prepend=-1) != 0)]  # copies for different salts may meet in one bucket
            src, self.dst, self.h, self.label = src[order], self.dst[order], self.h[order], self.label[order]
        self.start = np.flatnonzero(np.concatenate([np.ones(min(1, len(src)), bool), src[1:] != src[:-1]]))
        self.nodes, self.deg = src[self.start], np.diff(np.append(self.start, len(src)))
        self.row = np.repeat(np.arange(len(self.nodes)), self.deg)

    def at(self, node: np.ndarray) -> np.ndarray:
        """Row of each node; all are there."""
        return np.searchsorted(self.nodes, node)

    def has(self, node: np.ndarray) -> np.ndarray:
        return self.nodes[np.minimum(self.at(node), len(self.nodes) - 1)] == node if len(self.nodes) else np.zeros(len(node), bool)

    def of_lists(self, f: np.ufunc, values: np.ndarray) -> np.ndarray:
        """`values` of edges reduced by f over each list."""
        return f.reduceat(values, self.start) if len(self.start) else values[:0]

    @cached_property
    def stats(self) -> dict[str, np.ndarray]:
        return {"h_max": self.of_lists(np.maximum, self.h), "h_min": self.of_lists(np.minimum, self.h), "h_sum": self.of_lists(np.add, self.h), "deg_cur": self.deg.astype(float)}

    def found(self, row: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(begin, end) of the edges to dst in the list of each row; lists are in the order of dst, and all are halved together."""
        ends = []
        for before in (np.less, np.less_equal):
            low, high = self.start[row], self.start[row] + self.deg[row]
            while (open_ := low < high).any():
                mid = (low + high) // 2
                right = open_ & before(self.dst[np.minimum(mid, len(self.dst) - 1)], dst)
                low, high = np.where(right, mid + 1, low), np.where(open_ & ~right, mid, high)
            ends.append(low)
        return ends[0], ends[1]


def _spread(begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(owner, place) of all places in the stretches."""
    n = end - begin
    owner = np.repeat(np.arange(len(n)), n)
    return owner, np.arange(len(owner)) - np.repeat(np.cumsum(n) - n, n) + begin[owner]


def _stretches(n: np.ndarray, limit: int) -> list[slice]:
    """Slices of walkers whose `n` add up to about `limit`."""
    cuts = np.flatnonzero(np.diff((np.cumsum(n) - n) // limit)) + 1
    return [slice(a, b) for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(n)])] if len(n) else []


def _ragged(owner: np.ndarray, values: np.ndarray, rows: int) -> pa.ListArray:
    """Lists of the values of owners 0 to rows - 1; owners are in order."""
    return pa.ListArray.from_arrays(pa.array(np.searchsorted(owner, np.arange(rows + 1)).astype(np.int32)), pa.array(values))


def _flat(column: pa.ChunkedArray, rows: int) -> tuple[np.ndarray, np.ndarray]:
    """(owner, value) of a column of lists; null is empty."""
    whole = column.combine_chunks()
    n = np.asarray(whole.value_lengths().fill_null(0))
    return np.repeat(np.arange(rows), n), whole.flatten().to_numpy(zero_copy_only=False)


def near_edges(states: DataFrame, graph: WalkGraph) -> DataFrame:
    """(prev, cur, near): the places in cur's list of edges to neighbours of prev, for distinct states that have any. The shorter of the two lists is sent to the other."""
    deg = graph.node_stats.select("src", "deg")
    other = deg.select(F.col("src").alias("prev"), F.col("deg").alias("_p"))
    sized = states.join(deg.select(F.col("src").alias("cur"), F.col("deg").alias("_c")).hint("merge"), "cur").join(other.hint("merge"), "prev")
    by_cur = F.col("_c") <= F.col("_p")
    ready = sized.select("prev", "cur", by_cur.alias("by_cur"), F.when(by_cur, F.col("cur")).otherwise(F.col("prev")).alias("short"))

    def send(rows: pa.Table, edges: pa.Table) -> pa.Table:
        at = Lists(edges)
        row = at.at(rows.column("short").to_numpy()) if len(rows) else np.zeros(0, np.int64)
        owner, place = _spread(at.start[row], at.start[row] + at.deg[row])
        return pa.table({"prev": rows.column("prev"), "cur": rows.column("cur"), "by_cur": rows.column("by_cur"), "ids": _ragged(owner, at.dst[place], len(rows))})

    def meet(rows: pa.Table, edges: pa.Table) -> pa.Table:
        at = Lists(edges)
        prev, cur = rows.column("prev").to_numpy(), rows.column("cur").to_numpy()
        by = rows.column("by_cur").combine_chunks().to_numpy(zero_copy_only=False).astype(bool)
        out = []
        for mine in (by, ~by):
            some = np.flatnonzero(mine)
            owner, ids = _flat(rows.column("ids").take(pa.array(some)), len(some))
            begin, end = at.found(at.at((prev if mine is by else cur)[some])[owner], ids) if len(some) else (owner, owner)
            if mine is by:  # places of the shorter list itself
                place = np.arange(len(owner)) - np.searchsorted(owner, owner)
                hit = end > begin
                who, place = owner[hit], place[hit]
            else:
                k, place = _spread(begin, end)
                who, place = owner[k], place - at.start[at.at(cur[some])][owner[k]] if len(some) else place
                pair = np.unique(np.stack([who, place], 1), axis=0) if len(who) else np.zeros((0, 2), np.int64)  # parallel edges of the shorter list
                who, place = pair[:, 0], pair[:, 1]
            have, who = np.unique(who, return_inverse=True)
            out.append(pa.table({"prev": prev[some][have], "cur": cur[some][have], "near": _ragged(who, place.astype(np.int32), len(have))}))
        return pa.concat_tables(out)

    edges = lambda: graph.packed.groupBy("bucket")
    sent = ready.withColumn("bucket", bucket_of("short", graph.buckets)).groupBy("bucket").cogroup(edges()).applyInArrow(_ifany(send), "prev long, cur long, by_cur boolean, ids array<long>")
    owner = sent.withColumn("owner", F.when(F.col("by_cur"), F.col("prev")).otherwise(F.col("cur"))).withColumn("bucket", bucket_of("owner", graph.buckets))
    return owner.groupBy("bucket").cogroup(edges()).applyInArrow(_ifany(meet), "prev long, cur long, near array<int>")


def _ifany(f):
    """`f`, with no rows where no walker came to the bucket."""

    def run(rows: pa.Table, edges: pa.Table) -> pa.Table:
        return f(rows, edges if len(rows) else edges.slice(0, 0))

    return run


class Here:
    """Walkers at their lists, all at their first step (prev is -1) or all not: the lists' plain weights, and each walker's near edges with their own."""

    def __init__(self, lists: Lists, program: WeightProgram, row: np.ndarray, prev: np.ndarray, step: int, near_owner: np.ndarray, near_place: np.ndarray):
        """near: the places in their lists of edges to neighbours of prev, by walker."""
        self.lists, self.program, self.row, self.prev, self.step, self.size = lists, program, row, prev, step, len(lists.dst)
        env = {"h": lists.h, "label": lists.label, "dst": lists.dst, "cur": lists.nodes[lists.row], "step": step, "linked": np.zeros(self.size, bool)}
        self.plain = np.array(np.broadcast_to(np.asarray(program.full.evaluate(env | {"prev": np.full(self.size, -1 if len(prev) and prev[0] == -1 else ELSEWHERE)}), float), (self.size,)))
        # Near edges with their own weights: to neighbours of prev, and back.
        owner, edge, linked = near_owner, lists.start[row][near_owner] + near_place, np.ones(len(near_owner), bool)
        back, at = _spread(*lists.found(row, prev))
        key = np.concatenate([owner * np.int64(self.size) + edge, back * np.int64(self.size) + at])
        self.key, which = np.unique(key, return_index=True)  # of an edge that is both, the first: linked
        linked = np.concatenate([linked, np.zeros(len(back), bool)])[which]
        self.owner, self.edge = np.divmod(self.key, max(self.size, 1))
        owner, edge = self.owner, self.edge
        env = {"h": lists.h[edge], "label": lists.label[edge], "dst": lists.dst[edge], "cur": lists.nodes[row[owner]], "prev": prev[owner], "step": step, "linked": linked}
        self.weight = np.broadcast_to(np.asarray(program.full.evaluate(env), float), edge.shape)

    def take(self, some: np.ndarray) -> Here:
        """Those walkers alone, by their numbers in order."""
        out = object.__new__(Here)
        out.__dict__.update(self.__dict__)
        mine = np.minimum(np.searchsorted(some, self.owner), max(len(some) - 1, 0))
        kept = some[mine] == self.owner if len(some) else np.zeros(len(self.owner), bool)
        out.row, out.prev, out.owner, out.edge, out.weight = self.row[some], self.prev[some], mine[kept], self.edge[kept], self.weight[kept]
        out.key = out.owner * np.int64(self.size) + out.edge
        return out

    @property
    def deg(self) -> np.ndarray:
        return self.lists.deg[self.row]

    @property
    def start(self) -> np.ndarray:
        return self.lists.start[self.row]

    @property
    def positive(self) -> np.ndarray:
        """How many of each walker's edges have positive weights."""
        some = np.concatenate([[0], np.cumsum(self.plain > 0)])
        return some[self.start + self.deg] - some[self.start] + np.bincount(self.owner, (self.weight > 0).astype(float) - (self.plain[self.edge] > 0), len(self.row)).astype(np.int64)

    def totals(self) -> tuple[np.ndarray, np.ndarray]:
        """(greatest weight, sum of weights) of each walker's list, from the plain ones; the list itself is read where all its greatest plain weights are near."""
        lists, n = self.lists, len(self.row)
        most, whole = lists.of_lists(np.maximum, self.plain), lists.of_lists(np.add, self.plain)[self.row]
        ties = lists.of_lists(np.add, (self.plain == most[lists.row]).astype(np.int64))
        hidden = np.bincount(self.owner, self.plain[self.edge] == most[self.row[self.owner]], n) >= ties[self.row]
        top = np.where(hidden, -np.inf, most[self.row])
        np.maximum.at(top, self.owner, self.weight)
        rest = np.flatnonzero(hidden)
        for part in _stretches(self.deg[rest], 1_000_000):
            some = rest[part]
            owner, edge = _spread(self.start[some], self.start[some] + self.deg[some])
            top[some] = np.maximum.reduceat(self.weights(some[owner], edge), np.cumsum(self.deg[some]) - self.deg[some])
        return top, whole + np.bincount(self.owner, self.weight - self.plain[self.edge], n)

    def weights(self, owner: np.ndarray, edge: np.ndarray) -> np.ndarray:
        """The edges' weights for their walkers."""
        if not len(self.key):
            return self.plain[edge]
        key = owner * np.int64(self.size) + edge
        at = np.minimum(np.searchsorted(self.key, key), len(self.key) - 1)
        return np.where(self.key[at] == key, self.weight[at], self.plain[edge])


def visit(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, act: Callable[[Here, np.ndarray], pa.Table], schema: str) -> DataFrame:
    """What `act` makes of walkers at their lists and of their ids, for all stored walkers that aren't at dead ends."""
    states = settle(walkers.where("prev is not null").select("prev", "cur").distinct()) if program.needs("linked") else None
    if states is not None and not states.isEmpty():  # on a first step there are none, and the lists aren't read for them
        here = walkers.select("walk_id", "step", "prev", "cur").join(near_edges(states, graph).hint("merge"), ["prev", "cur"], "left")
    else:
        here = walkers.select("walk_id", "step", "prev", "cur").withColumn("near", F.lit(None).cast("array<int>"))
    crowds = settle(walkers.groupBy("cur").agg(F.count("*").alias("n")).where(F.col("n") > CROWD).select("cur", F.ceil(F.col("n") / CROWD).cast("int").alias("salts")))
    program.full, program.analysis  # parsed once, here  # noqa: B018

    def run(rows: pa.Table, edges: pa.Table) -> pa.Table:
        lists = Lists(edges)
        rows = rows.filter(pa.array(lists.has(rows.column("cur").to_numpy()), pa.bool_()))
        walk, step, cur = (rows.column(c).to_numpy() for c in ("walk_id", "step", "cur"))
        prev = rows.column("prev").fill_null(-1).to_numpy()
        owner, place = _flat(rows.column("near"), len(rows)) if len(rows) else (np.zeros(0, np.int64),) * 2
        out = []
        for first in (True, False):
            for k in np.unique(step) if len(rows) else ():
                some = np.flatnonzero((step == k) & ((prev == -1) == first))
                if not len(some):
                    continue
                mine = np.searchsorted(some, owner)
                kept = (mine < len(some)) & (some[np.minimum(mine, len(some) - 1)] == owner)
                out.append(act(Here(lists, program, lists.at(cur[some]), prev[some], int(k), mine[kept], place[kept]), walk[some]))
        return pa.concat_tables(out) if out else empty

    empty = pa.table({c: pa.array([], pa.string() if t == "string" else pa.int64()) for c, t in (x.split() for x in schema.split(", "))})
    come = lambda some, bucket, edges: some.withColumn("bucket", bucket).select("bucket", "walk_id", "step", "prev", "cur", "near").groupBy("bucket").cogroup(edges.groupBy("bucket")).applyInArrow(_ifany(run), schema)
    if crowds.isEmpty():
        return come(here, bucket_of("cur", graph.buckets), graph.packed)
    here = settle(here.join(F.broadcast(crowds), "cur", "left"))  # a row for each CROWD of walkers
    many = 2 * int(walkers.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    salted = graph.edges.join(F.broadcast(crowds.withColumnRenamed("cur", "src")), "src").withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)))
    crowded = here.where("salts is not null").withColumn("salt", F.pmod(F.xxhash64("walk_id"), F.col("salts")).cast("int"))
    there = come(crowded, bucket_of("cur", many, "salt"), salted.select("src", "idx", "dst", "h", "label", bucket_of("src", many, "salt").alias("bucket")))
    return there.unionByName(come(here.where("salts is null"), bucket_of("cur", graph.buckets), graph.packed))


STEP = "walk_id long, next long, reads long, draws long"


def _moved(here: Here, walk: np.ndarray, to: np.ndarray, reads: np.ndarray, draws: np.ndarray, **more) -> pa.Table:
    on = to >= 0
    return pa.table({"walk_id": walk[on], "next": here.lists.dst[to[on]], "reads": reads[on], "draws": draws[on]} | {k: pa.array(v[on].tolist(), pa.string()) for k, v in more.items()})


def list_jumps(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, seed: int, lane: int) -> DataFrame:
    """(walk_id, next, reads, draws) of stored walkers, as `samplers.jump_lanes` picks from all candidates."""

    def act(here: Here, walk: np.ndarray) -> pa.Table:
        return _moved(here, walk, *jump_in_place(here, rng.states(seed, walk, np.full(len(walk), here.step), rng.JUMP), lane))

    return visit(walkers, graph, program, act, STEP)


def list_keys(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, seed: int) -> DataFrame:
    """(walk_id, next, reads, draws) of stored walkers, as the least keys of all candidates pick."""

    def act(here: Here, walk: np.ndarray) -> pa.Table:
        reads = here.positive
        return _moved(here, walk, least_keys(here, rng.states(seed, walk, np.full(len(walk), here.step), rng.KEY)), reads, reads)

    return visit(walkers, graph, program, act, STEP)


def list_adaptive(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, seed: int, kind: str, ratio: float, threshold: int, trials: int, reservoir: str, lane: int) -> DataFrame:
    """(walk_id, next, reads, draws, mode) of stored walkers: each is tried by rejection under the derived bound, `trials` times at most, if the
    selector `kind` says so, and the others, as those whom no trial served, take the reservoir (keys or jump)."""

    def act(here: Here, walk: np.ndarray) -> pa.Table:
        n, row = len(walk), here.row
        states = lambda tag: rng.states(seed, walk, np.full(n, here.step), tag)
        env = {k: v[row] for k, v in here.lists.stats.items()} | {"step": here.step, "prev": here.prev, "cur": here.lists.nodes[row]}
        bound, total = (np.broadcast_to(np.asarray(x.evaluate(env), float), (n,)) for x in (program.analysis.bound, program.analysis.total))
        if kind == "exact":
            top, whole = here.totals()
        rejects = {
            "rejection": lambda: np.ones(n, bool), "reservoir": lambda: np.zeros(n, bool), "cost": lambda: ratio * bound < total, "exact": lambda: ratio * top < whole,
            "degree": lambda: here.deg >= threshold, "random": lambda: rng.uniforms(states(rng.COIN), np.zeros(n)) < 0.5,
        }[kind]()
        out, tried = trials_in_place(here, states(rng.SLOT), states(rng.HEIGHT), bound, np.flatnonzero(rejects), trials)
        reads, draws, accepted = tried.copy(), 2 * tried, out >= 0
        left = np.flatnonzero(~accepted)
        if len(left):
            rest, state = here.take(left), tuple(x[left] for x in states(rng.KEY if reservoir == "keys" else rng.JUMP))
            if reservoir == "keys":
                out[left], more = least_keys(rest, state), (rest.positive,) * 2
            else:
                out[left], *more = jump_in_place(rest, state, lane)
            reads[left] += more[0]
            draws[left] += more[1]
        return _moved(here, walk, out, reads, draws, mode=np.where(accepted, "rejection", reservoir))

    return visit(walkers, graph, program, act, f"{STEP}, mode string")


def trials_in_place(here: Here, slots, heights, bound: np.ndarray, pending: np.ndarray, trials: int) -> tuple[np.ndarray, np.ndarray]:
    """(edge or -1, trials made) of walkers, of whom those in `pending` make at most `trials`."""
    out, tried, deg, start = np.full(len(here.row), -1, np.int64), np.zeros(len(here.row), np.int64), here.deg, here.start
    for t in range(trials):
        if not len(pending):
            break
        item = np.full(len(pending), t)
        edge = start[pending] + np.minimum((rng.uniforms((slots[0][pending], slots[1][pending]), item) * deg[pending]).astype(np.int64), deg[pending] - 1)
        ok = rng.uniforms((heights[0][pending], heights[1][pending]), item) * bound[pending] < here.weights(pending, edge)
        out[pending[ok]] = edge[ok]
        tried[pending] += 1
        pending = pending[~ok]
    return out, tried


def running_sums(w: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Running sums within each list (lists begin at `first`), added in the list's order; lists of one length are the rows of one table."""
    size, acc = np.diff(np.append(first, len(w))), np.empty(len(w))
    order = np.argsort(size, kind="stable")
    for same in np.split(order, np.flatnonzero(np.diff(size[order])) + 1) if len(order) else ():
        at = first[same][:, None] + np.arange(size[same[0]])
        acc[at] = np.cumsum(w[at], axis=1)
    return acc


def list_prefixes(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, seed: int) -> DataFrame:
    """(walk_id, next, reads, draws) of stored walkers, as the running sums of all candidates pick (see `samplers.prefix_step`)."""

    def act(here: Here, walk: np.ndarray) -> pa.Table:
        state, out, deg, positive = rng.states(seed, walk, np.full(len(walk), here.step), rng.KEY), np.full(len(walk), -1, np.int64), here.deg, here.positive
        for part in _stretches(deg, 1_000_000):
            owner, item = _spread(np.zeros(part.stop - part.start, np.int64), deg[part])
            who, edge = owner + part.start, item + here.start[part][owner]
            w = here.weights(who, edge)
            acc = running_sums(w, np.cumsum(deg[part]) - deg[part])
            hit = np.flatnonzero((rng.uniforms((state[0][who], state[1][who]), item) * acc < w) & (w > 0))
            out[who[hit]] = edge[hit]  # the last one stays
        return _moved(here, walk, out, 2 * positive, positive)

    return visit(walkers, graph, program, act, STEP)


def least_keys(here: Here, state) -> np.ndarray:
    """The edge of each walker's least key -ln(u)/w, or -1. At hubs, items of great uniforms come first: all others have keys of
    -ln(1 - 2^-j)/top at least, top being the greatest weight (see `samplers.hub_step`). Where these don't decide, more items are drawn."""
    deg, start, out = here.deg, here.start, np.full(len(here.row), -1, np.int64)
    top = here.lists.of_lists(np.maximum, here.plain)[here.row]
    np.maximum.at(top, here.owner, here.weight)
    with np.errstate(divide="ignore", invalid="ignore"):
        depth = np.log2(here.lists.of_lists(np.add, here.plain)[here.row] / (SURE * top))
    level = np.where(deg >= HUB, np.select([depth >= j for j in reversed(rng.CREST)], list(reversed(rng.CREST)), 0), 0)

    def draw(who: np.ndarray, item: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(walkers, their least key, its edge) among the items drawn."""
        edge = start[who] + item
        w = here.weights(who, edge)
        with np.errstate(divide="ignore"):
            key = np.where(w > 0, -np.log(rng.uniforms((state[0][who], state[1][who]), item)) / w, np.inf)
        begin = np.flatnonzero(np.diff(who, prepend=-1))
        least = np.minimum.reduceat(key, begin) if len(who) else key
        hit = np.flatnonzero((key == np.repeat(least, np.diff(np.append(begin, len(who))))) & (key < np.inf))
        at = np.full(len(here.row), -1, np.int64)
        at[who[hit][::-1]] = edge[hit][::-1]
        return who[begin], least, at[who[begin]]

    for j in reversed(rng.CREST):
        at = np.flatnonzero(level == j)
        level[at] = 0
        for part in _stretches(deg[at] >> int(j), 200_000):
            some = at[part]
            owner, item = rng.high_items((state[0][some], state[1][some]), deg[some], int(j))
            who, least, edge = draw(some[owner], item)
            sure = least < -np.log1p(-(2.0 ** -int(j))) / top[who] * (1 - 1e-12)
            out[who[sure]] = edge[sure]
        if j - 2 >= 10:
            level[at[out[at] < 0]] = j - 2
    rest = np.flatnonzero((out < 0) & (deg > 0))
    for part in _stretches(deg[rest], 1_000_000):
        some = rest[part]
        owner, item = _spread(np.zeros(len(some), np.int64), deg[some])
        who, _, edge = draw(some[owner], item)
        out[who] = edge
    return out


def jump_in_place(here: Here, state, lane: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(edge or -1, reads, draws) of walkers."""
    lists, row, n, size, plain, key, edge, weight = here.lists, here.row, len(here.row), here.size, here.plain, here.key, here.edge, here.weight
    reads = here.positive
    # Running sums of plain weights, each lane's scaled to its largest.
    begins = lists.start[lists.row]
    lane_of = (np.arange(size) - begins) // lane
    cut = np.flatnonzero(np.diff(lists.row, prepend=-1) | np.diff(lane_of, prepend=-1))
    top = np.maximum.reduceat(plain, cut) if size else plain
    top = np.where(top > 0, top, 1.0)
    lane_at = np.repeat(np.arange(len(cut)), np.diff(np.append(cut, size)))
    v = np.where(plain > 0, np.maximum(plain / top[lane_at], 1e-300), 0.0) if size else plain
    acc = np.concatenate([[0.0], np.cumsum(v)])
    after = np.full(size + 1, size)
    after[:size] = np.minimum.accumulate(np.where(v > 0, np.arange(size), size)[::-1])[::-1]  # the next place of positive plain weight
    out, draws = np.full(n, -1, np.int64), np.zeros(n, np.int64)
    lanes = -(-lists.deg[row] // lane)
    for part in _stretches(lanes, 200_000):
        mine, number = _spread(np.zeros(part.stop - part.start, np.int64), lanes[part])
        mine = mine + part.start
        begin = lists.start[row[mine]] + number * lane
        end = np.minimum(begin + lane, lists.start[row[mine]] + lists.deg[row[mine]])
        scale = top[lane_at[begin]]
        pointer, last = np.searchsorted(key, mine * np.int64(size) + begin), np.searchsorted(key, mine * np.int64(size) + end)
        pos = begin.copy()
        edges, weights = np.append(edge, size), np.append(weight, 0.0)

        def land(units: np.ndarray, mass: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            """(place or -1, scaled weight) of the first item at which the sum from `pos` on reaches `mass`; `pos` goes behind it."""
            to, w, mass = np.full(len(units), -1, np.int64), np.zeros(len(units)), mass.copy()
            open_ = np.arange(len(units))
            while len(open_):
                u = units[open_]
                stop = np.where(pointer[u] < last[u], edges[pointer[u]], end[u])
                with np.errstate(over="ignore"):
                    i = after[np.minimum(np.maximum(np.searchsorted(acc[1:], acc[pos[u]] + mass[open_]), pos[u]), size)]
                hit = i < stop
                to[open_[hit]], w[open_[hit]], pos[u[hit]] = i[hit], v[i[hit]], i[hit] + 1
                open_, u, stop = open_[~hit], u[~hit], stop[~hit]
                mass[open_] = np.maximum(mass[open_] - (acc[stop] - acc[pos[u]]), 0)
                pos[u] = stop
                more = stop < end[u]  # else the lane is over
                open_, u, stop = open_[more], u[more], stop[more]
                own = np.where(weights[pointer[u]] > 0, np.maximum(weights[pointer[u]] / scale[u], 1e-300), 0.0)
                pointer[u] += 1
                pos[u] = stop + 1
                hit = (own > 0) & (mass[open_] <= own)
                to[open_[hit]], w[open_[hit]] = stop[hit], own[hit]
                mass[open_] -= own
                open_ = open_[~hit]
            return to, w

        draw = lambda units, k: rng.uniforms((state[0][mine[units]], state[1][mine[units]]), (number[units] << 20) + k)  # noqa: E731, B023
        units = np.arange(len(mine))
        place, w = land(units, np.zeros(len(units)))
        active = units[place >= 0]
        best, count = np.full(len(mine), -np.inf), np.zeros(len(mine), np.int64)
        best[active], count[active] = np.log(draw(active, 0)) / w[place >= 0], 1
        active = active[best[active] < 0]
        while len(active):
            with np.errstate(over="ignore"):
                to, w = land(active, np.log(draw(active, count[active])) / best[active])
            count[active] += 1
            on = to >= 0
            active, to, w = active[on], to[on], w[on]
            low = np.exp(w * best[active])
            best[active] = np.log(low + draw(active, count[active]) * (1 - low)) / w
            count[active] += 1
            place[active] = to
            active = active[best[active] < 0]
        with np.errstate(over="ignore"):
            key_of = np.where(place >= 0, best / scale, -np.inf)
        order = np.lexsort((key_of, mine))
        tops = order[np.flatnonzero(np.append(np.diff(mine[order]) != 0, True))]
        out[mine[tops]] = place[tops]
        draws += np.bincount(mine, count, n).astype(np.int64)
    return out, reads, draws
