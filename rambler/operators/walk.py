"""Whole walks: supersteps over a partitioned graph, or one Arrow stage over a replicated one. Both give the same walks."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass, field
from functools import cached_property, reduce

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rambler.functions import rng
from rambler.functions.store import settle
from rambler.plans.program import WeightProgram

from .graph import WalkGraph
from .plain import Near, Plain, blocks, by_inverse, greatest, last_by_prefix, least_keys, lines
from .samplers import HUB, STEPS, SURE, alias_picks, at_lists, jump_lanes, running_sums, splits, stretches

#: Edges up to which mode 'auto' replicates the graph (about 40 bytes each in every worker).
REPLICATED_EDGES = 25_000_000
#: Edges of a stored graph that pass through the driver's heap at once.
READ_EDGES = 4_000_000


@dataclass(frozen=True)
class WalkConfig:
    steps: int = 80
    seed: int = 42
    mode: str = "auto"
    trials: int = 8
    rounds: int = 2
    partitions: int | None = None
    sampler_options: dict = field(default_factory=dict)


def one_per_node(graph: WalkGraph) -> DataFrame:
    return graph.node_stats.select(F.col("src").alias("start")) if graph.kept else graph.edges.select(F.col("src").alias("start")).distinct()


def placed(starts: DataFrame, parts: int, how: str = "hash") -> DataFrame:
    """Walks dealt over workers by the hash of their start, or by ranges of it."""
    return starts.repartition(parts, "start") if how == "hash" else starts.repartitionByRange(parts, "start")


def random_walks(graph: WalkGraph, program: WeightProgram, starts: DataFrame | None = None, sampler: str = "adaptive", config: WalkConfig | None = None) -> DataFrame:
    """(walk_id, step, node), step 0 being the start; a walk ends early at a dead end. walk_id: the column of starts, or the start."""
    config = config or WalkConfig()
    starts = one_per_node(graph) if starts is None else starts
    if "walk_id" not in starts.columns:
        starts = starts.withColumn("walk_id", F.col("start"))
    mode = config.mode
    if mode == "auto":
        mode = "replicated" if sampler in REPLICATED and graph.edges.count() <= REPLICATED_EDGES else "superstep"
    return (walk_replicated if mode == "replicated" else walk_superstep)(graph, program, starts, sampler, config)


def walk_superstep(graph: WalkGraph, program: WeightProgram, starts: DataFrame, sampler: str, config: WalkConfig, log: bool = False) -> DataFrame:
    """One join of walkers and edges for each step. Every step's rows are stored as they come, which also ends the lineage: a lost executor costs one step at most."""
    step_of: Callable = STEPS[sampler]
    options = dict(config.sampler_options)
    if sampler in ("rejection_exact", "rejection_bound", "adaptive"):
        options |= {"trials": config.trials, "rounds": config.rounds}
    if not graph.kept:
        graph = graph.stored()  # edges, pairs and statistics are read at every step, but computed once
    if log and not at_lists(graph, program):  # steps at the lists always count
        graph = WalkGraph(graph.edges, graph.kept, True)
    now = settle(starts.select("walk_id", F.lit(0).alias("step"), F.lit(None).cast("long").alias("prev"), F.col("start").cast("long").alias("cur")))
    steps = [now.select("walk_id", "step", F.col("cur").alias("node"), *([F.lit(None).cast("long").alias("reads"), F.lit(None).cast("long").alias("draws"), F.lit(None).cast("string").alias("mode")] if log else []))]
    for k in range(min(config.steps, program.depth or config.steps)):
        taken = step_of(now, graph, program, config.seed, **options)
        moved = now.join(taken, "walk_id").select("walk_id", F.lit(k + 1).alias("step"), F.col("cur").alias("prev"), F.col("next").alias("cur"), "reads", "draws", "mode")
        now = settle(moved)
        steps.append(now.select("walk_id", "step", F.col("cur").alias("node"), *(["reads", "draws", "mode"] if log else [])))
        now = now.select("walk_id", "step", "prev", "cur")
    return reduce(DataFrame.unionByName, steps)


# Replicated -------------------------------------------------------------------------------------------------------------
class Csr:
    """The graph in arrays: nodes in order, their lists one after another, and (node, neighbour) pairs for existence tests."""

    def __init__(self, src: np.ndarray, dst: np.ndarray, h: np.ndarray, label: np.ndarray):
        self.heavy: dict = {}
        self.plains: dict = {}
        if len(src) and not _ordered(src, dst, label):
            order = np.lexsort((label, dst, src))
            src, dst, h, label = src[order], dst[order], h[order], label[order]
        self.h, self.label = h, label
        self.start = np.flatnonzero(np.concatenate([np.ones(min(1, len(src)), bool), src[1:] != src[:-1]]))
        self.nodes, self.deg = src[self.start], np.diff(np.append(self.start, len(src)))
        self.h_max, self.h_min = np.maximum.reduceat(self.h, self.start) if len(src) else self.h, np.minimum.reduceat(self.h, self.start) if len(src) else self.h
        self.h_sum = np.add.reduceat(self.h, self.start) if len(src) else self.h
        self.names = np.unique(np.concatenate([self.nodes, np.unique(dst)]))
        self.to = np.searchsorted(self.names, dst).astype(np.int32)
        self.name = np.searchsorted(self.names, self.nodes)
        self.row_of = np.full(len(self.names), -1, np.int64)
        self.row_of[self.name] = np.arange(len(self.nodes))
        # Marks of the neighbours' hashes, 16 to 32 bits for each and a list's together: most that aren't there end at one look instead of a binary search.
        bits = np.minimum(np.frexp(self.deg)[1] + 4, 32)
        self.shift, size = (32 - bits).astype(np.uint32), np.left_shift(1, bits - 3)
        self.base = np.cumsum(size) - size
        self.marks = np.zeros(int(size.sum()), np.uint8)
        for a in range(0, len(src), 1_000_000):
            at, bit = self._marks(np.searchsorted(self.start, np.arange(a, min(a + 1_000_000, len(src))), side="right") - 1, self.to[a : a + 1_000_000])
            for k in range(8):
                self.marks[at[bit == k]] |= np.uint8(1 << k)

    @cached_property
    def dst(self) -> np.ndarray:
        return self.names[self.to]

    def ends(self, edge: np.ndarray) -> np.ndarray:
        return self.names[self.to[edge]]

    def plain(self, program: WeightProgram, prev_row: np.ndarray) -> Plain | None:
        """What walkers share who all have a previous node, for programs that split and give each edge a positive weight; that of the last program is kept."""
        if not len(prev_row) or prev_row.min() < 0:
            return None
        if program not in self.plains:
            found = Plain(self, program) if splits(program) else None
            self.plains = {program: found if found is not None and found.usable else None}
        return self.plains[program]

    def place(self, row: np.ndarray, to: np.ndarray) -> np.ndarray:
        """The first edge, of the list of each row, to `to` or one after it; the list's end if there is none."""
        low, high = self.start[row], self.start[row] + self.deg[row]
        last = len(self.to) - 1
        for _ in range(int(self.deg[row].max()).bit_length() if len(row) else 0):
            mid = (low + high) >> 1
            right = (self.to[np.minimum(mid, last)] < to) & (low < high)
            low, high = np.where(right, mid + 1, low), np.where(right, high, mid)
        return low

    def near(self, row: np.ndarray, prev_row: np.ndarray, linked: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(walker, edge, linked) in order, of edges back to each walker's previous node and, if `linked` is asked for, to that node's neighbours."""
        back = self.name[prev_row]
        owner, edge = _spread(self.place(row, back), self.place(row, back + 1))
        found = [(owner, edge, self.linked(prev_row[owner], self.to[edge]) if linked else np.zeros(len(owner), bool))]
        ends = lambda r: (self.to[self.start[r]], self.to[self.start[r] + self.deg[r] - 1])
        (a, b), (c, d) = ends(row), ends(prev_row)
        meet, by_cur = (a <= d) & (c <= b) & linked, self.deg[row] <= self.deg[prev_row]
        for mine, short, other in ((np.flatnonzero(meet & by_cur), row, prev_row), (np.flatnonzero(meet & ~by_cur), prev_row, row)):
            parts = [(np.zeros(0, np.int64),) * 2]
            for some in blocks(self.deg[short[mine]]):
                some = mine[some]
                at, there = lines(self.start[short[some]], self.deg[short[some]])
                maybe = self.marked(other[some][:, None], np.take(self.to, at, mode="clip"))
                if there is not None:
                    maybe &= there
                parts.append((some[np.nonzero(maybe)[0]], at[maybe]))
            who, edge = (np.concatenate(x) for x in zip(*parts))
            to = self.to[edge]
            own = to != back[who]
            who, edge, to = who[own], edge[own], to[own]
            begin = self.place(other[who], to)
            hit = np.flatnonzero((begin < self.start[other[who]] + self.deg[other[who]]) & (self.to[np.minimum(begin, len(self.to) - 1)] == to))
            who, edge, to, begin = who[hit], edge[hit], to[hit], begin[hit]
            if short is prev_row:
                k, edge = _spread(begin, self.place(row[who], to + 1))
                who = who[k]
            found.append((who, edge, np.ones(len(who), bool)))
        owner, edge, linked = (np.concatenate(x) for x in zip(*found))
        key, which = np.unique(owner * np.int64(len(self.to) + 1) + edge, return_index=True)  # an edge is met again by the shorter list's parallel ones
        return owner[which], edge[which], linked[which]

    def heaviest(self, row: int, most: int = 512) -> tuple[np.ndarray, float]:
        """(places of a list's heaviest edges, greatest h of the others)."""
        if row not in self.heavy:
            h = self.h[self.start[row] : self.start[row] + self.deg[row]]
            order = np.argpartition(-h, most)
            self.heavy[row] = np.sort(order[:most]), float(h[order[most]])
        return self.heavy[row]

    def _marks(self, row: np.ndarray, to: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(byte, bit) of the mark of each pair."""
        slot = to.astype(np.uint32)
        slot *= np.uint32(0x9E3779B1)
        slot >>= self.shift[row]
        bit = slot.astype(np.uint8)
        bit &= np.uint8(7)
        slot >>= np.uint32(3)
        return self.base[row] + slot, bit

    def at(self, node: np.ndarray) -> np.ndarray:
        """Row of each node that has edges, else -1."""
        if not len(self.names):
            return np.full(len(node), -1, np.int64)
        k = np.minimum(np.searchsorted(self.names, node), len(self.names) - 1)
        return np.where(self.names[k] == node, self.row_of[k], -1)

    def marked(self, row: np.ndarray, to: np.ndarray) -> np.ndarray:
        """Whether the pairs may be there; the shape is that of `to`."""
        at, bit = self._marks(row, to)
        found = np.take(self.marks, at)
        found >>= bit
        found &= np.uint8(1)
        return found.view(bool)

    def linked(self, row: np.ndarray, to: np.ndarray) -> np.ndarray:
        out = (row >= 0) & self.marked(row, to)
        maybe = np.flatnonzero(out)
        row, to = row[maybe], to[maybe]
        at = self.place(row, to)
        out[maybe] = (at < self.start[row] + self.deg[row]) & (self.to[np.minimum(at, len(self.to) - 1)] == to)
        return out

    def weights(self, program: WeightProgram, edge: np.ndarray, row: np.ndarray, prev: np.ndarray, prev_row: np.ndarray, step: int) -> np.ndarray:
        env = {"h": self.h[edge], "label": self.label[edge], "dst": self.ends(edge), "prev": prev, "cur": self.nodes[row], "step": step, "deg_cur": self.deg[row].astype(float)}
        if program.needs("deg_prev"):
            env["deg_prev"] = np.where(prev_row >= 0, self.deg[prev_row], 1).astype(float)
        if program.needs("linked"):
            env["linked"] = self.linked(prev_row, self.to[edge])
        return np.broadcast_to(np.asarray(program.full.evaluate(env), float), edge.shape)


def _ordered(src: np.ndarray, dst: np.ndarray, label: np.ndarray) -> bool:
    up = lambda x, then: (x[1:] > x[:-1]) | (x[1:] == x[:-1]) & then
    return bool(up(src, up(dst, label[1:] >= label[:-1])).all())


def _spread(begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(owner, place) of all places in the stretches."""
    n = end - begin
    owner = np.repeat(np.arange(len(n)), n)
    return owner, np.arange(len(owner)) - np.repeat(np.cumsum(n) - n, n) + begin[owner]


def _expand(csr: Csr, row: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(owner, edge, first place of each owner) of all candidates of the walkers in `row`."""
    deg = csr.deg[row]
    first = np.concatenate([[0], np.cumsum(deg)[:-1]])
    owner = np.repeat(np.arange(len(row)), deg)
    return owner, np.arange(len(owner)) - first[owner] + csr.start[row][owner], first


#: Reservoirs that needn't read whole lists of programs that split.
IN_PLACE = frozenset({"keys", "prefix", "inverse"})


def _reservoir(csr: Csr, program, seed, how, walk, row, prev, prev_row, step) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(edge or -1, reads, draws) by keys, prefix sums, inverse transform, jumps or alias tables, for walkers whose node has edges."""
    if (plain := csr.plain(program, prev_row)) is not None and how in IN_PLACE:
        return _in_place(csr, program, seed, how, walk, row, prev, prev_row, step, plain)
    return _over_all(csr, program, seed, how, walk, row, prev, prev_row, step)


def _in_place(csr: Csr, program, seed, how, walk, row, prev, prev_row, step, plain: Plain) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """As `_over_all`, with what the walkers share."""
    deg, state = csr.deg[row], lambda tag: rng.states(seed, walk, np.full(len(walk), step), tag)
    if how == "keys":
        return least_keys(plain, state(rng.KEY), row, prev, prev_row), deg, deg
    near = Near(plain, row, prev, prev_row)
    if how == "prefix":
        out, unsure = last_by_prefix(plain, near, state(rng.KEY), row)
    else:
        out, unsure = by_inverse(plain, near, rng.uniforms(state(rng.PICK), np.zeros(len(walk))), row)
    for part in stretches(deg[at := np.flatnonzero(unsure)]):
        some = at[part]
        out[some] = _over_all(csr, program, seed, how, walk[some], row[some], prev[some], prev_row[some], step)[0]
    return out, 2 * deg, deg if how == "prefix" else np.ones(len(row), np.int64)


def _over_all(csr: Csr, program, seed, how, walk, row, prev, prev_row, step) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    owner, edge, first = _expand(csr, row)
    if (plain := csr.plain(program, prev_row)) is not None:
        near, w = Near(plain, row, prev, prev_row), plain.weight[edge]
        w[first[near.owner] + near.edge - csr.start[row[near.owner]]] = near.weight
    else:
        w = csr.weights(program, edge, row[owner], prev[owner], prev_row[owner], step)
    idx = edge - csr.start[row][owner]
    out = np.full(len(row), -1, np.int64)
    positive = np.add.reduceat((w > 0).astype(np.int64), first)
    if how == "keys":
        a, b = rng.states(seed, walk, np.full(len(walk), step), rng.KEY)
        u = rng.uniforms((a[owner], b[owner]), idx)
        with np.errstate(divide="ignore"):
            key = np.where(w > 0, -np.log(u) / w, np.inf)
        least = np.minimum.reduceat(key, first)
        hit = np.flatnonzero((key == least[owner]) & (key < np.inf))
        out[owner[hit][::-1]] = edge[hit][::-1]
        return out, positive, positive
    if how in ("jump", "jump_shared"):
        at, _, draws = jump_lanes(w, owner, idx, rng.states(seed, walk, np.full(len(walk), step), rng.JUMP), len(row), shared=how == "jump_shared")
        return np.where(at >= 0, edge[at], -1), positive, draws
    if how == "alias":
        some = np.flatnonzero(w > 0)
        if len(some):
            begin = np.flatnonzero(np.diff(owner[some], prepend=-1))
            who = owner[some[begin]]
            out[who] = edge[some[alias_picks(w[some], begin, rng.states(seed, walk[who], np.full(len(who), step), rng.PICK))]]
        return out, positive, np.full(len(row), 2, np.int64)
    acc = running_sums(w, first)
    whole = acc[np.append(first[1:], len(acc)) - 1]
    if how == "prefix":
        a, b = rng.states(seed, walk, np.full(len(walk), step), rng.KEY)
        u = rng.uniforms((a[owner], b[owner]), idx)
        hit = np.flatnonzero((u * acc < w) & (w > 0))
        out[owner[hit]] = edge[hit]  # the last one stays
        return out, 2 * positive, positive
    u = rng.uniforms(rng.states(seed, walk, np.full(len(walk), step), rng.PICK), np.zeros(len(walk)))
    hit = np.flatnonzero((acc > (u * whole)[owner]) & (w > 0))
    out[owner[hit][::-1]] = edge[hit][::-1]
    return out, 2 * positive, np.ones(len(row), np.int64)


def _hub_keys(csr: Csr, program, seed, walk, row, prev, prev_row, step) -> np.ndarray:
    """The edge of the least key of each walker, or -1 where the greatest uniforms don't decide (see `samplers.hub_step`).

    A list's heaviest edges are all drawn; of the others, whose bound is lower, those of great uniforms only."""
    out = np.full(len(row), -1, np.int64)
    if program.analysis.bound is None:
        return out
    heavy = [csr.heaviest(r) for r in row]
    rest = np.array([h for _, h in heavy])
    env = {"h_max": rest, "h_min": csr.h_min[row], "h_sum": csr.h_sum[row], "deg_cur": csr.deg[row].astype(float), "deg_prev": np.where(prev_row >= 0, csr.deg[prev_row], np.nan), "step": step, "prev": prev, "cur": csr.nodes[row]}
    with np.errstate(invalid="ignore", divide="ignore"):
        bound = np.broadcast_to(np.asarray(_null_skipping(program.analysis.bound, env), float), (len(row),))
        total = np.broadcast_to(np.asarray(_null_skipping(program.analysis.total, env), float), (len(row),))
        depth = np.log2(total / (SURE * bound))
    level = np.select([depth >= j for j in reversed(rng.CREST)], list(reversed(rng.CREST)), 0)
    state = rng.states(seed, walk, np.full(len(walk), step), rng.KEY)
    for j in np.unique(level[level > 0]):
        at = np.flatnonzero(level == j)
        for part in stretches((csr.deg[row[at]] >> int(j)) + len(heavy[0][0]), 500_000):
            some = at[part]
            owner, item = rng.high_items((state[0][some], state[1][some]), csr.deg[row[some]], int(j))
            sure = [heavy[k][0] for k in some]
            owner = np.concatenate([owner, np.repeat(np.arange(len(some)), [len(x) for x in sure])])
            item = np.concatenate([item, *sure])
            order = np.argsort(owner, kind="stable")
            owner, item = owner[order], item[order]
            who, edge = some[owner], csr.start[row[some]][owner] + item
            w = csr.weights(program, edge, row[who], prev[who], prev_row[who], step)
            with np.errstate(divide="ignore"):
                key = np.where(w > 0, -np.log(rng.uniforms((state[0][who], state[1][who]), item)) / w, np.inf)
            first = np.searchsorted(owner, np.arange(len(some)))  # each walker has heavy edges
            least = np.minimum.reduceat(key, first)
            limit = -np.log1p(-(2.0 ** -int(j))) / bound[some] * (1 - 1e-12)
            hit = np.flatnonzero((key == least[owner]) & (key < limit[owner]))
            out[who[hit][::-1]] = edge[hit][::-1]
    return out


def _rejected(csr: Csr, program, seed, bound, limit, walk, row, prev, prev_row, step) -> tuple[np.ndarray, np.ndarray]:
    """(edge or -1, trials made) after at most `limit` trials, all pending walkers trying together."""
    out, trials = np.full(len(row), -1, np.int64), np.zeros(len(row), np.int64)
    slots, heights = (rng.states(seed, walk, np.full(len(walk), step), t) for t in (rng.SLOT, rng.HEIGHT))
    pending = np.arange(len(row))
    for t in range(limit):
        if not len(pending):
            break
        item = np.full(len(pending), t)
        deg = csr.deg[row[pending]]
        place = np.minimum((rng.uniforms((slots[0][pending], slots[1][pending]), item) * deg).astype(np.int64), deg - 1)
        edge = csr.start[row[pending]] + place
        w = csr.weights(program, edge, row[pending], prev[pending], prev_row[pending], step)
        ok = rng.uniforms((heights[0][pending], heights[1][pending]), item) * bound[pending] < w
        out[pending[ok]] = edge[ok]
        trials[pending] += 1
        pending = pending[~ok]
    return out, trials


def _greatest(csr: Csr, program, plain: Plain, row, prev, prev_row, step) -> np.ndarray:
    """The greatest weight of each walker's list."""
    out = np.empty(len(row))
    for part in stretches(np.minimum(csr.deg[row], csr.deg[prev_row])):
        out[part], hidden = greatest(plain, Near(plain, row[part], prev[part], prev_row[part]), row[part])
        for some in stretches(csr.deg[row[at := part.start + np.flatnonzero(hidden)]]):
            mine = at[some]
            owner, edge, first = _expand(csr, row[mine])
            out[mine] = np.maximum.reduceat(csr.weights(program, edge, row[mine][owner], prev[mine][owner], prev_row[mine][owner], step), first)
    return out


REPLICATED = frozenset({"keys", "prefix", "inverse", "jump", "jump_shared", "alias", "rejection_bound", "rejection_exact", "adaptive"})


def advance(csr: Csr, program: WeightProgram, sampler: str, config: WalkConfig, walk, row, prev, prev_row, step: int, counted: bool = True):
    """(edge or -1, reads, draws, rejected?) for walkers whose node has edges. Without `counted`, reads and draws of hubs may be left out."""
    how = sampler if sampler in ("keys", "prefix", "inverse", "jump", "jump_shared", "alias") else config.sampler_options.get("reservoir", "keys") if sampler == "adaptive" else "keys"
    analysis = program.analysis
    n = len(row)
    reads, draws, by_trial = np.zeros(n, np.int64), np.zeros(n, np.int64), np.zeros(n, bool)
    out = np.full(n, -1, np.int64)
    rejects = np.zeros(n, bool)
    if sampler in ("rejection_bound", "adaptive", "rejection_exact") and analysis.bound is not None:
        env = {"h_max": csr.h_max[row], "h_min": csr.h_min[row], "h_sum": csr.h_sum[row], "deg_cur": csr.deg[row].astype(float), "deg_prev": np.where(prev_row >= 0, csr.deg[prev_row], np.nan), "step": step, "prev": prev, "cur": csr.nodes[row]}
        with np.errstate(invalid="ignore"):
            bound = np.broadcast_to(np.asarray(_null_skipping(analysis.bound, env), float), (n,))
            total = np.broadcast_to(np.asarray(_null_skipping(analysis.total, env), float), (n,))
        options = config.sampler_options
        kind = options.get("kind", "cost") if sampler == "adaptive" else "rejection"
        plain = csr.plain(program, prev_row)
        if sampler == "rejection_exact" and plain is not None:
            reads += csr.deg[row]
            bound = _greatest(csr, program, plain, row, prev, prev_row, step)
        elif sampler == "rejection_exact" or kind == "exact":
            owner, edge, first = _expand(csr, row)
            w = csr.weights(program, edge, row[owner], prev[owner], prev_row[owner], step)
            top, whole = np.maximum.reduceat(w, first), np.add.reduceat(w, first)
            reads += csr.deg[row] if sampler == "rejection_exact" else 0
            if sampler == "rejection_exact":
                bound = top
        with np.errstate(invalid="ignore"):
            rejects = {
                "rejection": lambda: np.ones(n, bool), "reservoir": lambda: np.zeros(n, bool), "cost": lambda: options.get("ratio", 2.0) * bound < total, "exact": lambda: options.get("ratio", 2.0) * top < whole,
                "degree": lambda: csr.deg[row] >= options.get("threshold", 1000), "random": lambda: rng.uniforms(rng.states(config.seed, walk, np.full(n, step), rng.COIN), np.zeros(n)) < 0.5,
            }[kind]()
        at = np.flatnonzero(rejects)
        if len(at):
            limit = config.trials + (config.rounds - 1) * 3 * config.trials
            out[at], trials = _rejected(csr, program, config.seed, bound[at], limit, walk[at], row[at], prev[at], prev_row[at], step)
            reads[at] += trials
            draws[at] += 2 * trials
            by_trial = out >= 0
    left = np.flatnonzero(out < 0)
    if how == "keys" and not counted and len(hubs := left[csr.deg[row[left]] >= HUB]):
        out[hubs] = _hub_keys(csr, program, config.seed, walk[hubs], row[hubs], prev[hubs], prev_row[hubs], step)
        left = np.flatnonzero(out < 0)
    shared = how in IN_PLACE and csr.plain(program, prev_row) is not None
    for part in stretches(csr.deg[row[left]], 10_000_000 if shared else 1_000_000):
        at = left[part]
        out[at], r, d = _reservoir(csr, program, config.seed, how, walk[at], row[at], prev[at], prev_row[at], step)
        reads[at] += r
        draws[at] += d
    return out, reads, draws, by_trial


def _null_skipping(node, env):
    """greatest() skips nulls (NaN here), as it does in SQL: deg_prev is null on the first step."""
    if node.kind == "fn" and node.value == "greatest":
        return np.fmax.reduce([np.broadcast_to(np.asarray(_null_skipping(a, env), float), np.shape(env["h_max"])) for a in node.args])
    return node.evaluate(env)


_GRAPHS: dict[int, Csr] = {}


def copy_of(token: int, shared) -> Csr:
    """A worker's own copy of the graph sent. (A function of the module, so that its tasks share one table: a nested function takes a copy of it along.)"""
    if token not in _GRAPHS:
        _GRAPHS.clear()
        _GRAPHS[token] = Csr(*shared.value)
    return _GRAPHS[token]


def walk_replicated(graph: WalkGraph, program: WeightProgram, starts: DataFrame, sampler: str, config: WalkConfig, log: bool = False) -> DataFrame:
    """Every worker holds the whole graph and takes its walks through all steps: no shuffle after the starts are placed.

    The driver reads the edges once, as Arrow columns. Graphs beyond REPLICATED_EDGES are walked in supersteps, which give the same walks."""
    if sampler in REPLICATED and graph.edges.count() > REPLICATED_EDGES:
        return walk_superstep(graph, program, starts, sampler, config, log)
    schema = "walk_id long, step int, node long" + (", reads long, draws long, mode string" if log else "")
    return _dealt(starts, config).mapInArrow(_worker(graph, program, sampler, config, log), schema)


def _dealt(starts: DataFrame, config: WalkConfig) -> DataFrame:
    parts = config.partitions or 2 * starts.sparkSession.sparkContext.defaultParallelism
    return placed(starts.select(F.col("walk_id").cast("long").alias("walk_id"), F.col("start").cast("long").alias("start")), parts)


def _copies(graph: WalkGraph):
    """(broadcast edges, token) of a graph; read by the driver once if it is stored."""
    if (found := vars(graph).get("copies")) is None:
        columns, parts = ("src", "dst", "h", "label"), -(-graph.edges.count() // READ_EDGES) if graph.kept else 1
        tables = [graph.edges.where(F.pmod(F.xxhash64("src"), F.lit(parts)) == k).select(*columns).toArrow() for k in range(parts)] if parts > 1 else [graph.edges.select(*columns).toArrow()]
        table = pa.concat_tables(tables)
        found = graph.edges.sparkSession.sparkContext.broadcast(tuple(table.column(c).to_numpy() for c in columns)), int(np.random.default_rng().integers(2**62))
        if graph.kept:
            vars(graph)["copies"] = found
    return found


def forget_copies(graph: WalkGraph) -> None:
    """Frees what `walk_replicated` sent of a stored graph, once its walks are stored."""
    if "copies" in vars(graph):
        vars(graph).pop("copies")[0].destroy()


def _worker(graph: WalkGraph, program: WeightProgram, sampler: str, config: WalkConfig, log: bool, anew: bool = False) -> Callable[[Iterable[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """What a worker does with its starts: all their steps over its own copy of the graph, which it keeps for further walks unless they are to be `anew`."""
    if sampler not in REPLICATED:
        raise ValueError(f"{sampler} runs in supersteps only")
    if (n := graph.edges.count()) > REPLICATED_EDGES:
        raise ValueError(f"{n} edges are too many to replicate")
    shared, token = _copies(graph)
    token = np.random.default_rng().integers(2**62) if anew else token
    steps = min(config.steps, program.depth or config.steps)
    program.full, program.analysis  # parsed once, here  # noqa: B018

    def copied() -> Csr:
        return copy_of(token, shared)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        csr = copied()
        for batch in batches:
            walk, cur = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            prev, prev_row = np.full(len(walk), -1, np.int64), np.full(len(walk), -1, np.int64)
            none = np.zeros(len(walk), np.int64)
            yield _batch(walk, 0, cur, none, none, none > 0, log)
            for k in range(steps):
                row = csr.at(cur)
                alive = row >= 0
                walk, cur, prev, prev_row, row = walk[alive], cur[alive], prev[alive], prev_row[alive], row[alive]
                if not len(walk):
                    break
                edge, reads, draws, by_trial = advance(csr, program, sampler, config, walk, row, prev, prev_row, k, log)
                on = edge >= 0
                walk, prev, prev_row, cur = walk[on], cur[on], row[on], csr.ends(edge[on])
                yield _batch(walk, k + 1, cur, reads[on], draws[on], by_trial[on], log)

    run.copied = copied
    return run


def walk_cost(graph: WalkGraph, program: WeightProgram, starts: DataFrame | None, sampler: str, config: WalkConfig) -> DataFrame:
    """(part, steps, cpu_seconds, wall_seconds, copy_seconds): what each worker's walks cost it in the replicated mode, and apart from that the seconds of copying the graph.

    Graphs beyond REPLICATED_EDGES are walked in supersteps at once: one row for all workers, whose cpu_seconds are the seconds that tasks ran
    (with their Python workers'); `partitions` are then the partitions of shuffles, and scans keep theirs. Nothing is copied."""
    starts = one_per_node(graph) if starts is None else starts
    starts = starts if "walk_id" in starts.columns else starts.withColumn("walk_id", F.col("start"))
    if graph.edges.count() > REPLICATED_EDGES:
        return _superstep_cost(graph, program, starts, sampler, config)
    walked = _worker(graph, program, sampler, config, False, True)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        began = time.perf_counter()
        walked.copied()
        cpu, wall = time.process_time(), time.perf_counter()
        steps = sum(b.num_rows for b in walked(batches))
        row = TaskContext.get().partitionId(), steps, time.process_time() - cpu, time.perf_counter() - wall, wall - began
        yield pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(row, (pa.int32(), pa.int64(), *[pa.float64()] * 3))], ["part", "steps", "cpu_seconds", "wall_seconds", "copy_seconds"])

    return _dealt(starts, config).mapInArrow(run, _COST)


_COST = "part int, steps long, cpu_seconds double, wall_seconds double, copy_seconds double"


def _superstep_cost(graph: WalkGraph, program: WeightProgram, starts: DataFrame, sampler: str, config: WalkConfig) -> DataFrame:
    spark, key = starts.sparkSession, "spark.sql.shuffle.partitions"
    partitions = spark.conf.get(key)
    spark.conf.set(key, str(config.partitions or partitions))
    try:
        busy, began = _task_seconds(spark), time.perf_counter()
        steps = walk_superstep(graph, program, starts, sampler, config).count()
        wall = time.perf_counter() - began
        return spark.createDataFrame([(0, steps, _task_seconds(spark) - busy, wall, 0.0)], _COST)
    finally:
        spark.conf.set(key, partitions)


def _task_seconds(spark: SparkSession) -> float:
    """Seconds that tasks have run so far, on all executors."""
    context = spark.sparkContext._jsc.sc()
    context.listenerBus().waitUntilEmpty()
    executors = context.statusStore().executorList(False)
    return sum(executors.apply(k).totalDuration() for k in range(executors.size())) / 1000


_MODES = pa.array(["reservoir", "rejection"])


def _batch(walk, step, node, reads, draws, by_trial, log) -> pa.RecordBatch:
    columns = [pa.array(walk), pa.array(np.full(len(walk), step, np.int32)), pa.array(node)]
    names = ["walk_id", "step", "node"]
    if log:
        columns += [pa.array(reads), pa.array(draws), _MODES.take(pa.array(by_trial.astype(np.int8))) if step else pa.nulls(len(walk), pa.string())]
        names += ["reads", "draws", "mode"]
    return pa.RecordBatch.from_arrays(columns, names)


def profile_ratio(graph: WalkGraph, program: WeightProgram, nodes: int = 2000, repeats: int = 3, seed: int = 42) -> DataFrame:
    """(ratio, trial_ns, read_ns): what a rejection trial costs beside a candidate of the reservoir, both timed in one task on walkers
    from `nodes` nodes (those of the least hashes; a bounded sample), the best of `repeats` runs. No row if the program has no bound."""
    spark = graph.edges.sparkSession
    starts = one_per_node(graph).orderBy(F.xxhash64("start"), "start").limit(nodes)
    near = graph.edges.join(F.broadcast(starts), F.col("src") == F.col("start"), "left_semi")
    table = near.select("src", "dst", "h", "label").toArrow()
    shared = spark.sparkContext.broadcast(tuple(table.column(c).to_numpy() for c in ("src", "dst", "h", "label")))
    program.full, program.analysis  # parsed once, here  # noqa: B018

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _ in batches:
            csr = Csr(*shared.value)
            if program.analysis.bound is None or not len(csr.nodes):
                continue
            row = np.arange(len(csr.nodes))
            walk, none, best = csr.nodes, np.full(len(row), -1, np.int64), {}
            for k in range(repeats):
                for how in ("keys", "rejection_bound"):
                    began = time.perf_counter()
                    _, reads, draws, _ = advance(csr, program, how, WalkConfig(seed=seed), walk, row, none, none, k)
                    cost = (time.perf_counter() - began) * 1e9 / max(1, (reads if how == "keys" else draws // 2).sum())
                    best[how] = min(best.get(how, np.inf), cost)
            yield pa.RecordBatch.from_arrays([pa.array([best["rejection_bound"] / best["keys"]]), pa.array([best["rejection_bound"]]), pa.array([best["keys"]])], ["ratio", "trial_ns", "read_ns"])

    return spark.range(0, 1, 1, 1).mapInArrow(run, "ratio double, trial_ns double, read_ns double")


def walk_log(graph: WalkGraph, program: WeightProgram, starts: DataFrame | None, sampler: str, config: WalkConfig) -> DataFrame:
    """The walk's steps with what each cost: (walk_id, step, node, reads, draws, mode)."""
    starts = one_per_node(graph) if starts is None else starts
    starts = starts if "walk_id" in starts.columns else starts.withColumn("walk_id", F.col("start"))
    mode = config.mode if config.mode != "auto" else "replicated" if sampler in REPLICATED else "superstep"
    return (walk_replicated if mode == "replicated" else walk_superstep)(graph, program, starts, sampler, config, log=True).where("step > 0")
