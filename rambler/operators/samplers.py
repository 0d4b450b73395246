"""One step of every walker, by each of the samplers. All take any weight program and give the same law.

Walkers: (walk_id, step, prev, cur). Result: (walk_id, next, reads, draws, mode) for walkers that have an edge of positive weight;
the others are absent (a dead end). Ties can't matter: draws have 52 bits.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rambler.functions import rng
from rambler.functions.store import settle
from rambler.plans.program import WeightProgram

from .graph import WalkGraph
from .lists import HUB, SURE, list_adaptive, list_jumps, list_keys, list_prefixes, running_sums

OUT = ("walk_id", "next", "reads", "draws", "mode")
LANE = 4096
#: Lists of at least so many neighbours have their true sums and maxima from `weight_totals`.
LONG = 256
#: Graphs of more edges are stepped at the lists, as are those with hubs.
LIST_EDGES = 25_000_000
#: Nodes from which on tables with a row for each node or walker aren't left to a broadcast, which passes through the driver.
BROADCAST_NODES = 100_000


def at_lists(graph: WalkGraph, program: WeightProgram) -> bool:
    """Whether walkers shall come to the lists, so that no candidate becomes a row."""
    return graph.kept and splits(program) and (graph.largest[1] >= HUB or graph.size > LIST_EDGES)


def kept_for(graph: WalkGraph, program: WeightProgram, jumps: bool = False) -> WalkGraph:
    """The graph kept for steps of `program`: as packed lists alone if all of them are made there, else stored."""
    if not splits(program):
        return graph.stored()
    listed = graph.listed()
    return listed if jumps or at_lists(listed, program) else listed.stored()


def attach_stats(walkers: DataFrame, graph: WalkGraph, previous: bool) -> DataFrame:
    """deg_cur and the list's statistics (and deg_prev) beside each walker. The statistics' size is left to Catalyst: small ones are broadcast."""
    stats = wide(graph.node_stats, graph)
    out = walkers.join(stats.withColumnsRenamed({"src": "cur", "deg": "deg_cur"}), "cur")
    if previous:
        out = out.join(stats.select(F.col("src").alias("prev"), F.col("deg").alias("deg_prev")), "prev", "left")
    return out


def wide(rows: DataFrame, graph: WalkGraph) -> DataFrame:
    """`rows` (one for each node, walker or edge), kept from being broadcast if the graph has many nodes."""
    return rows.hint("merge") if graph.kept and graph.largest[0] >= BROADCAST_NODES else rows


def linked_flag(rows: DataFrame, graph: WalkGraph) -> DataFrame:
    """linked: an edge leads from prev to dst."""
    pairs = wide(graph.pairs, graph).select(F.col("src").alias("_p"), F.col("dst").alias("_d"))
    joined = rows.join(pairs, (F.col("prev") == F.col("_p")) & (F.col("dst") == F.col("_d")), "left")
    return joined.withColumn("linked", F.col("_p").isNotNull()).drop("_p", "_d")


def weighed(rows: DataFrame, graph: WalkGraph, program: WeightProgram) -> DataFrame:
    """Adds w to rows that have an edge's columns and the walker's."""
    if program.needs("linked"):
        rows = linked_flag(rows, graph)
    return rows.withColumn("w", F.expr(program.sql()))


def candidates(walkers: DataFrame, graph: WalkGraph, program: WeightProgram) -> DataFrame:
    """Every neighbour of every walker with its weight; edges of weight 0 are left out."""
    if program.needs("deg_cur") or program.needs("deg_prev"):
        if "deg_cur" not in walkers.columns:
            walkers = attach_stats(walkers, graph, program.needs("deg_prev"))
    joined = walkers.join(wide(graph.edges, graph).withColumnRenamed("src", "cur"), "cur")
    return weighed(joined, graph, program).where("w > 0")


def _with_state(walkers: DataFrame, seed: int, tag: int) -> DataFrame:
    a, b = rng.state_columns(seed, tag)
    return walkers.withColumn("s1", a).withColumn("s2", b)


def key_step(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, seed: int) -> DataFrame:
    """Reservoir by random keys: least -ln(u)/w. One hash aggregate; no sort, no window, no prefix sum. On large graphs and those with hubs,
    walkers of programs that split come to the lists; for other programs, walkers at hubs are served by their greatest uniforms where these decide."""
    if at_lists(graph, program):
        return list_keys(walkers, graph, program, seed).withColumn("mode", F.lit("keys"))
    if graph.kept and not graph.counted and program.analysis.bound is not None and graph.largest[1] >= HUB:
        served, rest = hub_step(walkers, graph, program, seed)
        return served.unionByName(all_keys_step(rest, graph, program, seed))
    return all_keys_step(walkers, graph, program, seed)


def hub_step(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, seed: int) -> tuple[DataFrame, DataFrame]:
    """(served, other walkers). A key is -ln(u)/w, and no w exceeds the derived bound: of items whose u is below 1 - 2^-j, none has a key
    below -ln(1 - 2^-j)/bound. So if the least key of the items with greater u is below that, it is the least of the list. Those items
    are found from the generator turned round (`rng.high_items`), a few dozen of a list of any length."""
    stats = attach_stats(walkers.select("walk_id", "step", "prev", "cur"), graph, True).withColumns({"bound": F.expr(program.analysis.bound_sql), "est_sum": F.expr(program.analysis.sum_sql)})
    depth = F.floor(F.log2(F.col("est_sum") / (SURE * F.col("bound"))))
    level = F.when(F.col("deg_cur") >= HUB, F.coalesce(*[F.when(depth >= j, j) for j in reversed(rng.CREST)], F.lit(0))).otherwise(0)
    ready = settle(stats.select("walk_id", "step", "prev", "cur", "deg_cur", "bound", F.coalesce(level, F.lit(0)).alias("level")))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            walk, step, cur, deg, bound, level = (batch.column(c).to_numpy() for c in ("walk_id", "step", "cur", "deg_cur", "bound", "level"))
            prev = batch.column("prev")
            for j in np.unique(level):
                at = np.flatnonzero(level == j)
                for part in stretches(deg[at] >> int(j), 200_000):
                    some = at[part]
                    state = rng.states(seed, walk[some], step[some], rng.KEY)
                    owner, item = rng.high_items(state, deg[some], int(j))
                    who = some[owner]
                    u = rng.uniforms((state[0][owner], state[1][owner]), item)
                    limit = -np.log1p(-(2.0 ** -int(j))) / bound[some] * (1 - 1e-12)
                    yield pa.RecordBatch.from_arrays([pa.array(walk[who]), pa.array(step[who]), prev.take(pa.array(who)), pa.array(cur[who]), pa.array(item.astype(np.int32)), pa.array(u), pa.array(limit[owner])], ["walk_id", "step", "prev", "cur", "idx", "u", "limit"])

    items = ready.where("level > 0").mapInArrow(run, "walk_id long, step int, prev long, cur long, idx int, u double, limit double")
    if program.needs("deg_cur") or program.needs("deg_prev"):
        items = items.join(wide(ready.select("walk_id", "deg_cur"), graph), "walk_id")
        items = items.join(wide(graph.node_stats.select(F.col("src").alias("prev"), F.col("deg").alias("deg_prev")), graph), "prev", "left")
    rows = weighed(items.join(wide(graph.edges, graph).withColumnRenamed("src", "cur"), ["cur", "idx"]), graph, program).where("w > 0").withColumn("key", -F.log("u") / F.col("w"))
    best = rows.groupBy("walk_id").agg(F.min_by("dst", "key").alias("next"), F.min("key").alias("key"), F.first("limit").alias("limit"), F.count("*").alias("reads")).where("key < limit")
    best = settle(best.select("walk_id", "next", "reads", F.col("reads").alias("draws"), F.lit("keys").alias("mode")))
    return best, settle(ready.join(wide(best.select("walk_id"), graph), "walk_id", "left_anti").select("walk_id", "step", "prev", "cur"))


def all_keys_step(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, seed: int) -> DataFrame:
    """Every neighbour's key is drawn."""
    rows = rng.with_uniform(candidates(_with_state(walkers, seed, rng.KEY), graph, program), "u", ("s1", "s2"), F.col("idx"))
    return rows.groupBy("walk_id", "cur").agg(F.min_by("dst", -F.log("u") / F.col("w")).alias("next"), F.count("*").alias("reads")).select("walk_id", "next", "reads", F.col("reads").alias("draws"), F.lit("keys").alias("mode"))


def prefix_step(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, seed: int) -> DataFrame:
    """Reservoir with prefix sums: the last neighbour i with u_i * W_i < w_i. Reads weights and running sums."""
    if at_lists(graph, program):
        return list_prefixes(walkers, graph, program, seed).withColumn("mode", F.lit("prefix"))
    rows = rng.with_uniform(candidates(_with_state(walkers, seed, rng.KEY), graph, program), "u", ("s1", "s2"), F.col("idx"))
    running = Window.partitionBy("walk_id", "cur").orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)
    rows = rows.withColumn("acc", F.sum("w").over(running))
    taken = F.when(F.col("u") * F.col("acc") < F.col("w"), F.col("idx"))
    return rows.groupBy("walk_id", "cur").agg(F.max_by("dst", taken).alias("next"), F.count("*").alias("n")).select("walk_id", "next", (2 * F.col("n")).alias("reads"), F.col("n").alias("draws"), F.lit("prefix").alias("mode"))


def inverse_step(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, seed: int) -> DataFrame:
    """Inverse transform: one uniform against the running sums."""
    rows = candidates(walkers.withColumn("u", rng.uniform(seed, "walk_id", "step", rng.PICK, "0")), graph, program)
    lists = Window.partitionBy("walk_id", "cur")
    rows = rows.withColumn("acc", F.sum("w").over(lists.orderBy("idx").rowsBetween(Window.unboundedPreceding, 0))).withColumn("n", F.count("*").over(lists)).withColumn("whole", F.max("acc").over(lists))
    return rows.where(F.col("acc") > F.col("u") * F.col("whole")).groupBy("walk_id", "cur").agg(F.min_by("dst", "idx").alias("next"), F.first("n").alias("n")).select("walk_id", "next", (2 * F.col("n")).alias("reads"), F.lit(1).cast("long").alias("draws"), F.lit("inverse").alias("mode"))


# Rejection --------------------------------------------------------------------------------------------------------------
def proposals(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, seed: int, first: int, trials: int) -> DataFrame:
    """`trials` proposals for each walker (with deg_cur and bound): only the proposed edges are looked up, by (src, idx)."""
    a, b = rng.state_columns(seed, rng.SLOT)
    c, d = rng.state_columns(seed, rng.HEIGHT)
    rows = walkers.withColumns({"s1": a, "s2": b, "s3": c, "s4": d}).withColumn("trial", F.explode(F.sequence(F.lit(first), F.lit(first + trials - 1))))
    rows = rng.with_uniform(rng.with_uniform(rows, "u", ("s1", "s2"), F.col("trial")), "v", ("s3", "s4"), F.col("trial"))
    rows = rows.withColumn("idx", F.least(F.floor(F.col("u") * F.col("deg_cur")), F.col("deg_cur") - 1).cast("int"))
    looked = rows.join(wide(graph.edges, graph).withColumnRenamed("src", "cur"), ["cur", "idx"])
    return weighed(looked, graph, program)


def rejection_rounds(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, seed: int, trials: int = 8, rounds: int = 2, extra_reads: str = "0") -> tuple[DataFrame, DataFrame]:
    """(accepted, pending) after bounded rounds; the first accepted trial counts, so the law doesn't depend on trials and rounds.

    Each round's rows are stored (a row for each walker): no round runs twice, and what follows joins plain tables."""
    done, pending, at = None, settle(walkers), 0
    for r in range(rounds):
        size = trials if r == 0 else trials * 3
        tried = proposals(pending, graph, program, seed, at, size)
        hits = tried.where(F.col("v") * F.col("bound") < F.col("w")).groupBy("walk_id", "cur").agg(F.min_by("dst", "trial").alias("next"), F.min("trial").alias("trial"), F.first(F.expr(extra_reads)).alias("x"))
        hits = settle(hits.select("walk_id", "next", (F.col("trial") + 1 + F.col("x")).cast("long").alias("reads"), (2 * (F.col("trial") + 1)).cast("long").alias("draws"), F.lit("rejection").alias("mode")))
        done = hits if done is None else done.unionByName(hits)
        pending = settle(pending.join(wide(hits.select("walk_id"), graph), "walk_id", "left_anti"))
        at += size
    return done, pending


def bound_step(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, seed: int, trials: int = 8, rounds: int = 2, bound: Column | None = None) -> DataFrame:
    """Rejection under the derived bound; walkers that no trial served go to the key sampler, whose draws are independent of the trials."""
    analysis = program.analysis
    if analysis.bound is None and bound is None:
        return key_step(walkers, graph, program, seed)
    ready = attach_stats(walkers, graph, program.needs("deg_prev")).withColumn("bound", bound if bound is not None else F.expr(analysis.bound_sql))
    done, pending = rejection_rounds(ready, graph, program, seed, trials, rounds)
    return done.unionByName(key_step(pending.select("walk_id", "step", "prev", "cur"), graph, program, seed))


def exact_step(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, seed: int, trials: int = 8, rounds: int = 2) -> DataFrame:
    """Rejection under the true maximum, for which all weights of the list are reduced first."""
    top = candidates(walkers, graph, program).groupBy("walk_id").agg(F.max("w").alias("bound"))
    ready = attach_stats(walkers, graph, program.needs("deg_prev")).join(top, "walk_id")
    done, pending = rejection_rounds(ready, graph, program, seed, trials, rounds, "deg_cur")
    return done.unionByName(key_step(pending.select("walk_id", "step", "prev", "cur"), graph, program, seed))


# Lists in numpy ---------------------------------------------------------------------------------------------------------
def jump_pick(w: np.ndarray, draw, lane: int = 0) -> tuple[int, float, int]:
    """(place, log of the best key, draws) over one lane of positive weights, by exponential jumps.

    The first item gets a key; then weight is skipped until it exceeds ln(u)/ln(best); the item landed on gets a key drawn given
    that it beats the best one, which keeps the law exact. Logs throughout, so tiny and huge weights do no harm."""
    acc = np.cumsum(w)
    best_at, best, n = 0, np.log(draw(0, lane)) / w[0], 1
    at = 0
    while True:
        threshold = np.log(draw(n, lane)) / best
        n += 1
        landing = int(np.searchsorted(acc, acc[at] + threshold, side="left"))
        if landing >= len(w):
            return best_at, float(best), n
        # key = r^(1/w) with r uniform in (best^w, 1); in logs, and exact for small best^w.
        low = np.exp(w[landing] * best)
        best = np.log(low + draw(n, lane) * (1 - low)) / w[landing]
        n += 1
        best_at = at = landing
        if not best < 0:
            return best_at, float(best), n


def jump_lanes(w, owner, idx, state, walkers: int, lane: int = LANE, shared: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(place in w or -1, log of the best key, draws) of each walker by keys with jumps: all lanes jump at once, over one running sum of weights scaled to each lane's largest.

    With `shared`, a walker's lanes have one maximum between them: each jump is against the best key that any of them has so far, so
    lanes skip further. What they skip has a lower key than that, and what they land on gets one drawn above it; the law is the same."""
    out, top_key, draws = np.full(walkers, -1, np.int64), np.full(walkers, -np.inf), np.zeros(walkers, np.int64)
    some = np.flatnonzero(w > 0)
    if not len(some):
        return out, top_key, draws
    who, part = owner[some], idx[some] // lane
    first = np.flatnonzero(np.concatenate([[True], (who[1:] != who[:-1]) | (part[1:] != part[:-1])]))
    end, mine, number = np.append(first[1:], len(some)), who[first], part[first]
    top = np.maximum.reduceat(w[some], first)
    if shared:
        whole = np.zeros(walkers)
        np.maximum.at(whole, mine, top)
        top = whole[mine]  # keys of all lanes on one scale
    v = np.maximum(w[some] / np.repeat(top, end - first), 1e-300)
    acc = np.cumsum(v)
    draw = lambda units, k: rng.uniforms((state[0][mine[units]], state[1][mine[units]]), (number[units] << 20) + k)
    every, n = np.arange(len(first)), np.ones(len(first), np.int64)
    best, at, held = np.log(draw(every, 0)) / v[first], first.copy(), np.full(walkers, -np.inf)
    np.maximum.at(held, mine, best)
    bar = lambda units: held[mine[units]] if shared else best[units]
    active = every[bar(every) < 0]
    while len(active):
        beat = bar(active)
        with np.errstate(over="ignore"):
            to = np.maximum(np.searchsorted(acc, acc[at[active]] + np.log(draw(active, n[active])) / beat), at[active] + 1)
        n[active] += 1
        on = to < end[active]
        active, to, beat = active[on], to[on], beat[on]
        # The landing's key is drawn given that it beats the best one.
        low = np.exp(v[to] * beat)
        best[active] = np.log(low + draw(active, n[active]) * (1 - low)) / v[to]
        n[active] += 1
        at[active] = to
        if shared:
            np.maximum.at(held, mine[active], best[active])
        active = active[bar(active) < 0]
    with np.errstate(over="ignore"):
        key = best / top
    order = np.lexsort((key, mine))
    last = order[np.flatnonzero(np.append(mine[order][1:] != mine[order][:-1], True))]
    out[mine[last]], top_key[mine[last]] = some[at[last]], key[last]
    return out, top_key, np.bincount(mine, n, walkers).astype(np.int64)


def stretches(deg: np.ndarray, limit: int = 1_000_000) -> Iterator[slice]:
    """Slices of walkers whose candidates number about `limit` at most, so memory is bounded."""
    if len(deg):
        block = (np.cumsum(deg) - deg) // limit
        cuts = np.flatnonzero(np.diff(block)) + 1
        for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(deg)]):
            yield slice(a, b)


def alias_tables(w: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(probability of each slot's own item, the other item's place) of all lists at once; weights are positive, lists not empty and begin at `first`.

    What light items lack of a slot and what heavy ones have beyond it are laid along one line. A light item is filled by the heavy
    one whose stretch covers its beginning; a heavy one that ends within a light item's stretch lacks the rest and is filled by the next."""
    size = np.diff(np.append(first, len(w)))
    which = np.repeat(np.arange(len(first)), size)
    v = w / np.maximum.reduceat(w, first)[which]
    share = v * (size / np.add.reduceat(v, first))[which]
    is_heavy = (share >= 1) | (v == 1)  # the largest always is, whatever the rounding
    lack, extra = np.where(is_heavy, 0, 1 - share), np.where(is_heavy, np.maximum(share - 1, 0), 0)
    lacked, given = running_sums(lack, first), running_sums(extra, first)
    light, heavy = np.flatnonzero(~is_heavy), np.flatnonzero(is_heavy)
    line = lambda at, value: which[at] + np.minimum(value / size[which[at]], 1 - 1e-12)
    ends = line(heavy, given[heavy])
    first_heavy = np.searchsorted(which[heavy], np.arange(len(first)))
    last_heavy = np.append(first_heavy[1:], len(heavy)) - 1
    own, other = np.ones(len(w)), np.arange(len(w))
    own[light] = share[light]
    other[light] = heavy[np.clip(np.searchsorted(ends, line(light, lacked[light] - lack[light])), first_heavy[which[light]], last_heavy[which[light]])]
    within = np.searchsorted(line(light, lacked[light]), ends, side="right")
    j = np.flatnonzero((within < len(light)) & (np.arange(len(heavy)) < last_heavy[which[heavy]]))
    j = j[which[light[within[j]]] == which[heavy[j]]]
    own[heavy[j]] = np.clip(1 + given[heavy[j]] - lacked[light[within[j]]], 0, 1)
    other[heavy[j]] = heavy[j + 1]
    return own, other


def alias_picks(w: np.ndarray, first: np.ndarray, state) -> np.ndarray:
    """A place in w for each list: a slot by one uniform, its own item or the other by a second."""
    own, other = alias_tables(w, first)
    size = np.diff(np.append(first, len(w)))
    slot, coin = (rng.uniforms(state, np.full(len(first), k)) for k in (0, 1))
    at = first + np.minimum((slot * size).astype(np.int64), size - 1)
    return np.where(coin < own[at], at, other[at])


def _lists(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, lane: int | None) -> DataFrame:
    """A row for each walker (and lane): its positive weights and their edges in the list's order."""
    rows = candidates(walkers, graph, program).withColumn("lane", F.floor(F.col("idx") / lane).cast("int") if lane else F.lit(0))
    return rows.groupBy("walk_id", "step", "lane").agg(F.array_sort(F.collect_list(F.struct("idx", "dst", "w"))).alias("e")).select("walk_id", "step", "lane", F.col("e.dst").alias("dst"), F.col("e.w").alias("w"))


def jump_step(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, seed: int, lane: int = LANE) -> DataFrame:
    """Reservoir by keys with jumps: lanes of at most `lane` neighbours, and the best lane wins. Walkers of programs that split come to the lists; for others, lists are gathered for each walker."""
    if graph.kept and splits(program):
        return list_jumps(walkers, graph, program, seed, lane).withColumn("mode", F.lit("jump"))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            walk, step, number = (batch.column(i).to_numpy() for i in range(3))
            offsets, dst, w = batch.column(3).offsets.to_numpy(), batch.column(3).values.to_numpy(), batch.column(4).values.to_numpy()
            size = np.diff(offsets)
            for part in stretches(size):
                first, last = int(offsets[part.start]), int(offsets[part.stop])
                owner = np.repeat(np.arange(part.stop - part.start), size[part])
                idx = number[part][owner].astype(np.int64) * lane + np.arange(last - first) - (offsets[part] - first)[owner]
                at, best, n = jump_lanes(w[first:last], owner, idx, rng.states(seed, walk[part], step[part], rng.JUMP), len(size[part]), lane)
                yield pa.RecordBatch.from_arrays([pa.array(walk[part]), pa.array(dst[first + at]), pa.array(best), pa.array(size[part].astype(np.int64)), pa.array(n)], ["walk_id", "dst", "best", "reads", "draws"])

    lanes = _lists(walkers, graph, program, lane).mapInArrow(run, "walk_id long, dst long, best double, reads long, draws long")
    return lanes.groupBy("walk_id").agg(F.max_by("dst", "best").alias("next"), F.sum("reads").alias("reads"), F.sum("draws").alias("draws")).withColumn("mode", F.lit("jump"))


def alias_step(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, seed: int) -> DataFrame:
    """Alias tables, built anew for each walker's list, as its weights hold for this step alone."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            walk, step = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            offsets, dst, w = batch.column(3).offsets.to_numpy(), batch.column(3).values.to_numpy(), batch.column(4).values.to_numpy()
            size = np.diff(offsets)
            for part in stretches(size):
                lo, hi = int(offsets[part.start]), int(offsets[part.stop])
                at = lo + alias_picks(w[lo:hi], (offsets[part] - lo).astype(np.int64), rng.states(seed, walk[part], step[part], rng.PICK))
                yield pa.RecordBatch.from_arrays([pa.array(walk[part]), pa.array(dst[at]), pa.array(size[part].astype(np.int64)), pa.array(np.full(len(at), 2, np.int64)), pa.array(["alias"] * len(at))], list(OUT))

    return _lists(walkers, graph, program, None).mapInArrow(run, "walk_id long, next long, reads long, draws long, mode string")


# Selection --------------------------------------------------------------------------------------------------------------
def prefers_rejection(kind: str, program: WeightProgram, seed: int, ratio: float = 2.0, threshold: int = 1000) -> Column:
    """The selector as a boolean over (walk_id, step, deg_cur, bound, est_sum): cost, degree, random, rejection or reservoir."""
    if program.analysis.bound is None or kind == "reservoir":
        return F.lit(False)
    return {
        "rejection": F.lit(True),
        "cost": F.lit(ratio) * F.col("bound") < F.col("est_sum"),
        "degree": F.col("deg_cur") >= threshold,
        "random": rng.uniform(seed, "walk_id", "step", rng.COIN, "0") < 0.5,
    }[kind]


def step_costs(ratio: float = 2.0) -> dict[str, Column]:
    """Costs of a step over (deg_cur, bound, est_sum), in reads of a candidate: the reservoir reads the list; a trial costs `ratio`, and deg * bound / sum of them are expected."""
    return {"cost_reservoir": F.col("deg_cur").cast("double"), "cost_rejection": F.lit(ratio) * F.col("deg_cur") * F.col("bound") / F.col("est_sum")}


def adaptive_step(walkers: DataFrame, graph: WalkGraph, program: WeightProgram, seed: int, kind: str = "cost", ratio: float = 2.0, threshold: int = 1000, trials: int = 8, rounds: int = 2, reservoir: str = "keys") -> DataFrame:
    """Each walker takes the sampler that the selector prefers for it now: rejection, or the reservoir named (keys, jump, prefix). Expects stored walkers, as both branches read them.

    With jumps, and with keys on large graphs and those with hubs, walkers of programs that split come to the lists and take their whole step there."""
    if program.analysis.bound is not None and reservoir != "prefix" and (at_lists(graph, program) or reservoir == "jump" and graph.kept and splits(program)):
        return list_adaptive(walkers, graph, program, seed, kind, ratio, threshold, trials + (rounds - 1) * 3 * trials, reservoir, LANE)
    reservoir = {"keys": key_step, "jump": jump_step, "prefix": prefix_step}[reservoir]
    if program.analysis.bound is None:
        return reservoir(walkers, graph, program, seed)
    ready = attach_stats(walkers, graph, program.needs("deg_prev")).withColumn("bound", F.expr(program.analysis.bound_sql)).withColumn("est_sum", F.expr(program.analysis.sum_sql))
    if kind == "exact":
        ready = ready.join(true_weights(walkers, graph, program), "walk_id").withColumn("rejects", F.lit(ratio) * F.col("w_max") < F.col("w_sum"))
    else:
        ready = ready.withColumn("rejects", prefers_rejection(kind, program, seed, ratio, threshold))
    ready = settle(ready)
    done, pending = rejection_rounds(ready.where("rejects"), graph, program, seed, trials, rounds)
    plain = ["walk_id", "step", "prev", "cur"]
    rest = settle(ready.where("not rejects").select(*plain).unionByName(pending.select(*plain)))
    return done.unionByName(reservoir(rest, graph, program, seed))


STEPS = {"keys": key_step, "prefix": prefix_step, "inverse": inverse_step, "rejection_exact": exact_step, "rejection_bound": bound_step, "jump": jump_step, "jump_shared": jump_step, "alias": alias_step, "adaptive": adaptive_step}


# Sums and maxima of weights without all candidates ------------------------------------------------------------------------------
def splits(program: WeightProgram) -> bool:
    """The weight of an edge that neither leads back nor to a neighbour of the previous node is the edge's own: the previous node counts by `linked` and `dst = prev` alone."""

    def aside(node) -> bool:
        if node.kind == "var":
            return node.value in ("h", "label", "dst", "cur", "linked")
        names = [a.value for a in node.args if a.kind == "var"]
        if node.kind == "op" and "prev" in names:
            return node.value == "isnull" or node.value in ("=", "<>") and sorted(names) == ["dst", "prev"]
        return all(aside(a) for a in node.args)

    return aside(program.full)


def plain_weights(graph: WalkGraph, program: WeightProgram) -> DataFrame:
    """(src, idx, dst, h, label, plain): each edge with its weight for walkers that come from elsewhere."""
    far = graph.edges.withColumns({"linked": F.lit(False), "prev": F.lit(-(2**63)).cast("long"), "cur": F.col("src")})
    return far.withColumn("plain", F.expr(program.sql()).cast("double")).drop("linked", "prev", "cur")


def weight_totals(states: DataFrame, graph: WalkGraph, program: WeightProgram) -> DataFrame:
    """(prev, cur, w_sum, w_max) of distinct states (prev, cur), prev not null, for programs that split: a node's sum of plain weights is corrected
    by the edges back and to neighbours of the previous node, which are found from the shorter of the two lists. w_max is null where
    such an edge has the greatest plain weight. Expects a stored graph and stored states."""
    edges = settle(plain_weights(graph, program))
    e = lambda: wide(edges.withColumnRenamed("src", "cur"), graph)
    sums = settle(edges.groupBy(F.col("src").alias("cur")).agg(F.sum("plain").alias("plain_sum"), F.max("plain").alias("plain_max"), F.count("*").alias("deg_cur")))
    ready = states.join(wide(sums, graph), "cur").join(wide(graph.node_stats, graph).select(F.col("src").alias("prev"), F.col("deg").alias("deg_prev")), "prev", "left")
    ready = settle(ready.withColumn("deg_prev", F.coalesce("deg_prev", F.lit(0))))
    keys, pairs = ready.select("prev", "cur"), wide(graph.pairs, graph)
    short = ready.where("deg_cur <= deg_prev").select("prev", "cur").join(e(), "cur").join(pairs.withColumnRenamed("src", "prev"), ["prev", "dst"])
    long = ready.where("deg_cur > deg_prev").select("prev", "cur").join(pairs.withColumnRenamed("src", "prev"), "prev").join(e(), ["cur", "dst"])
    linked = short.select("prev", "cur", "dst", "h", "label", "plain").unionByName(long.select("prev", "cur", "dst", "h", "label", "plain")).where("dst <> prev").withColumn("linked", F.lit(True))
    back = keys.withColumn("dst", F.col("prev")).join(e(), ["cur", "dst"]).select("prev", "cur", "dst", "h", "label", "plain")
    near = linked.unionByName(linked_flag(back, graph)).withColumn("w", F.expr(program.sql()).cast("double"))
    off = near.groupBy("prev", "cur").agg(F.sum(F.col("w") - F.col("plain")).alias("more"), F.max("w").alias("near_max"), F.max("plain").alias("near_plain"))
    out = ready.join(wide(off, graph), ["prev", "cur"], "left")
    top = F.when(F.col("near_plain").isNull() | (F.col("near_plain") < F.col("plain_max")), F.greatest("plain_max", "near_max"))
    return out.select("prev", "cur", (F.col("plain_sum") + F.coalesce("more", F.lit(0.0))).alias("w_sum"), top.alias("w_max"))


def true_weights(walkers: DataFrame, graph: WalkGraph, program: WeightProgram) -> DataFrame:
    """(walk_id, w_max, w_sum) of stored walkers' lists; from all candidates where lists are short or there is no other way."""
    known = None
    if graph.kept and splits(program):
        at = wide(graph.node_stats.where(F.col("deg") >= LONG), graph).select(F.col("src").alias("cur"))
        states = settle(walkers.where("prev is not null").select("prev", "cur").distinct().join(at, "cur", "left_semi"))
        totals = settle(weight_totals(states, graph, program).where("w_max > 0"))
        known = settle(walkers.join(wide(totals, graph), ["prev", "cur"]).select("walk_id", "w_max", "w_sum"))
        walkers = walkers.join(wide(known.select("walk_id"), graph), "walk_id", "left_anti")
    rest = candidates(walkers, graph, program).groupBy("walk_id").agg(F.max("w").alias("w_max"), F.sum("w").alias("w_sum"))
    return rest if known is None else known.unionByName(rest)


def bound_soundness(graph: WalkGraph, program: WeightProgram, states: DataFrame) -> DataFrame:
    """(prev, cur, top, bound) of the given states (prev, cur, step): the greatest weight, and the derived bound, which may not be below it."""
    top = candidates(states, graph, program).groupBy("prev", "cur", "step").agg(F.max("w").alias("top"))
    return attach_stats(top, graph, program.needs("deg_prev")).select("prev", "cur", "top", F.expr(program.analysis.bound_sql).alias("bound"))


def transition_probabilities(graph: WalkGraph, program: WeightProgram, states: DataFrame) -> DataFrame:
    """(prev, cur, step, dst, w, p) for all candidates of the given states (prev, cur, step): the exact law."""
    rows = candidates(states, graph, program)
    return rows.select("prev", "cur", "step", "dst", "w", (F.col("w") / F.sum("w").over(Window.partitionBy("prev", "cur", "step"))).alias("p"))
