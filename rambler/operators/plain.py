"""Lists read in place by many walkers of the replicated mode, for programs that split (`samplers.splits`).

An edge's weight is then its plain one for all walkers but those it leads back, or on to a neighbour of the previous node. Plain weights,
their running sums, and the least and greatest weight an edge can have, are computed once for all walkers; a walker's near edges are found from
the shorter of two lists. Draws are narrowed by one word of their two and 32-bit bounds, and what these leave open is computed as over all
candidates; where running sums in another order of adding can't tell, `unsure` walkers are left to that. So the choices are the same."""

from __future__ import annotations

from functools import cached_property

import numpy as np

from rambler.functions import rng

#: A previous node that no edge's destination equals, and that isn't null.
ELSEWHERE = -(2**63)
#: Candidates of a block of walkers, which shall stay in a core's cache.
BLOCK = 1 << 16
#: Share of the sums added that rounding may change.
ROUNDING = 1e-11


class Plain:
    """What all walkers beyond their first step share."""

    def __init__(self, csr, program):
        self.csr, self.program = csr, program

    def _weights(self, at: slice, back: bool, linked: bool) -> np.ndarray:
        csr = self.csr
        dst = csr.names[csr.to[at]]
        row = np.searchsorted(csr.start, np.arange(at.start, at.start + len(dst)), side="right") - 1 if self.program.needs("cur") else np.zeros(len(dst), np.int64)
        prev = dst if back else np.full(len(dst), ELSEWHERE)
        env = {"h": csr.h[at], "label": csr.label[at], "dst": dst, "cur": csr.nodes[row], "prev": prev, "linked": np.full(len(dst), linked)}
        return np.broadcast_to(np.asarray(self.program.full.evaluate(env), float), dst.shape)

    def _stretches(self):
        return [slice(a, min(a + 1_000_000, len(self.csr.h))) for a in range(0, len(self.csr.h), 1_000_000)]

    @cached_property
    def weight(self) -> np.ndarray:
        return np.concatenate([np.zeros(0), *[self._weights(at, False, False) for at in self._stretches()]])

    @cached_property
    def bounds(self) -> tuple[np.ndarray, np.ndarray]:
        """(least, greatest) weight of each edge for any walker, in 32 bits, rounded away from each other."""
        low, high = np.empty((2, len(self.csr.h)), np.float32)
        for at in self._stretches():
            ways = [self._weights(at, back, linked) for back in (False, True) for linked in (False, True)]
            with np.errstate(over="ignore", under="ignore"):
                low[at] = np.nextafter(np.minimum.reduce(ways).astype(np.float32), np.float32(-np.inf))
                high[at] = np.nextafter(np.maximum.reduce(ways).astype(np.float32), np.float32(np.inf))
        return low, high

    @cached_property
    def usable(self) -> bool:
        """All weights are positive, and finite in 32 bits; so each walker reads its whole list."""
        low, high = self.bounds
        return not len(low) or bool(low.min() > 0 and np.isfinite(high.max()))

    @cached_property
    def sums(self) -> np.ndarray:
        """Running sums of the plain weights of each list."""
        from .lists import running_sums

        return running_sums(self.weight, self.csr.start)

    @cached_property
    def tops(self) -> tuple[np.ndarray, np.ndarray]:
        """(greatest plain weight of each list, how many edges have it)."""
        top = np.maximum.reduceat(self.weight, self.csr.start)
        return top, np.add.reduceat((self.weight == np.repeat(top, self.csr.deg)).astype(np.int64), self.csr.start)


class Near:
    """Walkers' near edges, by walker and place: their own weights, and running sums of what these are more than the plain ones."""

    def __init__(self, plain: Plain, row: np.ndarray, prev: np.ndarray, prev_row: np.ndarray):
        csr, self.size = plain.csr, np.int64(len(plain.csr.h) + 1)
        if not (plain.program.needs("prev") or plain.program.needs("linked")):
            self.owner, self.edge, linked = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, bool)
        else:
            self.owner, self.edge, linked = csr.near(row, prev_row, plain.program.needs("linked"))
        self.key = self.owner * self.size + self.edge
        env = {"h": csr.h[self.edge], "label": csr.label[self.edge], "dst": csr.ends(self.edge), "cur": csr.nodes[row[self.owner]], "prev": prev[self.owner], "linked": linked}
        self.weight = np.broadcast_to(np.asarray(plain.program.full.evaluate(env), float), self.edge.shape)
        self.first = np.searchsorted(self.owner, np.arange(len(row) + 1))
        self.more = self.weight - plain.weight[self.edge]
        self.acc = np.concatenate([[0.0], np.cumsum(self.more)])
        self.moved = np.concatenate([[0.0], np.cumsum(np.abs(self.more))])

    def weights(self, plain: Plain, owner: np.ndarray, edge: np.ndarray) -> np.ndarray:
        out = plain.weight[edge]
        if len(self.key):
            key = owner * self.size + edge
            at = np.minimum(np.searchsorted(self.key, key), len(self.key) - 1)
            hit = self.key[at] == key
            out[hit] = self.weight[at[hit]]
        return out

    def sums(self, plain: Plain, owner: np.ndarray, edge: np.ndarray) -> np.ndarray:
        """The walkers' running sums up to the edges."""
        if not len(self.key):
            return plain.sums[edge]
        return plain.sums[edge] + (self.acc[np.searchsorted(self.key, owner * self.size + edge, side="right")] - self.acc[self.first[owner]])

    def error(self, plain: Plain, row: np.ndarray) -> np.ndarray:
        """What rounding may change a walker's running sums by. Those of `more` go over all walkers."""
        csr = plain.csr
        return ROUNDING * (plain.sums[csr.start[row] + csr.deg[row] - 1] + (self.moved[self.first[1:]] - self.moved[self.first[:-1]])) + 1e-12 * self.moved[-1]


def blocks(deg: np.ndarray):
    """Walkers by lists of about one length, at most BLOCK candidates each with those that fill the lines."""
    order, a = np.argsort(deg, kind="stable"), 0
    sizes = deg[order]
    while a < len(order):
        least = int(sizes[a])
        b = int(np.searchsorted(sizes, least + max(4, least // 8), side="right"))
        b = max(a + 1, min(b, a + BLOCK // int(sizes[b - 1])))
        yield order[a:b]
        a = b


def lines(start: np.ndarray, deg: np.ndarray) -> tuple[np.ndarray, np.ndarray | None]:
    """(edges of each list in a line, which of them are in the list, or None if all are)."""
    places = np.arange(int(deg.max()))
    return start[:, None] + places[None, :], None if deg.min() == len(places) else places[None, :] < deg[:, None]


def _words(csr, state: np.ndarray, row: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    """(first words of the draws of each walker's candidates in a line, their edges, which of them exist)."""
    edge, there = lines(csr.start[row], csr.deg[row])
    return rng.mix(state[:, None] ^ np.arange(edge.shape[1], dtype=np.uint32)[None, :]), edge, there


def least_keys(plain: Plain, state, row, prev, prev_row) -> np.ndarray:
    """The edge of each walker's least key -ln(u)/w. It is (1 - u)/high at least, and no more than any one candidate's -ln(u)/low."""
    csr, (low, high), found = plain.csr, plain.bounds, []
    for some in blocks(csr.deg[row]):
        x, edge, there = _words(csr, state[0][some], row[some])
        least = np.invert(x, out=x).astype(np.float32)
        least /= np.take(high, edge, mode="clip")
        if there is not None:
            least[~there] = np.inf
        best = np.arange(len(some)), least.argmin(axis=1)
        with np.errstate(divide="ignore"):
            limit = -np.log1p(-np.minimum((x[best] + 1.0) / 4294967296.0, 1.0)) / low[edge[best]] * (4294967296.0 * (1 + 1e-5))
        who, place = np.nonzero(least <= limit.astype(np.float32)[:, None])
        found.append((some[who], edge[who, place]))
    who, edge = (np.concatenate(x) for x in zip(*found))
    w = csr.weights(plain.program, edge, row[who], prev[who], prev_row[who], 0)
    key = -np.log(rng.uniforms((state[0][who], state[1][who]), edge - csr.start[row[who]])) / w
    begin = np.flatnonzero(np.diff(who, prepend=-1))
    hit = np.flatnonzero(key == np.repeat(np.minimum.reduceat(key, begin), np.diff(np.append(begin, len(who)))))[::-1]
    out = np.empty(len(row), np.int64)
    out[who[hit]] = edge[hit]
    return out


def last_by_prefix(plain: Plain, near: Near, state, row) -> tuple[np.ndarray, np.ndarray]:
    """(edge, unsure) of the last candidate with u * sum < w."""
    csr, (_, high), found = plain.csr, plain.bounds, []
    out, unsure, error = np.full(len(row), -1, np.int64), np.zeros(len(row), bool), near.error(plain, row)
    lost = np.bincount(near.owner, np.maximum(-near.more, 0), len(row)) + error
    for some in blocks(csr.deg[row]):
        x, edge, there = _words(csr, state[0][some], row[some])
        least = np.take(plain.sums, edge, mode="clip")  # of the running sums
        least -= lost[some][:, None]
        least *= x
        maybe = least <= np.take(high, edge, mode="clip") * np.float64(4294967296.0)
        if there is not None:
            maybe &= there
        who, place = np.nonzero(maybe)
        found.append((some[who], edge[who, place]))
    who, edge = (np.concatenate(x) for x in zip(*found))
    off = rng.uniforms((state[0][who], state[1][who]), edge - csr.start[row[who]]) * near.sums(plain, who, edge)
    off -= near.weights(plain, who, edge)
    unsure[who[np.abs(off) <= error[who]]] = True
    out[who[off < 0]] = edge[off < 0]  # the last one stays
    return out, unsure | (out < 0)


def by_inverse(plain: Plain, near: Near, u: np.ndarray, row: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(edge, unsure) of the first candidate whose running sum exceeds u of the whole."""
    csr, every = plain.csr, np.arange(len(row))
    begin, end = csr.start[row], csr.start[row] + csr.deg[row]
    aim = u * near.sums(plain, every, end - 1)
    low, high = begin.copy(), end - 1
    while (open_ := np.flatnonzero(low < high)).size:
        mid = (low[open_] + high[open_]) // 2
        over = near.sums(plain, open_, mid) > aim[open_]
        high[open_], low[open_] = np.where(over, mid, high[open_]), np.where(over, low[open_], mid + 1)
    error = 2 * near.error(plain, row)
    before = np.where(low > begin, near.sums(plain, every, np.maximum(low - 1, begin)), -np.inf)
    return low, (near.sums(plain, every, low) - aim <= error) | (aim - before <= error)


def greatest(plain: Plain, near: Near, row: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(greatest weight, unsure) of each walker's list; unsure where all edges of the greatest plain weight are near."""
    top, ties = plain.tops
    hidden = np.bincount(near.owner, plain.weight[near.edge] == top[row[near.owner]], len(row)) >= ties[row]
    out = top[row].copy()
    np.maximum.at(out, near.owner, near.weight)
    return out, hidden
