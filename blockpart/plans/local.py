"""The same algorithm on one machine with sparse arrays: the serial baseline, and the engine for graphs that fit it.

Rules, draws and numbers of blocks are those of the Spark plans, so both engines give the same partitions.
"""

from __future__ import annotations

import os
import traceback
from contextlib import ExitStack
from dataclasses import dataclass, field
from multiprocessing import Pipe

import numpy as np

from blockpart.functions import draws as threads
from blockpart.functions.draws import numbers, side_by_side, strings
from blockpart.operators.merge import forest

#: Edges (undirected ones in both directions) and nodes of a graph that goes to this engine unasked; and of one that it takes on the driver, a larger one goes to a single task of an executor.
LOCAL_EDGES, LOCAL_NODES = 2_000_000, 200_000
DRIVER_EDGES, DRIVER_NODES = 500_000, 50_000
#: Cells of a dense table that stands in for sorted keys, for each of them at most SPARE; and rows of neighbouring blocks whose gains are made at a time.
DENSE, SPARE, GAIN_ROWS = 1 << 22, 16, 1 << 17
#: Bytes of draws that one process of a search keeps from try to try.
KEPT = 1 << 26
#: Edges from on which a task's search takes a second process.
HELPED = 1 << 16
#: Keys from which on they are looked up in tables of slots, not by a search; and the odd factors of these tables, one after another for keys whose slot was taken.
FILTER = 1 << 15
FACTORS = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0xD6E8FEB86659FD93)
#: Blocks of the dense tables of fixtures.
LIMIT = 4000


def phi(x: np.ndarray) -> np.ndarray:
    x = np.asarray(x, float)
    return np.log(np.where(x > 0, x, 1.0)) * np.maximum(x, 0.0)


def h(x: float) -> float:
    return float(phi(1 + x) - phi(x))


def draws(seed: int, phase: str, it: int, idents, k: object = 0) -> np.ndarray:
    """The counter-based draws of the Spark plans."""
    return strings(seed, phase, it, idents, k)


# ---- dense tables, for fixtures and measures ---------------------------------------------------------------------

def counts(a: np.ndarray, b: np.ndarray, blocks: int) -> np.ndarray:
    if blocks > LIMIT:
        raise ValueError("too many blocks for a dense table")
    half = np.zeros((blocks, a.shape[1]))
    np.add.at(half, b, a)
    m = np.zeros((blocks, blocks))
    np.add.at(m.T, b, half.T)
    return m


def log_posterior(m: np.ndarray) -> float:
    return float(phi(m).sum() - phi(m.sum(0)).sum() - phi(m.sum(1)).sum())


def description_length(m: np.ndarray, n: int) -> float:
    e, b = m.sum(), len(m)
    return float((e * h(b * b / e) if e else 0.0) + n * np.log(max(b, 1)) - log_posterior(m))


# ---- graphs and counts as sorted keys ----------------------------------------------------------------------------

@dataclass
class Graph:
    """Edges between nodes 0 .. n - 1, added up; ids are the nodes' names in draws, in rising order."""

    ids: np.ndarray
    src: np.ndarray
    dst: np.ndarray
    w: np.ndarray
    first: np.ndarray = field(init=False)

    def __post_init__(self):
        key, inverse = np.unique(self.src * len(self.ids) + self.dst, return_inverse=True)
        self.w = np.bincount(inverse, self.w, len(key))
        self.src, self.dst = key // max(len(self.ids), 1), key % max(len(self.ids), 1)
        loop, one = self.src == self.dst, self.src != self.dst
        zero = np.zeros(int(one.sum()))
        self.i = np.concatenate([self.src, self.dst[one]])
        self.j = np.concatenate([self.dst, self.src[one]])
        self.out = np.concatenate([np.where(loop, 0.0, self.w), zero])
        self.in_ = np.concatenate([np.zeros(len(self.w)), self.w[one]])
        self.loop = np.concatenate([np.where(loop, self.w, 0.0), zero])
        order = np.argsort(self.i, kind="stable")
        self.i, self.j, self.out, self.in_, self.loop = (x[order] for x in (self.i, self.j, self.out, self.in_, self.loop))
        self.first = np.searchsorted(self.i, np.arange(len(self.ids) + 1))
        self.whole = bool((self.w == np.floor(self.w)).all() and self.w.sum() < 1 << 50)

    @classmethod
    def dense(cls, a: np.ndarray) -> "Graph":
        src, dst = np.nonzero(a)
        return cls(np.arange(len(a)), src, dst, a[src, dst])

    @property
    def names(self) -> list[str]:
        return list(map(str, self.ids.tolist()))


def grouped(key: np.ndarray) -> tuple[np.ndarray, object]:
    """The different keys, rising, and a function that adds up values by key, in the order of rows. Key and row are sorted as one number where 63 bits hold both."""
    bits = max(len(key) - 1, 1).bit_length()
    if len(key) and int(key.max()) < 1 << (63 - bits):
        both = np.sort((key << bits) | np.arange(len(key)))
        order, key = both & ((1 << bits) - 1), both >> bits
    else:
        order = np.argsort(key, kind="stable")
        key = key[order]
    new = np.ones(len(key), bool)
    new[1:] = key[1:] != key[:-1]
    own = np.cumsum(new) - 1
    found = key[new]
    return found, lambda x: np.bincount(own, x[order], len(found))


def near_blocks(i: np.ndarray, t: np.ndarray, out, in_, loop, blocks: int):
    """i, t, k_out, k_in, w_self, sorted and added up."""
    key = i * blocks + t
    top = (int(i.max()) + 1) * blocks if len(i) else 0
    if top <= min(DENSE, 4 * len(i)):
        found = np.flatnonzero(np.bincount(key, minlength=top))
        total = lambda x: np.bincount(key, x, top)[found]
    else:
        found, total = grouped(key)
    own = found // blocks
    return own, found - own * blocks, total(out), total(in_), total(loop) if loop.any() else np.zeros(len(found))


class Cells:
    """M as sorted keys with values, its degrees, and both directions together by block with running weights."""

    def __init__(self, r: np.ndarray, s: np.ndarray, m: np.ndarray, blocks: int):
        key, self.blocks, self.table, self.slots = r * blocks + s, blocks, None, []
        if blocks * blocks <= min(DENSE, SPARE * len(key)):
            self.tabled(np.bincount(key, m, blocks * blocks))
            return
        key, total = grouped(key)
        value = total(m)
        self.key, self.m = key[value != 0], value[value != 0]
        self.r = self.key // blocks
        self.s = self.key - self.r * blocks
        self.d_out, self.d_in = np.bincount(self.r, self.m, blocks), np.bincount(self.s, self.m, blocks)
        self.d = self.d_out + self.d_in
        if len(self.key) >= FILTER:
            left = np.arange(len(self.key), dtype=np.int32)
            for factor in FACTORS:
                bits = len(left).bit_length() + 2
                place = np.full(1 << bits, -1, np.int32)
                at = self.slot(self.key[left], factor, bits)
                place[at] = left
                self.slots.append((factor, bits, place))
                left = left[place[at] != left]
                if not len(left):
                    break
            self.crowded = len(left) > 0

    def tabled(self, table: np.ndarray) -> None:
        self.table, square = table, table.reshape(self.blocks, self.blocks)
        self.d_out, self.d_in = square.sum(1), square.sum(0)
        self.d = self.d_out + self.d_in

    def __getattr__(self, name: str) -> np.ndarray:
        """Keys and values of a table, which sweeps do without, when they are first asked for."""
        if name not in ("key", "m", "r", "s"):
            raise AttributeError(name)
        self.key = np.flatnonzero(self.table)
        self.m, self.r = self.table[self.key], self.key // self.blocks
        self.s = self.key - self.r * self.blocks
        return getattr(self, name)

    def after(self, g: Graph, b: np.ndarray, to: np.ndarray) -> "Cells":
        """The counts once nodes have gone from b to `to`: in a table of whole numbers from the edges of nodes that moved, an edge between two such from its source."""
        i = np.flatnonzero(b != to)
        count = g.first[i + 1] - g.first[i]
        if self.table is None or not g.whole or int(count.sum()) > len(g.i) // 4:
            return cells(g, to, self.blocks)
        rows, i, table = spans(g.first[i], count), np.repeat(i, count), self.table.copy()
        j, out, in_ = g.j[rows], g.out[rows] + g.loop[rows], g.in_[rows]
        from_, into = np.flatnonzero(out), np.flatnonzero((in_ != 0) & (b[j] == to[j]))
        for x, y, w in ((i[from_], j[from_], out[from_]), (j[into], i[into], in_[into])):
            np.subtract.at(table, b[x] * self.blocks + b[y], w)
            np.add.at(table, to[x] * self.blocks + to[y], w)
        found = Cells.__new__(Cells)
        found.blocks, found.slots = self.blocks, []
        found.tabled(table)
        return found

    @staticmethod
    def slot(key: np.ndarray, factor: int, bits: int) -> np.ndarray:
        return (key.view(np.uint64) * np.uint64(factor)) >> np.uint64(64 - bits)

    def at(self, r: np.ndarray, s: np.ndarray) -> np.ndarray:
        key = r * self.blocks + s
        if self.table is not None:
            return self.table[key]
        if not len(self.key):
            return np.zeros(len(r))
        if not self.slots:
            return self.searched(key)
        out, rows = np.zeros(len(key)), None
        for factor, bits, place in self.slots:  # a free slot: no such key; a slot of another key: perhaps in the next table
            found = place[self.slot(key if rows is None else key[rows], factor, bits)]
            taken = np.flatnonzero(found >= 0)
            found, rows = found[taken], taken if rows is None else rows[taken]
            same = self.key[found] == key[rows]
            out[rows[same]] = self.m[found[same]]
            rows = rows[~same]
        if self.crowded:
            out[rows] = self.searched(key[rows])
        return out

    def searched(self, key: np.ndarray) -> np.ndarray:
        place = np.minimum(np.searchsorted(self.key, key), len(self.key) - 1)
        return np.where(self.key[place] == key, self.m[place], 0.0)

    def running(self, inner: bool = True, only: np.ndarray | None = None) -> "Running":
        """Running weights of all blocks, or at least of `only`."""
        if self.table is not None:
            both = self.table.reshape(self.blocks, self.blocks)
            both = both + both.T
            if not inner:
                np.fill_diagonal(both, 0.0)
            return RunningTable(both)
        keep = np.ones(len(self.key), bool) if inner else self.r != self.s
        if only is not None:
            need = np.zeros(self.blocks, bool)
            need[only] = True
            keep &= need[self.r] | need[self.s]
        u, t, m = np.concatenate([self.r[keep], self.s[keep]]), np.concatenate([self.s[keep], self.r[keep]]), np.concatenate([self.m[keep]] * 2)
        key, total = grouped(u * self.blocks + t)
        return Running(key // self.blocks, key % self.blocks, total(m), self.blocks)

    def log_posterior(self) -> float:
        return float(phi(self.m).sum() - phi(self.d_out).sum() - phi(self.d_in).sum())


class Running:
    def __init__(self, u: np.ndarray, t: np.ndarray, m: np.ndarray, blocks: int):
        self.t, self.first, self.total = t, np.searchsorted(u, np.arange(blocks + 1)), np.bincount(u, m, blocks)
        over = np.concatenate([[0.0], np.cumsum(m)])
        self.base, self.high = over[self.first[:-1]], over[1:]

    def look_up(self, u: np.ndarray, x: np.ndarray) -> np.ndarray:
        place = np.searchsorted(self.high, self.base[u] + x, "right")
        return self.t[np.clip(place, self.first[u], self.first[u + 1] - 1)]


class RunningTable:
    """The same of a table: a cell without weight is no draw's."""

    def __init__(self, both: np.ndarray):
        self.both, self.total, self.high = both, both.sum(1), np.cumsum(both)
        self.base = np.concatenate([[0.0], self.high[len(both) - 1 :: len(both)][:-1]])

    def look_up(self, u: np.ndarray, x: np.ndarray) -> np.ndarray:
        t = np.searchsorted(self.high, self.base[u] + x, "right") - u * len(self.both)
        for k in np.flatnonzero(t >= len(self.both)).tolist():  # rounded to the end of the row
            t[k] = np.flatnonzero(self.both[u[k]])[-1]
        return t


def cells(g: Graph, b: np.ndarray, blocks: int) -> Cells:
    return Cells(b[g.src], b[g.dst], g.w, blocks)


def spans(start: np.ndarray, count: np.ndarray) -> np.ndarray:
    lead = np.cumsum(count) - count
    return np.repeat(start - lead, count) + np.arange(int(count.sum()))


def even_parts(count: np.ndarray) -> list[tuple[int, int]]:
    """Ranges of movers with about as many rows each, GAIN_ROWS at most if no mover has more; some for each thread where they are shared."""
    ends = np.cumsum(count)
    rows = int(ends[-1]) if len(ends) else 0
    parts = -(-rows // GAIN_ROWS) if rows else 1
    if rows >= threads.SHARED:
        parts += -parts % threads.THREADS
    cuts = np.unique(np.concatenate([[0], np.searchsorted(ends, np.arange(1, parts) * rows // parts) + 1, [len(count)]]))
    return list(zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True))


def gains(own: np.ndarray, r: np.ndarray, s: np.ndarray, near: tuple, first: np.ndarray, m: Cells, whole: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """d_s, p_fwd, p_bwd of moves, by the closed form; near: own, t, k_out, k_in, w_self with the rows of own from first[own] on. whole: movers are all of r, so that their weights are the counts of r. So many moves at a time as have GAIN_ROWS rows."""
    count = first[own + 1] - first[own]
    parts = even_parts(count)
    if len(parts) < 2:
        return gains_at_once(own, r, s, near, first, m, whole)
    part = lambda x: gains_at_once(own[x[0] : x[1]], r[x[0] : x[1]], s[x[0] : x[1]], near, first, m, whole)
    return tuple(np.concatenate(x) for x in zip(*side_by_side(part, parts, int(count.sum())), strict=True))


def gains_at_once(own: np.ndarray, r: np.ndarray, s: np.ndarray, near: tuple, first: np.ndarray, m: Cells, whole: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    count = first[own + 1] - first[own]
    rows, k = spans(first[own], count), np.repeat(np.arange(len(own)), count)
    t, ko, ki, w = (x[rows] for x in near[1:])
    rk, sk = r[k], s[k]
    a, b = (ko, ki) if whole else (m.at(rk, t), m.at(t, rk))
    c, e, d = m.at(sk, t), m.at(t, sk), m.d[t]
    far, blocks, n = (t != rk) & (t != sk), m.blocks, len(own)
    step = lambda x, y: phi(x + y) - phi(x)
    total = lambda x: np.bincount(k, x, n).astype(float)
    sides = np.zeros((4, len(rows)))
    for x, y, to in ((a, -ko, 0), (b, -ki, 1), (c, ko, 2), (e, ki, 3)):
        some = np.flatnonzero(far & (y != 0))
        sides[to, some] = step(x[some], y[some])
    g = total(sides[0] + sides[1] + sides[2] + sides[3])
    f = total((ko + ki + 2 * w) * (c + e + 1) / (d + blocks))
    back = total(np.where(far, (ko + ki) * (a + b - ko - ki + 1) / (d + blocks), 0.0))
    o, i, loop = total(ko), total(ki), total(w)
    at_r, at_s = t == rk, t == sk
    or_, nr, os, ns = total(ko * at_r), total(ki * at_r), total(ko * at_s), total(ki * at_s)
    rr, sr, rs, ss = m.at(r, r), m.at(s, r), m.at(r, s), m.at(s, s)
    k_out, k_in, weight = o + loop, i + loop, o + i + 2 * loop
    c_rr, c_ss, c_rs, c_sr = -or_ - nr - loop, os + ns + loop, nr - os, or_ - ns
    corners = step(rr, c_rr) + step(ss, c_ss) + step(rs, c_rs) + step(sr, c_sr)
    sides = step(m.d_out[r], -k_out) + step(m.d_out[s], k_out) + step(m.d_in[r], -k_in) + step(m.d_in[s], k_in)
    back += (or_ + nr) * (2 * (rr + c_rr) + 1) / (m.d[r] - weight + blocks) + (os + ns + 2 * loop) * (rs + c_rs + sr + c_sr + 1) / (m.d[s] + weight + blocks)
    with np.errstate(invalid="ignore", divide="ignore"):
        return g + corners - sides, f / weight, back / weight


def accepted(d_s: np.ndarray, p_fwd: np.ndarray, p_bwd: np.ndarray, beta: float, draw: np.ndarray) -> np.ndarray:
    return draw < np.round(np.minimum(1.0, np.exp(np.clip(beta * np.round(d_s, 9), -700, 700)) * p_bwd / p_fwd), 9)


# ---- schedules ---------------------------------------------------------------------------------------------------

class Drawn:
    """Draws of the nodes low .. high - 1 in one search. Those of a node in a sweep are the same in every try, so they are made once and kept, up to KEPT bytes."""

    def __init__(self, seed: int, ids: np.ndarray, low: int = 0, high: int | None = None):
        self.seed, self.low, self.ids, self.kept, self.room = seed, low, ids[low:high], {}, KEPT

    def of(self, phase: str, it: int, k: int = 0, nodes: np.ndarray | None = None) -> np.ndarray:
        own = slice(None) if nodes is None else nodes - self.low
        if (phase, it, k) not in self.kept:
            if self.room < 8 * len(self.ids):
                return numbers(self.seed, phase, it, self.ids[own], None, k)
            self.room -= 8 * len(self.ids)
            self.kept[phase, it, k] = numbers(self.seed, phase, it, self.ids, None, k)
        return self.kept[phase, it, k][own]


def near_movers(g: Graph, b: np.ndarray, blocks: int, seed: int, it: int, movers: np.ndarray) -> tuple[tuple, np.ndarray, np.ndarray]:
    """Neighbouring blocks of movers, as of near_blocks, their number by mover, and the row of the block that each mover with any has drawn."""
    count = g.first[movers + 1] - g.first[movers]
    rows = spans(g.first[movers], count)
    near = near_blocks(np.repeat(np.arange(len(movers)), count), b[g.j[rows]], g.out[rows], g.in_[rows], g.loop[rows], blocks)
    own, t, count = near[0], near[1], np.bincount(near[0], minlength=len(movers))
    wait, drawn = np.zeros(len(own)), np.flatnonzero(np.repeat(count > 1, count))  # a single one needs no draw
    k = near[2][drawn] + near[3][drawn] + 2 * near[4][drawn]
    wait[drawn] = -np.log(1 - numbers(seed, "prop", it, g.ids[movers[own[drawn]]], t[drawn])) / k
    some = np.flatnonzero(count)
    if not len(some):
        return near, count, some
    least = np.minimum.reduceat(wait, (np.cumsum(count) - count)[some])
    lead = np.flatnonzero(wait == np.repeat(least, count[some]))
    return near, count, lead[np.concatenate([[True], own[lead][1:] != own[lead][:-1]])]  # ties to the least t


def step(g: Graph, b: np.ndarray, m: Cells, seed: int, it: int, beta: float, explore: float | None, only: np.ndarray | None) -> np.ndarray:
    """New blocks; all nodes see the same counts."""
    return moved(b, moves(g, b, m, seed, it, beta, explore, only, Drawn(seed, g.ids)))


def moved(b: np.ndarray, *found: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    after = b.copy()
    for i, s in found:
        after[i] = s
    return after


def moves(g: Graph, b: np.ndarray, m: Cells, seed: int, it: int, beta: float, explore: float | None, only: np.ndarray | None, drawn: Drawn) -> tuple[np.ndarray, np.ndarray]:
    """Nodes that move, of the drawn ones, and their new blocks."""
    blocks = m.blocks
    movers = drawn.low + (np.arange(len(drawn.ids)) if only is None else np.flatnonzero(only))
    if not len(movers):
        return movers, movers
    degree = g.first[movers + 1] - g.first[movers]
    parts = even_parts(degree)
    found = side_by_side(lambda x: near_movers(g, b, blocks, seed, it, movers[x[0] : x[1]]), parts, int(degree.sum()))
    past = np.cumsum([0] + [len(x[0][0]) for x in found])
    near = (np.concatenate([x[0][0] + low for x, (low, _) in zip(found, parts, strict=True)]), *(np.concatenate([x[0][k] for x in found]) for k in range(1, 5)))
    lead = np.concatenate([x[2] + low for x, low in zip(found, past.tolist(), strict=False)])
    first = np.concatenate([[0], np.cumsum(np.concatenate([x[1] for x in found]))])
    if not len(lead):
        return lead, lead
    at, u = near[0][lead], near[1][lead]
    i = movers[at]
    roam = drawn.of("prop", it, 1, i) < (blocks / (m.d[u] + blocks) if explore is None else explore)
    s, near_u = np.empty(len(i), np.int64), u[~roam]
    s[roam] = np.minimum(np.floor(drawn.of("prop", it, 2, i[roam]) * blocks), blocks - 1)
    s[~roam] = m.running(only=near_u).look_up(near_u, drawn.of("prop", it, 3, i[~roam]) * m.d[near_u])
    new = s != b[i]
    at, s, i = at[new], s[new], i[new]
    d_s, fwd, bwd = gains(at, b[i], s, near, first, m)
    yes = accepted(d_s, fwd, bwd, beta, drawn.of("acc", it, 0, i))
    return i[yes], s[yes]


def batched(g: Graph, b: np.ndarray, blocks: int, seed: int, it: int, q: int, beta: float, explore: float | None, damp: float = 1.0) -> np.ndarray:
    return batched_with(g, b, cells(g, b, blocks), seed, it, q, beta, explore, damp)[0]


def batched_with(g: Graph, b: np.ndarray, m: Cells, seed: int, it: int, q: int, beta: float, explore: float | None, damp: float = 1.0, drawn: Drawn | None = None, others=None) -> tuple[np.ndarray, Cells]:
    """New blocks and their counts; others: takes the moves of the drawn nodes and gives those of all others."""
    drawn = Drawn(seed, g.ids) if drawn is None else drawn
    draw = drawn.of("batch", it) if q > 1 or damp < 1 else None
    for k in range(q):
        only = None if draw is None else draw < damp if q == 1 else np.floor(draw * q) == k
        own = moves(g, b, m, seed, it, beta, explore, only, drawn)
        after = moved(b, own) if others is None else moved(b, own, others(own))
        b, m = after, m.after(g, b, after)
    return b, m


class Helper:
    """A second process for the sweeps, as an executor has two cores and two threads wait for each other's Python: it takes the upper nodes, with half of the rows,
    and after each batch both tell the other their moves. It ends with its pipe, or with the process that it helps."""

    def __init__(self, g: Graph, sweep):
        self.cut = int(np.searchsorted(g.first, len(g.i) // 2))
        (asked, self.to), (self.back, answer) = Pipe(False), Pipe(False)
        self.b = None
        self.pid = os.fork()
        if not self.pid:
            try:
                self.to.close()
                self.back.close()
                with threads.one_thread():
                    self.serve(g, sweep, asked, answer)
            except EOFError:
                pass
            except BaseException:
                traceback.print_exc()
            finally:
                os._exit(0)
        asked.close()
        answer.close()

    def serve(self, g: Graph, sweep, asked, answer) -> None:
        def others(own: tuple) -> tuple:
            answer.send(own)
            return asked.recv()

        b = m = None
        while True:
            it, blocks, given = asked.recv()
            if given is not None:
                b, m = given, cells(g, given, blocks)
            b, m = sweep(b, m, it, self.cut, None, others)

    def others(self, own: tuple) -> tuple:
        found = self.back.recv()
        self.to.send(own)
        return found

    def swept(self, b: np.ndarray, m: Cells, it: int, sweep) -> tuple[np.ndarray, Cells]:
        try:
            self.to.send((it, m.blocks, None if b is self.b else b))
            with threads.one_thread():
                self.b, m = sweep(b, m, it, 0, self.cut, self.others)
        except (EOFError, BrokenPipeError) as lost:
            raise RuntimeError("the second process of the search has ended") from lost
        return self.b, m

    def close(self) -> None:
        self.to.close()
        self.back.close()
        os.waitpid(self.pid, 0)


class Sparse:
    """M by row and by column, for one move after another."""

    def __init__(self, rows, blocks: int):
        self.blocks, self.row, self.col, self.d_out, self.d_in = blocks, {}, {}, {}, {}
        for r, s, v in rows:
            self.add(int(r), int(s), float(v))

    def add(self, r: int, s: int, v: float) -> None:
        for table, x, y in ((self.row, r, s), (self.col, s, r)):
            own = table.setdefault(x, {})
            own[y] = own.get(y, 0.0) + v
            if not own[y]:
                del own[y]
        self.d_out[r] = self.d_out.get(r, 0.0) + v
        self.d_in[s] = self.d_in.get(s, 0.0) + v

    def at(self, r: int, s: int) -> float:
        return self.row.get(r, {}).get(s, 0.0)

    def degree(self, t: int) -> float:
        return self.d_out.get(t, 0.0) + self.d_in.get(t, 0.0)


def _phi(x: float) -> float:
    return x * float(np.log(x)) if x > 0 else 0.0


def visit(i: int, name: str, near: list[tuple[int, float, float]], loop: float, now: dict[int, int], m: Sparse, seed: int, it: int, beta: float, explore: float | None) -> None:
    """One node's update with the newest blocks `now` and counts m, which it changes; near: (block, out, in) of neighbours."""
    r, ko, ki = now[i], {}, {}
    for t, o, n in near:
        ko[t], ki[t] = ko.get(t, 0.0) + o, ki.get(t, 0.0) + n
    k = {t: ko[t] + ki[t] for t in ko}
    if loop:
        k[r] = k.get(r, 0.0) + 2 * loop
    k = {t: x for t, x in sorted(k.items()) if x > 0}
    if not k:
        return
    one = lambda ident, phase="prop", x=0: float(draws(seed, phase, it, (ident,), x)[0])
    u = min((-float(np.log(1 - one(f"{name}:{t}"))) / x, t) for t, x in k.items())[1]
    blocks, d_u = m.blocks, m.degree(u)
    if one(name, x=1) < (blocks / (d_u + blocks) if explore is None else explore):
        s = min(int(one(name, x=2) * blocks), blocks - 1)
    else:
        x, s, total = one(name, x=3) * d_u, r, 0.0
        row, col = m.row.get(u, {}), m.col.get(u, {})
        for t in sorted(row.keys() | col.keys()):
            total += row.get(t, 0.0) + col.get(t, 0.0)
            if total > x:
                s = t
                break
    if s == r:
        return
    delta: dict[tuple[int, int], float] = {}
    for t in ko:
        for p, q, v in ((r, t, -ko[t]), (s, t, ko[t]), (t, r, -ki[t]), (t, s, ki[t])):
            delta[p, q] = delta.get((p, q), 0.0) + v
    if loop:
        for p, v in ((r, -loop), (s, loop)):
            delta[p, p] = delta.get((p, p), 0.0) + v
    k_out, k_in = sum(ko.values()) + loop, sum(ki.values()) + loop
    weight = k_out + k_in
    gain = sum(_phi(m.at(p, q) + v) - _phi(m.at(p, q)) for (p, q), v in delta.items())
    for d, x in ((m.d_out, k_out), (m.d_in, k_in)):
        a, b = d.get(r, 0.0), d.get(s, 0.0)
        gain -= _phi(a - x) - _phi(a) + _phi(b + x) - _phi(b)
    ahead = sum(x * (m.at(t, s) + m.at(s, t) + 1) / (m.degree(t) + blocks) for t, x in k.items())
    k[r] = k.get(r, 0.0) - 2 * loop
    k[s] = k.get(s, 0.0) + 2 * loop
    after = lambda p, q: m.at(p, q) + delta.get((p, q), 0.0)
    back = sum(x * (after(t, r) + after(r, t) + 1) / (m.degree(t) - weight * (t == r) + weight * (t == s) + blocks) for t, x in k.items())
    if accepted(np.float64(gain), np.float64(ahead / weight), np.float64(back / weight), beta, np.float64(one(name, "acc"))):
        for (p, q), v in delta.items():
            if v:
                m.add(p, q, v)
        now[i] = s


def visiting_order(names, seed: int, it: int) -> list[int]:
    draw = draws(seed, "order", it, names)
    return sorted(range(len(draw)), key=lambda k: (draw[k], k))


def sequential(g: Graph, b: np.ndarray, blocks: int, seed: int, it: int, beta: float, explore: float | None) -> np.ndarray:
    """One node after another, in an order that is drawn, each with all earlier moves."""
    m = cells(g, b, blocks)
    table, now = Sparse(zip(m.r.tolist(), m.s.tolist(), m.m.tolist(), strict=True), blocks), dict(enumerate(b.tolist()))
    order = np.lexsort((g.j, g.i))
    first = np.searchsorted(g.i[order], np.arange(len(b) + 1))
    names = g.names
    for i in visiting_order(names, seed, it):
        own = order[first[i] : first[i + 1]]
        near = [(now[j], o, n) for j, o, n in zip(g.j[own].tolist(), g.out[own].tolist(), g.in_[own].tolist(), strict=True) if j != i]
        visit(i, names[i], near, float(g.loop[own].sum()), now, table, seed, it, beta, explore)
    return np.array([now[i] for i in range(len(b))])


# ---- the engine --------------------------------------------------------------------------------------------------

def relabel(b: np.ndarray) -> np.ndarray:
    """Blocks numbered by their least node."""
    _, first, number = np.unique(b, return_index=True, return_inverse=True)
    return np.argsort(np.argsort(first))[number]


class LocalEngine:
    """States are block vectors, numbered 0 .. B - 1 by least node."""

    def __init__(self, graph: Graph, cfg, seed: int, helped: bool = False):
        self.g, self.cfg, self.seed, self.drawn, self.helper, self.until = graph, cfg, seed, {}, None, ExitStack()
        if cfg.schedule not in ("sync", "batched", "sequential"):
            raise ValueError(f"the local engine has no schedule {cfg.schedule}")
        if helped and cfg.schedule != "sequential":
            self.helper = Helper(graph, self.swept)
            self.until.callback(self.helper.close)

    def __enter__(self) -> "LocalEngine":
        return self

    def __exit__(self, *error) -> None:
        self.until.close()

    def swept(self, b: np.ndarray, m: Cells, it: int, low: int = 0, high: int | None = None, others=None) -> tuple[np.ndarray, Cells]:
        """One sweep of the nodes low .. high - 1, and of all others by what `others` says."""
        if low not in self.drawn:
            self.drawn[low] = Drawn(self.seed, self.g.ids, low, high)
        cfg = self.cfg
        return batched_with(self.g, b, m, self.seed, it, cfg.batches, cfg.step_beta, cfg.explore, cfg.damp, self.drawn[low], others)

    def start(self, given: np.ndarray | None) -> np.ndarray:
        return relabel(np.arange(len(self.g.ids)) if given is None else given)

    def blocks(self, b: np.ndarray) -> int:
        return int(b.max()) + 1 if len(b) else 0

    def shrink(self, b: np.ndarray, target: int) -> np.ndarray:
        while (blocks := self.blocks(b)) > target:
            root = merges(cells(self.g, b, blocks), target, self.cfg.proposals, self.seed + blocks)
            b = relabel(np.array([root.get(x, x) for x in range(blocks)])[b])
        return b

    def settle(self, b: np.ndarray, tau: float) -> tuple[np.ndarray, int]:
        from blockpart.plans.sweep import converged

        cfg, blocks = self.cfg, self.blocks(b)
        m = cells(self.g, b, blocks)
        past, sweeps = [m.log_posterior()], 0
        while sweeps < cfg.max_sweeps and not converged(past, tau, cfg.window):
            if cfg.schedule == "sequential":
                b = sequential(self.g, b, blocks, self.seed, sweeps, cfg.step_beta, cfg.explore)
                m = cells(self.g, b, blocks)
            else:
                b, m = self.helper.swept(b, m, sweeps, self.swept) if self.helper else self.swept(b, m, sweeps)
            past.append(m.log_posterior())
            sweeps += 1
        return relabel(b), sweeps

    def length(self, b: np.ndarray) -> tuple[float, float]:
        """S and H."""
        blocks, half = self.blocks(b), 1.0 if self.cfg.directed else 0.5
        s, e = half * cells(self.g, b, blocks).log_posterior(), half * float(self.g.w.sum())
        size = blocks * blocks if self.cfg.directed else blocks * (blocks + 1) / 2
        return s, (e * h(size / e) if e else 0.0) + len(b) * float(np.log(max(blocks, 1))) - s


def merges(m: Cells, target: int, tries: int, seed: int) -> dict[int, int]:
    """Roots after the best merges that leave `target` blocks: for each block the best of its draws, the best blocks first."""
    blocks = m.blocks
    some = np.flatnonzero(m.d > 0)
    r = np.repeat(some, tries)
    turn = np.tile(np.arange(tries), len(some))
    draw = lambda x, of: numbers(seed, "prop", 0, r[of], turn[of], x)
    outer, all_ = m.running(inner=False), m.running()
    alone = outer.total[r] <= 0
    u = np.where(alone, 0, r)
    u[~alone] = outer.look_up(r[~alone], draw(0, ~alone) * outer.total[r[~alone]])
    roam = alone | (draw(1, slice(None)) < blocks / (m.d[u] + blocks))
    s = np.empty(len(r), np.int64)
    s[roam] = np.minimum(np.floor(draw(2, roam) * blocks), blocks - 1)
    s[~roam] = all_.look_up(u[~roam], draw(3, ~roam) * m.d[u[~roam]])
    key = np.unique((r * blocks + s)[r != s])
    r, s = key // blocks, key % blocks
    other, inner = m.r != m.s, m.r == m.s
    zero = lambda x: np.zeros(int(x.sum()))
    near = near_blocks(np.concatenate([m.r[other], m.s[other], m.r[inner]]), np.concatenate([m.s[other], m.r[other], m.s[inner]]), np.concatenate([m.m[other], zero(other), zero(inner)]), np.concatenate([zero(other), m.m[other], zero(inner)]), np.concatenate([zero(other), zero(other), m.m[inner]]), blocks)
    d_s, _, _ = gains(r, r, s, near, np.searchsorted(near[0], np.arange(blocks + 1)), m, whole=True)
    order = np.lexsort((s, -np.round(d_s, 9), r))
    lead = order[np.concatenate([[True], r[order][1:] != r[order][:-1]])] if len(order) else order
    found = forest(list(zip(r[lead].tolist(), s[lead].tolist(), d_s[lead].tolist(), strict=True)), blocks - target)
    return found or {1: 0}


def fit(g: Graph, start: np.ndarray | None = None, **options) -> tuple[np.ndarray, list[dict]]:
    """The best partition and the history of tries."""
    from blockpart.plans.search import FitConfig, explored

    cfg = FitConfig(**options)
    return explored(LocalEngine(g, cfg, cfg.seed), cfg, start)
