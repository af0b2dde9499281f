"""The small-graph multilevel kernels that run inside one task: contraction, label propagation, first blocks, local search.

Graphs are adjacency arrays of the smallest types that hold them; loops are loops because each step depends on the one before
it. Those over large models run in Java (`loops`), all others in plain Python, step by step the same. In Python they turn a
window of the arrays to lists at a time, and what they reach in any order is an unboxed array, so a model of many million
vertices takes tens of bytes a vertex and edge.
"""

from __future__ import annotations

import heapq
import math
from array import array
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np

from cutstream.functions.columns import M31, MIX
from cutstream.params import PartitionParams
from cutstream.plans import loops


#: Half-edges that a step of Level.of sorts, that a window of a loop has as lists, and vertices whose weights to blocks are kept.
SORTED, WINDOW, KEPT = 1 << 21, 1 << 17, 1 << 17


def compact(x: np.ndarray) -> np.ndarray:
    """Weights as the smallest of uint8, float32 and float64 that holds each exactly."""
    x = np.asarray(x)
    if x.dtype == np.uint8:
        return x
    for kind in (np.uint8, np.float32):
        if kind != np.uint8 or not len(x) or (x.min() >= 0 and x.max() <= 255):
            y = x.astype(kind)
            if np.array_equal(y, x):
                return y
    return np.asarray(x, np.float64)


def unboxed(x: np.ndarray, kind: str) -> array:
    """A changeable copy that Python reads number by number, of type kind."""
    out = array(kind)
    out.frombytes(np.ascontiguousarray(x, dtype=np.dtype(kind)).view(np.uint8))
    return out


def windows(ptr: np.ndarray, most: int = 0) -> Iterator[tuple[int, int]]:
    """Ranges of vertices with about `most` half-edges and vertices together, one vertex at least."""
    lo, n, most = 0, len(ptr) - 1, most or WINDOW
    while lo < n:
        hi = min(lo + most, n, max(lo + 1, int(np.searchsorted(ptr, ptr[lo] + most, "right")) - 1))
        yield lo, hi
        lo = hi


def mix31(x, seed: int = 0):
    """The mixer of functions.columns, for numbers and arrays."""
    a, s, b, t = MIX
    x = (x + seed * 7919 % M31) % M31 * a % M31
    x = x ^ (x >> s)
    x = x * b % M31
    return x ^ (x >> t)


@dataclass
class Level:
    """A weighted graph: neighbours of u are adj[ptr[u]:ptr[u + 1]]."""

    weight: np.ndarray
    ptr: np.ndarray
    adj: np.ndarray
    w: np.ndarray

    @property
    def n(self) -> int:
        return len(self.weight)

    @classmethod
    def of(cls, weight: np.ndarray, a: np.ndarray, b: np.ndarray, w: np.ndarray) -> Level:
        """From undirected edges; parallel ones are summed, loops dropped."""
        n = len(weight)
        keep = a != b
        if not keep.all():
            a, b, w = a[keep], b[keep], w[keep]
        del keep
        if loops.worth(n + 2 * len(a)) and (made := loops.joined(n, a, b, w)):
            return cls.made(weight, *made)
        ends = np.zeros(n + 1, np.int64)
        for side in (a, b):
            ends[1:] += np.bincount(side, minlength=n)
        np.cumsum(ends, out=ends)
        degree, adj, sums = np.zeros(n, np.int32), [], []
        for lo, hi in windows(ends, SORTED):
            i, j = np.flatnonzero((a >= lo) & (a < hi)), np.flatnonzero((b >= lo) & (b < hi))
            key = np.concatenate([a[i], b[j]]).astype(np.int64)
            key = (key - lo) * n + np.concatenate([b[i], a[j]])
            order = np.argsort(key, kind="stable")
            key, both = key[order], np.concatenate([w[i], w[j]]).astype(np.float64)[order]
            if not len(key):
                continue
            first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
            key = key[first]
            degree[lo:hi] = np.bincount(key // n, minlength=hi - lo)
            adj.append((key % n).astype(np.int32))
            sums.append(compact(np.add.reduceat(both, first)))
        ptr = np.zeros(n + 1, np.int32 if len(a) < 1 << 30 else np.int64)
        np.cumsum(degree, out=ptr[1:])
        return cls(compact(weight), ptr, np.concatenate(adj) if adj else np.zeros(0, np.int32), np.concatenate(sums) if sums else np.zeros(0, np.uint8))

    @classmethod
    def made(cls, weight: np.ndarray, ptr: np.ndarray, adj: np.ndarray, w: np.ndarray) -> Level:
        """From arrays that lie in a file, the weights as doubles."""
        sums = [compact(w[lo : lo + SORTED]) for lo in range(0, len(w), SORTED)]
        return cls(compact(weight), ptr, np.array(adj), np.concatenate([np.zeros(0, np.uint8), *sums]))

    def edges(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        out = [(np.zeros(0, np.int32), self.adj[:0], self.w[:0])]
        for lo, hi in windows(self.ptr, SORTED):
            s, e = int(self.ptr[lo]), int(self.ptr[hi])
            u = np.repeat(np.arange(lo, hi, dtype=np.int32), np.diff(self.ptr[lo : hi + 1]))
            once = u < self.adj[s:e]
            out.append((u[once], self.adj[s:e][once], self.w[s:e][once]))
        return tuple(np.concatenate(x) for x in zip(*out, strict=True))

    def window(self, lo: int, hi: int) -> tuple[list[int], list[int], list[float], list[float]]:
        """ptr, adj, w and weight of vertices lo to hi, as lists; ptr is from 0 on."""
        s, e = int(self.ptr[lo]), int(self.ptr[hi])
        return (self.ptr[lo : hi + 1] - s).tolist(), self.adj[s:e].tolist(), self.w[s:e].tolist(), self.weight[lo:hi].tolist()


def contract(g: Level, labels: np.ndarray) -> tuple[Level, np.ndarray]:
    """One vertex for each label, in label order; returns (coarse graph, coarse vertex of each vertex)."""
    used = np.zeros(int(labels.max()) + 1 if len(labels) else 0, bool)
    used[labels] = True
    to = (np.cumsum(used, dtype=np.int32) - 1)[labels]
    del used
    if loops.worth(g.n + len(g.adj)):
        weight = np.zeros(int(to.max()) + 1)
        for lo in range(0, g.n, SORTED):
            weight += np.bincount(to[lo : lo + SORTED], g.weight[lo : lo + SORTED], len(weight))
        if made := loops.contracted(g, to, len(weight)):
            return Level.made(weight, *made), to
    a, b, w = g.edges()
    a, b = to[a], to[b]
    return Level.of(np.bincount(to, g.weight), a, b, w), to


def tie_seed(seed: int, turn: int) -> int:
    """Seed of a round's random ties, so that a tie is broken anew in each."""
    return seed + 131 * turn


def label_propagation(g: Level, rounds: int, most: float, seed: int, tie: str = "random", within: np.ndarray | None = None) -> np.ndarray:
    """Size-constrained clusters: in natural order, each vertex joins the strongest adjacent cluster that has room.

    Equally strong ones, the present one included, are told apart by a keyed number of the round (`random`) or by label.
    within: vertices of different values there never share a cluster. Stops when a round moves nothing. After the first
    round only vertices are looked at whose choice may differ: those next to a vertex that moved since, those that met a tie
    (for random ones) and those for which a stronger cluster had no room.
    """
    if loops.worth(g.n + len(g.adj)):
        found = loops.clusters(g, rounds, most, [tie_seed(seed, turn) * 7919 % M31 for turn in range(rounds)], MIX, tie == "random", within)
        if found is not None:
            return found
    label, size = unboxed(np.arange(g.n), "i"), unboxed(g.weight, "d")
    own = unboxed(within, "i") if within is not None else None
    due = bytearray(b"\1") * g.n
    (m1, s1, m2, s2), mask = MIX, M31 - 1
    for turn in range(rounds):
        moved, keyed = 0, tie_seed(seed, turn) * 7919 % M31
        for lo, hi in windows(g.ptr):
            u = due.find(1, lo, hi)
            if u < 0:
                continue
            ptr, adj, w, weight = g.window(lo, hi)
            while u >= 0:
                due[u] = 0
                votes: dict[int, float] = {}
                start, end, c = ptr[u - lo], ptr[u - lo + 1], weight[u - lo]
                if own is None:
                    for e in range(start, end):
                        x = label[adj[e]]
                        votes[x] = votes[x] + w[e] if x in votes else w[e]
                else:
                    for e in range(start, end):
                        if own[adj[e]] == own[u]:
                            x = label[adj[e]]
                            votes[x] = votes[x] + w[e] if x in votes else w[e]
                now, room = label[u], most - c
                best, strength, rank = now, votes.get(now, 0.0), None
                for x, v in votes.items():
                    if v < strength or x == now:
                        continue
                    if size[x] > room:
                        due[u] = 1
                    elif v > strength:
                        best, strength, rank = x, v, None
                    elif tie == "random":
                        due[u] = 1
                        if rank is None:  # mix31 of u * 1_000_003 + best by the round's seed, written out as it is most of the time
                            rank = (u * 1_000_003 + best + keyed & mask) * m1 & mask
                            rank = (rank ^ rank >> s1) * m2 & mask
                            rank ^= rank >> s2
                        other = (u * 1_000_003 + x + keyed & mask) * m1 & mask
                        other = (other ^ other >> s1) * m2 & mask
                        other ^= other >> s2
                        if other < rank:
                            best, rank = x, other
                    elif x < best:
                        best = x
                if best != now:
                    size[now] -= c
                    size[best] += c
                    label[u] = best
                    moved += 1
                    for v in adj[start:end]:
                        due[v] = 1
                u = due.find(1, u + 1, hi)
        if not moved:
            break
    return np.frombuffer(label, np.int32)


def coarsen(g: Level, p: PartitionParams, lmax: float, within: np.ndarray | None = None) -> tuple[list[Level], list[np.ndarray]]:
    """Levels from fine to coarse and the maps between them, until few enough vertices or hardly any shrinking."""
    levels, maps = [g], []
    stop = max((g.n + p.k) / (2 * p.x * p.k), p.x * p.k)
    while levels[-1].n >= stop and levels[-1].n > 1:
        fine = levels[-1]
        most = max(float(fine.weight.max()), lmax / p.cluster_factor)
        coarse, to = contract(fine, label_propagation(fine, p.coarsen_rounds, most, p.seed + len(maps), p.tie, within))
        if coarse.n > 0.95 * fine.n:
            break
        levels.append(coarse)
        maps.append(to)
        if within is not None:
            inner = np.zeros(coarse.n, np.int32)
            inner[to] = within
            within = inner
    return levels, maps


class Blocks:
    """Loads of k blocks, their penalties, and the choice of the best block.

    A block without a connection is never better than the least loaded one, so only connected blocks and that one are
    scored: the choice does not depend on k. A heap finds the least loaded block; its stale entries are skipped.
    """

    #: Whether a move is scored as here, and whether all blocks are.
    whole, all = True, False

    def __init__(self, p: PartitionParams, scale: float, most: float, loads=None):
        self.p, self.alpha, self.scale, self.most = p, scale, scale * p.gamma, most
        self.load = [0.0] * p.k if loads is None else [float(x) for x in loads]
        self.table = (self.scale * np.power(np.arange(4096) * (most / 4095), p.gamma - 1)).tolist() if p.power == "table" else None
        self.discount, self.root = p.objective == "capacity_discount", p.gamma == 1.5 and p.power == "exact"
        self.penalty = [self._penalty(x) for x in self.load]
        self._fill()

    def _fill(self) -> None:
        self.heap = [(x, i) for i, x in enumerate(self.load)]
        heapq.heapify(self.heap)

    def _penalty(self, load: float) -> float:
        if self.discount:
            return 1 - load / self.most if self.most else 0.0
        if load <= 0:
            return 0.0
        if self.table is not None:
            return self.table[min(4095, int(load / self.most * 4095))]
        return self.scale * (math.sqrt(load) if self.root else load ** (self.p.gamma - 1))

    def set_loads(self, loads: list[float]) -> None:
        self.load, self.penalty = loads, [self._penalty(x) for x in loads]
        self._fill()

    def add(self, i: int, c: float) -> None:
        self.load[i] = x = self.load[i] + c
        self.penalty[i] = self._penalty(x)
        heapq.heappush(self.heap, (x, i))
        if len(self.heap) > 8 * self.p.k + 64:
            self._fill()

    def add_all(self, blocks: np.ndarray, c: np.ndarray) -> None:
        """add for many vertices."""
        total = np.bincount(blocks, c, self.p.k)
        for i in np.unique(blocks).tolist():
            self.add(i, float(total[i]))

    def score(self, conn: float, c: float, i: int) -> float:
        return conn * self.penalty[i] if self.discount else conn - c * self.penalty[i]

    def least(self) -> int:
        """The least loaded block, the lowest of equals."""
        while self.heap[0][0] != self.load[self.heap[0][1]]:
            heapq.heappop(self.heap)
        return self.heap[0][1]

    def best_of_all(self, conn: dict[int, float], c: float) -> int:
        """Feasible block of the best score; ties to the lower load, then the lower number; -1 if none has room."""
        load, most, best = self.load, self.most - c, self.least()
        if load[best] > most:
            return -1
        score = self.score(conn.get(best, 0.0), c, best)
        for i, x in conn.items():
            if load[i] <= most and i != best:
                s = self.score(x, c, i)
                if s > score or (s == score and (load[i], i) < (load[best], best)):
                    best, score = i, s
        return best


class AllBlocks(Blocks):
    """The same choices by scoring every block for every vertex, so time grows with k as the one-pass greedies are published."""

    all = True

    def best_of_all(self, conn: dict[int, float], c: float) -> int:
        load, most, best, score = self.load, self.most - c, -1, 0.0
        for i in range(self.p.k):
            if load[i] <= most:
                s = self.score(conn.get(i, 0.0), c, i)
                if best < 0 or s > score or (s == score and load[i] < load[best]):
                    best, score = i, s
        return best


@dataclass
class Connections:
    """Weight of the edges of each vertex to blocks outside: u has block[ptr[u]:ptr[u + 1]], the lower first, of these weights."""

    ptr: np.ndarray
    block: np.ndarray
    w: np.ndarray

    def __getitem__(self, u: int) -> dict[int, float]:
        s, e = int(self.ptr[u]), int(self.ptr[u + 1])
        return dict(zip(self.block[s:e].tolist(), self.w[s:e].tolist(), strict=True)) if s < e else {}

    def window(self, lo: int, hi: int) -> tuple[list[int], list[int], list[float]]:
        s, e = int(self.ptr[lo]), int(self.ptr[hi])
        return (self.ptr[lo : hi + 1] - s).tolist(), self.block[s:e].tolist(), self.w[s:e].tolist()

    @classmethod
    def of(cls, found: list[dict[int, float]] | Connections) -> Connections:
        if isinstance(found, Connections):
            return found
        ptr = np.concatenate([[0], np.cumsum([len(x) for x in found])]).astype(np.int64)
        both = [y for x in found for y in sorted(x.items())]
        return cls(ptr, np.array([i for i, _ in both], np.int32), np.array([x for _, x in both], np.float64))

    @classmethod
    def joined(cls, parts: list[Connections]) -> Connections:
        """Of vertices one part after another."""
        if not parts:
            return cls(np.zeros(1, np.int64), np.zeros(0, np.int32), np.zeros(0))
        before = np.cumsum([0, *(len(x.block) for x in parts)])
        kind = np.int32 if before[-1] < 1 << 31 else np.int64
        return cls(np.concatenate([np.zeros(1, kind), *(x.ptr[1:].astype(kind) + kind(y) for x, y in zip(parts, before, strict=False))]), np.concatenate([x.block for x in parts]), np.concatenate([x.w for x in parts]))

    @classmethod
    def summed(cls, n: int, u: np.ndarray, block: np.ndarray, w: np.ndarray, k: int) -> Connections:
        """From parts: vertex, block (-1: none), weight; parts of a vertex are summed in their order."""
        if not len(u):
            return cls(np.zeros(n + 1, np.int32), np.zeros(0, np.int32), np.zeros(0))
        if (u[1:] < u[:-1]).any():
            order = np.argsort(u, kind="stable")
            u, block, w = u[order], block[order], w[order]
        count, blocks, sums = np.zeros(n, np.int32), [], []
        starts = np.searchsorted(u, np.arange(n + 1, dtype=u.dtype))
        for lo, hi in windows(starts, SORTED):
            s, e = int(starts[lo]), int(starts[hi])
            near = block[s:e] >= 0
            key = (u[s:e][near].astype(np.int64) - lo) * k + block[s:e][near]
            order = np.argsort(key, kind="stable")
            key = key[order]
            if not len(key):
                continue
            first = np.concatenate([[True], key[1:] != key[:-1]])
            sums.append(compact(np.bincount(np.cumsum(first) - 1, w[s:e][near][order])))
            key = key[first]
            count[lo:hi] = np.bincount(key // k, minlength=hi - lo)
            blocks.append((key % k).astype(np.int32))
        ptr = np.zeros(n + 1, np.int32 if len(u) < 1 << 31 else np.int64)
        np.cumsum(count, out=ptr[1:])
        return cls(ptr, np.concatenate(blocks) if blocks else np.zeros(0, np.int32), np.concatenate(sums) if sums else np.zeros(0))


def connections(n: int, a: np.ndarray, block: np.ndarray, w: np.ndarray, k: int) -> Connections:
    """For each of n vertices, the weight of its edges to each block: edge by edge its end a, the other end's block, weight."""
    return Connections.summed(n, a, block, w, k)


def first_blocks(g: Level, conn: list[dict[int, float]] | Connections, state: Blocks, start: np.ndarray | None = None) -> np.ndarray:
    """Greedy blocks in natural order over all k; -1 where no block has room. start: vertices that have a block already."""
    conn = Connections.of(conn)
    if loops.known(state) and loops.worth(g.n + len(g.adj) + len(conn.block)):
        found = loops.placed(g, conn, state, np.full(g.n, -1, np.int32) if start is None else start)
        if found is not None:
            return found
    out = unboxed(np.full(g.n, -1) if start is None else start, "i")
    for lo, hi in windows(g.ptr):
        if start is not None and not (start[lo:hi] < 0).any():
            continue
        ptr, adj, w, weight = g.window(lo, hi)
        for u in range(lo, hi):
            if out[u] >= 0:
                continue
            c = conn[u]
            for e in range(ptr[u - lo], ptr[u - lo + 1]):
                i = out[adj[e]]
                if i >= 0:
                    c[i] = c.get(i, 0.0) + w[e]
            i = state.best_of_all(c, weight[u - lo])
            if i >= 0:
                out[u] = i
                state.add(i, weight[u - lo])
    return np.frombuffer(out, np.int32)


def bisected(g: Level, state: Blocks) -> np.ndarray:
    """The rejected first partition: recursive bisection, whatever the blocks hold already.

    A set of vertices is cut where a breadth-first order from its far end reaches its share of the weight; both halves are
    cut on until each has one block. Loads of earlier buffers play no part, so blocks may overflow: that is its fault.
    """
    ptr, adj = g.ptr.tolist(), g.adj.tolist()
    out = np.zeros(g.n, np.int64)

    def breadth_first(own: list[int], start: int) -> list[int]:
        waiting, order = set(own), []
        for s in [start, *own]:
            if s in waiting:
                waiting.discard(s)
                queue = [s]
                for u in queue:
                    for v in adj[ptr[u] : ptr[u + 1]]:
                        if v in waiting:
                            waiting.discard(v)
                            queue.append(v)
                order += queue
        return order

    todo = [(list(range(g.n)), 0, state.p.k)]
    while todo:
        own, low, k = todo.pop()
        if k == 1 or not own:
            out[own] = low
            continue
        order = breadth_first(own, breadth_first(own, own[0])[-1])
        total = np.cumsum(g.weight[order])
        cut = int(np.searchsorted(total, total[-1] * (k // 2) / k, "right"))
        todo += [(order[:cut], low, k // 2), (order[cut:], low + k // 2, k - k // 2)]
    state.add_all(out, g.weight)
    return out


def at_border(g: Level, block: np.ndarray, conn: Connections) -> bytearray:
    """1 for each vertex with an edge to a block that is not its own."""
    out = np.zeros(g.n, np.uint8)
    for ptr, other in ((g.ptr, lambda s, e: block[g.adj[s:e]]), (conn.ptr, lambda s, e: conn.block[s:e])):
        for lo, hi in windows(ptr, SORTED):
            own = np.repeat(np.arange(lo, hi, dtype=np.int32), np.diff(ptr[lo : hi + 1]))
            out[own[other(int(ptr[lo]), int(ptr[hi])) != block[own]]] = 1
    return bytearray(out)


def refine(g: Level, block: np.ndarray, conn: list[dict[int, float]] | Connections, state: Blocks, rounds: int, trace: list | None = None) -> np.ndarray:
    """Local search: take a vertex out, put it to the adjacent block of the best score that has room; it may stay.

    Only vertices at a border are looked at. The weights to adjacent blocks are kept for KEPT of them and changed with each
    move; those of others are summed when it is their turn.
    """
    conn = Connections.of(conn)
    if trace is None and loops.known(state) and loops.worth(g.n + len(g.adj) + len(conn.block)):
        found = loops.searched(g, block, conn, state, rounds)
        if found is not None:
            return found
    out = unboxed(block, "i")
    border, near = at_border(g, np.asarray(block), conn), {}
    for _ in range(rounds):
        moved = 0
        for lo, hi in windows(g.ptr):
            u = border.find(1, lo, hi)
            if u < 0:
                continue
            ptr, adj, w, weight = g.window(lo, hi)
            cptr, cblock, cw = conn.window(lo, hi)
            while u >= 0:
                at, now = u - lo, out[u]
                start, end = ptr[at], ptr[at + 1]
                c = near.get(u)
                if c is None:
                    c = dict(zip(cblock[cptr[at] : cptr[at + 1]], cw[cptr[at] : cptr[at + 1]], strict=True))
                    for e in range(start, end):
                        if (i := out[adj[e]]) >= 0:
                            c[i] = c[i] + w[e] if i in c else w[e]
                    if len(near) < KEPT:
                        near[u] = c
                if now < 0 or not c or (len(c) == 1 and now in c):
                    border[u] = 0  # until a neighbour moves
                    near.pop(u, None)
                    u = border.find(1, u + 1, hi)
                    continue
                x = weight[at]
                state.add(now, -x)
                best, score = now, state.score(c.get(now, 0.0), x, now)
                stay, room = score, state.most - x
                for i in sorted(c) if len(c) > 2 else c:
                    if i != now and state.load[i] <= room:
                        s = state.score(c[i], x, i)
                        if s > score or (s == score and best != now and (state.load[i], i) < (state.load[best], best)):
                            best, score = i, s
                state.add(best, x)
                if best != now:
                    out[u] = best
                    moved += 1
                    if trace is not None:
                        trace.append((u, now, best, stay, score))
                    for e in range(start, end):
                        v = adj[e]
                        border[v] = 1
                        d = near.get(v)
                        if d is None:
                            continue
                        left = d[now] - w[e]
                        if left > 1e-9:
                            d[now] = left
                        else:
                            del d[now]
                        d[best] = d.get(best, 0.0) + w[e]
                u = border.find(1, u + 1, hi)
        if not moved:
            break
    return np.frombuffer(out, np.int32).copy()


def raised(conn: Connections, to: np.ndarray, n: int, k: int) -> Connections:
    """Connections to blocks summed over the members of each coarse vertex."""
    return Connections.summed(n, np.repeat(to, np.diff(conn.ptr)), conn.block, conn.w, k)


def multilevel(levels: list[Level], maps: list[np.ndarray], conn: list[dict[int, float]] | Connections, state: Blocks, p: PartitionParams, previous: np.ndarray | None = None) -> tuple[np.ndarray, bool]:
    """Blocks of the finest level's vertices; whether every vertex fitted. state's loads end as those of the model.

    previous: blocks of the finest level from an earlier pass, constant on clusters; they replace the greedy start.
    """
    conns = [Connections.of(conn)]
    for to, level in zip(maps, levels[1:], strict=True):
        conns.append(raised(conns[-1], to, level.n, p.k))
    if previous is not None:
        block = previous
        for to, level in zip(maps, levels[1:], strict=True):
            up = np.zeros(level.n, np.int32)
            up[to] = block
            block = up
        state.add_all(block, levels[-1].weight)
    elif p.initial == "recursive_bisection":
        block = bisected(levels[-1], state)
    else:
        block = first_blocks(levels[-1], conns[-1], state)
    for depth in range(len(levels) - 1, -1, -1):
        block = refine(levels[depth], block, conns[depth], state, p.refine_rounds)
        if depth:
            block = block[maps[depth - 1]]
            if (block < 0).any():  # members of a vertex that fitted nowhere try again one level finer
                block = first_blocks(levels[depth - 1], conns[depth - 1], state, block)
    fits = True
    for u in np.flatnonzero(block < 0).tolist():
        i = int(np.argmin(state.load))
        block[u], fits = i, False
        state.add(i, float(levels[0].weight[u]))
    return block, fits
