"""A layered proximity graph in numpy: seeded build, beam search that can be resumed, and search filtered during traversal.

A vector's links go to the nearest that come before it in the order of ids, thinned so that they point in different directions; those
that it is linked from are added and thinned alike. The nearest ones are found by products of blocks of the matrix of vectors, which
for the rows of a shard costs no more than a search for each, and all rows of a block are thinned side by side.
"""

from __future__ import annotations

import heapq
import math
import pickle
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np


def level_of(vec_id: int, m: int, seed: int) -> int:
    """Level drawn from a hash of the id, so that a rebuilt shard is the same graph."""
    h = ((int(vec_id) ^ seed) * 0x9E3779B97F4A7C15 + 0xD1B54A32D192ED03) & (1 << 64) - 1
    h = ((h ^ h >> 31) * 0xBF58476D1CE4E5B9) & (1 << 64) - 1
    return int(-math.log(((h >> 11) + 0.5) / (1 << 53)) / math.log(m))


#: Bytes of a piece of a graph.
PIECE = 1 << 19


@dataclass
class Graph:
    ids: np.ndarray
    blocks: np.ndarray
    vectors: np.ndarray
    #: For each level where a place's links begin (one more entry at the end), and the links.
    levels: list[tuple[np.ndarray, np.ndarray]]
    entry: int
    #: Distances worked out so far.
    work: int = 0

    def pieces(self, size: int = PIECE) -> Iterator[bytes]:
        """The graph as runs of at most `size` bytes, the first of which begins with what the arrays are."""
        arrays = [self.ids, self.blocks, self.vectors, *[x for level in self.levels for x in level]]
        head = pickle.dumps(([(a.dtype.str, a.shape) for a in arrays], self.entry), protocol=5)
        held, room = [], max(size, len(head) + 8)
        for one in (len(head).to_bytes(8, "little"), head, *[np.ascontiguousarray(a).reshape(-1).view(np.uint8) for a in arrays]):
            rest = memoryview(one)
            while len(rest):
                held.append(rest[:room])
                room, rest = room - len(held[-1]), rest[room:]
                if not room:
                    yield b"".join(held)
                    held, room = [], size
        if held:
            yield b"".join(held)

    def dump(self) -> bytes:
        return b"".join(self.pieces())

    @staticmethod
    def load(data: bytes) -> Graph:
        made = Joined()
        made.add(data)
        return made.graph()

    def near(self, i: int, level: int = 0) -> np.ndarray:
        at, links = self.levels[level]
        return links[at[i] : at[i + 1]]

    def distance(self, x: np.ndarray, at: np.ndarray) -> np.ndarray:
        self.work += len(at)
        d = self.vectors[at] - x
        return np.einsum("ij,ij->i", d, d)


class Joined:
    """A graph out of its pieces in their order, each copied to its place as it comes, so that no second copy is held."""

    def __init__(self) -> None:
        self.arrays: list[np.ndarray] | None = None
        self.open: list[np.ndarray] = []
        self.entry = -1

    def add(self, piece: bytes) -> None:
        rest = np.frombuffer(piece, np.uint8)
        if self.arrays is None:
            n = int.from_bytes(rest[:8].tobytes(), "little")
            kinds, self.entry = pickle.loads(rest[8 : 8 + n].tobytes())
            self.arrays = [np.empty(shape, kind) for kind, shape in kinds]
            self.open = [a.reshape(-1).view(np.uint8) for a in self.arrays if a.size]
            rest = rest[8 + n :]
        while len(rest):
            to = self.open.pop(0)
            k = min(len(to), len(rest))
            to[:k], rest = rest[:k], rest[k:]
            if k < len(to):
                self.open.insert(0, to[k:])

    def graph(self) -> Graph | None:
        """None as long as pieces are missing."""
        if self.arrays is None or self.open:
            return None
        ids, blocks, vectors, *levels = self.arrays
        return Graph(ids, blocks, vectors, list(zip(levels[::2], levels[1::2], strict=True)), self.entry)


def _beam(g: Graph, x: np.ndarray, starts: list[tuple[float, int]], efs: int, level: int) -> list[tuple[float, int]]:
    """The efs nearest found, nearest first."""
    seen = np.zeros(len(g.ids), bool)
    seen[[i for _, i in starts]] = True
    todo = list(starts)
    heapq.heapify(todo)
    best = [(-d, i) for d, i in starts]
    heapq.heapify(best)
    while todo:
        d, i = heapq.heappop(todo)
        if len(best) >= efs and d > -best[0][0]:
            break
        near = g.near(i, level)
        _take(g, x, near[~seen[near]], seen, efs, todo, best)
    return sorted((-d, i) for d, i in best)


def _take(g: Graph, x: np.ndarray, near: np.ndarray, seen: np.ndarray, efs: int, todo: list[tuple[float, int]], best: list[tuple[float, int]]) -> None:
    """Note new places that are near enough among those to expand and the efs best."""
    if not len(near):
        return
    seen[near] = True
    dist = g.distance(x, near)
    if len(best) >= efs:  # the bound only falls
        low = dist < -best[0][0]
        near, dist = near[low], dist[low]
    for dj, j in zip(dist.tolist(), near.tolist(), strict=True):
        if len(best) < efs or dj < -best[0][0]:
            heapq.heappush(todo, (dj, j))
            heapq.heappush(best, (-dj, j))
            if len(best) > efs:
                heapq.heappop(best)


#: Beams from which on several places are expanded at once, and the most of them.
_WIDE, _AT_ONCE = 32, 32


def _reached(g: Graph, at: np.ndarray) -> np.ndarray:
    """The base layer's neighbours of several places, one list behind the other."""
    begin, links = g.levels[0]
    first = begin[at]
    count = begin[at + 1] - first
    end = np.cumsum(count)
    return links[np.arange(end[-1]) + np.repeat(first - end + count, count)]


def _wide(g: Graph, x: np.ndarray, start: tuple[float, int], efs: int, allowed: np.ndarray | None = None, two_hop: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Distances and places of the efs nearest found (allowed ones only), nearest first, by a beam held in arrays.

    A step expands the nearest open places, no more than an eighth of what the beam holds, which the beam will hardly lose; of a
    beam that has room for all places the order does not matter, and all open ones are expanded. It ends as a search by single
    places does: when the efs nearest are all expanded."""
    seen, whole = np.zeros(len(g.ids), bool), efs >= len(g.ids)
    stamp = np.empty(len(g.ids), np.int64)
    todo = np.array([start[1]])
    seen[todo] = True
    if allowed is None or allowed[start[1]]:
        dist, at, open_ = np.array([start[0]]), todo, np.array([False])
    else:
        dist, at, open_ = np.empty(0), np.empty(0, np.int64), np.empty(0, bool)
    while len(todo):
        near = _reached(g, todo)
        near = near[~seen[near]]
        if allowed is not None:
            may = allowed[near]
            if two_hop and not may.all():
                barred = near[~may]
                seen[barred] = True  # what lies behind is met once
                behind = _reached(g, barred)
                near = np.concatenate([near[may], behind[allowed[behind] & ~seen[behind]]])
            else:
                near = near[may]
        if len(near):
            nth = np.arange(len(near))
            stamp[near] = nth
            near = near[stamp[near] == nth]
            seen[near] = True
            d = g.distance(x, near)
            if len(dist) >= efs:
                low = d < dist[-1]
                near, d = near[low], d[low]
            if len(near):
                order = np.argsort(d)
                near, d = near[order], d[order]
                new = np.searchsorted(dist, d, side="right") + np.arange(len(d))
                old = np.ones(len(dist) + len(d), bool)
                old[new] = False
                both = []
                for a, b in ((dist, d), (at, near), (open_, True)):
                    c = np.empty(len(old), a.dtype)
                    c[old], c[new] = a, b
                    both.append(c[:efs])
                dist, at, open_ = both
        spots = np.flatnonzero(open_)
        if not whole:
            spots = spots[: min(_AT_ONCE, len(dist) // 8 + 1)]
        todo, open_[spots] = at[spots], False
    return dist, at


def thinned(near: np.ndarray, d: np.ndarray, m: int) -> np.ndarray:
    """For each row the places of at most m of its neighbours (-1: none): those nearer to the row's vector than to one another, filled up by
    the nearest rest. near: neighbours less that vector, nearest first; d: their squared distances (infinite: no neighbour)."""
    open_ = np.isfinite(d)
    real, kept, count = open_.copy(), np.zeros(d.shape, bool), np.zeros(len(d), np.int64)
    # what is still open: rows, and of each row its open neighbours, in arrays that shrink as these become few
    at, spot = np.arange(len(d)), np.broadcast_to(np.arange(d.shape[1]), d.shape)
    each = at[:, None]
    far = d
    while len(live := np.flatnonzero(open_.any(1) & (count[at] < m))):
        left = int(open_[live].sum(1).max())
        if 4 * len(live) * left <= 3 * open_.size:
            order = np.argsort(~open_[live], axis=1, kind="stable")[:, :left]
            pick = live[:, None], order
            near, far, open_, spot, at = near[pick], far[pick], open_[pick], spot[pick], at[live]
            live = np.arange(len(at))
        first = open_.argmax(1)
        chosen = live, first[live]
        kept[at[live], spot[chosen]], open_[chosen] = True, False
        count[at[live]] += 1
        one = near[np.arange(len(at)), first]
        # nearer to this one than to the row's vector: |b - a|^2 < |b|^2 where 2 ab > |a|^2
        both = np.matmul(near, one[:, :, None])[live, :, 0]
        reach = far[chosen][:, None]
        open_[live] &= (2 * both <= reach) & ((reach > 0) | (far[live] > 0))  # of copies of the row's vector one is enough
    order = np.argsort(np.where(kept, 0, np.where(real, 1, 2)), axis=1, kind="stable")[:, :m]
    return np.where(real[each, order], order, -1)


def _sorted(v: np.ndarray, rows: np.ndarray, others: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """others (-1: none) nearest first, less the rows' vectors, and their squared distances. Rows that come in that order are not moved."""
    near = v[others]
    near -= v[rows][:, None]
    d = np.where(others >= 0, np.einsum("ijk,ijk->ij", near, near), np.inf)
    one, two = d[:, :-1], d[:, 1:]
    off = np.flatnonzero(((two < one) | ((two == one) & (others[:, 1:] < others[:, :-1]))).any(1))
    if len(off):
        pick = off[:, None], np.lexsort((others[off], d[off]), axis=1)
        others[off], near[off], d[off] = others[pick], near[pick], d[pick]
    return others, near, d


#: Numbers of a block of distances, and of a block of neighbours' components.
_BLOCK, _NEAR = 4 << 20, 1 << 20


def linked(v: np.ndarray, m: int, most: int, efc: int) -> tuple[np.ndarray, np.ndarray, int]:
    """Where each vector's links begin and the links, both ways; and the number of distances. Links are held in four bytes, no shard has more rows."""
    n, work = len(v), 0
    forth = np.full((n, m), -1, np.int32)
    mid = v - v.mean(0)
    norm = np.einsum("ij,ij->i", mid, mid)
    a = 1
    while a < n:
        b = min(n, a + max(1, min(_BLOCK // (a + 512), _NEAR // (min(efc, a) * v.shape[1] or 1), 512)))
        rows = np.arange(a, b)
        d = norm[:b] - 2 * (mid[a:b] @ mid[:b].T)
        d[np.arange(b) >= rows[:, None]] = np.inf
        work += len(rows) * b
        if b > efc:
            others = np.argpartition(d, efc - 1, axis=1)[:, :efc]
            d = np.take_along_axis(d, others, 1)
            order = np.argsort(d, axis=1)
            others, d = np.take_along_axis(others, order, 1), np.take_along_axis(d, order, 1)
            others[np.isinf(d)] = -1
        else:
            others = np.where(np.isinf(d), -1, np.arange(b))
        others, near, d = _sorted(v, rows, others)
        take = thinned(near, d, m)
        forth[a:b, : take.shape[1]] = np.where(take >= 0, np.take_along_axis(others, take, 1), -1)
        work += others.size
        a = b
    del mid
    # each place's own links, then those of later ones in their order, dealt to their places by blocks of rows
    out = np.empty(n, np.int64)
    back = np.zeros(n, np.int64)
    few = max(1, _NEAR // m)
    for a in range(0, n, few):
        there = forth[a : a + few] >= 0
        out[a : a + few] = there.sum(1)
        back += np.bincount(forth[a : a + few][there], minlength=n)
    count = out + back
    at = np.append(0, np.cumsum(count))
    links = np.empty(at[-1], np.int32)
    free = at[:-1] + out
    for a in range(0, n, few):
        from_, slot = np.nonzero(forth[a : a + few] >= 0)
        to = forth[a : a + few][from_, slot]
        from_ += a
        links[at[from_] + np.arange(len(from_)) - np.repeat(np.cumsum(out[a : a + few]) - out[a : a + few], out[a : a + few])] = to
        order = np.argsort(to, kind="stable")
        to, from_ = to[order], from_[order]
        each = np.bincount(to, minlength=n)
        links[free[to] + np.arange(len(to)) - (np.cumsum(each) - each)[to]] = from_
        free += each
    del forth
    over = np.flatnonzero(count > most)
    over = over[np.argsort(count[over], kind="stable")]
    keep = np.ones(len(links), bool)
    a = 0
    while a < len(over):
        b = a + 1
        while b < len(over) and (b - a + 1) * count[over[b]] * v.shape[1] <= _NEAR:
            b += 1
        rows = over[a:b]
        wide = np.arange(count[rows].max())
        spots = np.where(wide < count[rows][:, None], at[rows][:, None] + wide, -1)
        others, near, d = _sorted(v, rows, np.where(spots >= 0, links[spots], -1))
        take = thinned(near, d, most)
        mine = np.sort(np.where(take >= 0, np.take_along_axis(others, take, 1), -1), axis=1)
        keep[spots[spots >= 0]] = False
        for r, row in zip(rows.tolist(), mine, strict=True):
            links[at[r] : at[r] + most] = row
            keep[at[r] : at[r] + most] = True
        work += others.size
        a = b
    return np.append(0, np.cumsum(np.minimum(count, most))), links[keep], work


def build(ids: np.ndarray, vectors: np.ndarray, blocks: np.ndarray | None = None, m: int = 16, efc: int = 64, seed: int = 1) -> Graph:
    order = np.argsort(ids, kind="stable")
    ids, given = np.asarray(ids)[order], np.asarray(vectors)[order]
    vectors = given.astype(np.float64, copy=False)
    blocks = np.zeros(len(ids), np.int64) if blocks is None else np.asarray(blocks)[order]
    top = np.array([level_of(i, m, seed) for i in ids.tolist()], np.int64)
    # four bytes a number are kept as they are: distances are worked out in eight all the same
    g = Graph(ids, blocks, given if given.dtype == np.float32 else vectors, [], -1)
    for level in range(int(top.max(initial=0)) + 1):
        held = np.flatnonzero(top >= level)
        at, links, work = linked(vectors[held], m, 2 * m if level == 0 else m, efc)
        count = np.zeros(len(ids), np.int64)
        count[held] = np.diff(at)
        g.levels.append((np.append(0, np.cumsum(count)), links if len(held) == len(ids) else held.astype(np.int32)[links]))
        g.work += work
    if len(ids):
        g.entry = int(top.argmax())
    return g


class Cursor:
    """Base-layer search that expands a number of places and may go on later, in another task too: dump() holds all that it knows."""

    def __init__(self, g: Graph, x: np.ndarray, state: bytes | None = None) -> None:
        self.g, self.x = g, np.asarray(x, np.float64)
        self.popped: list[tuple[float, int]] = []
        self.todo: list[tuple[float, int]] = []
        if state is not None:
            d, i, n = pickle.loads(state)
            both = list(zip(d.tolist(), i.tolist(), strict=True))
            self.popped, self.todo = both[:n], both[n:]
        elif g.entry >= 0:
            self.todo = _entry(g, self.x)
        self.seen = np.zeros(len(g.ids), bool)
        self.seen[[i for _, i in self.popped + self.todo]] = True

    def dump(self) -> bytes:
        """Places expanded, then places open (a heap), with their distances."""
        both = self.popped + self.todo
        return pickle.dumps((np.array([d for d, _ in both]), np.array([i for _, i in both], np.int64), len(self.popped)), protocol=5)

    def resume(self, more: int, bound: float = math.inf) -> list[tuple[float, int]]:
        """Expand up to `more` further places, nearest open one first; end when the nearest open one is not below the bound."""
        new = []
        while self.todo and len(new) < more:
            if self.todo[0][0] >= bound:
                break
            d, i = heapq.heappop(self.todo)
            new.append((d, i))
            near = self.g.near(i)
            near = near[~self.seen[near]]
            if len(near):
                self.seen[near] = True
                for dj, j in zip(self.g.distance(self.x, near).tolist(), near.tolist(), strict=True):
                    heapq.heappush(self.todo, (dj, j))
        self.popped += new
        return new

    def nearest(self, n: int) -> list[tuple[float, int]]:
        """The n nearest of all places seen."""
        return heapq.nsmallest(n, self.popped + self.todo)


def _entry(g: Graph, x: np.ndarray) -> list[tuple[float, int]]:
    """Where search begins in the base layer."""
    at = [(float(g.distance(x, np.array([g.entry]))[0]), g.entry)]
    for level in range(len(g.levels) - 1, 0, -1):
        at = _beam(g, x, at, 1, level)[:1]
    return at


def found(g: Graph, x: np.ndarray, efs: int) -> tuple[np.ndarray, np.ndarray]:
    """Squared distances and places of the efs nearest found, nearest first."""
    if g.entry < 0:
        return np.empty(0), np.empty(0, np.int64)
    x = np.asarray(x, np.float64)
    at = _entry(g, x)
    if efs >= min(_WIDE, len(g.ids)):
        return _wide(g, x, at[0], efs)
    got = _beam(g, x, at, efs, 0)
    return np.array([d for d, _ in got]), np.array([i for _, i in got], np.int64)


def search(g: Graph, x: np.ndarray, k: int, efs: int) -> list[tuple[float, int]]:
    """The k nearest found, as (squared distance, place)."""
    d, at = found(g, x, max(efs, k))
    return list(zip(d[:k].tolist(), at[:k].tolist(), strict=True))


def filtered(g: Graph, x: np.ndarray, allowed: np.ndarray, k: int, efs: int, two_hop: bool, bound: float = 1 / 12) -> list[tuple[float, int]]:
    """Search that keeps to allowed places: with two_hop through the neighbours of barred neighbours, else through a list that
    the build has made longer. Below the bound of selectivity all allowed places are scanned."""
    x = np.asarray(x, np.float64)
    share = allowed.mean() if len(allowed) else 0.0
    if share < bound:
        at = np.flatnonzero(allowed)
        return sorted(zip(g.distance(x, at).tolist(), at.tolist(), strict=True))[:k]
    at = _entry(g, x)
    if efs >= min(_WIDE, len(g.ids)):
        d, at = _wide(g, x, at[0], efs, allowed, two_hop)
        return list(zip(d[:k].tolist(), at[:k].tolist(), strict=True))
    seen, todo = np.zeros(len(g.ids), bool), list(at)
    seen[at[0][1]] = True
    best: list[tuple[float, int]] = [(-at[0][0], at[0][1])] if allowed[at[0][1]] else []
    while todo:
        d, i = heapq.heappop(todo)
        if len(best) >= efs and d > -best[0][0]:
            break
        near = g.near(i)
        may = allowed[near]
        ok = near[may]
        if two_hop and not may.all():
            ok = np.concatenate([ok, *[g.near(j) for j in near[~may].tolist()]])
            ok = ok[allowed[ok] & ~seen[ok]]
            ok = ok[np.sort(np.unique(ok, return_index=True)[1])]
        _take(g, x, ok[~seen[ok]], seen, efs, todo, best)
    return sorted((-d, i) for d, i in best)[:k]
