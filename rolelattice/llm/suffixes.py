"""Suffix arrays in numpy: refinement of still tied groups by doubled ranks, common prefixes, and binary search."""

from __future__ import annotations

import numpy as np


def refine(keys: np.ndarray, covers: int, depth: int, ends: np.ndarray | None = None) -> np.ndarray:
    """Starts of the suffixes sorted by their first `depth` symbols. keys order the first `covers` symbols of each suffix.

    Each round compares twice as far, by the rank of the place where the compared part ends, and sorts only groups that are
    still tied. ends: for each start the end of its own text (default: of the whole); beyond it nothing sorts first."""
    n = len(keys)
    if n == 0:
        return np.zeros(0, np.int64)
    order = np.argsort(keys, kind="stable")
    new = np.append(True, keys[order[1:]] != keys[order[:-1]])
    rank = np.empty(n + 1, np.int64)
    rank[n] = -1
    rank[order] = np.maximum.accumulate(np.where(new, np.arange(n), 0))
    h = covers
    while h < depth:
        tied = np.flatnonzero(~(new & np.append(new[1:], True)))
        if not len(tied):
            break
        s = order[tied]
        to = s + h
        key = rank[np.where(to < (n if ends is None else ends[s]), to, n)]
        group = rank[s]
        sub = np.lexsort((key, group))
        s, key, group = s[sub], key[sub], group[sub]
        order[tied] = s
        new[tied] = np.append(True, (group[1:] != group[:-1]) | (key[1:] != key[:-1]))
        rank[s] = np.maximum.accumulate(np.where(new, np.arange(n), 0))[tied]
        h *= 2
    return order


def words8(buf: np.ndarray) -> np.ndarray:
    """The eight bytes from each place as one big-endian number (zeros beyond the end)."""
    out = np.zeros(len(buf), np.uint64)
    for j in range(8):
        out <<= np.uint64(8)
        out[: max(0, len(buf) - j)] |= buf[j:]
    return out


def kasai(buf: np.ndarray, order: np.ndarray, ends: np.ndarray, cap: int, lanes: int = 4096) -> np.ndarray:
    """For each place of the suffix array the common prefix with the suffix before it, at most cap and within both texts.

    Going through the text, a suffix shares all but one symbol of what the suffix one place earlier shared; many stretches of
    the text are gone through side by side, and comparisons take eight bytes at a time."""
    n = len(order)
    if n == 0:
        return np.zeros(0, np.int64)
    before = np.full(n, -1, np.int64)
    before[order[1:]] = order[:-1]
    w = np.concatenate([words8(buf), np.zeros(cap + 8, np.uint64)])
    length = np.zeros(n, np.int64)
    each = max(64, -(-n // lanes))
    first = np.arange(0, n, each)
    have = np.zeros(len(first), np.int64)
    for t in range(each):
        pos = first + t
        live = pos < n
        pos = pos[live]
        prev = before[pos]
        most = np.where(prev >= 0, np.minimum(np.minimum(ends[pos] - pos, ends[prev] - prev), cap), 0)
        k = np.minimum(np.maximum(have[live] - 1, 0), most)
        go = np.flatnonzero(k < most)
        while len(go):
            a, b = w[pos[go] + k[go]], w[prev[go] + k[go]]
            x = a ^ b
            same = x == 0
            k[go[same]] += 8
            rest = go[~same]
            if len(rest):
                top = x[~same]
                lead = np.zeros(len(rest), np.int64)
                for shift in (32, 16, 8):
                    zero = (top >> np.uint64(64 - shift)) == 0
                    lead += np.where(zero, shift // 8, 0)
                    top = np.where(zero, top << np.uint64(shift), top)
                k[rest] += lead
            go = go[same]
            go = go[k[go] < most[go]]
        k = np.minimum(k, most)
        length[pos] = k
        have[live] = k
    return length[order]


def bounds(seq: np.ndarray, order: np.ndarray, queries: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First and end place in the suffix array of the suffixes that begin with queries[i, :lengths[i]], by binary search for all queries together."""
    n, q, wide = len(order), len(queries), queries.shape[1]
    padded = np.concatenate([seq.astype(np.int64), np.full(wide, -1, np.int64)])
    inside = np.arange(wide) < lengths[:, None]

    def search(right: bool) -> np.ndarray:
        low, high = np.zeros(q, np.int64), np.full(q, n, np.int64)
        while True:
            open_ = np.flatnonzero(low < high)
            if not len(open_):
                return low
            mid = (low[open_] + high[open_]) // 2
            have = padded[order[mid][:, None] + np.arange(wide)]
            differs = (have != queries[open_]) & inside[open_]
            at = differs.argmax(1)
            rows = np.arange(len(open_))
            less = np.where(differs[rows, at], have[rows, at] < queries[open_][rows, at], right)
            low[open_] = np.where(less, mid + 1, low[open_])
            high[open_] = np.where(less, high[open_], mid)

    return search(False), search(True)
