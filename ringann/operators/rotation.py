"""Rotation index of code strings: for each cyclic rotation the objects in sorted order, linked to the next rotation.

Kernels work on one shard in numpy; a shard is bounded by `shard_rows`, so an index of any size is a table of
bounded rows. Strings are compared through rotated rows of big-endian bytes, so that a bisection step is one
comparison and equal strings are ordered by position in the shard, which is by id.
"""

from __future__ import annotations

import functools
import heapq

import numpy as np

from ringann.functions.runs import run_lengths


#: Limit of the bits by position and symbol that a scan of a shard may keep.
TABLE_BYTES = 16 << 20


class Shard:
    """codes[n, m] in id order; order[m, n]: row numbers by rotated string; link[m, n]: rank in the next rotation."""

    def __init__(self, ids: np.ndarray, codes: np.ndarray, order: np.ndarray | None = None, link: np.ndarray | None = None):
        self.ids, self.codes = ids, codes
        self.n, self.m = codes.shape
        if order is None:
            order, link = build(codes)
        self.order, self.link = order, link
        self.steps, self.least = 0, self.n
        self.seen = np.zeros(self.n, bool)  # all false between searches

    def scan(self, strings: list[np.ndarray], k: int) -> tuple[np.ndarray, np.ndarray]:
        """(rows, longest runs with any of the strings): the k best by (run descending, id). Every distinct code string is
        compared once; rows are in id order, so the first of those that tie with the last have the least ids."""
        if not hasattr(self, "kinds"):
            self.kinds, self.kind = distinct(self.codes)
        k = min(k, self.n)
        if not k:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        lens = run_lengths(self.kinds, strings[0])
        for other in strings[1:]:
            lens = np.maximum(lens, run_lengths(self.kinds, other))
        lens = lens.astype(np.uint8 if self.m < 256 else np.int64)
        if self.kind is not None:
            lens = lens[self.kind]
        sizes = np.bincount(lens, minlength=self.m + 1)[::-1].cumsum()[::-1]  # rows of this run or a longer one
        least = int(np.flatnonzero(sizes >= k)[-1])
        above = np.flatnonzero(lens > least)
        rows = np.concatenate([above[np.argsort(-lens[above].astype(np.int64), kind="stable")], np.flatnonzero(lens == least)[: k - len(above)]])
        return rows, lens[rows].astype(np.int64)

    @functools.cached_property
    def table(self) -> tuple[list, np.ndarray] | None:
        """(codes of every position in order, for each of them a row of bits that says which strings have it there, and a last
        row without bits), or None where that is large."""
        values = [np.unique(c) for c in self.codes.T]
        words = -(-self.n // 64)
        if (sum(map(len, values)) + 1) * words * 8 > TABLE_BYTES:
            return None
        bits = np.zeros((sum(map(len, values)) + 1, words * 8), np.uint8)
        packed = [np.packbits(c == v[:, None], axis=1, bitorder="little") for c, v in zip(np.ascontiguousarray(self.codes.T), values)]
        bits[:-1, : -(-self.n // 8)] = np.concatenate(packed) if packed else 0
        return values, bits.view(np.uint64)

    def slots(self, strings: np.ndarray) -> np.ndarray:
        """[len(strings), m]: rows of the table for every string, the last where no string of the shard has its symbol."""
        values, bits = self.table
        out, start = np.empty(strings.shape, np.int64), 0
        for i, v in enumerate(values):
            at = np.minimum(np.searchsorted(v, strings[:, i]), len(v) - 1)
            out[:, i] = np.where(v[at] == strings[:, i], start + at, len(bits) - 1)
            start += len(v)
        return out

    def _same(self, slots: np.ndarray, skip: tuple[int, int] | None, length: int) -> np.ndarray:
        """[m + length - 1, words]: bits of the strings that agree at each position, round and on for a run of this length from
        the last, without rows skip[0] to skip[1]."""
        same = self.table[1][np.concatenate([slots, slots[: length - 1]])]
        if skip:
            out = np.zeros(same.shape[1] * 64, np.uint8)
            out[skip[0] : skip[1]] = 1
            same &= ~np.packbits(out, bitorder="little").view(np.uint64)
        return same

    def with_run(self, slots: np.ndarray, length: int, skip: tuple[int, int] | None = None) -> int:
        """Number of strings whose longest run has this length or more."""
        if length <= 0:
            return self.n
        left, have = self._same(slots, skip, length), 1
        while have < length:  # what runs on for `have` from here and from `step` on runs on for both
            step = min(have, length - have)
            left = left[: len(left) - step] & left[step:]
            have += step
        return int(np.bitwise_count(np.bitwise_or.reduce(left[: self.m], axis=0)).sum())

    def among(self, slots: np.ndarray, k: int, skip: tuple[int, int] | None = None) -> np.ndarray:
        """Which rows are the k best by (run descending, id): a pass over bits for every length up to that of the last."""
        same = self._same(slots, skip, self.m + 1)
        left, before, above = same[: self.m].copy(), None, None
        row_bits = lambda words: np.unpackbits(words.view(np.uint8), bitorder="little")[: self.n].view(bool)
        for length in range(1, self.m + 1):
            above = np.bitwise_or.reduce(left, axis=0)
            if int(np.bitwise_count(above).sum()) < k:
                break
            before = above
            if length < self.m:
                left &= same[length : length + self.m]
            else:
                above = np.zeros_like(above)
        out = row_bits(above).copy()
        some = np.ones(self.n, bool) if before is None else row_bits(before)
        if before is None and skip:
            some[skip[0] : skip[1]] = False
        tied = np.flatnonzero(some & ~out)
        out[tied[: max(0, k - int(out.sum()))]] = True
        return out

    def pair_runs(self, rows: np.ndarray, strings: np.ndarray, at: np.ndarray, step: int) -> np.ndarray:
        """Run lengths of rows with strings[at], `step` pairs at a time."""
        return np.concatenate([np.zeros(0, np.int64), *(run_lengths(self.codes[rows[i : i + step]], strings[at[i : i + step]]) for i in range(0, len(rows), step))])

    def rotated(self, row: int, rot: int) -> np.ndarray:
        row = self.codes[row]
        return np.concatenate([row[rot:], row[:rot]])

    def shares(self, rank: int, rot: int, q: np.ndarray, length: int) -> bool:
        """Whether the string at this rank of a rotation has the first `length` symbols of q."""
        row = self.codes[self.order[rot, rank]]
        head = min(length, self.m - rot)
        return bool((row[rot : rot + head] == q[:head]).all() and (row[: length - head] == q[head:length]).all())


def distinct(codes: np.ndarray) -> tuple[np.ndarray, np.ndarray | None]:
    """(distinct strings, number of each row's string), or the codes as they are, narrowed, where few are equal."""
    low, high = (int(codes.min()), int(codes.max())) if codes.size else (0, 0)
    kinds, kind = np.unique(np.ascontiguousarray(codes).view(np.dtype((np.void, codes.shape[1] * codes.itemsize))).ravel(), return_inverse=True) if codes.size else (codes, None)
    few = kind is not None and 2 * len(kinds) < len(codes)
    out = kinds.view(codes.dtype).reshape(len(kinds), codes.shape[1]) if few else codes
    narrow = np.int8 if -128 <= low and high < 128 else np.int16 if -(1 << 15) <= low and high < 1 << 15 else codes.dtype
    return np.ascontiguousarray(out.astype(narrow)), kind if few else None


def build(codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Full sort of the last rotation only; each earlier one is a stable sort of its successor by one symbol."""
    n, m = codes.shape
    order, link = np.empty((m, n), np.int32), np.empty((m, n), np.int32)
    last = np.roll(codes, -(m - 1), axis=1)
    order[m - 1] = np.lexsort(last.T[::-1]) if n else []
    for i in range(m - 2, -1, -1):
        nxt = order[i + 1]
        order[i] = nxt[np.argsort(codes[nxt, i], kind="stable")]
    pos = np.empty(n, np.int32)
    for i in range(m):
        pos[order[(i + 1) % m]] = np.arange(n, dtype=np.int32)
        link[i] = pos[order[i]]
    return order, link


def _lcp(a: np.ndarray, b: np.ndarray) -> int:
    diff = a != b
    return int(diff.argmax()) if diff.any() else len(a)


def _bisect(shard: Shard, rot: int, q: np.ndarray, lo: int, hi: int) -> int:
    """Number of ranks whose string is <= q, knowing that it is in [lo, hi]."""
    order, codes, m = shard.order[rot], shard.codes, shard.m
    while lo < hi:
        mid = (lo + hi) // 2
        shard.steps += 1
        row = codes[order[mid]]
        row = np.concatenate([row[rot:], row[:rot]])
        k = _lcp(row, q)
        if k == m or row[k] < q[k]:
            lo = mid + 1
        else:
            hi = mid
    return lo


def bounds(shard: Shard, q: np.ndarray, narrowed: bool = True) -> np.ndarray:
    """[m, 4]: lower rank, upper rank, and their common prefixes with q, by rotation. Absent bounds have length 0.

    Narrowed: where both prefixes have a symbol or more, both bounds stay on their sides in the next rotation,
    so the search goes on between their links; else it starts anew over the whole rotation.
    """
    m, n = shard.m, shard.n
    out = np.zeros((m, 4), np.int64)
    lo, hi = 0, n
    for i in range(m):
        rq = np.concatenate([q[i:], q[:i]])
        up = _bisect(shard, i, rq, lo, hi)
        low_len = _lcp(shard.rotated(shard.order[i, up - 1], i), rq) if up else 0
        up_len = _lcp(shard.rotated(shard.order[i, up], i), rq) if up < n else 0
        out[i] = up - 1, up, low_len, up_len
        if narrowed and low_len and up_len:
            lo, hi = int(shard.link[i, up - 1]) + 1, int(shard.link[i, up])
        else:
            lo, hi = 0, n
    return out


def _plateau(shard: Shard, rank: int, rot: int, step: int, q: np.ndarray, length: int) -> int:
    """First rank from `rank` on, in direction step, that shares less than `length` with q: prefixes only get shorter away from q."""
    room = shard.n - 1 - rank if step > 0 else rank
    if not length:
        return rank + step * (room + 1)
    good, reach = 0, 1
    while reach <= room and shard.shares(rank + step * reach, rot, q, length):
        good, reach = reach, reach * 2
    bad = min(reach, room + 1)
    while bad - good > 1:
        mid = (good + bad) // 2
        if shard.shares(rank + step * mid, rot, q, length):
            good = mid
        else:
            bad = mid
    return rank + step * bad


def _merge(shard: Shard, heap: list, k: int, ties: bool) -> tuple[np.ndarray, np.ndarray]:
    """(rows, run lengths), the longest prefix first; `ties` goes on through all entries as long as the k-th.

    Each step takes all neighbours of one list that share the same prefix length, so that plateaus of equal
    lengths cost a few comparisons. A list has one entry at a time, so strings are never compared in the heap.
    """
    rows, lens, count, need = [], [], 0, None
    while heap:
        neg, probe, rot, step, rank, q = heapq.heappop(heap)
        length = -neg
        if count >= k and (not ties or length < need):
            break
        end = _plateau(shard, rank, rot, step, q, length)
        part = shard.order[rot, rank:end] if step > 0 else shard.order[rot, end + 1 : rank + 1][::-1]
        new = part[~shard.seen[part]]
        if not ties:
            new = new[: k - count]
        if len(new):
            shard.seen[new] = True
            rows.append(new)
            lens.append(np.full(len(new), length, np.int32))
            count += len(new)
            if need is None and count >= k:
                need = length
        if 0 <= end < shard.n:
            heapq.heappush(heap, (-_lcp(shard.rotated(shard.order[rot, end], rot), q), probe, rot, step, end, q))
    found = np.concatenate(rows) if rows else np.zeros(0, np.int32)
    shard.seen[found] = False
    return found, np.concatenate(lens) if lens else np.zeros(0, np.int32)


def push_heads(shard: Shard, heap: list, bound: np.ndarray, rotations, q: np.ndarray, probe: int) -> None:
    for i in rotations:
        low, up, low_len, up_len = bound[i]
        rq = np.concatenate([q[i:], q[:i]])
        if low >= 0:
            heapq.heappush(heap, (-int(low_len), probe, int(i), -1, int(low), rq))
        if up < shard.n:
            heapq.heappush(heap, (-int(up_len), probe, int(i), 1, int(up), rq))


#: A scan of all code strings is cheaper than the merge from this part of the shard on, as 1 / SCAN.
SCAN = 50


def scan_rows(shard: Shard, q: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """What k_search_rows gives with ties, from the run lengths of all strings: for k that are a good part of the shard."""
    lens = run_lengths(shard.codes, q)
    k = min(k, shard.n)
    least = np.partition(lens, shard.n - k)[shard.n - k] if k else 0
    rows = np.flatnonzero(lens >= least) if k else np.zeros(0, np.int64)
    return rows, lens[rows].astype(np.int32)


def k_search_rows(shard: Shard, q: np.ndarray, k: int, ties: bool = False, narrowed: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """(rows, run lengths) of k objects with the longest runs; with ties, all that tie with the k-th as well."""
    heap: list = []
    b = bounds(shard, q, narrowed)
    push_heads(shard, heap, b, range(shard.m), q, 0)
    return _merge(shard, heap, min(k, shard.n), ties)


def k_search(shard: Shard, q: np.ndarray, k: int, ties: bool = False, narrowed: bool = True) -> dict[int, int]:
    """k_search_rows as {row: run length}."""
    rows, lens = k_search_rows(shard, q, k, ties, narrowed)
    return dict(zip(rows.tolist(), lens.tolist()))


def cut_rows(rows: np.ndarray, lens: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(rows, run lengths) by (run length descending, id), k at most."""
    by = np.lexsort((ids[rows], -lens))[:k]
    return rows[by], lens[by]


def cut_ties(found: dict[int, int], ids: np.ndarray, k: int) -> list[tuple[int, int]]:
    """[(row, run length)] by (run length descending, id), k at most."""
    return sorted(found.items(), key=lambda x: (-x[1], ids[x[0]]))[:k]
