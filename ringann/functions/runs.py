"""Code strings: rotations, common prefixes and longest aligned runs, as columns and in numpy."""

from __future__ import annotations

import functools

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def rotate(codes: Column, i) -> Column:
    i = F.lit(i) if isinstance(i, int) else i
    return F.concat(F.slice(codes, i + 1, F.size(codes) - i), F.slice(codes, F.lit(1), i))


def lcp_len(a: Column, b: Column) -> Column:
    """Length of the common prefix: positions before the first difference."""
    first = F.array_position(F.zip_with(a, b, lambda x, y: (x != y).cast("int")), 1)
    return F.when(first == 0, F.size(a)).otherwise(first - 1).cast("int")


def run_len(a: Column, b: Column) -> Column:
    """Longest cyclic stretch of positions at which both strings agree, at most their length."""
    same = F.array_join(F.zip_with(a, b, lambda x, y: F.when(x == y, "1").otherwise("0")), "")
    longest = F.array_max(F.transform(F.split(F.concat(same, same), "0", -1), F.length))
    return F.least(longest, F.size(a)).cast("int")


def run_start(a: Column, b: Column) -> Column:
    """Smallest 0-based rotation whose common prefix is the longest run; 0 if nothing agrees."""
    same = F.array_join(F.zip_with(a, b, lambda x, y: F.when(x == y, "1").otherwise("0")), "")
    need = F.repeat(F.lit("1"), run_len(a, b))
    return F.when(run_len(a, b) == 0, 0).otherwise(F.instr(F.concat(same, same), need) - 1).cast("int")


def is_aligned_run(a: Column, b: Column, start: int, length: int) -> Column:
    """Whether positions start .. start + length - 1, cyclic, agree; the empty run always does."""
    if not length:
        return F.lit(True)
    return F.slice(rotate(a, start), 1, length) == F.slice(rotate(b, start), 1, length)


def equal_positions(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x == y).cast("int")), F.lit(0), lambda s, x: s + x)


@functools.cache
def _run_table(m: int) -> np.ndarray:
    """Longest cyclic run of ones of every number of m bits."""
    text = [f"{v:0{m}b}" * 2 for v in range(1 << m)]
    return np.array([min(m, max(map(len, t.split("0")))) for t in text], np.int64)


def run_lengths(codes: np.ndarray, query: np.ndarray) -> np.ndarray:
    """Run length of every row of codes[n, m] with one query, or with a query of its own in query[n, m].

    Up to 64 positions, matches are the bits of one number, and a run of l + 1 positions is left where the runs of l
    meet themselves turned by one; else one pass over the doubled match matrix.
    """
    n, m = codes.shape
    if not n or not m:
        return np.zeros(n, np.int64)
    if m <= 8:
        same = np.zeros(n, np.uint8)
        for i in range(m):
            same |= (codes[:, i] == query[..., i]).view(np.uint8) << np.uint8(i)
        return _run_table(m)[same].astype(np.int64)
    same = codes == query
    if m > 64:
        gap = np.where(np.concatenate([same, same], axis=1), -1, np.arange(2 * m))
        return np.minimum((np.arange(2 * m) - np.maximum.accumulate(gap, axis=1)).max(axis=1), m)
    packed = np.zeros((n, 8), np.uint8)
    packed[:, : (m + 7) // 8] = np.packbits(same, axis=1, bitorder="little")
    left = packed.view("<u8").ravel().astype(np.uint64)
    out, rows = np.zeros(n, np.int64), np.arange(n)
    one, top, mask = np.uint64(1), np.uint64(m - 1), np.uint64((1 << m) - 1)
    for length in range(1, m + 1):
        some = left != 0
        left, rows = left[some], rows[some]
        if not len(rows):
            break
        out[rows] = length
        left = left & ((left << one | left >> top) & mask)
    return out
