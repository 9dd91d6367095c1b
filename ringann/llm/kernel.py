"""Vectorised text kernels shared by the Arrow-batch operators.

A batch of strings is seen as one byte buffer with row offsets. Words, lines and windows are spans of
it; a span's hash comes from one running sum, so no Python object exists per word.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

CHUNK_BYTES = 1 << 21
BASE, BASE2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)
_POWERS: dict = {}


def byte_class(*ranges: tuple[int, int]) -> np.ndarray:
    """Lookup table of 256 booleans: True outside the given inclusive byte ranges."""
    table = np.ones(256, bool)
    for lo, hi in ranges:
        table[lo : hi + 1] = False
    return table


#: Bytes of words that are separated by ASCII white space, and bytes of words of letters and digits.
NOT_SPACE = byte_class((0x20, 0x20), (0x09, 0x0D))
ALNUM = byte_class((0x00, 0x2F), (0x3A, 0x60), (0x7B, 0x7F))
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def mix(x: np.ndarray) -> np.ndarray:
    """64-bit finaliser; every output bit depends on every input bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


BYTE_CODES = mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x2545F4914F6CDD1D))


def powers(n: int, base: np.uint64) -> tuple[np.ndarray, np.ndarray]:
    """base**i and its inverse modulo 2**64 for i < n; kept and grown between calls of a worker."""
    kept = _POWERS.get(int(base))
    if kept is None or len(kept[0]) < n:
        size = max(n, 1 << 16)
        inverse = np.uint64(pow(int(base), -1, 1 << 64))
        rows = []
        for b in (base, inverse):
            row = np.full(size, b, np.uint64)
            row[0] = 1
            rows.append(np.cumprod(row))
        kept = _POWERS[int(base)] = (rows[0], rows[1])
    return kept


class Rolling:
    """Hashes of arbitrary spans [s, e) of a sequence of 64-bit codes."""

    def __init__(self, codes: np.ndarray, base: np.uint64 = BASE):
        up, self.down = powers(len(codes) + 1, base)
        self.sums = np.zeros(len(codes) + 1, np.uint64)
        np.cumsum(codes * up[: len(codes)], out=self.sums[1:])

    def spans(self, s: np.ndarray, e: np.ndarray) -> np.ndarray:
        return mix((self.sums[e] - self.sums[s]) * self.down[s] + (e - s).astype(np.uint64))


def column_bytes(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(offsets int64[n+1], bytes) of a string column; null counts as empty."""
    col = pc.fill_null(col.cast(pa.large_string()), "")
    _, off, data = col.buffers()
    off = np.frombuffer(off, np.int64)[col.offset : col.offset + len(col) + 1]
    return off, np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)


def text_chunks(batches, column: str = "text", limit: int = CHUNK_BYTES):
    """Yields (rows, offsets, bytes): runs of rows of about `limit` bytes; a longer row stands alone."""
    for batch in batches:
        if not batch.num_rows:
            continue
        off, data = column_bytes(batch.column(column))
        lo = 0
        while lo < batch.num_rows:
            hi = max(lo + 1, int(np.searchsorted(off, off[lo] + limit, "right")) - 1)
            hi = min(hi, batch.num_rows)
            yield batch.slice(lo, hi - lo), off[lo : hi + 1] - off[lo], data[off[lo] : off[hi]]
            lo = hi


def words(data: np.ndarray, off: np.ndarray, table: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of `table` bytes inside rows, and each row's first word index."""
    inside = table[data]
    edge = inside.copy()
    edge[1:] &= ~inside[:-1]
    cut = off[:-1][np.diff(off) > 0]
    edge[cut] = inside[cut]
    starts = np.flatnonzero(edge)
    edge = inside.copy()
    edge[:-1] &= ~inside[1:]
    cut = off[1:][np.diff(off) > 0] - 1
    edge[cut] = inside[cut]
    return starts, np.flatnonzero(edge) + 1, np.searchsorted(starts, off)


def row_of(first: np.ndarray) -> np.ndarray:
    """Row number of each item, from every row's first item index."""
    return np.repeat(np.arange(len(first) - 1), np.diff(first))


BLOCK_BYTES = 1 << 14


def bit_places(h: np.ndarray, bits: int) -> np.ndarray:
    """Two bit positions of each hash, in a bitmap of `bits` bits."""
    m = np.uint64(bits - 1)
    return np.stack([h & m, (h >> np.uint64(37)) * np.uint64(0x9E3779B1) & m]).astype(np.int64)


def set_bits(bitmap: np.ndarray, places: np.ndarray) -> None:
    np.bitwise_or.at(bitmap, places >> 3, (1 << (places & 7)).astype(np.uint8))


def has_bits(bitmap: np.ndarray, places: np.ndarray) -> np.ndarray:
    return ((bitmap[places >> 3] >> (places & 7)) & 1).astype(bool).all(axis=0)


def merged_bitmap(df, hashes, bits: int) -> np.ndarray:
    """One bitmap of the hashes that `hashes(batches)` yields over df: bits/8 bytes on the driver, at any input size."""

    def fill(batches):
        bitmap = np.zeros(bits // 8, np.uint8)
        for h in hashes(batches):
            set_bits(bitmap, bit_places(h, bits).ravel())
        parts = bitmap.reshape(-1, BLOCK_BYTES)
        used = np.flatnonzero(parts.any(axis=1))
        for lo in range(0, len(used), 64):
            ids = used[lo : lo + 64]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int32()), pa.array([zlib.compress(parts[i].tobytes(), 6) for i in ids], pa.binary())], names=["block", "z"])

    def merge(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = np.zeros(BLOCK_BYTES, np.uint8)
        for batch in batches:
            for z in batch.column("z"):
                out |= np.frombuffer(zlib.decompress(z.as_py()), np.uint8)
        yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()], pa.int32()), pa.array([zlib.compress(out.tobytes())], pa.binary())], names=["block", "z"])

    schema = "block int, z binary"
    bitmap = np.zeros(bits // 8, np.uint8)
    for block, z in df.mapInArrow(fill, schema).groupBy("block").applyInArrow(merge, schema).collect():
        bitmap[block * BLOCK_BYTES : (block + 1) * BLOCK_BYTES] = np.frombuffer(zlib.decompress(bytes(z)), np.uint8)
    return bitmap
