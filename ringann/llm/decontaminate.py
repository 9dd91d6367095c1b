"""Benchmark decontamination: a broadcast set of hashed test windows, scanned over token windows.

Every benchmark item gives its windows of `window` consecutive words (an item with fewer words, but not
none, is one window). The 64-bit hashes of these windows are broadcast in one sorted array; executors slide
over every document's words, look windows up and verify each hit word by word.

Edge cases: null or empty text has no words; an item without words has no window; an item without id is
searched, but not listed; repeated items count once by id; repeated document rows are judged one by one;
an empty benchmark gives clean documents; other columns stay in `remove` and are ignored by `scan`. The broadcast
is checked against `max_bytes` before anything is gathered; a larger benchmark raises and is to be given in parts.
"""

from __future__ import annotations

import hashlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringann.llm.kernel import ALNUM, BYTE_CODES, LOWER, Rolling, text_chunks, words

WINDOW = 10
MAX_BYTES = 256 << 20  # of the broadcast windows
OUT = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, hits array<struct<start:long,end:long>>"


def _word_codes(data: np.ndarray, off: np.ndarray):
    low = LOWER[data]
    starts, ends, first = words(low, off, ALNUM)
    return low, starts, ends, first, Rolling(BYTE_CODES[low]).spans(starts, ends)


class WindowSet:
    """Windows by length, as arrays: sorted hashes with a bitmap over their top bits, and beside each hash its item
    and its place in the items' words, which lie in one buffer. About 24 bytes a window and the text once."""

    def __init__(self, items: list[tuple[str | None, bytes]], window: int = WINDOW):
        self.names = sorted({i for i, _ in items if i is not None})
        place = {x: n for n, x in enumerate(self.names)}
        joined = b"\n".join(t for _, t in items)
        off = np.concatenate([[0], np.cumsum([len(t) + 1 for _, t in items])]).astype(np.int64)
        if len(items):
            off[-1] -= 1
        self.low, self.starts, self.ends, first, codes = _word_codes(np.frombuffer(joined, np.uint8), off)
        owner = np.array([place.get(i, -1) for i, _ in items], np.int32)
        count = np.diff(first)
        roll, self.sizes = Rolling(codes), {}
        for size in sorted({min(int(c), window) for c in count if c}):
            which = np.flatnonzero(np.minimum(count, window) == size)
            n = count[which] - size + 1
            at = np.repeat(first[which] - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
            item = np.repeat(owner[which], n)
            h = roll.spans(at, at + size)
            by = np.lexsort((item, h))
            h, at, item = h[by], at[by], item[by]
            bits = np.zeros(1 << 20, bool)
            bits[h >> np.uint64(44)] = True
            self.sizes[size] = (h, bits, at, item)

    @classmethod
    def of(cls, fields: dict) -> WindowSet:
        """A set from the fields of another: these are broadcast, so that workers unpickle arrays and no class."""
        out = cls.__new__(cls)
        vars(out).update(fields)
        return out

    def _tokens(self, i: int, size: int) -> bytes:
        return b" ".join(self.low[self.starts[j] : self.ends[j]].tobytes() for j in range(i, i + size))

    def scan(self, data: np.ndarray, off: np.ndarray):
        """(first word index per row, covered mask over words, word spans, items by row)."""
        low, starts, ends, first, codes = _word_codes(data, off)
        n = len(starts)
        roll = Rolling(codes)
        delta = np.zeros(n + 1, np.int64)
        items: dict[int, set] = defaultdict(set)
        for size, (hashes, bits, places, owners) in self.sizes.items():
            if n < size:
                continue
            at = np.arange(n - size + 1)
            h = roll.spans(at, at + size)
            keep = np.flatnonzero(bits[h >> np.uint64(44)])
            if not len(keep):
                continue
            at, h = at[keep], h[keep]
            lo = np.searchsorted(hashes, h)
            row = np.searchsorted(first, at, "right") - 1
            good = (hashes[np.minimum(lo, len(hashes) - 1)] == h) & (lo < len(hashes)) & (at + size <= first[row + 1])
            known: dict[int, dict[bytes, set]] = {}
            for i, code, a, r in zip(at[good], h[good], lo[good], row[good]):
                texts = known.get(int(code))
                if texts is None:  # windows of this hash by their words
                    texts = known[int(code)] = {}
                    for j in range(a, np.searchsorted(hashes, code, "right")):
                        texts.setdefault(self._tokens(places[j], size), set()).add(int(owners[j]))
                found = texts.get(b" ".join(low[starts[j] : ends[j]].tobytes() for j in range(i, i + size)))
                if found is not None:
                    delta[i] += 1
                    delta[i + size] -= 1
                    items[int(r)] |= found
        return first, np.cumsum(delta[:n]) > 0, starts, ends, items


def window_set(benchmark: DataFrame, window: int = WINDOW, max_bytes: int = MAX_BYTES) -> WindowSet:
    """The windows of benchmark(item_id, text) on the driver, after a check that they fit max_bytes."""
    rows = benchmark.select(F.col("item_id").cast("string").alias("item_id"), F.coalesce("text", F.lit("")).alias("text"))
    # A word gives a window at most, and has two bytes at least with what parts it from the next.
    told = rows.agg(F.sum(F.octet_length("text")).alias("n"), F.sum(F.regexp_count("text", F.lit(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"))).alias("w")).first()
    size = (told["n"] or 0) + 48 * (told["w"] or 0)
    if size > max_bytes:
        raise ValueError(f"the benchmark's windows take about {size} bytes of {max_bytes}; give it in parts")
    return WindowSet([(r[0], r[1].encode()) for r in rows.toLocalIterator()], window)


def scan(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, max_bytes: int = MAX_BYTES) -> DataFrame:
    """One row per document row: word counts, the items found, and the byte spans of hit runs."""
    shared = docs.sparkSession.sparkContext.broadcast(vars(window_set(benchmark, window, max_bytes)))

    def run(batches):
        known = WindowSet.of(shared.value)
        for rows, off, data in text_chunks(batches):
            first, hit, starts, ends, items = known.scan(data, off)
            n = rows.num_rows
            total = np.concatenate([[0], np.cumsum(hit)])
            n_hit = total[first[1:]] - total[first[:-1]]
            ids = [[known.names[x] for x in sorted(items.get(i, ())) if x >= 0] for i in range(n)]
            runs = []
            for i in range(n):
                if not n_hit[i]:
                    runs.append([])
                    continue
                m = hit[first[i] : first[i + 1]]
                edge = np.diff(np.concatenate([[0], m.astype(np.int8), [0]]))
                s, e = starts[first[i] : first[i + 1]], ends[first[i] : first[i + 1]]
                runs.append([{"start": int(s[a] - off[i]), "end": int(e[b - 1] - off[i])} for a, b in zip(np.flatnonzero(edge == 1), np.flatnonzero(edge == -1))])
            yield pa.RecordBatch.from_arrays(
                [
                    rows.column("doc_id"),
                    pa.array(np.diff(first), pa.int64()),
                    pa.array(n_hit, pa.int64()),
                    pa.array([len(x) for x in ids], pa.int64()),
                    pa.array([hashlib.sha256(",".join(x).encode()).hexdigest() for x in ids]),
                    pa.array(n_hit > 0),
                    pa.array(runs, pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))),
                ],
                names=["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated", "hits"],
            )

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, OUT)


def remove(docs: DataFrame, benchmark: DataFrame, mode: str = "documents", window: int = WINDOW, max_bytes: int = MAX_BYTES) -> DataFrame:
    """docs without contaminated documents (`documents`), or with the hit runs cut out of the texts (`spans`).

    All columns of docs stay. The work happens in one scan; nothing is joined back.
    """
    shared = docs.sparkSession.sparkContext.broadcast(vars(window_set(benchmark, window, max_bytes)))
    at = docs.columns.index("text")

    def run(batches):
        known = WindowSet.of(shared.value)
        for rows, off, data in text_chunks(batches):
            first, hit, starts, ends, _ = known.scan(data, off)
            total = np.concatenate([[0], np.cumsum(hit)])
            bad = total[first[1:]] > total[first[:-1]]
            if mode == "documents":
                yield rows.filter(pa.array(~bad))
                continue
            texts = rows.column(at).to_pylist()
            for i in np.flatnonzero(bad):
                mask = np.ones(off[i + 1] - off[i], bool)
                for j in range(first[i], first[i + 1]):
                    if hit[j]:
                        mask[starts[j] - off[i] : ends[j] - off[i]] = False
                texts[i] = data[off[i] : off[i + 1]][mask].tobytes().decode()
            cols = list(rows.columns)
            cols[at] = pa.array(texts, rows.schema.field(at).type)
            yield pa.RecordBatch.from_arrays(cols, schema=rows.schema)

    return docs.mapInArrow(run, docs.schema)


def op10_decontaminate(spark, sf_dir: str) -> DataFrame:
    docs, bench = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    return scan(docs, bench).drop("hits")


OP10_SQL = r"""
WITH low AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents
), item AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark
), win AS (
  SELECT DISTINCT item_id, least(10, len(w)) AS n, list_slice(w, i, i + least(10, len(w)) - 1) AS g
  FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 9, 1) + 1)) AS i FROM item WHERE len(w) > 0)
), sizes AS (SELECT DISTINCT n FROM win
), dwin AS (
  SELECT doc_id, n, i, list_slice(w, i, i + n - 1) AS g
  FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM low CROSS JOIN sizes WHERE len(w) >= n)
), hit AS (SELECT doc_id, d.n, i, item_id FROM dwin d JOIN win USING (n, g)
), covered AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM hit) GROUP BY doc_id
), named AS (SELECT doc_id, count(*) AS n_items, string_agg(x, ',' ORDER BY x) AS ids FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS x FROM hit) GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
  sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM low LEFT JOIN covered USING (doc_id) LEFT JOIN named USING (doc_id)
"""
