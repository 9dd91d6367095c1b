"""Line deduplication with two Bloom filters, of once-seen and of twice-seen line keys.

A key is a line stripped of ASCII white space at both ends, A-Z lower-cased. Keys of at least `min_chars` code
points that are found in at least `min_docs` documents lose all their lines except those in the largest doc_id.

Pass 1 fills, per task, a bitmap of keys seen in a document and one of keys seen in a second document; they are
sent in small compressed blocks and merged block by block (twice-seen: in either twice-bitmap, or in both
once-bitmaps). The filters are sized by the number of lines, up to MOST_BITS; a fuller filter only lets more keys
through.
Pass 2 shuffles only keys in the twice-filter: 128-bit hash and doc_id, once per document, pre-aggregated; that
count is exact. Pass 3 removes the lines and joins the doomed keys to their documents by doc_id.

Edge cases: null or empty text is one empty line; rows that share a doc_id count as one document; a row without
doc_id is left as it is and supports no key; empty tables give empty results; columns of docs that are named like
the operator's own are replaced, other columns stay.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType, StructField, StructType

from ringann.llm.kernel import BASE2, BYTE_CODES, LOWER, NOT_SPACE, Rolling, row_of, text_chunks

MIN_CHARS, MIN_DOCS = 20, 3
MOST_BITS = 1 << 29  # 64 MB in a task and on the driver
BLOCK = 1 << 17  # bits in a block
FIRST_BYTE = np.array([(b & 0xC0) != 0x80 for b in range(256)])


def line_table(data: np.ndarray, off: np.ndarray):
    """(start, end, first line of each row, key hashes h1 and h2, code points of each key)."""
    n_rows = len(off) - 1
    breaks = np.flatnonzero(data == 10)
    first = np.searchsorted(breaks, off) + np.arange(n_rows + 1)
    total = len(breaks) + n_rows
    last = np.zeros(total, bool)
    last[first[1:] - 1] = True
    start, end = np.empty(total, np.int64), np.empty(total, np.int64)
    end[last], end[~last] = off[1:], breaks
    opening = np.zeros(total, bool)
    opening[first[:-1]] = True
    start[opening], start[~opening] = off[:-1], breaks + 1
    solid = np.flatnonzero(NOT_SPACE[data])
    if len(solid):
        a = np.searchsorted(solid, start)
        b = np.searchsorted(solid, end) - 1
        some = b >= a
        ks = np.where(some, solid[np.minimum(a, len(solid) - 1)], start)
        ke = np.where(some, solid[np.maximum(b, 0)] + 1, start)
    else:
        ks, ke = start, start.copy()
    low = LOWER[data]
    codes = BYTE_CODES[low]
    points = np.concatenate([[0], np.cumsum(FIRST_BYTE[data])])
    return start, end, first, Rolling(codes).spans(ks, ke), Rolling(codes, BASE2).spans(ks, ke), points[ke] - points[ks]


def _doc_keys(rows, off, data, min_chars):
    """Distinct long keys of each row, in row order: (row, h1, h2)."""
    _, _, first, h1, h2, points = line_table(data, off)
    row = row_of(first)
    keep = points >= min_chars
    row, h1, h2 = row[keep], h1[keep], h2[keep]
    order = np.lexsort((h2, h1, row))
    row, h1, h2 = row[order], h1[order], h2[order]
    new = np.ones(len(row), bool)
    new[1:] = (row[1:] != row[:-1]) | (h1[1:] != h1[:-1]) | (h2[1:] != h2[:-1])
    row, h1, h2 = row[new], h1[new], h2[new]
    known = rows.column("doc_id").is_valid().to_numpy(zero_copy_only=False)[row]
    return row[known], h1[known], h2[known]


def _places(h1: np.ndarray, h2: np.ndarray, bits: int) -> np.ndarray:
    """Two bit positions of each key."""
    m = np.uint64(bits - 1)
    return np.stack([h1 & m, h2 & m]).astype(np.int64)


def _set(bitmap: np.ndarray, places: np.ndarray) -> None:
    np.bitwise_or.at(bitmap, places >> 3, (1 << (places & 7)).astype(np.uint8))


def _has(bitmap: np.ndarray, places: np.ndarray) -> np.ndarray:
    return ((bitmap[places >> 3] >> (places & 7)) & 1).astype(bool).all(axis=0)


def filter_bits(docs: DataFrame) -> int:
    """16 bits for every line, a power of two, MOST_BITS at most."""
    n = docs.agg(F.sum(F.length("text") - F.length(F.replace("text", F.lit("\n"))) + 1)).first()[0] or 0
    return min(MOST_BITS, max(8 * BLOCK, 1 << (16 * n).bit_length()))


def twice_filter(docs: DataFrame, min_chars: int, bits: int) -> np.ndarray:
    """The merged twice-seen bitmap, of bits/8 bytes: a fixed size whatever the input."""
    step = BLOCK // 8

    def fill(batches):
        once, twice = np.zeros(bits // 8, np.uint8), np.zeros(bits // 8, np.uint8)
        for rows, off, data in text_chunks(batches):
            row, h1, h2 = _doc_keys(rows, off, data, min_chars)
            _, where, count = np.unique(h1, return_index=True, return_counts=True)
            again = where[count > 1]
            p = _places(h1[where], h2[where], bits)
            seen = _has(once, p)
            _set(twice, p[:, seen].ravel())
            _set(twice, _places(h1[again], h2[again], bits).ravel())
            _set(once, p.ravel())
        ids = np.flatnonzero(once.reshape(-1, step).any(axis=1))
        for lo in range(0, len(ids), 64):
            part = ids[lo : lo + 64]
            yield pa.RecordBatch.from_arrays(
                [pa.array(part, pa.int32()), pa.array([zlib.compress(once[i * step : (i + 1) * step].tobytes(), 6) for i in part], pa.binary()), pa.array([zlib.compress(twice[i * step : (i + 1) * step].tobytes(), 6) for i in part], pa.binary())],
                names=["block", "once", "twice"],
            )

    def merge(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        once, twice = np.zeros(step, np.uint8), np.zeros(step, np.uint8)
        for batch in batches:
            for a, b in zip(batch.column("once"), batch.column("twice")):
                a = np.frombuffer(zlib.decompress(a.as_py()), np.uint8)
                twice |= np.frombuffer(zlib.decompress(b.as_py()), np.uint8) | (once & a)
                once |= a
        if twice.any():
            yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()], pa.int32()), pa.array([zlib.compress(twice.tobytes())], pa.binary())], names=["block", "twice"])

    parts = docs.select("doc_id", "text").mapInArrow(fill, "block int, once binary, twice binary").groupBy("block").applyInArrow(merge, "block int, twice binary")
    out = np.zeros(bits // 8, np.uint8)
    for block, twice in parts.collect():
        out[block * step : (block + 1) * step] = np.frombuffer(zlib.decompress(bytes(twice)), np.uint8)
    return out


def doomed_keys(docs: DataFrame, min_chars: int, min_docs: int, bits: int) -> DataFrame:
    """(doc_id, keys): packed 16-byte keys whose lines the document loses."""
    shared = docs.sparkSession.sparkContext.broadcast(twice_filter(docs, min_chars, bits))

    def suspects(batches):
        known = shared.value
        for rows, off, data in text_chunks(batches):
            row, h1, h2 = _doc_keys(rows, off, data, min_chars)
            keep = _has(known, _places(h1, h2, bits))
            ids = rows.column("doc_id").to_numpy(zero_copy_only=False)
            yield pa.RecordBatch.from_arrays([pa.array(h1[keep].view(np.int64)), pa.array(h2[keep].view(np.int64)), pa.array(ids[row[keep]].astype(np.int64))], names=["h1", "h2", "doc_id"])

    found = docs.select("doc_id", "text").mapInArrow(suspects, "h1 long, h2 long, doc_id long")
    # Two levels: a very common key is spread over 64 parts by document before its parts meet.
    part = found.groupBy("h1", "h2", F.pmod(F.xxhash64("doc_id"), F.lit(64)).alias("part")).agg(F.sort_array(F.collect_set("doc_id")).alias("ids"))
    heads = part.groupBy("h1", "h2").agg(F.sum(F.size("ids")).alias("n"), F.max(F.element_at("ids", -1)).alias("top")).where(F.col("n") >= min_docs)
    lost = part.join(heads, ["h1", "h2"]).select("h1", "h2", "top", F.explode("ids").alias("doc_id")).where("doc_id <> top")
    return lost.groupBy("doc_id").agg(F.collect_list(F.struct("h1", "h2")).alias("keys"))


def drop_lines(docs: DataFrame, min_chars: int = MIN_CHARS, min_docs: int = MIN_DOCS, bits: int | None = None) -> DataFrame:
    """docs (doc_id, text, ...) with kept text, n_lines (before), n_dropped and kept_sha256."""
    docs = docs.drop("n_lines", "n_dropped", "kept_sha256", "__keys").withColumn("doc_id", F.col("doc_id").cast("long"))
    bits = bits or filter_bits(docs)
    doomed = doomed_keys(docs, min_chars, min_docs, bits).withColumnRenamed("keys", "__keys")
    joined = docs.join(doomed, "doc_id", "left").select(*[docs[c] for c in docs.columns], "__keys")
    schema = StructType([StructField(f.name, f.dataType) for f in docs.schema.fields] + [StructField("n_lines", LongType()), StructField("n_dropped", LongType()), StructField("kept_sha256", StringType())])
    at = docs.columns.index("text")

    def cut(batches):
        for rows, off, data in text_chunks(batches):
            start, end, first, h1, h2, points = line_table(data, off)
            keys = rows.column("__keys").to_pylist()
            texts = rows.column(at).to_pylist()
            lost = np.zeros(rows.num_rows, np.int64)
            sums = []
            for i in range(rows.num_rows):
                a, b = first[i], first[i + 1]
                raw = data[off[i] : off[i + 1]].tobytes()
                if keys[i]:
                    bad = {(k["h1"] & (1 << 64) - 1, k["h2"] & (1 << 64) - 1) for k in keys[i]}
                    keep = [not (points[j] >= min_chars and (int(h1[j]), int(h2[j])) in bad) for j in range(a, b)]
                    raw = b"\n".join(raw[start[j] - off[i] : end[j] - off[i]] for j, k in zip(range(a, b), keep) if k)
                    lost[i] = keep.count(False)
                    texts[i] = raw.decode()
                sums.append(hashlib.sha256(raw).hexdigest())
            cols = list(rows.columns)[:-1]
            cols[at] = pa.array(texts, rows.schema.field(at).type)
            names = [f.name for f in schema.fields]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(np.diff(first), pa.int64()), pa.array(lost), pa.array(sums)], names=names)

    return joined.mapInArrow(cut, schema)


def op7_line_dedup(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return drop_lines(docs).drop("text")


OP7_SQL = r"""
WITH l AS (
  SELECT doc_id, i, line, translate(trim(line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k
  FROM (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS i FROM documents)
), bad AS (SELECT k, max(doc_id) AS top FROM l WHERE length(k) >= 20 GROUP BY k HAVING count(DISTINCT doc_id) >= 3)
SELECT doc_id, count(*)::BIGINT AS n_lines, (count(*) FILTER (WHERE top IS NOT NULL AND top <> doc_id))::BIGINT AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (WHERE top IS NULL OR top = doc_id), '')) AS kept_sha256
FROM l LEFT JOIN bad USING (k) GROUP BY doc_id
"""
