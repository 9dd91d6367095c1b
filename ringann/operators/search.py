"""Ring index and ring search over DataFrames.

data(obj_id, vec), queries(qid, vec). The index is a table of one packed row per shard, and queries are packed in
blocks by the executors; every block meets every shard once, each meeting returns its own best candidates
(verified in place), and one small shuffle by qid merges them. Shards and blocks are bounded, so executors hold one
of each, whatever the size of data or query set, and no query passes through the driver.

Edge cases: rows whose vector is null, of another length, holds null or NaN, or is zero where angles are asked,
are left out as objects and give no result as queries; equal distances and run lengths are ordered by obj_id;
repeated ids are objects of their own; empty data or queries give an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ringann.functions import runs, theory
from ringann.functions.vectors import DISTANCES
from ringann.operators import probe, rotation
from ringann.operators.families import Family, Sets, matrix, usable
from ringann.operators.topk import broadcast_queries, top_k
from ringann.sources.staging import stage

SHARD_ROWS = 100_000
QUERY_BLOCK = 250
BROADCAST_QUERIES = 50_000  # 50 MB at 128 dimensions
PACKED = "shard int, n int, m int, d int, ids binary, codes binary, ord binary, link binary, vecs binary, offs binary"
CELL_BYTES = 64 << 20
CELL_QUERIES = 20_000
CELL_LISTED = 200_000  # listed rows that a task tells the candidates of
CELL_FOUND = 4_000_000  # rows that a cell of data gives; a quarter of them is found at once
CELL_QUERIES_FROM, CELL_PIECE, CELL_BLOCK = 1000, 1000, 64  # queries beyond which data meet them in cells; rows of data and queries in one piece
LISTED, LISTED_ROWS = 2, 100_000  # rows listed for every one asked where the nearest are looked for first, and from how many objects on
BLOCK = "q_n int, q_ids binary, q_vecs binary, q_offs binary, q_codes binary, q_alts binary, q_scores binary"
RESULT = "qid long, rnk int, obj_id long, dist double"


def distances(metric: str, x, q) -> np.ndarray:
    if metric == "euclidean":
        return np.sqrt(((x - q) ** 2).sum(axis=1))
    if metric == "manhattan":
        return np.abs(x - q).sum(axis=1)
    if metric == "hamming":
        return (x != q).sum(axis=1).astype(np.float64)
    if metric == "angular":
        cosine = (x @ q) / (np.linalg.norm(x, axis=1) * np.linalg.norm(q))
        return np.arccos(np.clip(cosine, -1, 1))
    if metric == "jaccard":
        at = np.minimum(np.searchsorted(q, x.flat), max(0, len(q) - 1))
        hit = np.concatenate([[0], np.cumsum(q[at] == x.flat)]) if len(q) else np.zeros(len(x.flat) + 1, np.int64)
        same = hit[x.off[1:]] - hit[x.off[:-1]]
        union = np.diff(x.off) + len(q) - same
        return np.where(union > 0, 1 - same / np.maximum(union, 1), 0.0)
    raise ValueError(f"unknown metric {metric}")


SET_ROWS = 1000


def jaccard_distances(x: Sets, q: Sets) -> np.ndarray:
    """[len(q), len(x)]: distances("jaccard", x, q[j]) of all queries at once. Every member is looked up once among the members
    of all queries, and only meetings of equal members are counted."""
    by = np.argsort(q.flat, kind="stable")
    members, owner = q.flat[by], np.repeat(np.arange(len(q)), np.diff(q.off))[by]
    lo, hi = np.searchsorted(members, x.flat), np.searchsorted(members, x.flat, "right")
    row, same = np.repeat(np.arange(len(x)), np.diff(x.off)), np.zeros(len(q) * len(x), np.int64)
    met = np.flatnonzero(hi > lo)
    ends = np.cumsum(hi[met] - lo[met])
    start = 0
    while start < len(met):  # about four million meetings at a time
        done = ends[start - 1] if start else 0
        stop = max(start + 1, int(np.searchsorted(ends, done + (1 << 22), "right")))
        some = met[start:stop]
        n = hi[some] - lo[some]
        at = np.repeat(lo[some] - (np.cumsum(n) - n), n) + np.arange(n.sum())
        same += np.bincount(owner[at] * len(x) + np.repeat(row[some], n), minlength=len(same))
        start = stop
    same = same.reshape(len(q), len(x))
    union = np.diff(x.off) + np.diff(q.off)[:, None] - same
    return np.where(union > 0, 1 - same / np.maximum(union, 1), 0.0)


def _bytes(points) -> tuple[bytes, bytes]:
    if isinstance(points, Sets):
        return points.flat.astype(np.int64).tobytes(), points.off.astype(np.int64).tobytes()
    return np.ascontiguousarray(points, np.float64).tobytes(), b""


def _points(raw, offs, n: int):
    if len(offs):
        return Sets(np.frombuffer(raw, np.int64), np.frombuffer(offs, np.int64))
    return np.frombuffer(raw, np.float64).reshape(n, -1)


def _joined(parts: list):
    return Sets.joined(parts) if isinstance(parts[0], Sets) else np.concatenate(parts)


def build_index(data: DataFrame, family: Family, shard_rows: int = SHARD_ROWS, rows: int | None = None, shard: Column | None = None) -> DataFrame:
    """Packed shards. One shuffle of (id, vector); codes are computed where the shard is built. Objects are dealt
    out by a hash of the id, or as the column `shard` says."""
    data = usable(data, family)
    shards = None
    if shard is None:
        n = data.count() if rows is None else rows
        shards = max(1, -(-n // shard_rows))
        shard = F.pmod(F.xxhash64("obj_id"), F.lit(shards))

    def pack(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, vecs = [], []
        for b in batches:
            ids.append(b.column("obj_id").to_numpy())
            vecs.append(family.points(b.column("vec")))
        ids, vecs = np.concatenate(ids), _joined(vecs)
        by = np.argsort(ids, kind="stable")
        ids, vecs = ids[by], vecs[by]
        s = rotation.Shard(ids, family.codes(vecs))
        raw, offs = _bytes(vecs)
        cells = [ids.astype(np.int64).tobytes(), s.codes.astype(np.int32).tobytes(), s.order.tobytes(), s.link.tobytes(), raw, offs]
        yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()], pa.int32()), *[pa.array([v], pa.int32()) for v in (s.n, s.m, family.d or 0)], *[pa.array([c], pa.binary()) for c in cells]], names=["shard", "n", "m", "d", "ids", "codes", "ord", "link", "vecs", "offs"])

    kind = "array<double>" if family.d is not None else "array<long>"
    keyed = data.select("obj_id", F.col("vec").cast(kind).alias("vec"), shard.cast("int").alias("shard"))
    out = keyed.groupBy("shard").applyInArrow(pack, PACKED)
    out.n_shards, out.n_rows = shards, shards and n
    return out


def _unpack(b, i):
    n, m = (b.column(c)[i].as_py() for c in ("n", "m"))
    get = lambda c, t, *s: np.frombuffer(b.column(c)[i].as_buffer(), t).reshape(*s)
    s = rotation.Shard(get("ids", np.int64, n), get("codes", np.int32, n, m), get("ord", np.int32, m, n), get("link", np.int32, m, n))
    return s, _points(b.column("vecs")[i].as_buffer(), b.column("offs")[i].as_buffer(), n)


def query_blocks(queries: DataFrame, points, sets: bool = False, family: Family | None = None, n_alt: int = 0, block: int = QUERY_BLOCK, hint: bool = True) -> DataFrame:
    """queries(qid, vec) in packed blocks, with codes and alternatives if a family is given: no shuffle, nothing on
    the driver. Broadcast where a count shows that they are few, else they meet the data in a shuffled product of blocks."""

    def pack(batches):
        for b in batches:
            for lo in range(0, b.num_rows, block):
                part = b.slice(lo, block)
                x = points(part.column("vec"))
                raw, offs = _bytes(x)
                codes = family.codes(x).astype(np.int32).tobytes() if family is not None else b""
                alts, scores = family.alternatives(x, n_alt) if n_alt else (np.zeros(0, np.int32), np.zeros(0))
                cells = [part.column("qid").to_numpy().astype(np.int64).tobytes(), raw, offs, codes, np.ascontiguousarray(alts, np.int32).tobytes(), np.ascontiguousarray(scores, np.float64).tobytes()]
                yield pa.RecordBatch.from_arrays([pa.array([part.num_rows], pa.int32()), *[pa.array([c], pa.binary()) for c in cells]], names=["q_n", "q_ids", "q_vecs", "q_offs", "q_codes", "q_alts", "q_scores"])

    rows = queries.select("qid", F.col("vec").cast("array<long>" if sets else "array<double>").alias("vec"))
    packed = rows.mapInArrow(pack, BLOCK)
    if not hint:
        return packed
    few = rows.limit(BROADCAST_QUERIES + 1).count() <= BROADCAST_QUERIES
    return F.broadcast(packed) if few else packed


def _meetings(index: DataFrame, blocks: DataFrame) -> DataFrame:
    """Every shard with every query block. Where an index has fewer shards than twice the cores, each shard is sent to
    several tasks, which share the blocks; else shards stay where they are."""
    shards, cores = index.__dict__.get("n_shards"), 2 * index.sparkSession.sparkContext.defaultParallelism
    if not shards or shards >= cores:
        return index.join(blocks, F.lit(True))
    copies = -(-cores // shards)
    spread = index.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1)))).repartition(shards * copies, "shard", "copy")
    return spread.join(blocks, F.col("copy") == F.pmod(F.xxhash64("q_ids"), F.lit(copies)))


def _cell_keys(spark, n: int) -> list[int]:
    """n numbers that Spark's hash deals to n partitions, one to each; left to chance, some tasks would have several cells and others none."""
    keys = spark.range(40 * n + 100).select(F.col("id").cast("int").alias("key")).groupBy(F.pmod(F.hash("key"), F.lit(n)).alias("at")).agg(F.min("key").alias("key")).collect()
    found = [r["key"] for r in keys]
    return found + [-1 - i for i in range(n - len(found))]


def _cells(index: DataFrame, shards: int, rows: int, row: int, blocks: DataFrame, ways: int, meet, fields: list) -> tuple[DataFrame, int]:
    """(rows of meet(shards, blocks), parts of the index): every part of the index meets every part of the blocks in one
    cell, once. A part has about CELL_BYTES of shards, with `row` bytes a row; blocks are dealt in `ways` parts or more, so that
    cells are three a core or more."""
    parts = min(shards, max(1, -(-rows * row // CELL_BYTES)))
    cells = 3 * index.sparkSession.sparkContext.defaultParallelism
    ways = max(1, -(-cells // parts), ways)
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    left = index.withColumn("part", F.pmod("shard", F.lit(parts))).withColumn("way", every(ways))
    right = blocks.withColumn("way", F.pmod(F.xxhash64("q_ids"), F.lit(ways)).cast("int")).withColumn("part", every(parts))
    cell = F.get(F.array(*map(F.lit, _cell_keys(index.sparkSession, parts * ways))), F.col("part") * ways + F.col("way")).alias("cell")
    left, right = (df.select("*", cell).drop("part", "way").repartition(parts * ways, "cell").groupBy("cell") for df in (left, right))
    return _met(left, right, meet, fields), parts


def _met(left, right, meet, fields: list) -> DataFrame:
    """Rows of meet(left rows, right rows) for groups that have both."""
    out = pa.schema([(name, {"int": pa.int32(), "long": pa.int64(), "double": pa.float64(), "boolean": pa.bool_(), "binary": pa.binary()}[kind]) for name, kind in fields])

    def run(key, a: pa.Table, b: pa.Table) -> pa.Table:
        if not a.num_rows or not b.num_rows:
            return out.empty_table()
        return pa.Table.from_batches([*meet(a, b)], out)

    return left.cogroup(right).applyInArrow(run, ", ".join(map(" ".join, fields)))


def _block(b, i, m: int = 0):
    n = b.column("q_n")[i].as_py()
    ids = np.frombuffer(b.column("q_ids")[i].as_buffer(), np.int64)
    x = _points(b.column("q_vecs")[i].as_buffer(), b.column("q_offs")[i].as_buffer(), n)
    codes = np.frombuffer(b.column("q_codes")[i].as_buffer(), np.int32).reshape(n, m) if m else None
    alts = np.frombuffer(b.column("q_alts")[i].as_buffer(), np.int32)
    scores = np.frombuffer(b.column("q_scores")[i].as_buffer(), np.float64)
    return ids, x, codes, (alts.reshape(n, m, -1), scores.reshape(n, m, -1)) if len(alts) else None


def _asked(blocks: DataFrame, d: int) -> DataFrame:
    """(qid, vec) of packed blocks."""
    def unpack(batches):
        for b in batches:
            for i in range(b.num_rows):
                qids, x, _, _ = _block(b, i)
                vecs = pa.ListArray.from_arrays(pa.array(np.arange(len(qids) + 1) * d, pa.int32()), pa.array(x.ravel()))
                yield pa.RecordBatch.from_arrays([pa.array(qids), vecs], names=["qid", "vec"])

    return blocks.mapInArrow(unpack, "qid long, vec array<double>")


def index_stats(index: DataFrame) -> DataFrame:
    size = sum(F.octet_length(c).cast("long") for c in ("ids", "codes", "ord", "link"))
    return index.agg(F.count("*").alias("shards"), F.sum("n").alias("objects"), F.sum(size).alias("index_bytes"))


def write_index(index: DataFrame, path: str) -> None:
    """One folder for each shard, so that reads of some shards prune the rest."""
    index.write.mode("overwrite").partitionBy("shard").parquet(path)


def read_index(spark, path: str) -> DataFrame:
    out = spark.read.schema(PACKED).parquet(path).select(*[c.split()[0] for c in PACKED.split(", ")])
    out.n_shards = out.count()
    return out


def ring_search(index: DataFrame, family: Family, queries: DataFrame, lam: int | str, k: int = 1, metric: str | None = None, n_probes: int = 1, max_gap: int = probe.MAX_GAP, ties: str = "id", verify: str = "global", exclude_self: bool = False, n_alt: int = 4, skip: bool = True, query_block: int = QUERY_BLOCK, where: Column | None = None, listed: int | None = None) -> DataFrame:
    """(qid, rnk, obj_id, dist, run_len): the k nearest of the lam + k - 1 objects with the longest runs.

    ties='id' collects all that tie with the last candidate and orders them by id, so that results do not depend
    on shards; 'any' stops early. verify='global' cuts candidates to lam + k - 1 over all shards before ranking by
    distance, 'shard' ranks all shards' candidates, of which each shard sends its k nearest. exclude_self leaves out
    the object whose id is the query's. skip=False is the trivial multi-probe, which searches every rotation again.
    `where` is a condition on qid, obj_id and dist that results must meet before ranking. Where candidates are a good part of
    every shard, the listed * k nearest rows are found first, and then told whether they are candidates; 0 does not, None does
    from LISTED_ROWS objects on, where that saves more than its stages cost. Results are the same.
    """
    metric = metric or family.metric
    least, every = lam + k - 1, where is not None
    alts = n_alt if n_probes > 1 else 0
    sized = index.__dict__.get("n_rows") is not None
    queries = usable(queries, family)
    blocks = query_blocks(queries, family.points, family.d is None, family, alts, query_block, not sized)
    kind = "qid long, obj_id long, run_len int, dist double"
    if listed is None:
        listed = LISTED if sized and index.n_rows >= LISTED_ROWS else 0
    if listed and sized and verify == "shard" and ties == "id" and not every and not alts and metric in ("euclidean", "angular") and 8 * least * index.n_shards >= index.n_rows:
        blocks = blocks.persist()
        if (first := _nearest_first(index, family, blocks, least, k, listed * k, metric, exclude_self)) is not None:
            told, left = first
            found = told.where("candidate").select("qid", "obj_id", "dist", "run_len")
            if left is not None:
                found = found.join(left, "qid", "left_anti")
            found = top_k(found, k, ["dist", "obj_id"]).select("qid", "rnk", "obj_id", "dist", "run_len")
            if left is None:
                return found
            return found.union(ring_search(index, family, _asked(blocks, family.d).join(left, "qid", "left_semi"), lam, k, metric, verify="shard", exclude_self=exclude_self, query_block=query_block, listed=0))

    def ask(s, vecs, asked, best, near=None):
        """Answers of one shard, or of several as one, to a packed block of queries; `best` limits them by distance. `near`
        holds the `best` least distances of every query so far, where a block asks several shards."""
        qids, x, codes, other = asked
        cols: list[list] = [[], [], [], []]
        lo, hi = np.searchsorted(s.ids, qids), np.searchsorted(s.ids, qids, "right")
        own = hi - lo if exclude_self else np.zeros(len(qids), np.int64)  # only a shard that holds the query has one to leave out
        scan = ties == "id" and (least + int(own.max(initial=0))) * rotation.SCAN >= s.least
        most = least + int(own.max(initial=0))
        known: dict = {}
        if best and metric in ("euclidean", "angular") and scan and other is None and 8 * most >= s.n and own.max(initial=0) <= 1 and s.table is not None:
            if getattr(s, "near", None) is None:
                s.near = _Near(s, vecs, metric, best)
            near = np.full((len(qids), best), np.inf) if near is None else near
            at, rows, lens, dist = s.near.ask(x, codes, lo, lo + own, least, near[:, -1])
            nearer = np.full((len(qids), best), np.inf)
            nearer[at, np.arange(len(at)) - np.searchsorted(at, at)] = dist
            near[:] = np.sort(np.concatenate([near, nearer], axis=1), axis=1)[:, :best]
            return pa.RecordBatch.from_arrays([pa.array(c) for c in (qids[at], s.ids[rows], lens.astype(np.int32), dist)], names=["qid", "obj_id", "run_len", "dist"])
        for j in range(len(qids)):
            want = least + int(own[j])
            if scan and other is None:
                if (name := codes[j].tobytes()) not in known:
                    known[name] = s.scan([codes[j]], most)
                rows, lens = known[name]
            elif scan:
                rows, lens = s.scan(probe.strings(codes[j], other[0][j], other[1][j], n_probes, max_gap), most)
            elif other is None:
                rows, lens = rotation.k_search_rows(s, codes[j], want, ties == "id")
            else:
                rows, lens, _ = probe.search_rows(s, codes[j], other[0][j], other[1][j], want, n_probes, max_gap, skip, ties == "id")
            if own[j]:
                other_ids = (rows < lo[j]) | (rows >= hi[j])
                rows, lens = rows[other_ids], lens[other_ids]
            rows, lens = (rows[:least], lens[:least]) if scan else rotation.cut_rows(rows, lens, s.ids, least)
            dist = distances(metric, vecs[rows], x[j])
            if best:
                by = np.lexsort((s.ids[rows], dist))[:best]
                rows, lens, dist = rows[by], lens[by], dist[by]
            cols[0].append(np.full(len(rows), qids[j])), cols[1].append(s.ids[rows]), cols[2].append(lens.astype(np.int32)), cols[3].append(dist)
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in cols], names=["qid", "obj_id", "run_len", "dist"])

    def visit(batches):
        kept: tuple = (None, None, None)
        for b in batches:
            for i in range(b.num_rows):
                if kept[0] != (name := b.column("shard")[i].as_py()):
                    kept = (name, *_unpack(b, i))
                _, s, vecs = kept
                yield ask(s, vecs, _block(b, i, s.m), k if verify == "shard" and not every else 0)

    def meet(shards, asked):
        held = [_unpack(shards, i) for i in range(shards.num_rows)]
        best = k if verify == "shard" and not every else 0
        if verify == "global" and ties == "id" and all(least * rotation.SCAN >= s.n for s, _ in held):
            held = [_as_one(held)]
            best = k if whole and not every else 0
        for i in range(asked.num_rows):
            block = _block(asked, i, held[0][0].m)
            near = np.full((len(block[0]), best), np.inf) if best else None
            for s, vecs in held:
                yield ask(s, vecs, block, best, near)

    if sized:
        whole = index.n_rows * (16 + 12 * family.m + (8 * family.d if family.d else 4000)) <= CELL_BYTES
        row = 16 + 12 * family.m + (8 * family.d if family.d else 4000)
        out, _ = _cells(index, index.n_shards, index.n_rows, row, blocks, -(-queries.count() // CELL_QUERIES), meet, [tuple(f.split()) for f in kind.split(", ")])
    else:
        out = _meetings(index, blocks).mapInArrow(visit, kind)
    if verify == "global":
        out = top_k(out, least, [F.col("run_len").desc(), "obj_id"], rank="__r").drop("__r")
    if where is not None:
        out = out.where(where)
    return top_k(out, k, ["dist", "obj_id"]).select("qid", "rnk", "obj_id", "dist", "run_len")


def _as_one(held: list) -> tuple:
    """Several unpacked shards as one that can be scanned, in id order; it has no rotation order."""
    if len(held) == 1:
        return held[0]
    ids, vecs = np.concatenate([s.ids for s, _ in held]), _joined([v for _, v in held])
    by = np.argsort(ids, kind="stable")
    none = np.zeros((0, 0), np.int32)
    one = rotation.Shard(ids[by], np.concatenate([s.codes for s, _ in held])[by], none, none)
    one.least = min(s.n for s, _ in held)
    return one, vecs[by]


class _Near:
    """The nearest candidates of blocks of queries in a scanned shard, where candidates are a good part of it.

    One product of matrices in single precision rules out what is surely farther than the k-th found so far; whether the few
    rows left are candidates follows from their own runs and the number of rows with such runs, and distances are computed for
    candidates only. Of equal vectors, only as many as can be among the nearest are looked at: of two, the one with the
    smaller id is a candidate where the other is, and comes before it.
    """

    PAIRS = 1 << 15

    def __init__(self, s: rotation.Shard, vecs: np.ndarray, metric: str, best: int):
        self.s, self.vecs, self.metric, self.best = s, vecs, metric, best
        x = vecs / np.linalg.norm(vecs, axis=1)[:, None] if metric == "angular" else vecs
        raw = np.ascontiguousarray(vecs + 0.0).view(np.dtype((np.void, vecs.shape[1] * 8))).ravel()
        by = np.argsort(raw, kind="stable")
        new = np.concatenate([[True], raw[by][1:] != raw[by][:-1]])
        start = np.flatnonzero(new)
        copy = np.empty(s.n, np.int64)
        copy[by] = np.arange(s.n) - np.repeat(start, np.diff(np.append(start, s.n)))
        self.rows = np.flatnonzero(copy < best + np.unique(s.ids, return_counts=True)[1].max(initial=0))  # more than asked, for the query itself
        x = x[self.rows]
        size = (x * x).sum(axis=1)
        self.size = float(size.max(initial=0))
        self.side = np.ascontiguousarray(np.hstack([-2 * x, size[:, None], np.ones((len(x), 1))]).astype(np.float32).T)

    def _dist(self, rows: np.ndarray, x: np.ndarray) -> np.ndarray:
        """Distances of rows from a point each."""
        v = self.vecs[rows]
        if self.metric == "euclidean":
            return np.sqrt(((v - x) ** 2).sum(axis=1))
        cosine = (v * x).sum(axis=1) / (np.linalg.norm(v, axis=1) * np.linalg.norm(x, axis=1))
        return np.arccos(np.clip(cosine, -1, 1))

    def _close(self, x: np.ndarray, lo: np.ndarray, hi: np.ndarray, kth: np.ndarray) -> tuple:
        """(squared distances in single precision, half of what they may be off, query numbers and rows of pairs that may be
        among the `best` and within kth[j])."""
        y = x / np.linalg.norm(x, axis=1)[:, None] if self.metric == "angular" else x
        own = (y * y).sum(axis=1)
        far = np.hstack([y, np.ones((len(y), 1)), own[:, None]]).astype(np.float32) @ self.side
        slack = np.float32(2.0**-22 * (self.side.shape[0] + 2) * 2 * max(self.size, float(own.max(initial=0))))
        first, last = np.searchsorted(self.rows, lo), np.searchsorted(self.rows, hi)
        for j in np.flatnonzero(last > first):
            far[j, first[j] : last[j]] = np.inf
        fresh = np.isinf(kth)
        held = np.where(fresh, 0.0, kth)
        limit = (np.square(held) if self.metric == "euclidean" else 2 - 2 * np.cos(held)).astype(np.float32) + slack
        if fresh.any():
            limit[fresh] = np.partition(far[fresh], self.best - 1, axis=1)[:, self.best - 1] + 2 * slack if self.best <= far.shape[1] else np.inf
        at = np.flatnonzero((far <= limit[:, None]).ravel())
        at = at[np.isfinite(far.ravel()[at])]
        return far, slack, at // far.shape[1], self.rows[at % far.shape[1]]

    def _best(self, qs: np.ndarray, rows: np.ndarray, x: np.ndarray, kth: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(numbers of pairs by query, distance and id, at most `best` a query and none beyond its kth[j]; their distances)."""
        dist = np.concatenate([np.zeros(0), *(self._dist(rows[i : i + self.PAIRS], x[qs[i : i + self.PAIRS]]) for i in range(0, len(rows), self.PAIRS))])
        by = np.lexsort((self.s.ids[rows], dist, qs))
        place = np.arange(len(by)) - np.searchsorted(qs[by], qs[by])
        by = by[(place < self.best) & (dist[by] <= kth[qs[by]])]
        return by, dist[by]

    def ask(self, x: np.ndarray, codes: np.ndarray, lo: np.ndarray, hi: np.ndarray, least: int, kth: np.ndarray) -> tuple[np.ndarray, ...]:
        """(query numbers, rows, run lengths, distances), at most `best` a query and none beyond its kth[j], a distance that
        `best` others are known to keep. Rows lo[j] to hi[j] are the query itself."""
        s, best, fresh = self.s, self.best, np.isinf(kth)
        far, slack, qs, rows = self._close(x, lo, hi, kth)
        lens = s.pair_runs(rows, codes, qs, self.PAIRS)
        keep, more = np.ones(len(qs), bool), []
        for j, part, mask in _unsure(s, codes, lo, hi, least, qs, lens):
            keep[part] = mask[rows[part]]
            if fresh[j] and not keep[part].all():  # others come in for those that are no candidates
                keep[part] = False
                left = np.where(mask[self.rows], far[j], np.inf)
                edge = np.partition(left, best - 1)[best - 1] + 2 * slack if best <= far.shape[1] else np.inf
                more.append((j, self.rows[np.isfinite(left) & (left <= edge)]))
        qs, rows, lens = qs[keep], rows[keep], lens[keep]
        if more:
            extra_q, extra = np.concatenate([np.full(len(r), j) for j, r in more]), np.concatenate([r for _, r in more])
            qs, rows, lens = np.concatenate([qs, extra_q]), np.concatenate([rows, extra]), np.concatenate([lens, s.pair_runs(extra, codes, extra_q, self.PAIRS)])
        by, dist = self._best(qs, rows, x, kth)
        return qs[by], rows[by], lens[by], dist


def _halved(points: np.ndarray, most: int) -> list[np.ndarray]:
    """Row numbers in parts of at most `most`, halved along the coordinate in which a part varies most."""
    out, left = [], [np.arange(len(points))]
    while left:
        part = left.pop()
        if len(part) <= most:
            out.append(part)
            continue
        some = points[part]
        by = np.argpartition(some[:, some.var(axis=0).argmax()], len(part) // 2)
        left += [part[by[len(part) // 2 :]], part[by[: len(part) // 2]]]
    return [p for p in out if len(p)]


class _Tiles:
    """The nearest rows of queries, exactly.

    Rows are laid in tiles of near ones, queries in groups. A tile has a box of its rows' coordinates along the main axes and of
    what is left beside them; a query's distance from the box is no more than that from any row. A group takes the nearest
    tiles first, and later ones only for the queries that they may still have something for: by a product of matrices in single
    precision, which only rules out what is surely farther than the k-th so far.
    """

    TILE, GROUP, AXES = 1024, 256, 16

    def __init__(self, ids: np.ndarray, vecs: np.ndarray, metric: str, best: int):
        self.ids, self.vecs, self.metric, self.best = ids, vecs, metric, best
        self.own = int(np.unique(ids, return_counts=True)[1].max(initial=0))  # rows of one id
        kind = _numbered(vecs)
        by = np.lexsort((ids, kind))
        kind = kind[by]
        start = np.flatnonzero(np.diff(kind, prepend=-1))
        copy = np.arange(len(by)) - np.repeat(start, np.diff(np.append(start, len(by))))
        rows = by[copy < best + self.own]  # of equal vectors, no more than can be among the nearest
        x = self._scaled(vecs[rows])
        self.axes = np.linalg.eigh(x.T @ x)[1][:, ::-1][:, : self.AXES]
        at = self._coordinates(x)
        parts = _halved(at, self.TILE)
        self.rows = [rows[p] for p in parts]
        self.low, self.high = (np.array([f(at[p], axis=0) for p in parts]) for f in (np.min, np.max))
        self.sides, self.size = [], float((x * x).sum(axis=1).max(initial=0))
        for p in parts:
            side = np.zeros((x.shape[1] + 2, -(-len(p) // 8) * 8), np.float32)
            side[:-2, : len(p)], side[-2, : len(p)], side[-2, len(p) :], side[-1] = -2 * x[p].T, (x[p] * x[p]).sum(axis=1), 1e30, 1
            self.sides.append(side)

    def _scaled(self, x: np.ndarray) -> np.ndarray:
        return x / np.linalg.norm(x, axis=1)[:, None] if self.metric == "angular" else x

    def _coordinates(self, x: np.ndarray) -> np.ndarray:
        at = x @ self.axes
        return np.hstack([at, np.sqrt(np.maximum(0, (x * x).sum(axis=1) - (at * at).sum(axis=1)))[:, None]])

    def _dist(self, rows: np.ndarray, x: np.ndarray) -> np.ndarray:
        v = self.vecs[rows]
        if self.metric == "euclidean":
            return np.sqrt(((v - x) ** 2).sum(axis=1))
        cosine = (v * x).sum(axis=1) / (np.linalg.norm(v, axis=1) * np.linalg.norm(x, axis=1))
        return np.arccos(np.clip(cosine, -1, 1))

    def nearest(self, qids: np.ndarray, x: np.ndarray, exclude_self: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(query numbers, rows, distances) by (query, distance, id), `best` a query where there are as many."""
        y = self._scaled(x)
        found = [(np.zeros(0, np.int64),) * 2]
        for group in _halved(self._coordinates(y), self.GROUP):
            at, rows = self._group(qids[group], y[group], exclude_self)
            found.append((group[at], rows))
        at, rows = (np.concatenate(c) for c in zip(*found))
        step = _Near.PAIRS
        dist = np.concatenate([np.zeros(0), *(self._dist(rows[i : i + step], x[at[i : i + step]]) for i in range(0, len(rows), step))])
        by = np.lexsort((self.ids[rows], dist, at))
        by = by[np.arange(len(by)) - np.searchsorted(at[by], at[by]) < self.best]
        return at[by], rows[by], dist[by]

    def _group(self, qids: np.ndarray, y: np.ndarray, exclude_self: bool) -> tuple[np.ndarray, np.ndarray]:
        """(query numbers, rows) of all pairs that may be among the nearest, few more than these."""
        at, own = self._coordinates(y)[:, None], (y * y).sum(axis=1)
        gap = np.square(np.maximum(np.maximum(self.low - at, at - self.high), 0)).sum(axis=2)
        asked = np.hstack([y, np.ones((len(y), 1)), own[:, None]]).astype(np.float32)
        slack = np.float32(2.0**-22 * (y.shape[1] + 4) * 2 * max(self.size, float(own.max(initial=0))))
        kept = np.full((len(y), self.best), np.inf, np.float32)  # least squared distances so far
        limit = np.full(len(y), np.inf, np.float32)
        take = self.best + self.own * exclude_self
        found: list = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.float32))]
        for t in np.lexsort((gap.sum(axis=0), gap.min(axis=0, initial=np.inf))):
            some = np.flatnonzero(gap[:, t] <= limit)
            if not len(some):
                continue
            tile, most = self.rows[t], limit[some]
            far = asked[some] @ self.sides[t]
            if (fresh := np.isinf(most)).any() and take <= len(tile):
                most[fresh] = np.partition(far[fresh], take - 1, axis=1)[:, take - 1] + 2 * slack
            near = far <= most[:, None]
            words = np.flatnonzero(near.view(np.uint64))
            word, bit = np.nonzero(near.reshape(-1, 8)[words])
            cell = words[word] * 8 + bit
            qs, col = cell // far.shape[1], cell % far.shape[1]
            real = col < len(tile)
            if exclude_self:
                real[real] = self.ids[tile[col[real]]] != qids[some[qs[real]]]
            if not real.any():
                continue
            qs, col, size = qs[real], col[real], far.ravel()[cell[real]]
            found.append((some[qs], tile[col], size))
            start = np.flatnonzero(np.diff(qs, prepend=-1))
            times = np.diff(np.append(start, len(qs)))
            more = np.full((len(start), times.max()), np.inf, np.float32)
            more[np.repeat(np.arange(len(start)), times), np.arange(len(qs)) - np.repeat(start, times)] = size
            hit = some[qs[start]]
            kept[hit] = np.partition(np.concatenate([kept[hit], more], axis=1), self.best - 1, axis=1)[:, : self.best]
            limit[hit] = kept[hit, -1] + 2 * slack
        qs, rows, size = (np.concatenate(c) for c in zip(*found))
        last = size <= limit[qs]
        return qs[last], rows[last]


def nearest_in(ids: np.ndarray, vecs: np.ndarray, best: int, exclude_self: bool):
    """A function of qids and x that gives (query numbers, rows, Euclidean distances) by (query, distance, id), `best` a query
    where there are as many. Rows and queries that single precision cannot hold are compared one by one."""
    fits = lambda v: ((np.abs(v) < 1e12) & ((np.abs(v) > 1e-12) | (v == 0))).all(axis=1)
    held = fits(vecs)
    rows, odd = np.flatnonzero(held), np.flatnonzero(~held)
    tiles = _Tiles(ids[rows], vecs[rows], "euclidean", best) if len(rows) else None

    def ask(qids: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        asked = fits(x)
        qs, parts = np.flatnonzero(asked), [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
        if len(qs) and tiles is not None:
            at, row, dist = tiles.nearest(qids[qs], x[qs], exclude_self)
            parts.append((qs[at], rows[row], dist))
        for j in range(len(x)) if len(odd) else np.flatnonzero(~asked):
            left = odd if asked[j] else np.arange(len(ids))
            left = left[ids[left] != qids[j]] if exclude_self else left
            dist = distances("euclidean", vecs[left], x[j])
            by = np.lexsort((ids[left], dist))[:best]
            parts.append((np.full(len(by), j), left[by], dist[by]))
        at, row, dist = (np.concatenate(c) for c in zip(*parts))
        if len(parts) > 2:
            by = np.lexsort((ids[row], dist, at))
            by = by[np.arange(len(by)) - np.searchsorted(at[by], at[by]) < best]
            at, row, dist = at[by], row[by], dist[by]
        return at, row, dist

    return ask


def pair_distances(vecs: np.ndarray, rows: np.ndarray, x: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Euclidean distances of vecs[rows] from x[at]."""
    step = _Near.PAIRS
    return np.concatenate([np.zeros(0), *(np.sqrt(((vecs[rows[i : i + step]] - x[at[i : i + step]]) ** 2).sum(axis=1)) for i in range(0, len(rows), step))])


def data_cells(data: DataFrame, queries: DataFrame, prepare, best: int, fields: list) -> DataFrame | None:
    """Rows of prepare(ids, vectors, whole)(qids, query vectors), columns with `best` rows a query at most, where every part of data
    meets every part of the queries once; whole: a part is all data and no qid repeats. None where queries are few, so that data
    better stay where they are read."""
    if queries.limit(CELL_QUERIES_FROM + 1).count() <= CELL_QUERIES_FROM:
        return None
    asked, kinds = queries.agg(F.count("*"), F.count_distinct("qid")).first()
    n, d = data.agg(F.count("*"), F.max(F.size("vec"))).first()
    row = 8 + 8 * (d or 0)

    def pack(batches):
        for b in batches:
            for lo in range(0, b.num_rows, CELL_PIECE):
                part = b.slice(lo, CELL_PIECE)
                yield pa.RecordBatch.from_arrays([pa.array([part.num_rows], pa.int32()), *[pa.array([c], pa.binary()) for c in (part.column("obj_id").to_numpy().astype(np.int64).tobytes(), matrix(part.column("vec")).astype(np.float64).tobytes())]], names=["n", "ids", "vecs"])

    whole = n * row <= CELL_BYTES and kinds == asked

    def meet(shards, blocks):
        counts = shards.column("n").to_pylist()
        ids = np.concatenate([np.frombuffer(c.as_buffer(), np.int64) for c in shards.column("ids")])
        vecs = np.concatenate([_points(c.as_buffer(), b"", k) for c, k in zip(shards.column("vecs"), counts)])
        qids, x = (np.concatenate(c) for c in zip(*(_block(blocks, i)[:2] for i in range(blocks.num_rows))))
        ask, step = prepare(ids, vecs, whole), max(CELL_BLOCK, CELL_FOUND // 4 // best)
        for lo in range(0, len(qids), step):
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in ask(qids[lo : lo + step], x[lo : lo + step])], names=[f for f, _ in fields])

    packed = data.select("obj_id", F.col("vec").cast("array<double>").alias("vec")).mapInArrow(pack, "n int, ids binary, vecs binary")
    packed = packed.withColumn("shard", F.pmod(F.xxhash64("ids"), F.lit(1 << 30)).cast("int"))
    return _cells(packed, max(1, n), n, row, query_blocks(queries, matrix, block=CELL_BLOCK, hint=False), -(-asked // max(1, min(CELL_QUERIES, CELL_FOUND // best))), meet, fields)[0]


def _numbered(vecs: np.ndarray) -> np.ndarray:
    """The same number for equal rows."""
    raw = np.ascontiguousarray(vecs + 0.0).view(np.dtype((np.void, vecs.shape[1] * 8))).ravel()
    by = np.argsort(raw, kind="stable")
    out = np.empty(len(raw), np.int64)
    out[by] = np.cumsum(np.concatenate([[0], raw[by][1:] != raw[by][:-1]])) if len(raw) else 0
    return out


def _unsure(s: rotation.Shard, codes: np.ndarray, lo: np.ndarray, hi: np.ndarray, least: int, qs: np.ndarray, lens: np.ndarray) -> Iterator[tuple[int, slice, np.ndarray]]:
    """(query, its part of the pairs, its candidates as a mask of rows) where a pair's run is not long enough to be sure of.
    qs: query numbers of the pairs, in order; lens: their runs. Rows lo[j] to hi[j] are the query itself."""
    slots, known = None if s.table is None else s.slots(codes), {}
    ends = np.searchsorted(qs, np.arange(len(codes) + 1))
    for j in np.flatnonzero(ends[1:] > ends[:-1]):
        part = slice(ends[j], ends[j + 1])
        skip = (int(lo[j]), int(hi[j])) if hi[j] > lo[j] else None
        if slots is not None and s.with_run(slots[j], int(lens[part].min()), skip) <= least:
            continue
        name = (codes[j].tobytes(), skip)
        if (mask := known.get(name)) is None:
            if slots is not None:
                mask = s.among(slots[j], least, skip)
            else:
                rows, _ = s.scan([codes[j]], least + int(hi[j] - lo[j]))
                mask = np.zeros(s.n, bool)
                mask[rows[(rows < lo[j]) | (rows >= hi[j])][:least]] = True
            known[name] = mask
        yield j, part, mask


def _nearest_first(index: DataFrame, family: Family, blocks: DataFrame, least: int, k: int, size: int, metric: str, exclude_self: bool) -> tuple[DataFrame, DataFrame | None] | None:
    """(rows of every query's `size` nearest, qid, obj_id, run_len, dist and whether it is a candidate of its shard; qids that are
    left, without k candidates among as many rows, None if there are none), or None where qids repeat.

    Parts of the index meet parts of the blocks in cells for the nearest rows alone. Lists of a block are merged, and what is
    listed goes to its shard, where codes tell the candidates: every candidate that is not listed is farther than all that are.
    """
    def numbers(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(b"".join(b.column("q_ids").to_pylist()), np.int64))], names=["qid"])

    n, kinds = blocks.select("q_ids").mapInArrow(numbers, "qid long").agg(F.count("*"), F.count_distinct("qid")).first()
    if kinds < n or not n:
        return None
    none = np.zeros((0, 0), np.int32)
    pack = lambda name, kind, x: pa.array([np.ascontiguousarray(x, kind).tobytes()], pa.binary())
    lists = [("at", np.int32), ("shard", np.int32), ("row", np.int32), ("id", np.int64), ("dist", np.float64)]

    def meet(shards, asked):
        counts = shards.column("n").to_pylist()
        ids = np.concatenate([np.frombuffer(c.as_buffer(), np.int64) for c in shards.column("ids")])
        vecs = np.concatenate([_points(c.as_buffer(), b"", n) for c, n in zip(shards.column("vecs"), counts)])
        shard, row = np.repeat(shards.column("shard").to_numpy(), counts), np.concatenate([np.arange(n) for n in counts])
        blocks = [_block(asked, i)[:2] for i in range(asked.num_rows)]
        at, rows, dist = _Tiles(ids, vecs, metric, size).nearest(np.concatenate([q for q, _ in blocks]), np.concatenate([x for _, x in blocks]), exclude_self)
        ends = np.cumsum([0, *(len(q) for q, _ in blocks)])
        for i, (a, b) in enumerate(zip(*(np.searchsorted(at, e) for e in (ends[:-1], ends[1:])))):
            r = rows[a:b]
            cols = at[a:b] - ends[i], shard[r], row[r], ids[r], dist[a:b]
            yield pa.RecordBatch.from_arrays([pa.array([asked.column("q_ids")[i].as_py()], pa.binary()), *[pack(*f, c) for f, c in zip(lists, cols)]], names=["q_ids", *[f for f, _ in lists]])

    def merged(found: list) -> list[np.ndarray]:
        at, shard, row, ids, dist = (np.concatenate(c) for c in zip(*found))
        by = np.lexsort((ids, dist, at))
        by = by[np.arange(len(by)) - np.searchsorted(at[by], at[by]) < size]
        return [c[by] for c in (at, shard, row, ids, dist)]

    def deal(parts, asked):
        """Listed rows of a block by shard, with the codes of their queries."""
        qids, codes = np.frombuffer(asked.column("q_ids")[0].as_buffer(), np.int64), np.frombuffer(asked.column("q_codes")[0].as_buffer(), np.int32)
        codes = codes.reshape(len(qids), -1)
        at, shard, row, _, dist = merged([tuple(np.frombuffer(parts.column(f)[i].as_buffer(), t) for f, t in lists) for i in range(parts.num_rows)])
        by = np.argsort(shard, kind="stable")
        at, shard, row, dist = (c[by] for c in (at, shard, row, dist))
        first = np.flatnonzero(np.diff(shard, prepend=-1))
        for a, b in zip(first, np.append(first[1:], len(shard))):
            some, q = np.unique(at[a:b], return_inverse=True)
            cells = (("q_ids", np.int64, qids[some]), ("q_codes", np.int32, codes[some]), ("at", np.int32, q), ("row", np.int32, row[a:b]), ("dist", np.float64, dist[a:b]))
            yield pa.RecordBatch.from_arrays([pa.array([shard[a]], pa.int32()), *[pack(*c) for c in cells]], names=["shard", *[c[0] for c in cells]])

    def tell(shards, asked):
        count, m = shards.column("n")[0].as_py(), shards.column("m")[0].as_py()
        s = rotation.Shard(np.frombuffer(shards.column("ids")[0].as_buffer(), np.int64), np.frombuffer(shards.column("codes")[0].as_buffer(), np.int32).reshape(count, m), none, none)
        get = lambda c, t, i: np.frombuffer(asked.column(c)[i].as_buffer(), t)
        for i in range(asked.num_rows):
            qids, at, rows = get("q_ids", np.int64, i), get("at", np.int32, i), get("row", np.int32, i)
            codes = get("q_codes", np.int32, i).reshape(len(qids), m)
            lens, ok = s.pair_runs(rows, codes, at, _Near.PAIRS), np.ones(len(rows), bool)
            lo = np.searchsorted(s.ids, qids)
            for _, part, mask in _unsure(s, codes, lo, np.searchsorted(s.ids, qids, "right") if exclude_self else lo, least, at, lens):
                ok[part] = mask[rows[part]]
            yield pa.RecordBatch.from_arrays([pa.array(qids[at]), pa.array(s.ids[rows]), pa.array(lens.astype(np.int32)), pa.array(get("dist", np.float64, i)), pa.array(ok)], names=["qid", "obj_id", "run_len", "dist", "candidate"])

    wide = 8 * family.d
    fields = [(f, "binary") for f in ("q_ids", *[f for f, _ in lists])]
    found, _ = _cells(index.select("shard", "n", "ids", "vecs"), index.n_shards, index.n_rows, 8 + wide, blocks.select("q_n", "q_ids", "q_vecs", "q_offs", "q_alts", "q_scores"), -(-n * wide // CELL_BYTES), meet, fields)
    dealt = _met(found.groupBy("q_ids"), blocks.select("q_ids", "q_codes").groupBy("q_ids"), deal, [("shard", "int"), *[(f, "binary") for f in ("q_ids", "q_codes", "at", "row", "dist")]])
    # A shard is sent to as many tasks as its share of the lists asks for, and more where shards are few.
    copies = max(1, -(-n * size // (index.n_shards * CELL_LISTED)), -(-2 * index.sparkSession.sparkContext.defaultParallelism // index.n_shards))
    copy = F.explode(F.sequence(F.lit(0), F.lit(copies - 1))).alias("copy")
    left = index.select("shard", "n", "m", "ids", "codes", copy).groupBy("shard", "copy")
    right = dealt.withColumn("copy", F.pmod(F.xxhash64("q_ids"), F.lit(copies)).cast("int")).groupBy("shard", "copy")
    told = _met(left, right, tell, [("qid", "long"), ("obj_id", "long"), ("run_len", "int"), ("dist", "double"), ("candidate", "boolean")]).persist()
    left = told.groupBy("qid").agg(F.sum(F.col("candidate").cast("int")).alias("c"), F.count("*").alias("n")).where((F.col("c") < k) & (F.col("n") >= size)).select("qid")
    return told, None if left.isEmpty() else left


def search_work(index: DataFrame, family: Family, queries: DataFrame, lam: int, n_probes: int = 1, narrowed: bool = True, skip: bool = True, n_alt: int = 4) -> DataFrame:
    """(qid, steps, again, candidates): bisection steps, rotations searched again and candidates, summed over shards."""
    blocks = query_blocks(usable(queries, family), family.points, family.d is None, family, n_alt if n_probes > 1 else 0)

    def visit(batches):
        for b in batches:
            for i in range(b.num_rows):
                s, _ = _unpack(b, i)
                qids, _, codes, other = _block(b, i, s.m)
                rows = []
                for j in range(len(qids)):
                    s.steps = 0
                    if other is None:
                        found, again = rotation.k_search_rows(s, codes[j], lam, False, narrowed)[0], 0
                    else:
                        found, _, again = probe.search_rows(s, codes[j], other[0][j], other[1][j], lam, n_probes, skip=skip)
                    rows.append((s.steps, again, len(found)))
                yield pa.RecordBatch.from_arrays([pa.array(qids), *[pa.array([r[c] for r in rows], pa.int64()) for c in range(3)]], names=["qid", "steps", "again", "candidates"])

    work = index.join(blocks, F.lit(True)).mapInArrow(visit, "qid long, steps long, again long, candidates long")
    return work.groupBy("qid").agg(*[F.sum(c).alias(c) for c in ("steps", "again", "candidates")])


def search_bounds(index: DataFrame, family: Family, queries: DataFrame, narrowed: bool = True) -> DataFrame:
    """(qid, shard, rot, lower, upper, lower_len, upper_len): neighbours of the query in each rotation, null where there is none."""
    blocks = query_blocks(usable(queries, family), family.points, family.d is None, family)

    def visit(batches):
        for b in batches:
            for i in range(b.num_rows):
                s, _ = _unpack(b, i)
                qids, _, codes, _ = _block(b, i, s.m)
                for j in range(len(qids)):
                    at = rotation.bounds(s, codes[j], narrowed)
                    low = [int(s.ids[s.order[r, x]]) if x >= 0 else None for r, x in enumerate(at[:, 0])]
                    up = [int(s.ids[s.order[r, x]]) if x < s.n else None for r, x in enumerate(at[:, 1])]
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(s.m, qids[j])), pa.array(np.full(s.m, b.column("shard")[i].as_py(), np.int32)), pa.array(np.arange(s.m, dtype=np.int32)), pa.array(low, pa.int64()), pa.array(up, pa.int64()), pa.array(at[:, 2].astype(np.int32)), pa.array(at[:, 3].astype(np.int32))], names=["qid", "shard", "rot", "lower", "upper", "lower_len", "upper_len"])

    return index.join(blocks, F.lit(True)).mapInArrow(visit, "qid long, shard int, rot int, lower long, upper long, lower_len int, upper_len int")


def theory_lambda(index: DataFrame, family: Family, r: float, c: float) -> int:
    """Candidates that the guarantee asks for, from the family's collision probabilities and the index's size."""
    n = index.agg(F.sum("n")).first()[0] or 0
    p1, p2, _ = family.sensitivity(r, c)
    return theory.lambda_guarantee(family.m, max(1, n), p1, p2)


def decide(index: DataFrame, family: Family, queries: DataFrame, r: float, c: float, lam: int | str = "theory", exclude_self: bool = False) -> DataFrame:
    """(qid, obj_id, dist), null where nothing is found within c * r: the (R, c) decision, by default with the guarantee's candidates."""
    lam = theory_lambda(index, family, r, c) if lam == "theory" else lam
    return near_neighbor(ring_search(index, family, queries, lam, 1, exclude_self=exclude_self), queries, r, c)


def ring_knn_graph(data: DataFrame, family: Family, lam: int, k: int, shard_rows: int = SHARD_ROWS, shard: Column | None = None, **how) -> DataFrame:
    """(qid, rnk, obj_id, dist): for every object its k nearest others through the ring index."""
    index = build_index(data, family, shard_rows, shard=shard)
    return ring_search(index, family, data.withColumnRenamed("obj_id", "qid"), lam, k, exclude_self=True, **how).drop("run_len")


def ring_pairs(data: DataFrame, family: Family, lam: int, k: int, max_dist: float, **how) -> DataFrame:
    """(a, b, dist), a < b: pairs within max_dist that the graph holds from either side."""
    near = ring_knn_graph(data, family, lam, k, **how).where(F.col("dist") <= max_dist)
    return near.select(F.least("qid", "obj_id").alias("a"), F.greatest("qid", "obj_id").alias("b"), "dist").dropDuplicates(["a", "b"])


def ann_join(left: DataFrame, right: DataFrame, family: Family, lam: int, k: int, where: Column | None = None, selectivity: float = 1.0, **how) -> DataFrame:
    """Similarity join of left(qid, vec) with right(obj_id, vec): each left row's k nearest right rows that meet `where`.

    `where` may name qid, obj_id and dist; lam grows by 1 / selectivity, so that as many candidates are left after it.
    """
    lam = max(1, round(lam / selectivity))
    return ring_search(build_index(right, family), family, left, lam, k, where=where, **how).drop("run_len")


def near_neighbor(result: DataFrame, queries: DataFrame, r: float, c: float) -> DataFrame:
    """The (R, c) decision from a k=1 search: the object found within c * r, else null."""
    hit = result.where((F.col("rnk") == 1) & (F.col("dist") <= c * r)).select("qid", "obj_id", "dist")
    return queries.select("qid").join(hit, "qid", "left")


def ladder_search(indexes: list[tuple[DataFrame, Family]], queries: DataFrame, r0: float, c: float, lam: int | str, exclude_self: bool = False) -> DataFrame:
    """(qid, level, obj_id, dist): per query the first radius r0 * c^level at which the decision finds an object.

    indexes has one (index, family) for every level; a level asks only the queries that all before have left open.
    """
    out, open_ = None, queries
    for level, (index, family) in enumerate(indexes):
        r = r0 * c**level
        found = decide(index, family, open_, r, c, lam, exclude_self).where("obj_id IS NOT NULL").withColumn("level", F.lit(level)).select("qid", "level", "obj_id", "dist").persist()
        out = found if out is None else out.union(found)
        open_ = open_.join(found.select("qid"), "qid", "left_anti")
        if open_.isEmpty():
            break
    return out


def shared_ladder(index: DataFrame, family: Family, queries: DataFrame, r0: float, c: float, levels: int, lam: int, exclude_self: bool = False) -> DataFrame:
    """ladder_search with one index for all radii, for families whose quality is bounded at each of them.

    The nearest candidate is the same at every level, so one search decides all.
    """
    name = "cross_polytope" if type(family).__name__ == "CrossPolytope" else type(family).__name__
    if not theory.shareable(name, c, [r0 * c**i for i in range(levels)]):
        raise ValueError("the family needs an index for every radius")
    found = ring_search(index, family, queries, lam, 1, exclude_self=exclude_self)
    level = F.greatest(F.lit(0), F.ceil(F.log(F.col("dist") / (r0 * c)) / F.log(F.lit(c)) - 1e-12)).cast("int")
    level = F.when(F.col("dist") <= c * r0, 0).otherwise(level)
    return found.withColumn("level", level).where(F.col("level") < levels).select("qid", "level", "obj_id", "dist")


def k_search_brute(codes: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """Definition of k-search: run lengths of all pairs. For tests and small data; queries are broadcast if few."""
    q = broadcast_queries(queries.select("qid", F.col("codes").alias("qcodes")))
    pairs = codes.select("obj_id", "codes").join(q, F.lit(True)).withColumn("run_len", runs.run_len(F.col("codes"), F.col("qcodes")))
    return top_k(pairs.select("qid", "obj_id", "run_len"), k, [F.col("run_len").desc(), "obj_id"]).select("qid", "rnk", "obj_id", "run_len")


def rotation_table(codes: DataFrame, m: int) -> DataFrame:
    """(rot, rank, obj_id, next_rank), declaratively: for checks at small n."""
    from pyspark.sql import Window

    long = codes.select("obj_id", F.explode(F.sequence(F.lit(0), F.lit(m - 1))).alias("rot"), "codes").select("obj_id", "rot", runs.rotate(F.col("codes"), F.col("rot")).alias("s"))
    ranked = long.withColumn("rank", F.row_number().over(Window.partitionBy("rot").orderBy("s", "obj_id"))).select("rot", "rank", "obj_id")
    nxt = ranked.select(F.pmod(F.col("rot") - 1, F.lit(m)).alias("rot"), F.col("rank").alias("next_rank"), "obj_id")
    return ranked.join(nxt, ["rot", "obj_id"]).select("rot", "rank", "obj_id", "next_rank")


def k_search_window(codes: DataFrame, queries: DataFrame, m: int, k: int, shards: int = 1) -> DataFrame:
    """(qid, rnk, obj_id, run_len) from the k neighbours of every query on both sides of each rotation's order.

    Objects and queries of a rotation are ranked together in one window per shard, and neighbours meet by an
    equi-join on ranks. Among objects of the same run length any may be taken.
    """
    from pyspark.sql import Window

    every = F.explode(F.sequence(F.lit(0), F.lit(m - 1)))
    data = codes.select(F.pmod(F.xxhash64("obj_id"), F.lit(shards)).alias("part"), "obj_id", "codes", every.alias("rot"))
    asked = queries.select(F.explode(F.sequence(F.lit(0).cast("long"), F.lit(shards - 1).cast("long"))).alias("part"), F.col("qid").alias("obj_id"), "codes", F.sequence(F.lit(0), F.lit(m - 1)).alias("r")).select("part", "obj_id", "codes", F.explode("r").alias("rot"))
    both = data.withColumn("kind", F.lit(0)).unionByName(asked.withColumn("kind", F.lit(1))).withColumn("s", runs.rotate(F.col("codes"), F.col("rot")))
    order = Window.partitionBy("part", "rot").orderBy("s", "kind", "obj_id").rowsBetween(Window.unboundedPreceding, 0)
    ranked = both.withColumn("pos", F.sum(1 - F.col("kind")).over(order))
    sought = ranked.where("kind = 1").select("part", "rot", F.col("obj_id").alias("qid"), F.col("codes").alias("qcodes"), F.explode(F.sequence(F.col("pos") - k + 1, F.col("pos") + k)).alias("pos"))
    met = ranked.where("kind = 0").select("part", "rot", "pos", "obj_id", "codes").join(sought, ["part", "rot", "pos"]).dropDuplicates(["qid", "obj_id"])
    met = met.select("qid", "obj_id", runs.run_len(F.col("codes"), F.col("qcodes")).alias("run_len"))
    return top_k(met, k, [F.col("run_len").desc(), "obj_id"]).select("qid", "rnk", "obj_id", "run_len")


def k_search_prefix(codes: DataFrame, queries: DataFrame, m: int, k: int) -> DataFrame:
    """k-search as equi-joins on hashed prefixes of rotations: per query the longest prefix that k objects share.

    Bisects the prefix length in at most ceil(log2 m) + 1 rounds; a round joins unsolved queries only, at their own
    length, and its state of two numbers per query is a written table. Hashes only select: prefixes are compared.
    """
    def spread(df, ident, name):
        return df.select(ident, F.col("codes").alias(name), F.explode(F.sequence(F.lit(0), F.lit(m - 1))).alias("rot")).withColumn(f"{name}_s", runs.rotate(F.col(name), F.col("rot")))

    data, asked = spread(codes, "obj_id", "codes"), broadcast_queries(spread(queries, "qid", "qcodes"))
    key = lambda s: F.xxhash64(F.slice(s, F.lit(1), F.col("l")))

    def matches(state):
        """(qid, obj_id, codes, qcodes): objects that share the first l symbols with the query in some rotation."""
        right = asked.join(broadcast_queries(state), "qid").withColumn("p", key("qcodes_s"))
        lengths = broadcast_queries(state.select("l").distinct())
        left = data.join(lengths, F.lit(True)).withColumn("p", key("codes_s"))
        met = left.join(right, ["rot", "l", "p"]).where(F.slice("codes_s", F.lit(1), F.col("l")) == F.slice("qcodes_s", F.lit(1), F.col("l")))
        return met.select("qid", "obj_id", "codes", "qcodes")

    state = queries.select("qid", F.lit(0).alias("lo"), F.lit(m).alias("hi"))
    while not (busy := state.where("lo < hi")).isEmpty():
        mid = busy.withColumn("l", F.ceil((F.col("lo") + F.col("hi")) / 2).cast("int"))
        hits = matches(mid.select("qid", "l")).groupBy("qid").agg(F.count_distinct("obj_id").alias("c"))
        ok = F.coalesce(F.col("c"), F.lit(0)) >= k
        new = mid.join(hits, "qid", "left").select("qid", F.when(ok, F.col("l")).otherwise(F.col("lo")).alias("lo"), F.when(ok, F.col("hi")).otherwise(F.col("l") - 1).alias("hi"))
        state = stage(new.union(state.where("lo >= hi")))
    close = matches(state.where("lo > 0").select("qid", F.col("lo").alias("l")))
    # Where fewer than k objects share a symbol, all that do so count, and the smallest ids fill up.
    rest = state.where("lo = 0").select("qid")
    some = matches(rest.withColumn("l", F.lit(1)))
    fill = codes.select("obj_id", "codes").orderBy("obj_id").limit(2 * k)
    fill = broadcast_queries(rest.join(queries.select("qid", F.col("codes").alias("qcodes")), "qid")).join(F.broadcast(fill), F.lit(True)).select("qid", "obj_id", "codes", "qcodes")
    close = close.union(some).union(fill).dropDuplicates(["qid", "obj_id"])
    close = close.select("qid", "obj_id", runs.run_len(F.col("codes"), F.col("qcodes")).alias("run_len"))
    return top_k(close, k, [F.col("run_len").desc(), "obj_id"]).select("qid", "rnk", "obj_id", "run_len")


def exact_knn(data: DataFrame, queries: DataFrame, k: int, metric: str = "euclidean", exclude_self: bool = False) -> DataFrame:
    """(qid, rnk, obj_id, dist) over all data: the ground truth. Data is packed batch by batch where it is read,
    and a batch keeps k per query before the shuffle. Many queries meet parts of data in cells instead."""
    sets = metric == "jaccard"
    points = Sets.of if sets else matrix
    kind = "array<long>" if sets else "array<double>"
    good = F.col("vec").isNotNull() & ~F.exists("vec", lambda x: x.isNull())
    data, queries = data.where(good), queries.where(good)
    if metric == "angular":
        some = F.exists("vec", lambda x: x != 0)
        data, queries = data.where(some), queries.where(some)

    def pack(batches):
        for b in batches:
            step = SET_ROWS if sets else max(1, b.num_rows)
            for lo in range(0, b.num_rows, step):
                part = b.slice(lo, step)
                raw, offs = _bytes(points(part.column("vec")))
                yield pa.RecordBatch.from_arrays([pa.array([part.num_rows], pa.int32()), *[pa.array([c], pa.binary()) for c in (part.column("obj_id").to_numpy().astype(np.int64).tobytes(), raw, offs)]], names=["n", "ids", "vecs", "offs"])

    def scan(batches):
        for b in batches:
            for i in range(b.num_rows):
                ids = np.frombuffer(b.column("ids")[i].as_buffer(), np.int64)
                x = _points(b.column("vecs")[i].as_buffer(), b.column("offs")[i].as_buffer(), len(ids))
                qids, q, _, _ = _block(b, i)
                take = min(len(ids), k + exclude_self)
                cols: list[list] = [[], [], []]
                every = jaccard_distances(x, q) if sets else None
                for j in range(len(qids)):
                    d = distances(metric, x, q[j]) if every is None else every[j]
                    near = np.lexsort((ids, d))[:take]
                    cols[0].append(np.full(take, qids[j])), cols[1].append(ids[near]), cols[2].append(d[near])
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in cols], names=["qid", "obj_id", "dist"])

    def prepare(ids, x, whole):
        nearest = nearest_in(ids, x, k, exclude_self)

        def ask(qids, q):
            at, rows, dist = nearest(qids, q)
            return qids[at], ids[rows], dist

        return ask

    if metric == "euclidean" and (out := data_cells(data, queries, prepare, k, [("qid", "long"), ("obj_id", "long"), ("dist", "double")])) is not None:
        return top_k(out, k, ["dist", "obj_id"]).select("qid", "rnk", "obj_id", "dist")
    packed = data.select("obj_id", F.col("vec").cast(kind).alias("vec")).mapInArrow(pack, "n int, ids binary, vecs binary, offs binary")
    out = packed.join(query_blocks(queries, points, sets), F.lit(True)).mapInArrow(scan, "qid long, obj_id long, dist double")
    if exclude_self:
        out = out.where("qid <> obj_id")
    return top_k(out, k, ["dist", "obj_id"]).select("qid", "rnk", "obj_id", "dist")


def verify_pairs(cands: DataFrame, data: DataFrame, queries: DataFrame, k: int, metric: str, exclude_self: bool = False) -> DataFrame:
    """Nearest k of cands(qid, obj_id) by true distance; vectors are read only here."""
    if metric not in DISTANCES:
        raise ValueError(f"unknown metric {metric}")
    kind = "array<long>" if metric == "jaccard" else "array<double>"
    x = data.select("obj_id", F.col("vec").cast(kind).alias("vec"))
    q = broadcast_queries(queries.select("qid", F.col("vec").cast(kind).alias("qvec")))
    if exclude_self:
        cands = cands.where("qid <> obj_id")
    both = cands.select("qid", "obj_id").join(x, "obj_id").join(q, "qid")
    return top_k(both.select("qid", "obj_id", DISTANCES[metric](F.col("vec"), F.col("qvec")).alias("dist")), k, ["dist", "obj_id"]).select("qid", "rnk", "obj_id", "dist")
