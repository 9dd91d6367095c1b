"""Rival search frameworks, each as a candidate generator followed by the same verification.

Counting frameworks compare each batch of data with blocks of queries in place: only candidates leave a batch, with
their distance, so that no colliding pair is shuffled.

Edge cases are those of `search`: unusable vectors are left out, ties go by obj_id, empty inputs give empty results.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ringann.functions import theory
from ringann.functions.runs import equal_positions
from ringann.functions.vectors import euclidean
from ringann.operators.families import Family, encode, matrix, usable, valid_vectors
from ringann.operators.probe import perturbations
from ringann.operators.search import _block, data_cells, distances, nearest_in, pair_distances, query_blocks, verify_pairs
from ringann.operators.topk import broadcast_queries, top_k


def _buckets(codes: DataFrame, k: int, tables: int) -> DataFrame:
    """One row per table: (ident..., tbl, bucket) of k codes each."""
    return codes.withColumn("tbl", F.explode(F.sequence(F.lit(0), F.lit(tables - 1)))).withColumn("bucket", F.slice("codes", F.col("tbl") * k + 1, k)).drop("codes")


def static_concat(data: DataFrame, family: Family, queries: DataFrame, k_concat: int, tables: int, k: int, exclude_self: bool = False) -> DataFrame:
    """`tables` hash tables of k_concat concatenated codes; candidates share a bucket with the query."""
    data, queries = usable(data, family), usable(queries, family)
    left = _buckets(encode(data, family, False), k_concat, tables)
    right = broadcast_queries(_buckets(encode(queries, family, False), k_concat, tables))
    cands = left.join(right, ["tbl", "bucket"]).select("qid", "obj_id").distinct()
    return verify_pairs(cands, data, queries, k, family.metric, exclude_self)


def prefix_widening(data: DataFrame, family: Family, queries: DataFrame, k_concat: int, tables: int, k: int, least: int, exclude_self: bool = False) -> DataFrame:
    """static_concat with buckets of the longest prefix, k_concat codes at most, for which a query has `least` candidates or more.

    A level joins only the queries that longer prefixes left open; a query with fewer candidates at every length
    takes those of a single code.
    """
    data, queries = usable(data, family).persist(), usable(queries, family)
    left, right = encode(data, family, False), encode(queries, family, False)
    open_, found = queries.select("qid"), None
    for size in range(k_concat, 0, -1):
        cut = lambda df: _buckets(df, k_concat, tables).withColumn("bucket", F.slice("bucket", 1, size))  # noqa: E731, B023
        cands = cut(left).join(broadcast_queries(cut(right.join(open_, "qid", "left_semi"))), ["tbl", "bucket"]).select("qid", "obj_id").distinct()
        cands = cands.where("qid <> obj_id") if exclude_self else cands
        enough = cands.groupBy("qid").agg(F.count("*").alias("n")).where(F.col("n") >= (least if size > 1 else 1)).select("qid").persist()
        part = cands.join(broadcast_queries(enough), "qid", "left_semi")
        found = part if found is None else found.union(part)
        open_ = open_.join(enough, "qid", "left_anti")
    return verify_pairs(found, data, queries, k, family.metric, exclude_self)


def static_probe_keys(codes: np.ndarray, alt: np.ndarray, scores: np.ndarray, k_concat: int, tables: int, n_probes: int) -> list[tuple[int, list[int]]]:
    """(table, bucket) keys in ascending score per table; alternatives of every position may combine."""
    out = []
    for t in range(tables):
        at = slice(t * k_concat, (t + 1) * k_concat)
        for delta, _ in perturbations(scores[at], n_probes, max_gap=k_concat):
            key = codes[at].copy()
            for pos, a in delta:
                key[pos] = alt[at][pos, a]
            out.append((t, [int(v) for v in key]))
    return out


def multiprobe_static(data: DataFrame, family: Family, queries: DataFrame, k_concat: int, tables: int, k: int, n_probes: int, n_alt: int = 2, exclude_self: bool = False) -> DataFrame:
    """static_concat with extra buckets per table: neighbouring slots, or further vertices for cross-polytopes."""
    data, queries = usable(data, family), usable(queries, family)

    def keys(batches):
        for b in batches:
            x = matrix(b.column("vec"))
            if not len(x):
                continue
            codes, (alt, scores) = family.codes(x), family.alternatives(x, n_alt)
            rows = [(q, t, key) for i, q in enumerate(b.column("qid").to_pylist()) for t, key in static_probe_keys(codes[i], alt[i], scores[i], k_concat, tables, n_probes)]
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.list_(pa.int32()))], names=["qid", "tbl", "bucket"])

    right = broadcast_queries(queries.select("qid", F.col("vec").cast("array<double>").alias("vec")).mapInArrow(keys, "qid long, tbl int, bucket array<int>"))
    cands = _buckets(encode(data, family, False), k_concat, tables).join(right, ["tbl", "bucket"]).select("qid", "obj_id").distinct()
    return verify_pairs(cands, data, queries, k, family.metric, exclude_self)


def _by_level(data: DataFrame, queries: DataFrame, prepare: Callable, level_of: Callable, levels: int, metric: str, k: int, exclude_self: bool) -> DataFrame:
    """(qid, rnk, obj_id, dist, level): the k nearest candidates at the first level with k candidates or more, else at the last.

    prepare(x) projects a batch once, level_of(projected batch, projected query) gives each object's first level,
    `levels` or more for none. A batch sends what it has up to the level at which it alone has enough.
    """

    def scan(batches):
        for b in batches:
            for i in range(b.num_rows):
                ids = np.frombuffer(b.column("ids")[i].as_buffer(), np.int64)
                x = np.frombuffer(b.column("vecs")[i].as_buffer(), np.float64).reshape(len(ids), -1)
                qids, q, _, _ = _block(b, i)
                px, pq = prepare(x), prepare(q)
                cols: list[list] = [[], [], [], []]
                for j in range(len(qids)):
                    at = level_of(px, pq[j])
                    if exclude_self:
                        at = np.where(ids == qids[j], levels, at)
                    known = np.cumsum(np.bincount(np.minimum(at, levels), minlength=levels + 1)[:levels])
                    stop = min(int(np.searchsorted(known, k)), levels - 1)
                    rows = np.flatnonzero(at <= stop)
                    dist = distances(metric, x[rows], q[j])
                    if levels == 1:
                        near = np.lexsort((ids[rows], dist))[:k]
                        rows, dist = rows[near], dist[near]
                    cols[0].append(np.full(len(rows), qids[j])), cols[1].append(ids[rows]), cols[2].append(at[rows].astype(np.int32)), cols[3].append(dist)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in cols], names=["qid", "obj_id", "level", "dist"])

    def pack(batches):
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([pa.array([c], pa.binary()) for c in (b.column("obj_id").to_numpy().astype(np.int64).tobytes(), matrix(b.column("vec")).tobytes())], names=["ids", "vecs"])

    packed = data.select("obj_id", F.col("vec").cast("array<double>").alias("vec")).mapInArrow(pack, "ids binary, vecs binary")
    found = packed.join(query_blocks(queries, matrix), F.lit(True)).mapInArrow(scan, "qid long, obj_id long, level int, dist double")
    if levels > 1:
        w = Window.partitionBy("qid").orderBy("level")
        sums = found.groupBy("qid", "level").agg(F.count("*").alias("n")).withColumn("n", F.sum("n").over(w))
        stop = sums.groupBy("qid").agg(F.coalesce(F.min(F.when(F.col("n") >= k, F.col("level"))), F.lit(levels - 1)).alias("stop"))
        found = found.join(stop, "qid").where("level <= stop").select("qid", "obj_id", F.col("stop").alias("level"), "dist")
    return top_k(found, k, ["dist", "obj_id"]).select("qid", "rnk", "obj_id", "dist", "level")


def collision_count(data: DataFrame, family: Family, queries: DataFrame, threshold: int, k: int, c: int = 2, levels: int = 1, exclude_self: bool = False) -> DataFrame:
    """Candidates have `threshold` equal codes or more. With levels, slots c^level wide are tried until a query has k candidates."""

    def level_of(x, q):
        at = np.full(len(x), levels)
        for level in range(levels - 1, -1, -1):
            wide = c**level
            at[(x // wide == q // wide).sum(axis=1) >= threshold] = level
        return at

    return _by_level(usable(data, family), usable(queries, family), family.codes, level_of, levels, family.metric, k, exclude_self).drop("level")


def touched(data: DataFrame, family: Family, queries: DataFrame, exclude_self: bool = False) -> DataFrame:
    """(qid, touched): objects with one equal code or more."""
    codes = lambda df, ident: encode(usable(df, family), family, False).select(ident, "codes")
    q = broadcast_queries(codes(queries, "qid").withColumnRenamed("codes", "q"))
    pairs = codes(data, "obj_id").join(q, F.col("qid") != F.col("obj_id") if exclude_self else F.lit(True))
    return pairs.groupBy("qid").agg(F.sum((equal_positions(F.col("codes"), F.col("q")) > 0).cast("long")).alias("touched"))


def _gaussian(d: int, m: int, seed: int) -> np.ndarray:
    return np.random.Generator(np.random.Philox(seed)).standard_normal((d, m))


def query_aware_count(data: DataFrame, queries: DataFrame, d: int, m: int, width: float, threshold: int, k: int, c: float = 2.0, levels: int = 1, seed: int = 0, exclude_self: bool = False) -> DataFrame:
    """Candidates lie within width / 2 of the query in `threshold` projections or more; with levels the width grows by c until a query has k."""
    a = _gaussian(d, m, seed)
    edges = np.array([width * c**i / 2 for i in range(levels)])

    def level_of(y, q):
        return np.searchsorted(edges, np.partition(np.abs(y - q), threshold - 1, axis=1)[:, threshold - 1])

    data, queries = (valid_vectors(df, d)[0] for df in (data, queries))
    return _by_level(data, queries, lambda x: x @ a, level_of, levels, "euclidean", k, exclude_self).drop("level")


def projected_incremental(data: DataFrame, queries: DataFrame, d: int, dims: int, budget: int, k: int, c: float = 2.0, p_tau: float | None = None, seed: int = 0, exclude_self: bool = False) -> DataFrame:
    """Visits objects by distance in a Gaussian projection of `dims` dimensions, `budget` at most per query.

    With p_tau a query stops early: an object whose projected distance makes it unlikely, by the chi-square
    tail, that anything behind it beats the k-th distance so far divided by c is not visited.
    """
    a = _gaussian(d, dims, seed)
    data, queries = (valid_vectors(df, d)[0] for df in (data, queries))

    def project(x):
        """x @ a, added up in one order, so that equal vectors stay equal."""
        y = np.zeros((len(x), dims))
        for i in range(d):
            y += x[:, i : i + 1] * a[i]
        return y

    def prepare(ids, x, whole):
        nearest = nearest_in(ids, project(x), budget, exclude_self)

        def ask(qids, q):
            at, rows, far = nearest(qids, project(q))
            dist = pair_distances(x, rows, q, at)
            if whole and p_tau is None:  # all that a query visits is here
                by = np.lexsort((ids[rows], dist, at))
                by = by[np.arange(len(by)) - np.searchsorted(at[by], at[by]) < k]
                at, rows, far, dist = at[by], rows[by], far[by], dist[by]
            return qids[at], ids[rows], far, dist

        return ask

    def pack(batches):
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([pa.array([v], pa.binary()) for v in (b.column("obj_id").to_numpy().astype(np.int64).tobytes(), matrix(b.column("vec")).tobytes())], names=["ids", "vecs"])

    def scan(batches):
        for b in batches:
            for i in range(b.num_rows):
                ids = np.frombuffer(b.column("ids")[i].as_buffer(), np.int64)
                x = np.frombuffer(b.column("vecs")[i].as_buffer(), np.float64).reshape(len(ids), -1)
                qids, q, _, _ = _block(b, i)
                y, py = project(x), project(q)
                cols: list[list] = [[], [], [], []]
                for j in range(len(qids)):
                    far = distances("euclidean", y, py[j])
                    near = np.lexsort((ids, far))[: budget + exclude_self]
                    cols[0].append(np.full(len(near), qids[j])), cols[1].append(ids[near]), cols[2].append(far[near]), cols[3].append(distances("euclidean", x[near], q[j]))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(v)) for v in cols], names=["qid", "obj_id", "pdist", "dist"])

    out = data_cells(data, queries, prepare, budget, [("qid", "long"), ("obj_id", "long"), ("pdist", "double"), ("dist", "double")])
    if out is None:
        packed = data.select("obj_id", F.col("vec").cast("array<double>").alias("vec")).mapInArrow(pack, "ids binary, vecs binary")
        out = packed.join(query_blocks(queries, matrix), F.lit(True)).mapInArrow(scan, "qid long, obj_id long, pdist double, dist double")
        if exclude_self:
            out = out.where("qid <> obj_id")
    seen = top_k(out, budget, ["pdist", "obj_id"], rank="visit")
    if p_tau is not None:
        limit = stop_limit(dims, p_tau)

        def walk(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            t = pa.Table.from_batches(batches).sort_by("visit")
            far, dist = t["pdist"].to_numpy(), t["dist"].to_numpy()
            best: list[float] = []  # the k nearest so far, ascending
            stop = len(dist)
            for i in range(len(dist)):
                if len(best) == k and (far[i] * c / best[-1] if best[-1] > 0 else np.inf) ** 2 >= limit:
                    stop = i
                    break
                best = sorted([*best, dist[i]])[:k]
            yield from t.slice(0, stop).to_batches()

        seen = seen.select("qid", "obj_id", "pdist", "dist", "visit").groupBy("qid").applyInArrow(walk, "qid long, obj_id long, pdist double, dist double, visit int")
    return top_k(seen, k, ["dist", "obj_id"]).select("qid", "rnk", "obj_id", "dist")


def stop_limit(dims: int, p_tau: float) -> float:
    """Least hundredth at which the chi-square distribution with `dims` degrees reaches p_tau."""
    return next(x / 100 for x in range(1, 100_000) if theory.gamma_cdf(dims, x / 100) >= p_tau)


def _medians(placed: DataFrame, at) -> DataFrame:
    """(block, cut): the exact discrete median, the least value up to which half of the rows lie.

    Two approximate quantiles enclose it, and only the values between them are counted one by one.
    """
    ends = placed.groupBy("block").agg(F.percentile_approx(at, F.array(F.lit(0.499), F.lit(0.501)), 10000).alias("ends"), F.count(at).alias("all"))
    near = placed.select("block", at.alias("v")).join(F.broadcast(ends), "block").where(F.col("v") <= F.col("ends")[1])
    counts = near.withColumn("v", F.when(F.col("v") >= F.col("ends")[0], F.col("v"))).groupBy("block", "v").agg(F.count("*").alias("n"), F.first("all").alias("all"))
    upto = counts.withColumn("upto", F.sum("n").over(Window.partitionBy("block").orderBy(F.col("v").asc_nulls_first())))
    return upto.where((2 * F.col("upto") >= F.col("all")) & F.col("v").isNotNull()).groupBy("block").agg(F.min("v").alias("cut"))


def median_blocks(data: DataFrame, d: int, depth: int) -> DataFrame:
    """data with `block`: halved `depth` times at the median, within each block, of one coordinate after the other."""
    placed = data.withColumn("block", F.lit(0))
    for level in range(depth):
        at = F.get("vec", F.lit(level % d)).cast("double")
        placed = placed.join(F.broadcast(_medians(placed, at)), "block").withColumn("block", F.col("block") * 2 + (at > F.col("cut")).cast("int")).drop("cut")
    return placed


def boundary_objects(placed: DataFrame, d: int, projections: int, per: int, seed: int = 0) -> DataFrame:
    """(block, obj_id, vec): of each block and projection `per` objects, evenly spaced in projected order from the first to the last."""
    a = _gaussian(d, projections, seed)

    def project(batches):
        for b in batches:
            if b.num_rows:
                y = matrix(b.column("vec")) @ a
                yield pa.RecordBatch.from_arrays([b.column("block"), b.column("obj_id"), b.column("vec"), pa.ListArray.from_arrays(pa.array(np.arange(len(y) + 1) * projections, pa.int32()), pa.array(y.ravel()))], names=["block", "obj_id", "vec", "y"])

    long = placed.select("block", "obj_id", F.col("vec").cast("array<double>").alias("vec")).mapInArrow(project, "block int, obj_id long, vec array<double>, y array<double>")
    long = long.select("block", "obj_id", "vec", F.posexplode("y").alias("j", "y"))
    line = Window.partitionBy("block", "j")
    ranked = long.withColumns({"r": F.row_number().over(line.orderBy("y", "obj_id")) - 1, "n": F.count("*").over(line)})
    spots = F.transform(F.sequence(F.lit(0), F.lit(per - 1)), lambda i: F.floor(i * (F.col("n") - 1) / F.lit(max(1, per - 1))))
    return ranked.where(F.array_contains(spots, F.col("r").cast("long"))).select("block", "obj_id", "vec").dropDuplicates(["block", "obj_id"])


def query_aware_blocked(data: DataFrame, queries: DataFrame, d: int, m: int, width: float, threshold: int, k: int, leaf: int, projections: int, per: int, near_blocks: int, seed: int = 0, exclude_self: bool = False, halvings: int | None = None) -> DataFrame:
    """query_aware_count on few blocks per query: blocks have about `leaf` objects, or are as many as
    `halvings` make, are represented by boundary objects, and a query takes the near_blocks whose nearest boundary
    object is the nearest. Only these are read, in parts of some 20,000 objects."""
    data, queries = (valid_vectors(df, d)[0] for df in (data, queries))
    n = data.count()
    depth = max(0, int(np.ceil(np.log2(max(1, n) / leaf)))) if halvings is None else halvings
    parts = max(1, -(-n // (20_000 << depth)))
    placed = median_blocks(data.select("obj_id", F.col("vec").cast("array<double>").alias("vec")), d, depth)
    edge = boundary_objects(placed, d, projections, per, seed).select("block", F.col("vec").alias("bvec"))
    asked = queries.select("qid", F.col("vec").cast("array<double>").alias("vec"))
    far = edge.join(broadcast_queries(asked), F.lit(True)).groupBy("qid", "block").agg(F.min(euclidean(F.col("vec"), F.col("bvec"))).alias("far"))
    close = top_k(far, near_blocks, ["far", "block"]).select("qid", "block")
    a = _gaussian(d, m, seed)

    def count(key, left: pa.Table, right: pa.Table) -> pa.Table:
        cols: list[list] = [[], [], []]
        if left.num_rows and right.num_rows:
            ids, x, q = left["obj_id"].to_numpy(), matrix(left["vec"].combine_chunks()), matrix(right["vec"].combine_chunks())
            y, py, qids = x @ a, q @ a, right["qid"].to_numpy()
            for j in range(len(qids)):
                rows = np.flatnonzero(((np.abs(y - py[j]) <= width / 2).sum(axis=1) >= threshold) & ~(exclude_self & (ids == qids[j])))
                dist = distances("euclidean", x[rows], q[j])
                by = np.lexsort((ids[rows], dist))[:k]
                cols[0].append(np.full(len(by), qids[j])), cols[1].append(ids[rows][by]), cols[2].append(dist[by])
        kinds = (pa.int64(), pa.int64(), pa.float64())
        return pa.table({n: pa.array(np.concatenate(c) if c else [], t) for n, c, t in zip(("qid", "obj_id", "dist"), cols, kinds)})

    read = placed.join(broadcast_queries(close.select("block").distinct()), "block", "left_semi").withColumn("part", F.pmod(F.xxhash64("obj_id"), F.lit(parts)).cast("int"))
    sought = asked.join(close, "qid").withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))
    found = read.groupBy("block", "part").cogroup(sought.groupBy("block", "part")).applyInArrow(count, "qid long, obj_id long, dist double")
    return top_k(found, k, ["dist", "obj_id"]).select("qid", "rnk", "obj_id", "dist")


def random_candidates(data: DataFrame, queries: DataFrame, lam: int, k: int, metric: str, seed: int = 0) -> DataFrame:
    """Floor for recall: lam objects by a hash."""
    some = data.select("obj_id").orderBy(F.xxhash64("obj_id", F.lit(seed))).limit(lam)
    return verify_pairs(broadcast_queries(queries.select("qid")).join(some, F.lit(True)), data, queries, k, metric)
