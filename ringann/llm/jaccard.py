"""N-gram Jaccard join by PartEnum signatures.

Set of a document: its distinct shingles of `width` words. Sets fall into size bands such that two sets of
Jaccard similarity num/den or more are in the same or neighbouring bands; a band's instance knows k, the largest
symmetric difference of a similar pair whose smaller set is in the band. The hash domain of shingles is cut into
n1 partitions and each of these into n2 parts. Of a similar pair, at least `need` partitions hold k2 differences
or less, so that some subset of n2 - k2 of their parts is equal in both sets; a signature is the content hash of
one such subset, and all subsets are enumerated. `band_plan` chooses (n1, n2, k2) for every band by the number of
signatures and their selectivity: small sets take subsets of several parts, for large ones (n2, k2) = (1, 0), one
part per signature, is the cheapest. Spare partitions make `need` more than one: a set that shares fewer
signatures than it must share with a partner has none and drops out, before any comparison.

Equal sets form one class first, and classes are the nodes of the join, whatever ids their documents have. In a
bucket of equal signatures all classes are compared with one pivot, not with each other; pairs go first by size
and by a bound on the symmetric difference from 64 counters of either set, then exactly, on the texts, which
travel compressed. In buckets that then still hold several components, classes drop out that share too few
shingles with other components to have a partner there; after a second pivot, what is left is compared in cells
of two blocks, across components only. No link between different components is lost, no group is gathered, and
pairs are never listed.

Edge cases: null, empty or blank text has an empty set and no links; fewer than `width` words make one shingle of
the whole sequence; rows that share a doc_id are one node, linked through each of their texts; a row without
doc_id takes part like any other and gets the smallest doc_id of its component, or null if that has none; columns
other than doc_id and text are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ringann.llm.kernel import BYTE_CODES, LOWER, NOT_SPACE, Rolling, bit_places, has_bits, merged_bitmap, mix, text_chunks, words
from ringann.llm.shared import components, stage, unstage

WIDTH, NUM, DEN = 4, 85, 100
ROUNDS = 2
CELL = 512  # nodes in a block of the last comparison
BUCKETS = 64  # counters of a set's histogram
RIVALS = 20  # sets of half similarity that a signature is to tell apart, in the choice of a plan
C1, C2, C3 = np.uint64(0xA24BAED4963EE407), np.uint64(0x9FB21C651E98DF25), np.uint64(0xC2B2AE3D27D4EB4F)


def shingle_sets(off: np.ndarray, data: np.ndarray, width: int = WIDTH) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of every row."""
    low = LOWER[data]
    starts, ends, first = words(low, off, NOT_SPACE)
    codes = Rolling(BYTE_CODES[low]).spans(starts, ends)
    roll = Rolling(codes)
    at = np.arange(max(0, len(codes) - width + 1))
    grams = roll.spans(at, at + width)
    out = []
    for a, b in zip(first[:-1], first[1:]):
        if b - a >= width:
            out.append(np.unique(grams[a : b - width + 1]))
        elif b > a:
            out.append(roll.spans(np.array([a]), np.array([b])))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


Plan = tuple[int, int, int, int, int]  # band, n1, n2, k2, need


def choose(k: int, least: int) -> tuple[int, int, int, int]:
    """(n1, n2, k2, need) for a symmetric difference of up to k between sets of `least` shingles or more.

    The cost of a plan is its number of signatures, each weighted by the chance that sets of half similarity
    agree on the shingles it covers.
    """
    if k == 0:
        return 1, 1, 0, 1
    best = None
    for k2 in range(min(k, 3) + 1):
        n1 = k // (k2 + 1) + 1
        n1 += 1 + n1 // 10 if n1 > 1 else 0
        for n2 in range(k2 + 1, k2 + 5):
            cover = least * (n2 - k2) / (n1 * n2)
            cost = n1 * comb(n2, k2) * (1 + RIVALS * 0.5 ** (4 / 3 * cover))
            if best is None or cost < best[0]:
                best = cost, n1, n2, k2
    _, n1, n2, k2 = best
    return n1, n2, k2, n1 - k // (k2 + 1)


def band_plan(size: int, num: int = NUM, den: int = DEN) -> list[Plan]:
    """Plans of the instances a set of this size takes part in: its band and the one below."""
    lo, band, out = 1, 0, []
    while True:
        hi = den * lo // num
        if size <= den * hi // num:
            k = (den - num) * (hi + den * hi // num) // (den + num)
            out.append((band, *choose(k, lo)))
            if size <= hi:
                return out
        lo, band = hi + 1, band + 1


_SUBSETS: dict[tuple[int, int], np.ndarray] = {}


def _subsets(n2: int, k2: int) -> np.ndarray:
    """All subsets of n2 - k2 of n2 parts, as rows of zeros and ones."""
    found = _SUBSETS.get((n2, k2))
    if found is None:
        found = np.zeros((comb(n2, k2), n2), np.uint64)
        for i, at in enumerate(combinations(range(n2), n2 - k2)):
            found[i, list(at)] = 1
        _SUBSETS[n2, k2] = found
    return found


def _cuts(grams: np.ndarray, parts: int) -> np.ndarray:
    """Bounds of the parts of the hash domain in sorted shingles."""
    part = ((grams >> np.uint64(32)) * np.uint64(parts)) >> np.uint64(32)
    return np.searchsorted(part, np.arange(parts + 1, dtype=np.uint64))


def needs(grams: np.ndarray, plan: list[Plan]) -> tuple[int, int]:
    """How many signatures of even and of odd bands a set shares at least with a partner of that instance.

    A partition in which the set leaves a whole subset of parts empty may agree in nothing but emptiness.
    """
    out = [1, 1]
    for band, n1, n2, k2, need in plan:
        if need > 1:
            empty = (np.diff(_cuts(grams, n1 * n2)) == 0).reshape(n1, n2).sum(axis=1)
            out[band & 1] = max(1, need - int((empty >= n2 - k2).sum()))
    return out[0], out[1]


def signatures(grams: np.ndarray, plan: list[Plan]) -> np.ndarray:
    """Signatures of a set in the instances of its plan; the last bit is the band's parity.

    Subsets of empty parts are left out while the set surely shares another signature with any partner.
    """
    with np.errstate(over="ignore"):
        sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(mix(grams ^ C1))])
        out = []
        for band, n1, n2, k2, need in plan:
            cut = _cuts(grams, n1 * n2)
            pick = _subsets(n2, k2).T
            count = np.diff(cut).astype(np.uint64).reshape(n1, n2)
            risky = int(((count == 0).sum(axis=1) >= n2 - k2).sum())
            held = (count @ pick).ravel()
            own = ((sums[cut[1:]] - sums[cut[:-1]]).reshape(n1, n2) @ pick).ravel()
            at = np.arange(len(own), dtype=np.uint64)
            if risky < need:
                some = held > 0
                held, own, at = held[some], own[some], at[some]
            sig = mix(own + np.uint64(band + 1) * C1 + at * C2 + held * C3)
            out.append(sig & ~np.uint64(1) | np.uint64(band & 1))
        return np.concatenate(out)


def histogram(grams: np.ndarray) -> bytes:
    """Shingles by bucket of their hash, each counter stopping at 255: sums of differences bound the symmetric difference from below."""
    return np.minimum(np.bincount((grams & np.uint64(BUCKETS - 1)).astype(np.int64), minlength=BUCKETS), 255).astype(np.uint8).tobytes()


def _fingerprint(grams: np.ndarray) -> int:
    a = int(mix(grams ^ C2).sum(dtype=np.uint64)) if len(grams) else 0
    return a - (1 << 64) if a >> 63 else a


def _planner(num: int, den: int):
    plans: dict[int, list[Plan]] = {}

    def plan(size: int) -> list[Plan]:
        if size not in plans:
            plans[size] = band_plan(size, num, den)
        return plans[size]

    return plan


def members(docs: DataFrame, width: int = WIDTH, num: int = NUM, den: int = DEN) -> DataFrame:
    """(doc_id, t, n_shingles, f1, even, odd, hist) of every row of docs(doc_id, t, text): set size, set fingerprint, `needs`, histogram."""

    def run(batches):
        plan = _planner(num, den)
        for rows, off, data in text_chunks(batches):
            sets = shingle_sets(off, data, width)
            least = [needs(s, plan(len(s))) if len(s) else (1, 1) for s in sets]
            yield pa.RecordBatch.from_arrays(
                [rows.column("doc_id"), rows.column("t"), pa.array([len(s) for s in sets], pa.int64()), pa.array([_fingerprint(s) for s in sets], pa.int64()), pa.array([x[0] for x in least], pa.int32()), pa.array([x[1] for x in least], pa.int32()), pa.array([histogram(s) for s in sets], pa.binary())],
                names=["doc_id", "t", "n_shingles", "f1", "even", "odd", "hist"],
            )

    return docs.mapInArrow(run, "doc_id long, t long, n_shingles long, f1 long, even int, odd int, hist binary")


def signature_rows(docs: DataFrame, width: int = WIDTH, num: int = NUM, den: int = DEN) -> DataFrame:
    """(sig, f1): PartEnum signatures of every non-empty set; equal rows of one task are sent once."""

    def run(batches):
        plan = _planner(num, den)
        seen: set[int] = set()
        for rows, off, data in text_chunks(batches):
            sigs, owners = [], []
            for grams in shingle_sets(off, data, width):
                if not len(grams):
                    continue
                f1 = _fingerprint(grams)
                if f1 in seen:
                    continue
                if len(seen) < 1_000_000:  # 64 MB at most; a copy beyond it only costs rows
                    seen.add(f1)
                s = signatures(grams, plan(len(grams)))
                sigs.append(s)
                owners.append(np.full(len(s), f1, np.int64))
            for lo in range(0, len(sigs), 64):
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(sigs[lo : lo + 64]).view(np.int64)), pa.array(np.concatenate(owners[lo : lo + 64]))], names=["sig", "f1"])

    return docs.select("text").mapInArrow(run, "sig long, f1 long")


def packed_texts(docs: DataFrame, keep: list[str] = ()) -> DataFrame:
    """(doc_id, *keep, z, n): compressed text and its length in bytes."""
    types = dict(docs.dtypes)

    def run(batches):
        codec = pa.Codec("zstd", compression_level=3)
        for rows, off, data in text_chunks(batches):
            raw = data.tobytes()
            z = [codec.compress(raw[a:b], asbytes=True) if b > a else b"" for a, b in zip(off[:-1], off[1:])]
            yield pa.RecordBatch.from_arrays([*[rows.column(c) for c in ("doc_id", *keep)], pa.array(z, pa.binary()), pa.array(np.diff(off))], names=["doc_id", *keep, "z", "n"])

    return docs.mapInArrow(run, ", ".join(["doc_id long", *[f"{c} {types[c]}" for c in keep], "z binary", "n long"]))


def _packed_nodes(rows: DataFrame, wanted: DataFrame) -> DataFrame:
    """(node, z, n): the text of every wanted(node, doc_id, t), dealt out by node and kept on disk for several joins.

    A bitmap of the wanted rows, sized by their number and at most 32 MB, keeps other texts from being sent; what
    it lets through in error the join drops.
    """
    n = wanted.count()
    bits = 1 << min(28, max(17, (16 * n).bit_length()))

    def hashes(batches):
        for b in batches:
            yield mix(b.column("t").to_numpy().view(np.uint64))

    known = rows.sparkSession.sparkContext.broadcast(merged_bitmap(wanted.select("t"), hashes, bits))

    def likely(batches):
        for b in batches:
            yield b.filter(pa.array(has_bits(known.value, bit_places(mix(b.column("t").to_numpy().view(np.uint64)), bits))))

    some = rows.mapInArrow(likely, "doc_id long, t long, text string")
    found = packed_texts(some, ["t"]).withColumnsRenamed({"doc_id": "__d", "t": "__t"}).dropDuplicates(["__d", "__t"])
    one = wanted.join(found, F.col("doc_id").eqNullSafe(F.col("__d")) & (F.col("t") == F.col("__t"))).select("node", "z", "n")
    return one.repartition(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), "node").persist(StorageLevel.DISK_ONLY)


def likely_pairs(pairs: DataFrame, nodes: DataFrame, num: int = NUM, den: int = DEN) -> DataFrame:
    """pairs(a, b) without those that sizes or histograms tell apart: no similar pair goes."""
    side = lambda c: nodes.select(F.col("node").alias(c), F.col("size").alias(f"n{c}"), F.col("hist").alias(f"h{c}"))
    both = pairs.join(side("a"), "a").join(side("b"), "b").where(F.least("na", "nb") * den >= F.greatest("na", "nb") * num)

    def run(batches):
        for r in batches:
            if not r.num_rows:
                continue
            ha, hb = (np.frombuffer(b"".join(r.column(c).to_pylist()), np.uint8).reshape(-1, BUCKETS).astype(np.int64) for c in ("ha", "hb"))
            # A counter that stopped says nothing about the other side's.
            apart = np.where((ha == 255) | (hb == 255), 0, np.abs(ha - hb)).sum(axis=1)
            total = r.column("na").to_numpy() + r.column("nb").to_numpy()
            good = pa.array((den + num) * apart <= (den - num) * total)
            yield pa.RecordBatch.from_arrays([r.column("a").filter(good), r.column("b").filter(good)], names=["a", "b"])

    return both.mapInArrow(run, "a long, b long")


def verify(pairs: DataFrame, packed: DataFrame, width: int = WIDTH, num: int = NUM, den: int = DEN) -> DataFrame:
    """Those pairs (a, b) whose sets have den * |intersection| >= num * |union|, exactly."""
    left = pairs.join(packed.select(F.col("node").alias("a"), F.col("z").alias("za"), F.col("n").alias("na")), "a")
    both = left.join(packed.select(F.col("node").alias("b"), F.col("z").alias("zb"), F.col("n").alias("nb")), "b")

    def run(batches):
        codec = pa.Codec("zstd")
        kept: list = [None, None]

        def grams(z, n):
            raw = np.frombuffer(codec.decompress(z, int(n), asbytes=True), np.uint8) if n else np.zeros(0, np.uint8)
            return shingle_sets(np.array([0, len(raw)]), raw, width)[0]

        for batch in batches:
            good = np.zeros(batch.num_rows, bool)
            za, zb = batch.column("za"), batch.column("zb")
            na, nb = batch.column("na").to_pylist(), batch.column("nb").to_pylist()
            ids = batch.column("b").to_pylist()
            for i in range(batch.num_rows):
                if kept[0] != ids[i]:
                    kept = [ids[i], grams(zb[i].as_py(), nb[i])]
                x, y = grams(za[i].as_py(), na[i]), kept[1]
                if min(len(x), len(y)) * den < num * max(len(x), len(y)):
                    continue
                same = len(np.intersect1d(x, y, assume_unique=True))
                good[i] = den * same >= num * (len(x) + len(y) - same)
            mask = pa.array(good)
            yield pa.RecordBatch.from_arrays([batch.column("a").filter(mask), batch.column("b").filter(mask)], names=["a", "b"])

    return both.select("a", "b", "za", "na", "zb", "nb").mapInArrow(run, "a long, b long")


def _enough(rows: DataFrame, nodes: DataFrame, rarest: bool = False) -> DataFrame:
    """Open rows(sig, node, comp) with sizes, without nodes that share fewer signatures of an instance with other
    components than with any partner in it, then without closed buckets.

    rarest: of the `least` signatures a node shares with a partner, the one in the smallest bucket is not among
    its least - 1 signatures in the largest buckets, so these rows go too.
    """
    odd = F.col("sig").bitwiseAND(F.lit(1)) == 1
    if rarest:
        rows = rows.withColumn("wide", F.count("*").over(Window.partitionBy("sig")))
    joined = rows.join(nodes.select("node", F.col("size").alias("__s"), "even", "odd"), "node").withColumn("size", F.col("__s"))
    joined = joined.withColumn("least", F.when(odd, F.col("odd")).otherwise(F.col("even"))).withColumn("par", odd)
    own = Window.partitionBy("node", "par")
    kept = joined.withColumn("c", F.count("*").over(own)).where("c >= least")
    if rarest:
        kept = kept.withColumn("r", F.row_number().over(own.orderBy(F.col("wide").desc(), "sig"))).where("r >= least")
    return _several(kept.select("sig", "node", "size", "comp"))


def jaccard_groups(docs: DataFrame, width: int = WIDTH, num: int = NUM, den: int = DEN, rounds: int = ROUNDS) -> DataFrame:
    """(doc_id, t, n_shingles, grp, component_id) for every row of docs; t is a hash of the text, grp a key of the
    component, null for rows that no other can be linked with."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("t"), "text")
    own = stage(members(rows, width, num, den))
    bucket = Window.partitionBy("sig")
    met = signature_rows(rows, width, num, den).withColumns({"lo": F.min("f1").over(bucket), "hi": F.max("f1").over(bucket)}).where("lo < hi")
    raw = stage(met.select("sig", F.col("f1").alias("node")).distinct())
    # From here on rows are few: only signatures that two different sets share.
    first = F.min(F.struct("doc_id", "t"))
    every = own.where("n_shingles > 0").withColumnRenamed("f1", "node").join(raw.select("node").distinct(), "node", "left_semi")
    nodes = stage(every.groupBy("node").agg(F.first("n_shingles").alias("size"), F.first("even").alias("even"), F.first("odd").alias("odd"), F.first("hist").alias("hist"), first.alias("one")).select("node", "size", "even", "odd", "hist", "one.*"))
    met = stage(_enough(_enough(raw.withColumn("comp", F.col("node")), nodes), nodes).drop("comp"))
    unstage(raw)
    packed = _packed_nodes(rows, stage(nodes.select("node", "doc_id", "t").join(met.select("node").distinct(), "node", "left_semi")))
    twice = own.where("n_shingles > 0 AND doc_id IS NOT NULL").groupBy("doc_id").agg(F.min("f1").alias("b"), F.max("f1").alias("hi")).where("b < hi").select("doc_id", "b")
    links = stage(own.where("n_shingles > 0").join(twice, "doc_id").where("f1 <> b").select(F.col("f1").alias("a"), "b").distinct())
    tried, comp, done = None, _labels(links), [links]
    for r in range(rounds):
        open_ = _enough(_open_buckets(met, comp), nodes) if r else _open_buckets(met, comp)
        if r:
            before, open_ = met, stage(_prune(_prune(open_, packed, width, num, den), packed, width, num, den))
            met = open_
            unstage(before)
        lead = F.min(F.struct((F.xxhash64("node", F.lit(r)) if r else F.col("node")).alias("h"), F.col("node").alias("id"), "comp")).over(bucket)
        pairs = open_.withColumn("p", lead).where(F.col("comp") != F.col("p.comp")).select("node", F.col("p.id").alias("pivot"))
        pairs = pairs.select(F.greatest("node", "pivot").alias("a"), F.least("node", "pivot").alias("b")).distinct()
        if tried is not None:
            pairs = pairs.join(tried, ["a", "b"], "left_anti")
        pairs = stage(likely_pairs(pairs, nodes, num, den))
        found = stage(verify(pairs, packed, width, num, den))
        tried = pairs if tried is None else tried.union(pairs)
        done.append(found)
        links = links.union(found)
        comp = _labels(links)
    last = stage(_compare_cells(_enough(_enough(_open_buckets(met, comp), nodes), nodes, True), packed, width, num, den))
    if not last.isEmpty():
        comp = components(links.union(last))
    comp = stage(comp)
    packed.unpersist()
    unstage(met, nodes, last, *done)
    linked = own.withColumnRenamed("f1", "node").join(comp, "node", "left").select("doc_id", "t", "n_shingles", F.when(F.col("n_shingles") > 0, F.coalesce("comp", "node")).alias("grp"))
    least = linked.where("grp IS NOT NULL").groupBy(F.col("grp").alias("__g")).agg(F.min("doc_id").alias("__least"))
    out = linked.join(least, F.col("grp") == F.col("__g"), "left")
    return out.select("doc_id", "t", "n_shingles", "grp", F.when(F.col("grp").isNull(), F.col("doc_id")).otherwise(F.col("__least")).alias("component_id"))


def jaccard_components(docs: DataFrame, width: int = WIDTH, num: int = NUM, den: int = DEN, rounds: int = ROUNDS) -> DataFrame:
    """(doc_id, n_shingles, component_id) for every row of docs."""
    return jaccard_groups(docs, width, num, den, rounds).select("doc_id", "n_shingles", "component_id")


def keep_one(docs: DataFrame, width: int = WIDTH, num: int = NUM, den: int = DEN) -> DataFrame:
    """docs with one row of each component: of its smallest doc_id, a null one last, and of that the smallest text hash.

    Rows without words all stay, but for repeated rows of one doc_id and text, of which one stays.
    """
    found = jaccard_groups(docs, width, num, den)
    key = F.struct(F.col("doc_id").isNull().alias("nil"), F.col("doc_id"), F.col("t"))
    group = F.when(F.col("grp").isNull(), F.struct(F.lit(1).alias("kind"), F.coalesce("doc_id", F.lit(0)).alias("g"), F.col("t").alias("u"))).otherwise(F.struct(F.lit(0).alias("kind"), F.col("grp").alias("g"), F.lit(0).cast("long").alias("u")))
    best = found.groupBy(group.alias("grp")).agg(F.min(key).alias("k"))
    kept = stage(best.select(F.col("k.doc_id").alias("__d"), F.col("k.t").alias("__t")))
    # Rows of a doc_id and text given several times are told apart by number; these are few or the whole is small keys.
    again = found.groupBy("doc_id", "t").agg(F.count("*").alias("c")).where("c > 1").select(F.col("doc_id").alias("__rd"), F.col("t").alias("__rt"), F.lit(True).alias("__more"))
    marked = docs.withColumn("__h", F.xxhash64(F.coalesce("text", F.lit("")))).join(kept, F.col("doc_id").cast("long").eqNullSafe(F.col("__d")) & (F.col("__h") == F.col("__t")), "left_semi")
    marked = marked.join(again, F.col("doc_id").cast("long").eqNullSafe(F.col("__rd")) & (F.col("__h") == F.col("__rt")), "left").drop("__rd", "__rt")
    single = marked.where("__more IS NULL").drop("__more", "__h")
    return single.union(marked.where("__more").dropDuplicates(["doc_id", "__h"]).drop("__more", "__h"))


def _labels(links: DataFrame) -> DataFrame:
    return components(links) if not links.isEmpty() else links.sparkSession.createDataFrame([], "node long, comp long")


def _open_buckets(met: DataFrame, comp: DataFrame) -> DataFrame:
    """(sig, node, size, comp) of buckets that still hold more than one component."""
    named = met.select("sig", "node", "size").join(comp, "node", "left").select("sig", "node", "size", F.coalesce("comp", "node").alias("comp"))
    return _several(named)


def _several(rows: DataFrame) -> DataFrame:
    w = Window.partitionBy("sig")
    return rows.withColumns({"lo": F.min("comp").over(w), "hi": F.max("comp").over(w)}).where("lo < hi").drop("lo", "hi")


def _prune(open_: DataFrame, packed: DataFrame, width: int, num: int, den: int) -> DataFrame:
    """Rows of open buckets without nodes that provably have no partner in another component.

    A partner shares at least num / (num + den) of both sizes' sum, and every shared shingle occurs in another
    component. The partner's size is at least the bucket's smallest and num / den of the node's own.
    """
    open_ = stage(open_)
    nodes = open_.select("node", "comp").distinct()
    texts = nodes.join(packed, "node").select("node", "comp", "z", "n")

    def run(batches):
        codec = pa.Codec("zstd")
        for batch in batches:
            zs, ns = batch.column("z"), batch.column("n").to_pylist()
            for i in range(0, batch.num_rows, 32):
                j = min(i + 32, batch.num_rows)
                raw = [codec.decompress(zs[k].as_py(), ns[k], asbytes=True) if ns[k] else b"" for k in range(i, j)]
                sets = shingle_sets(np.concatenate([[0], np.cumsum([len(x) for x in raw])]), np.frombuffer(b"".join(raw), np.uint8), width)
                sizes = [len(x) for x in sets]
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(batch.column(c).to_numpy()[i:j], sizes)) for c in ("node", "comp")] + [pa.array(np.concatenate(sets).view(np.int64))], names=["node", "comp", "gram"])

    grams = texts.mapInArrow(run, "node long, comp long, gram long")
    w = Window.partitionBy("gram")
    shared = grams.withColumns({"lo": F.min("comp").over(w), "hi": F.max("comp").over(w)}).where("lo < hi").groupBy("node").agg(F.count("*").alias("m"))
    least = F.min("size").over(Window.partitionBy("sig"))
    kept = open_.join(shared, "node").withColumn("least", F.greatest(least, F.ceil(F.col("size") * num / den)))
    return _several(kept.where(F.col("m") * (num + den) >= num * (F.col("size") + F.col("least"))).select("sig", "node", "size", "comp"))


def _compare_cells(open_: DataFrame, packed: DataFrame, width: int, num: int, den: int, block: int = CELL) -> DataFrame:
    """Links (a, b) between different components inside open buckets, found without listing pairs.

    Buckets with the same members are compared once. A bucket's nodes are dealt to blocks of about `block`
    nodes; a cell is a pair of blocks, so that a task holds two blocks of sets whatever the bucket's size, and
    returns links only.
    """
    w = Window.partitionBy("sig")
    h = F.xxhash64("node")
    marked = stage(open_.withColumns({"c": F.count("*").over(w), "x": F.expr("bit_xor(xxhash64(node))").over(w), "y": F.max(h).over(w)}))
    first = marked.groupBy("c", "x", "y").agg(F.min("sig").alias("sig")).select("sig")
    nb = F.ceil(F.col("c") / block).cast("int")
    rows = marked.join(first, "sig", "left_semi").withColumn("nb", nb).withColumn("k", F.pmod(F.xxhash64("node", F.lit(7)), F.col("nb")).cast("int"))
    rows = rows.withColumn("o", F.explode(F.sequence(F.lit(0), F.col("nb") - 1)))
    rows = rows.select("sig", F.least("k", "o").alias("i"), F.greatest("k", "o").alias("j"), "k", "node", "comp")
    rows = rows.join(packed, "node")

    def compare(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = pa.Codec("zstd")
        ids, comps, sides, sets = [], [], [], []
        for batch in batches:
            zs, ns = batch.column("z"), batch.column("n").to_pylist()
            raw = [codec.decompress(zs[q].as_py(), ns[q], asbytes=True) if ns[q] else b"" for q in range(batch.num_rows)]
            sets += shingle_sets(np.concatenate([[0], np.cumsum([len(x) for x in raw])]).astype(np.int64), np.frombuffer(b"".join(raw), np.uint8), width)
            ids.append(batch.column("node").to_numpy())
            comps.append(batch.column("comp").to_numpy())
            sides.append(batch.column("k").to_numpy())
        ids, comps, sides = np.concatenate(ids), np.concatenate(comps), np.concatenate(sides)
        sizes = np.array([len(x) for x in sets])
        flat = np.concatenate(sets)
        owner = np.repeat(np.arange(len(sets)), sizes)
        _, place, seen = np.unique(flat, return_inverse=True, return_counts=True)
        keep = seen[place] > 1
        owner, place = owner[keep], np.unique(place[keep], return_inverse=True)[1]
        same = np.zeros((len(sets), len(sets)), np.float32)
        order = np.argsort(place, kind="stable")
        owner, place = owner[order], place[order]
        top = int(place[-1]) + 1 if len(place) else 0
        for lo in range(0, top, 4096):
            a, b = np.searchsorted(place, [lo, lo + 4096])
            m = np.zeros((len(sets), 4096), np.float32)
            m[owner[a:b], place[a:b] - lo] = 1
            same += m @ m.T
        both = same.astype(np.int64)
        good = (den * both >= num * (sizes[:, None] + sizes[None, :] - both)) & (comps[:, None] < comps[None, :])
        if key[1].as_py() != key[2].as_py():
            good &= sides[:, None] != sides[None, :]
        x, y = np.nonzero(good)
        yield pa.RecordBatch.from_arrays([pa.array(ids[x], pa.int64()), pa.array(ids[y], pa.int64())], names=["a", "b"])

    found = rows.groupBy("sig", "i", "j").applyInArrow(compare, "a long, b long")
    return found.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def op1_jaccard_join(spark, sf_dir: str) -> DataFrame:
    return jaccard_components(spark.read.parquet(f"{sf_dir}/documents.parquet"))


OP1_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), s AS (
  SELECT DISTINCT doc_id, list_slice(w, i, i + 3) AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 1) + 1)) AS i FROM w WHERE len(w) > 0)
), n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id
), p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS m FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY a.doc_id, b.doc_id
), l AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * m >= 85 * (x.n + y.n - m)
), e AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l
), r AS (SELECT doc_id AS node, doc_id AS reach FROM n UNION SELECT r.node, e.b FROM r JOIN e ON e.a = r.reach
), c AS (SELECT node, min(reach) AS c FROM r GROUP BY node)
SELECT w.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, coalesce(c, w.doc_id) AS component_id FROM w LEFT JOIN n USING (doc_id) LEFT JOIN c ON c.node = w.doc_id
"""
