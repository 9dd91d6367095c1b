"""Exact removal of repeated byte strings with a distributed difference-cover suffix array.

All bytes covered by a string of `length` bytes that also starts elsewhere go. To sort few suffixes, texts are
sampled at synchronising anchors: a position is an anchor if its hash is the least of some window of W hashes, so
equal passages have equal anchors but for their rims. Every repeated string holds an anchor, in its first 2 W
bytes, whose next REACH bytes repeat; anchors whose REACH bytes are unique end the search for all that no repeat
touches.

A candidate anchor's suffix is a sequence of DEPTH following anchors' symbols (hash of REACH bytes and gap).
Distinct suffixes are dealt to shards by their first symbol, so that all that can agree meet. Each shard builds a
difference-cover suffix array: sort sampled triples, recurse on their names, merge the remaining suffixes; then it
compares adjacent prefixes, which gives each anchor's longest agreement with any other. Agreements decide
whole stretches at once. Windows at the rims of stretches, which anchors leave open, are compared in blocks of BLOCK
starts that lie alike before their anchor: one row holds a 96-bit hash of the bytes that all windows of the block
share, and the bytes around them, from which each window's own bytes are compared as they are. A stretch that
repeats is listed against the rims by one of its occurrences. Of equal texts only one takes part in all this.

Edge cases: null text is empty; texts shorter than `length` stay; every row is a place of its own, so that rows
equal in doc_id and text remove each other's strings, as do rows of equal text without doc_id; matches inside one
document count; columns other than doc_id and text are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ringann.llm.kernel import BASE2, BYTE_CODES, Rolling, bit_places, has_bits, merged_bitmap, mix, text_chunks
from ringann.llm.shared import stage

LENGTH = 400
W, GRAM, DEPTH = 64, 8, 6
REACH = LENGTH - 2 * W  # bytes after an anchor that a repeat surely holds
SALTS = 64  # parts of a group of equal texts
BLOCK = 16  # windows compared by one row
BITS = 1 << 28  # of the bitmap of open blocks
C1 = np.uint64(0xA24BAED4963EE407)


def suffix_array(s: np.ndarray) -> np.ndarray:
    """Difference-cover suffix array of positive integers; every step is a sort or a search over whole arrays."""
    n = len(s)
    if n < 4:
        return np.array(sorted(range(n), key=lambda i: tuple(s[i:])), np.int64)
    t = np.concatenate([s, [0, 0, 0]])
    ones, twos, zeros = np.arange(1, n + (n % 3 == 1), 3), np.arange(2, n, 3), np.arange(0, n, 3)
    cover = np.concatenate([ones, twos])
    order = np.lexsort((t[cover + 2], t[cover + 1], t[cover]))
    triple = t[cover[order][:, None] + np.arange(3)]
    names = np.empty(len(cover), np.int64)
    names[order] = 1 + np.concatenate([[0], np.cumsum((triple[1:] != triple[:-1]).any(axis=1))])
    deep = suffix_array(names) if names.max() < len(cover) else np.argsort(names)
    sampled = cover[deep]
    rank = np.zeros(n + 4, np.int64)
    rank[sampled] = np.arange(1, len(sampled) + 1)
    sampled = sampled[sampled < n]
    rest = zeros[np.lexsort((rank[zeros + 1], t[zeros]))]
    # Place of each remaining suffix among the sampled ones, by bisection over all at once.
    lo, hi = np.zeros(len(rest), np.int64), np.full(len(rest), len(sampled))
    while (busy := lo < hi).any():
        mid = (lo + hi) >> 1
        other = sampled[np.minimum(mid, len(sampled) - 1)]
        one = other % 3 == 1
        a0, b0 = t[rest], t[other]
        a1 = np.where(one, rank[rest + 1], t[rest + 1])
        b1 = np.where(one, rank[other + 1], t[other + 1])
        after = (a0 > b0) | (a0 == b0) & ((a1 > b1) | ~one & (a1 == b1) & (rank[rest + 2] > rank[other + 2]))
        lo, hi = np.where(busy & after, mid + 1, lo), np.where(busy & ~after, mid, hi)
    out = np.empty(n, np.int64)
    at = lo + np.arange(len(rest))
    out[at] = rest
    free = np.ones(n, bool)
    free[at] = False
    out[free] = sampled
    return out


def agreements(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For distinct symbol rows (0 fills short ones at the end): longest prefix shared with any other row, and with the row sorted before."""
    n, depth = rows.shape
    flat = np.unique(rows, return_inverse=True)[1].reshape(rows.shape) + 2
    text = np.concatenate([flat, np.ones((n, 1), np.int64)], axis=1)
    keep = np.concatenate([rows != 0, np.ones((n, 1), bool)], axis=1)
    heads = np.concatenate([[0], np.cumsum(keep.sum(axis=1))])[:-1]
    order = suffix_array(text[keep])
    owner = np.full(int(keep.sum()), -1, np.int64)
    owner[heads] = np.arange(n)
    order = owner[order]
    order = order[order >= 0]
    a, b = rows[order[:-1]], rows[order[1:]]
    near = np.cumprod((a == b) & (a != 0), axis=1).sum(axis=1)
    out, before = np.zeros(n, np.int64), np.zeros(n, np.int64)
    before[order[1:]] = near
    out[order[:-1]] = near
    return np.maximum(out, before), before


def _sliding(x: np.ndarray, w: int, op) -> np.ndarray:
    """op over every w consecutive values, by prefix and suffix runs of blocks of w."""
    n = len(x)
    pad = -n % w
    fill = x[-1:] if n else x
    y = np.concatenate([x, np.repeat(fill, pad)]).reshape(-1, w)
    fore = op.accumulate(y, axis=1).ravel()
    back = op.accumulate(y[:, ::-1], axis=1)[:, ::-1].ravel()
    return op(back[: n - w + 1], fore[w - 1 : n])


def anchors(body: np.ndarray) -> tuple[np.ndarray, Rolling]:
    """Anchor positions of one text that have REACH bytes before them to the end."""
    roll = Rolling(BYTE_CODES[body])
    at = np.arange(len(body) - GRAM + 1)
    h = roll.spans(at, at + GRAM)
    least = _sliding(h, W, np.minimum)
    edge = np.concatenate([np.zeros(W - 1, np.uint64), least, np.zeros(W - 1, np.uint64)])
    most = _sliding(edge, W, np.maximum)
    found = np.flatnonzero(most == h)
    return found[found + REACH <= len(body)], roll


def _steps(found: np.ndarray, picked: np.ndarray) -> np.ndarray:
    """Anchor numbers of each picked anchor's suffix, len(found) where there is none.

    The next two anchors tell where a short agreement ends; three from LENGTH - REACH bytes on tell whether
    all windows up to the next anchor repeat. In between, REACH bytes of neighbours overlap.
    """
    far = np.searchsorted(found, found[picked] + (LENGTH - REACH))
    far = np.maximum(far, picked + 3)
    at = np.stack([picked, picked + 1, picked + 2, far, far + 1, far + 2], axis=1)
    return np.minimum(at, len(found))


def _contexts(found: np.ndarray, roll: Rolling, picked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Symbol rows of the picked anchors, and a 64-bit key: hashes of REACH bytes, each with its gap to the one before."""
    h = np.append(roll.spans(found, found + REACH), np.uint64(0))
    at = _steps(found, picked)
    place = np.append(found, 0)[at]
    gap = np.diff(place, axis=1, prepend=place[:, :1]).astype(np.uint64)
    rows = np.where(at < len(found), mix(h[at] + gap * C1) | np.uint64(1), np.uint64(0))
    key = np.zeros(len(picked), np.uint64)
    for c in range(DEPTH):
        key = mix(key * C1 + rows[:, c])
    return rows, key


def _blocks(found: np.ndarray, s: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(last start of its block, places before that) of each window start; equal windows have equal places.

    The first anchor W - 1 bytes or more behind a start is set by the window's bytes alone, so blocks are laid from it.
    """
    back = found[np.searchsorted(found, s + W - 1)] - (W - 1) - s
    return s + back % BLOCK, back % BLOCK


def _cores(roll: Rolling, top: np.ndarray, n_bytes: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash of the bytes that the windows of a block share, and of these with all bytes around them."""
    core = roll.spans(top, top + (LENGTH - BLOCK + 1))
    hull = roll.spans(np.maximum(top - (BLOCK - 1), 0), np.minimum(top + LENGTH, n_bytes))
    return core, mix(core + hull * C1)


def _edges(body: np.ndarray, top: np.ndarray) -> np.ndarray:
    """The BLOCK - 1 bytes on either side of each core, 0 outside the text."""
    padded = np.concatenate([np.zeros(BLOCK, np.uint8), body, np.zeros(BLOCK, np.uint8)])
    line = np.arange(BLOCK - 1)
    left = padded[BLOCK + top[:, None] - (BLOCK - 1) + line]
    return np.concatenate([left, padded[BLOCK + top[:, None] + (LENGTH - BLOCK + 1) + line]], axis=1)


def _texts(batch):
    codec = pa.Codec("zstd")
    z, n = batch.column("z"), batch.column("n").to_pylist()
    for i in range(batch.num_rows):
        yield i, np.frombuffer(codec.decompress(z[i].as_py(), n[i], asbytes=True), np.uint8)


def _lists(column) -> list[list[np.ndarray]]:
    """Rows of a column of lists of structs: for each row one array per field."""
    off, fields = column.offsets.to_numpy(), [f.to_numpy(zero_copy_only=False) for f in column.values.flatten()]
    return [[f[a:b] for f in fields] for a, b in zip(off[:-1], off[1:])]


def _packed(rows: np.ndarray):
    """Equally long rows as a binary column."""
    raw = np.ascontiguousarray(rows)
    wide = raw.nbytes // max(1, len(raw))
    off = np.arange(len(raw) + 1, dtype=np.int32) * np.int32(wide)
    return pa.Array.from_buffers(pa.binary(), len(raw), [None, pa.py_buffer(off), pa.py_buffer(raw)])


def _signed(x):
    return pa.array(np.ascontiguousarray(x).view(np.int64))


def repeats(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256) of every row, and spans: removed byte runs [start, stop)."""
    if length != LENGTH:
        raise ValueError("length is fixed with the anchors' reach")
    docs = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    docs = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63))).alias("d"), F.xxhash64("text").alias("t"), F.xxhash64(F.lit(1), "text").alias("u"), "text", F.col("doc_id").isNull().alias("nil"))

    def sample(batches):
        for rows, off, data in text_chunks(batches):
            out = []
            for i in np.flatnonzero(np.diff(off) >= length):
                found, roll = anchors(data[off[i] : off[i + 1]])
                h, one, times = np.unique(roll.spans(found, found + REACH), return_index=True, return_counts=True)
                out.append((i, found[one], h, times > 1))
            if out:
                owner = np.repeat([o[0] for o in out], [len(o[1]) for o in out])
                d, t, u = (rows.column(c).to_numpy()[owner] for c in ("d", "t", "u"))
                yield pa.RecordBatch.from_arrays([_signed(np.concatenate([o[2] for o in out])), pa.array(d), pa.array(t), pa.array(u), pa.array(np.concatenate([o[1] for o in out]), pa.int32()), pa.array(np.concatenate([o[3] for o in out]))], names=["h", "d", "t", "u", "pos", "many"])

    def whole(batches):
        for rows, off, data in text_chunks(batches):
            raw = data.tobytes()
            yield pa.RecordBatch.from_arrays([rows.column("d"), rows.column("t"), rows.column("u"), rows.column("nil"), pa.array(np.diff(off)), pa.array([hashlib.sha256(raw[a:b]).hexdigest() for a, b in zip(off[:-1], off[1:])], pa.string())], names=["d", "t", "u", "nil", "n_bytes", "sha"])

    def pack(batches):
        codec = pa.Codec("zstd", compression_level=3)
        for rows, off, data in text_chunks(batches):
            keep = np.diff(off) >= length
            raw = data.tobytes()
            z = [codec.compress(raw[off[i] : off[i + 1]], asbytes=True) for i in np.flatnonzero(keep)]
            m = pa.array(keep)
            yield pa.RecordBatch.from_arrays([rows.column("d").filter(m), rows.column("t").filter(m), pa.array(z, pa.binary()), pa.array(np.diff(off)[keep])], names=["d", "t", "z", "n"])

    w = Window.partitionBy("h")
    place = F.struct("t", "u", "pos")
    seen = docs.mapInArrow(sample, "h long, d long, t long, u long, pos int, many boolean").withColumns({"lo": F.min(place).over(w), "hi": F.max(place).over(w), "again": F.max("many").over(w)})
    cands = seen.where("lo <> hi or again").groupBy("t", "u").agg(F.min("d").alias("d"), F.sort_array(F.collect_set("pos")).alias("picks")).drop("u")
    packed = docs.mapInArrow(pack, "d long, t long, z binary, n long")
    work = stage(packed.join(cands, ["d", "t"]).dropDuplicates(["d", "t"]))

    def contexts(batches):
        for batch in batches:
            off, picks = batch.column("picks").offsets.to_numpy(), batch.column("picks").values.to_numpy()
            for i, body in _texts(batch):
                found, roll = anchors(body)
                h = roll.spans(found, found + REACH)
                at = np.flatnonzero(np.isin(h, h[np.searchsorted(found, picks[off[i] : off[i + 1]])]))
                rows, key = _contexts(found, roll, at)
                # Equal suffixes of one text are one row with all their places.
                key, one, group = np.unique(key, return_index=True, return_inverse=True)
                k, rows = len(key), rows[one]
                ends = np.concatenate([[0], np.cumsum(np.bincount(group, minlength=k))]).astype(np.int32)
                pos = pa.ListArray.from_arrays(pa.array(ends), pa.array(found[at][np.argsort(group, kind="stable")], pa.int32()))
                yield pa.RecordBatch.from_arrays([_signed(key), _packed(rows), _signed(rows[:, 0]), pa.array(np.full(k, batch.column("d")[i].as_py()), pa.int64()), pa.array(np.full(k, batch.column("t")[i].as_py()), pa.int64()), pos], names=["key", "row", "h", "d", "t", "pos"])

    def sort(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, rows, many = [], [], []
        for batch in batches:
            keys.append(batch.column("key").to_numpy())
            many.append(batch.column("c").to_numpy() > 1)
            rows.append(np.frombuffer(b"".join(x.as_py() for x in batch.column("row")), np.uint64).reshape(-1, DEPTH))
        rows, many = np.concatenate(rows), np.concatenate(many)
        size = (rows != 0).sum(axis=1)
        found, before = agreements(rows)
        found = np.where(many, size, found)
        # A suffix that agrees no further with any other than with the one sorted before it says nothing new.
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys)), pa.array(found, pa.int32()), pa.array(found >= size), pa.array(before < found)], names=["key", "same", "full", "lists"])

    suffixes = work.select("d", "t", "z", "n", "picks").mapInArrow(contexts, "key long, row binary, h long, d long, t long, pos array<int>")
    # Equal suffixes are one row before they reach a shard; a passage in very many documents is one suffix there.
    distinct = suffixes.groupBy("key").agg(F.sum(F.size("pos")).alias("c"), F.count("*").alias("texts"), F.first("row").alias("row"), F.first("h").alias("h"), F.min(F.struct("d", "t", F.col("pos")[0].alias("pos"))).alias("one"))
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    shards = max(16, 4 * parts)
    distinct = stage(distinct)
    ranked = distinct.select("key", "c", "row", F.pmod(F.xxhash64("h"), F.lit(shards)).alias("shard")).groupBy("shard").applyInArrow(sort, "key long, same int, full boolean, lists boolean")
    # A suffix with a partition's share of all rows is dealt to as many salts as it has shares; at most `parts` suffixes have one.
    share = F.ceil(F.col("texts") * F.lit(parts) / F.lit(max(1, distinct.agg(F.sum("texts")).first()[0] or 0))).cast("int")
    ranked = ranked.join(distinct.select("key", "one", F.explode(F.sequence(F.lit(0), share - 1)).alias("salt")), "key")
    hot = distinct.select("key", share.alias("share")).where("share > 1")
    salted = suffixes.select("key", "d", "t", "pos").join(F.broadcast(hot), "key", "left").withColumn("salt", F.coalesce(F.pmod(F.xxhash64("d", "t"), F.col("share")), F.lit(0)).cast("int"))
    places = F.transform("pos", lambda p: F.struct(p.alias("pos"), "same", "full", (F.col("lists") & (F.struct("d", "t", p.alias("pos")) == F.col("one"))).alias("lists")))
    told = salted.join(ranked, ["key", "salt"]).groupBy("d", "t").agg(F.sort_array(F.flatten(F.collect_list(places))).alias("told"))
    judged = stage(work.drop("picks").join(told, ["d", "t"]))

    def decide(body, told):
        """(windows known to repeat, those to be compared, those to be listed for these: masks of starts, anchors, Rolling)."""
        found, roll = anchors(body)
        n = len(body) - length + 1
        pos, same, full, new = told
        at = np.searchsorted(found, pos)
        steps, line = _steps(found, at), np.arange(len(at))
        sure = np.zeros(len(found), np.int64)  # end of what surely repeats from an anchor
        sure[at] = np.where(same > 0, found[np.minimum(steps[line, np.maximum(same, 1) - 1], len(found) - 1)] + REACH, 0)
        most = np.zeros(len(found), np.int64)  # what repeats from an anchor ends before
        differs = steps[line, np.minimum(same, DEPTH - 1)]
        most[at] = np.where(full | (differs >= len(found)), len(body) + 1, found[np.minimum(differs, len(found) - 1)] + REACH)
        s = np.arange(n)
        lists = np.zeros(len(found) + 1, bool)
        lists[1 + at] = new
        # Anchors up to each place; entry 0 of `sure` and `lists`, and the last of `most`, stand for no anchor.
        upto = np.zeros(len(body), np.int32)
        upto[found] = 1
        upto = np.cumsum(upto, dtype=np.int32)
        before, inner = upto[:n], upto[W - 2 : W - 2 + n]
        yes = np.append(0, sure)[before] >= s + length
        maybe = np.append(most, 0)[inner] >= s + length
        return yes, maybe & ~yes, yes & lists[before], found, roll

    def open_hashes(batches):
        for batch in batches:
            told = _lists(batch.column("told"))
            for i, body in _texts(batch):
                _, ask, _, found, roll = decide(body, told[i])
                top = np.unique(_blocks(found, np.flatnonzero(ask))[0])
                yield roll.spans(top, top + (length - BLOCK + 1))

    known = docs.sparkSession.sparkContext.broadcast(merged_bitmap(judged, open_hashes, BITS))

    def open_blocks(batches):
        bitmap = known.value
        for batch in batches:
            told = _lists(batch.column("told"))
            for i, body in _texts(batch):
                _, ask, listed, found, roll = decide(body, told[i])
                s = np.flatnonzero(ask | listed)
                if not len(s):
                    continue
                top, place = _blocks(found, s)
                first = np.flatnonzero(np.diff(top, prepend=-1))
                bit = 1 << place
                asked = np.bitwise_or.reduceat(np.where(ask[s], bit, 0), first)
                held = np.bitwise_or.reduceat(bit, first)
                top = top[first]
                core, key = _cores(roll, top, len(body))
                use = asked > 0
                use[~use] = has_bits(bitmap, bit_places(core[~use], BITS))
                top, core, key, asked, held = (v[use] for v in (top, core, key, asked, held))
                if not len(top):
                    continue
                # Equal blocks of one text are one row, which says what windows it has twice.
                _, one, group = np.unique(key, return_index=True, return_inverse=True)
                masks = np.zeros((3, len(one)), np.int64)  # asked, held, held twice
                np.bitwise_or.at(masks[0], group, asked)
                np.bitwise_or.at(masks[1], group, held)
                for j in range(BLOCK):
                    masks[2] |= (np.bincount(group, (held >> j) & 1, len(one)) > 1).astype(np.int64) << j
                k = len(one)
                second = Rolling(BYTE_CODES[body], BASE2).spans(top[one], top[one] + (length - BLOCK + 1))
                edges = _packed(_edges(body, top[one]))
                yield pa.RecordBatch.from_arrays([_signed(core[one]), pa.array((second >> np.uint64(33)).astype(np.int32)), edges, *(pa.array(m, pa.int32()) for m in masks), pa.array(np.full(k, batch.column("d")[i].as_py()), pa.int64()), pa.array(np.full(k, batch.column("t")[i].as_py()), pa.int64()), pa.array(top[one], pa.int32())], names=["h", "g", "edge", "asked", "held", "twice", "d", "t", "top"])

    # Of the blocks inside sure stretches only those are listed that may equal an open one, by a bitmap of fixed size.
    spot = F.struct("d", "t", "top")

    def met(*keys: str):
        w = Window.partitionBy("h", "g", *keys)
        return {"lo": F.min(spot).over(w), "hi": F.max(spot).over(w), "again": F.max("twice").over(w)}

    rows = judged.mapInArrow(open_blocks, "h long, g int, edge binary, asked int, held int, twice int, d long, t long, top int")
    rows = rows.withColumns(met()).where("lo <> hi or again <> 0").drop("lo", "hi", "again")
    rows = rows.withColumn("i", F.explode(F.expr(f"filter(sequence(0, {BLOCK - 1}), i -> (shiftright(held, i) & 1) = 1)")))
    rows = rows.select("h", "g", "d", "t", "top", "i", F.expr(f"substring(edge, {BLOCK} - i, {BLOCK - 1})").alias("edge"), F.expr("(shiftright(asked, i) & 1) = 1").alias("asked"), F.expr("shiftright(twice, i) & 1").alias("twice"))
    rows = rows.withColumns(met("i", "edge")).where("asked and (lo <> hi or again = 1)")
    more = rows.groupBy("d", "t").agg(F.collect_list(F.struct("top", "i")).alias("more"))

    def cut(batches):
        for batch in batches:
            told = _lists(batch.column("told"))
            out = []
            for i, body in _texts(batch):
                yes, ask, _, found, roll = decide(body, told[i])
                extra = batch.column("more")[i].as_py()
                if extra:
                    s = np.flatnonzero(ask)
                    top, place = _blocks(found, s)
                    hits = np.array([(e["top"], e["i"]) for e in extra])
                    hit = mix(_cores(roll, hits[:, 0], len(body))[1] + hits[:, 1].astype(np.uint64))
                    yes[s[np.isin(mix(_cores(roll, top, len(body))[1] + place.astype(np.uint64)), hit)]] = True
                delta = np.zeros(len(body) + 1, np.int64)
                hit = np.flatnonzero(yes)
                delta[hit] += 1
                np.subtract.at(delta, hit + length, 1)
                gone = np.cumsum(delta[:-1]) > 0
                edge = np.diff(np.concatenate([[0], gone.astype(np.int8), [0]]))
                runs = [{"start": int(a), "stop": int(b)} for a, b in zip(np.flatnonzero(edge == 1), np.flatnonzero(edge == -1))]
                out.append((int(gone.sum()), runs, hashlib.sha256(body[~gone].tobytes()).hexdigest()))
            yield pa.RecordBatch.from_arrays([batch.column("d"), batch.column("t"), pa.array([o[0] for o in out], pa.int64()), pa.array([o[2] for o in out], pa.string()), pa.array([o[1] for o in out], pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())])))], names=["d", "t", "n_removed", "kept", "spans"])

    cuts = judged.join(more, ["d", "t"], "left").mapInArrow(cut, "d long, t long, n_removed long, kept string, spans array<struct<start:long,stop:long>>").where("n_removed > 0")
    base = docs.mapInArrow(whole, "d long, t long, u long, nil boolean, n_bytes long, sha string")
    # A text that other rows hold too goes as a whole; its rows are dealt out by a salt.
    copied = docs.where(F.octet_length("text") >= length).groupBy("t", "u").agg(F.count("*").alias("c")).where("c > 1")
    copied = copied.select("t", "u", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"), F.lit(True).alias("copied"))
    out = base.join(cuts, ["d", "t"], "left").withColumn("salt", F.pmod(F.xxhash64("d"), F.lit(SALTS)).cast("int")).join(copied, ["t", "u", "salt"], "left")
    span = F.struct(F.lit(0).cast("long").alias("start"), F.col("n_bytes").alias("stop"))
    out = out.withColumns({"n_removed": F.when(F.col("copied"), F.col("n_bytes")).otherwise(F.col("n_removed")), "spans": F.when(F.col("copied"), F.array(span)).otherwise(F.col("spans")), "kept": F.when(F.col("copied"), F.lit(hashlib.sha256(b"").hexdigest())).otherwise(F.col("kept"))})
    return out.select(
        F.when(~F.col("nil"), F.col("d")).alias("doc_id"), "n_bytes", F.coalesce("n_removed", F.lit(0)).cast("long").alias("n_removed"),
        F.coalesce(F.size("spans"), F.lit(0)).cast("long").alias("n_spans"), F.coalesce("kept", "sha").alias("kept_sha256"), F.coalesce("spans", F.array().cast("array<struct<start:long,stop:long>>")).alias("spans"),
    )


def op5_suffix_dedup(spark, sf_dir: str) -> DataFrame:
    return repeats(spark.read.parquet(f"{sf_dir}/documents.parquet")).drop("spans")
