"""Language-model scoring by deleted interpolation of bigram, unigram and uniform estimates.

Documents are dealt to blocks by a hash of doc_id and text. A block sends its distinct unigrams and bigrams, sorted by
hash and cut into shards, with its own training counts; a shard sums them over all blocks and answers every
block with the totals in the order asked, so keys are never sent back. Blocks then score their documents
against the answers. A count gathered from the corpus thus crosses the network once each way, and no task or
driver holds the vocabulary.

Mixture weights, one triple for each bucket of log2 context frequency, are learned by expectation-maximisation
on deleted counts: tokens of all training documents are predicted from the totals without their own document, so that
weights do not depend on blocks. Their estimates reach the driver as a histogram of bounded size.

Edge cases: null text is empty and has one token, the end; unseen contexts use bucket 0; without training tokens
the model is uniform; repeated rows count each; a null doc_id hashes as the empty text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringann.llm.kernel import BYTE_CODES, LOWER, NOT_SPACE, Rolling, mix, row_of, words
from ringann.llm.jaccard import packed_texts
from ringann.llm.language import fold
from ringann.llm.shared import stage

FOLDS, HELD = 5, 1
BLOCK_BYTES = 6 << 20
CONTEXTS, STEP, FLOOR = 40, 4, 40  # context buckets; histogram steps per factor of 2; lowest log2 kept apart
END, START = np.uint64(0x1F83D9ABFB41BD6B), np.uint64(0x5BE0CD19137E2179)
C1, C2 = np.uint64(0xA24BAED4963EE407), np.uint64(0x9FB21C651E98DF25)
ROW = "block int, kind int, shard int, doc_id long, fold int, n long, z binary"


class Block:
    """Tokens of a block's documents: each document's words, then the end."""

    def __init__(self, raw: list[bytes], folds: np.ndarray):
        off = np.concatenate([[0], np.cumsum([len(x) for x in raw])]).astype(np.int64)
        low = LOWER[np.frombuffer(b"".join(raw), np.uint8)]
        starts, ends, first = words(low, off, NOT_SPACE)
        row = row_of(first)
        self.first = first + np.arange(len(first))
        self.codes = np.full(self.first[-1], END, np.uint64)
        self.codes[np.arange(len(starts)) + row] = Rolling(BYTE_CODES[low]).spans(starts, ends)
        before = np.empty_like(self.codes)
        before[1:], before[self.first[:-1]] = self.codes[:-1], START
        self.doc = np.repeat(np.arange(len(raw)), np.diff(self.first))
        self.train = (folds != HELD)[self.doc]
        self.uni, self.at1 = np.unique(np.concatenate([self.codes, [START]]), return_inverse=True)
        self.start, self.at1 = self.at1[-1], self.at1[:-1]
        self.bi, self.at2 = np.unique(mix(before * C1 + self.codes * C2), return_inverse=True)
        self.context = np.empty_like(self.at1)
        self.context[1:], self.context[self.first[:-1]] = self.at1[:-1], self.start
        # The start stands for one context per document; it is no token.
        self.own1 = np.bincount(self.at1[self.train], minlength=len(self.uni))
        self.own1[self.start] += int((folds != HELD).sum())
        self.own2 = np.bincount(self.at2[self.train], minlength=len(self.bi))


def _pack(x: np.ndarray) -> bytes:
    """Sorted keys as differences, or counts, in byte planes, compressed."""
    return pa.Codec("zstd", compression_level=1).compress(np.ascontiguousarray(x.view(np.uint8).reshape(len(x), x.itemsize).T).tobytes(), asbytes=True)


def _unpack(z: bytes, n: int, kind) -> np.ndarray:
    size = np.dtype(kind).itemsize
    raw = np.frombuffer(pa.Codec("zstd").decompress(z, n * size, asbytes=True), np.uint8)
    return np.ascontiguousarray(raw.reshape(size, n).T).view(kind).ravel()


def _read_block(batches):
    """(doc ids, folds, texts, answers by kind in shard order) of one block, documents in a fixed order."""
    codec, docs, answers = pa.Codec("zstd"), [], {1: [], 2: []}
    for batch in batches:
        kind, z, n = batch.column("kind").to_numpy(), batch.column("z"), batch.column("n").to_pylist()
        ids, folds, shard = batch.column("doc_id").to_pylist(), batch.column("fold").to_pylist(), batch.column("shard").to_pylist()
        for i in range(batch.num_rows):
            if kind[i] == 0:
                docs.append((ids[i], folds[i], codec.decompress(z[i].as_py(), n[i], asbytes=True) if n[i] else b""))
            else:
                answers[kind[i]].append((shard[i], n[i], z[i].as_py()))
    docs.sort(key=lambda d: (d[0] is None, d[0] or 0, d[1], d[2]))
    totals = {k: np.concatenate([_unpack(z, n, np.uint32) for _, n, z in sorted(v, key=lambda x: x[0])]) if v else None for k, v in answers.items()}
    return [d[0] for d in docs], np.array([d[1] for d in docs]), [d[2] for d in docs], totals


def _counts(rows: DataFrame, shards: int) -> DataFrame:
    """Answers: (block, kind, shard, n, z) with total training counts, and kind 3: distinct training tokens of a shard."""
    bits = np.uint64(64 - shards.bit_length() + 1)

    def ask(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, folds, texts, _ = _read_block(batches)
        b = Block(texts, folds)
        for kind, keys, own in ((1, b.uni, b.own1), (2, b.bi, b.own2)):
            own_shard = (keys >> bits).astype(np.int64) if shards > 1 else np.zeros(len(keys), np.int64)
            cut = np.append(np.flatnonzero(np.diff(own_shard, prepend=-1)), len(keys))
            part = own_shard[cut[:-1]]
            drop = np.uint64(0 if kind == 1 else 8)
            zs, cs = [], []
            for lo, hi in zip(cut[:-1], cut[1:]):
                zs.append(_pack(np.diff(keys[lo:hi] >> drop, prepend=np.uint64(0))))
                cs.append(_pack(own[lo:hi].astype(np.uint32)))
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.int32()), pa.array([kind] * len(part), pa.int32()), pa.array([key[0].as_py()] * len(part), pa.int32()), pa.array(np.diff(cut), pa.int64()), pa.array(zs, pa.binary()), pa.array(cs, pa.binary())], names=["shard", "kind", "block", "n", "z", "c"])

    def answer(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard, kind = key[0].as_py(), key[1].as_py()
        blocks, sizes, keys, own = [], [], [], []
        for batch in batches:
            for blk, n, z, c in zip(batch.column("block").to_pylist(), batch.column("n").to_pylist(), batch.column("z"), batch.column("c")):
                blocks.append(blk), sizes.append(n)
                keys.append(np.cumsum(_unpack(z.as_py(), n, np.uint64), dtype=np.uint64))
                own.append(_unpack(c.as_py(), n, np.uint32))
        known, at = np.unique(np.concatenate(keys), return_inverse=True)
        total = np.zeros(len(known), np.int64)
        np.add.at(total, at, np.concatenate(own))
        if kind == 1:
            used = total[known != START]
            yield pa.RecordBatch.from_arrays([pa.array([-1], pa.int32()), pa.array([3], pa.int32()), pa.array([shard], pa.int32()), pa.array([int(used.sum())], pa.int64()), pa.array([str(int((used > 0).sum())).encode()], pa.binary())], names=["block", "kind", "shard", "n", "z"])
        asked = np.minimum(total, 0xFFFFFFFF).astype(np.uint32)[at]
        edge = np.concatenate([[0], np.cumsum(sizes)])
        for lo in range(0, len(blocks), 256):
            hi = min(lo + 256, len(blocks))
            yield pa.RecordBatch.from_arrays([pa.array(blocks[lo:hi], pa.int32()), pa.array([kind] * (hi - lo), pa.int32()), pa.array([shard] * (hi - lo), pa.int32()), pa.array(sizes[lo:hi], pa.int64()), pa.array([_pack(asked[edge[i] : edge[i + 1]]) for i in range(lo, hi)], pa.binary())], names=["block", "kind", "shard", "n", "z"])

    asked = rows.groupBy("block").applyInArrow(ask, "shard int, kind int, block int, n long, z binary, c binary")
    return asked.groupBy("shard", "kind").applyInArrow(answer, "block int, kind int, shard int, n long, z binary")


def _in_document(doc: np.ndarray, at: np.ndarray) -> np.ndarray:
    """How often each token's key, by its number `at`, occurs in the token's document; documents lie in order."""
    at, by = at.astype(np.int32), np.argsort(at.astype(np.int32), kind="stable").astype(np.int32)
    new = np.ones(len(at) + 1, bool)
    new[1:-1] = (np.diff(at[by]) != 0) | (np.diff(doc[by]) != 0)
    size = np.diff(np.flatnonzero(new)).astype(np.int32)
    n = np.empty(len(at), np.int32)
    n[by] = np.repeat(size, size)
    return n


def _estimates(b: Block, totals, n_all: int, own: bool):
    """(context counts, bigram and unigram estimates, token counts) of every token, without the counts of its own
    document if `own`, which holds for training documents only."""
    t1, t2 = totals[1].astype(np.float64), totals[2].astype(np.float64)
    ctx, c2, c1, n = t1[b.context], t2[b.at2], t1[b.at1], n_all
    if own:
        mine = _in_document(b.doc, b.at1)
        before = np.empty_like(mine)
        before[1:], before[b.first[:-1]] = mine[:-1], 1
        ctx, c2, c1 = ctx - before, c2 - _in_document(b.doc, b.at2), c1 - mine
        n = n_all - np.diff(b.first)[b.doc]
    p2 = np.divide(c2, ctx, out=np.zeros(len(ctx)), where=ctx > 0)
    return ctx, np.minimum(p2, 1.0), c1 / np.maximum(n, 1), c1


def _bucket(ctx: np.ndarray) -> np.ndarray:
    return np.minimum(np.log2(ctx + 1).astype(np.int64), CONTEXTS - 1)


def learn(cells: list[tuple[int, int]], uniform: float, rounds: int = 50) -> np.ndarray:
    """Weights (bigram, unigram, uniform) by context bucket, from histogram cells (code, count)."""
    weights = np.tile([0.4, 0.5, 0.1], (CONTEXTS, 1))
    weights[0] = [0.0, 0.9, 0.1]
    if not cells:
        weights[:] = [0.0, 0.0, 1.0]
        return weights
    code, count = np.array(cells, np.int64).T
    q = FLOOR * STEP + 1
    ctx, q2, q1 = code // (q * q), code // q % q, code % q
    value = lambda v: np.where(v == FLOOR * STEP, 0.0, np.exp2(-v / STEP))
    p = np.stack([value(q2), value(q1), np.full(len(code), uniform)], axis=1)
    for _ in range(rounds):
        part = weights[ctx] * p
        part *= (count / part.sum(axis=1))[:, None]
        sums = np.zeros((CONTEXTS, 3))
        np.add.at(sums, ctx, part)
        sums += [0.01, 0.05, 0.01]
        weights = sums / sums.sum(axis=1, keepdims=True)
    weights[0] = [0.0, *(weights[0, 1:] / weights[0, 1:].sum())]
    return weights


def score(docs: DataFrame, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score) for every row of docs(doc_id, text)."""
    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = max(1, -(-total // block_bytes))
    shards = 1 << (blocks - 1).bit_length()
    which = F.pmod(F.xxhash64("doc_id", "z"), F.lit(blocks)).cast("int")
    packed = packed_texts(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"))
    rows = packed.select(which.alias("block"), F.lit(0).alias("kind"), F.lit(0).alias("shard"), "doc_id", fold(FOLDS).cast("int").alias("fold"), "n", "z")
    answers = stage(_counts(rows, shards))
    sums = answers.where("kind = 3").agg(F.sum("n"), F.sum(F.col("z").cast("string").cast("long"))).first()
    n_all, n_types = int(sums[0] or 0), int(sums[1] or 0)
    uniform = 1.0 / (n_types + 1)
    empty = answers.where("kind < 3").select("block", "kind", "shard", F.lit(None).cast("long").alias("doc_id"), F.lit(0).alias("fold"), "n", "z")

    def histogram(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _, folds, texts, totals = _read_block(batches)
        b = Block(texts, folds)
        ctx, p2, p1, _ = _estimates(b, totals, n_all, True)
        pick = b.train
        step = lambda p: np.where(p > 0, np.minimum(-np.log2(np.maximum(p, 1e-30)) * STEP, FLOOR * STEP - 1), FLOOR * STEP).astype(np.int64)
        q = FLOOR * STEP + 1
        code, n = np.unique(((_bucket(np.maximum(ctx, 0)) * q + step(p2)) * q + step(p1))[pick], return_counts=True)
        yield pa.RecordBatch.from_arrays([pa.array(code, pa.int64()), pa.array(n, pa.int64())], names=["code", "n"])

    cells = rows.union(empty).groupBy("block").applyInArrow(histogram, "code long, n long").groupBy("code").agg(F.sum("n").alias("n")).collect()
    weights = learn([(r[0], r[1]) for r in cells], uniform)

    def judge(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, folds, texts, totals = _read_block(batches)
        b = Block(texts, folds)
        ctx, p2, p1, c = _estimates(b, totals, n_all, False)
        w = weights[_bucket(ctx)]
        s = np.log10(w[:, 0] * p2 + w[:, 1] * p1 + w[:, 2] * uniform)
        base = np.log10((c + 0.5) / (n_all + 0.5 * (n_types + 1)))
        add = lambda x: np.add.reduceat(x, b.first[:-1])
        yield pa.RecordBatch.from_arrays(
            [pa.array(ids, pa.int64()), pa.array(folds == HELD), pa.array(np.diff(b.first), pa.int64()), pa.array(add((c > 0).astype(np.int64))), pa.array(np.full(len(ids), n_all), pa.int64()), pa.array(add(base)), pa.array(add(s))],
            names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"],
        )

    return rows.union(empty).groupBy("block").applyInArrow(judge, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def op4_lm_score(spark, sf_dir: str) -> DataFrame:
    return score(spark.read.parquet(f"{sf_dir}/documents.parquet"))
