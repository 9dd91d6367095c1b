"""Language identification by mixture inference.

Each learned language has a distribution of hashed byte trigrams, counted over all labelled training texts. A
document is a mixture of languages and of a uniform noise component; expectation-maximisation finds its
proportions from the trigram likelihoods, and languages leave the set, the least first, while the likelihood
penalised by half a log of the trigram count per language does not fall. The prediction is the language with
the largest proportion, the score its share among the languages.

Edge cases: null text or text without a letter is `und` with score 0; without training texts all is `und`; ties
go to the first language by code point; repeated rows count each; a null doc_id hashes as the empty text; an empty
table gives an empty result; kept columns that are named like the prediction's are replaced by it.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringann.llm.kernel import LOWER, byte_class, text_chunks

BUCKETS = 1 << 16
SMOOTH = 0.05
MOST_LANGS = 512  # 128 MB of probabilities
#: Letters for trigrams: ASCII letters and all bytes of non-ASCII characters; everything else is one space.
LETTER = byte_class((0x00, 0x40), (0x5B, 0x60), (0x7B, 0x7F))
FOLD = np.where(LETTER, LOWER, 32).astype(np.uint8)
ASCII_LETTER = byte_class((0x00, 0x40), (0x5B, 0x60), (0x7B, 0xFF))


def trigrams(data: np.ndarray) -> np.ndarray:
    """Bucket of the trigram that starts at each byte but the last two."""
    x = FOLD[data].astype(np.uint32)
    if len(x) < 3:
        return np.zeros(0, np.int64)
    h = (x[:-2] * np.uint32(65599) + x[1:-1]) * np.uint32(65599) + x[2:]
    h ^= h >> np.uint32(15)
    return ((h * np.uint32(2654435761)) >> np.uint32(16)).astype(np.int64)


def fit(docs: DataFrame) -> tuple[list[str], np.ndarray]:
    """(languages, probabilities by bucket) from docs(text, lang) with lang; sums are at most languages * BUCKETS rows."""

    def count(batches):
        totals: dict[str, np.ndarray] = {}
        for rows, off, data in text_chunks(batches):
            langs = rows.column("lang").to_pylist()
            for i, lang in enumerate(langs):
                t = totals.get(lang)
                if t is None:
                    t = totals[lang] = np.zeros(BUCKETS, np.int64)
                np.add.at(t, trigrams(data[off[i] : off[i + 1]]), 1)
        for lang, t in totals.items():
            at = np.flatnonzero(t)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.string()), pa.array(at, pa.int32()), pa.array(t[at])], names=["lang", "bucket", "n"])

    known = docs.where("lang IS NOT NULL")
    many = known.agg(F.approx_count_distinct("lang")).first()[0]
    if many > MOST_LANGS:
        raise ValueError(f"about {many} languages; the model is languages * {BUCKETS} numbers and takes {MOST_LANGS} at most")
    found = known.select("text", "lang").mapInArrow(count, "lang string, bucket int, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toArrow()
    langs = sorted(set(found["lang"].to_pylist()), key=lambda s: s.encode())
    probs = np.full((len(langs), BUCKETS), SMOOTH)
    place = {x: i for i, x in enumerate(langs)}
    if langs:
        np.add.at(probs, (np.array([place[x] for x in found["lang"].to_pylist()]), found["bucket"].to_numpy()), found["n"].to_numpy())
    return langs, (probs / probs.sum(axis=1, keepdims=True)).astype(np.float32)


def _em(like: np.ndarray, weight: np.ndarray, share: np.ndarray, rounds: int) -> tuple[np.ndarray, float]:
    for _ in range(rounds):
        mixed = share @ like
        share = share * (like @ (weight / mixed))
        share /= share.sum()
    return share, float(weight @ np.log(share @ like))


def infer(probs: np.ndarray, grams: np.ndarray, rounds: int = 8) -> np.ndarray:
    """Proportions of the languages and, last, of noise."""
    n_lang = len(probs)
    at, weight = np.unique(grams, return_counts=True)
    like = np.concatenate([probs[:, at], np.full((1, len(at)), 1.0 / BUCKETS, np.float32)]).astype(np.float64)
    weight = weight.astype(np.float64)
    active = np.arange(n_lang + 1)
    share, fit_ = _em(like, weight, np.full(n_lang + 1, 1 / (n_lang + 1)), rounds)
    cost = 0.5 * np.log(max(2.0, weight.sum()))
    while len(active) > 1:
        out = int(np.argmin(share))
        keep = np.delete(np.arange(len(active)), out)
        start = share[keep] + 1e-9
        part, fit2 = _em(like[active[keep]], weight, start / start.sum(), rounds // 2)
        if fit2 + cost < fit_:
            break
        active, share, fit_ = active[keep], part, fit2
    full = np.zeros(n_lang + 1)
    full[active] = share
    return full


def predict(docs: DataFrame, model: tuple[list[str], np.ndarray], keep: list[str] = ()) -> DataFrame:
    """(doc_id, *keep, lang_pred, score, noise, n_langs): the model is languages * BUCKETS numbers, broadcast."""
    langs, probs = model
    keep = [c for c in keep if c not in ("lang_pred", "score", "noise", "n_langs")]
    shared = docs.sparkSession.sparkContext.broadcast(probs)
    out = docs.select("doc_id", *keep).schema.simpleString()[7:-1] + ",lang_pred:string,score:double,noise:double,n_langs:int"

    def run(batches):
        table = shared.value
        for rows, off, data in text_chunks(batches):
            names, scores, noise, sizes = [], [], [], []
            letter = np.concatenate([[0], np.cumsum(ASCII_LETTER[data])])
            for i in range(rows.num_rows):
                a, b = off[i], off[i + 1]
                some = letter[b] > letter[a] or any(c.isalpha() for c in data[a:b].tobytes().decode())
                if not some or not len(langs):
                    names.append("und"), scores.append(0.0), noise.append(1.0), sizes.append(0)
                    continue
                body = data[a:b]
                grams = trigrams(body if b - a >= 3 else np.concatenate([body, np.full(3, 32, np.uint8)]))
                share = infer(table, grams)
                best = int(np.argmax(share[:-1]))
                total = share[:-1].sum()
                if total <= 0:  # all noise: the likeliest single language
                    best = int(np.argmax(np.log(table[:, grams]).sum(axis=1)))
                names.append(langs[best])
                scores.append(float(min(1.0, share[best] / total)) if total > 0 else 0.0)
                noise.append(float(share[-1]))
                sizes.append(int((share[:-1] > 0).sum()))
            yield pa.RecordBatch.from_arrays(
                [rows.column("doc_id"), *[rows.column(c) for c in keep], pa.array(names, pa.string()), pa.array(scores, pa.float64()), pa.array(noise, pa.float64()), pa.array(sizes, pa.int32())],
                names=["doc_id", *keep, "lang_pred", "score", "noise", "n_langs"],
            )

    return docs.select("doc_id", *keep, *(["text"] if "text" not in keep else [])).mapInArrow(run, ", ".join(x.replace(":", " ", 1) for x in out.split(",")))


def fold(n: int, column: str = "doc_id"):
    return F.crc32(F.coalesce(F.col(column).cast("string"), F.lit("")).cast("binary")) % n


def op3_language_id(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    model = fit(docs.where(fold(3) != 1))
    return predict(docs.select("doc_id", "text", (fold(3) == 1).alias("held_out")), model, ["held_out"])
