"""Vector sets of the experiments, built from the given tables: (obj_id, vec ARRAY<DOUBLE>)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ringann.sources.tables import read_table


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("obj_id"), F.col("embedding").cast("array<double>").alias("vec"))


def hashed_documents(docs: DataFrame, d: int, ident: str = "doc_id", text: str = "text") -> DataFrame:
    """(obj_id, vec): signed hashed trigrams of bytes of whole texts, A-Z lower-cased, of length 1; rows whose vector is zero are left out.

    Trigrams of a batch are numbered and added up as arrays, about 4 MB of text at a time.
    """
    import numpy as np
    import pyarrow as pa

    lower = np.arange(256, dtype=np.int64)
    lower[65:91] += 32

    def run(batches):
        for b in batches:
            col = b.column(1).cast(pa.large_string()).fill_null("")
            off = np.frombuffer(col.buffers()[1], np.int64)[col.offset : col.offset + len(col) + 1]
            data = np.frombuffer(col.buffers()[2], np.uint8) if col.buffers()[2] is not None else np.zeros(0, np.uint8)
            ids, lo = b.column(0), 0
            while lo < len(col):
                hi = min(len(col), max(lo + 1, int(np.searchsorted(off, off[lo] + (1 << 22), "right")) - 1))
                low = lower[data[off[lo] : off[hi]]]
                sums = np.zeros((hi - lo) * d)
                if len(low) > 2:
                    row = np.repeat(np.arange(hi - lo), np.diff(off[lo : hi + 1]))
                    h = (((low[:-2] << 16) | (low[1:-1] << 8) | low[2:]) * MULTIPLIER) & 0xFFFFFFFF
                    whole = row[:-2] == row[2:]
                    sums = np.bincount((row[:-2] * d + (h >> 8) % d)[whole], np.where(h >> 31, -1.0, 1.0)[whole], (hi - lo) * d)
                vec = sums.reshape(-1, d)
                size = np.sqrt((vec * vec).sum(axis=1))
                some = np.flatnonzero(size > 0)
                if len(some):
                    flat = pa.array((vec[some] / size[some, None]).ravel())
                    yield pa.RecordBatch.from_arrays([ids.slice(lo, hi - lo).take(pa.array(some)), pa.ListArray.from_arrays(pa.array(np.arange(len(some) + 1) * d, pa.int32()), flat)], names=["obj_id", "vec"])
                lo = hi

    return docs.select(F.col(ident).cast("long"), text).mapInArrow(run, "obj_id long, vec array<double>")


#: Of the multiplicative hash of a trigram's 24 bits.
MULTIPLIER = 2654435761


def sign_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(obj_id, vec): embeddings as bits, 1 where a coordinate is positive."""
    return embeddings(spark, sf_dir).select("obj_id", F.transform("vec", lambda x: (x > 0).cast("double")).alias("vec"))


def word_shingles(docs: DataFrame, width: int = 3, ident: str = "doc_id", text: str = "text") -> DataFrame:
    """(obj_id, vec ARRAY<LONG>): distinct shingles of `width` words as 28-bit numbers; fewer words are one shingle, none an empty set."""
    import hashlib

    import pyarrow as pa

    low = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))

    def run(batches):
        for b in batches:
            sets = []
            for t in b.column(1).to_pylist():
                w = (t or "").encode().translate(low).split()
                grams = {b" ".join(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} if w else ()
                sets.append(sorted({int(hashlib.md5(g).hexdigest()[:7], 16) for g in grams}))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sets, pa.list_(pa.int64()))], names=["obj_id", "vec"])

    return docs.select(F.col(ident).cast("long"), text).mapInArrow(run, "obj_id long, vec array<long>")


def page_texts(pages: DataFrame) -> DataFrame:
    """(page_id, text): pages without scripts, styles and tags."""
    bare = F.regexp_replace(F.coalesce("html", F.lit("")), r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    return pages.select("page_id", F.trim(F.regexp_replace(F.regexp_replace(bare, "<[^>]*>", " "), r"[ \t\n\r]+", " ")).alias("text"))


def standardize(df: DataFrame, columns: list[str]) -> DataFrame:
    """(obj_id, vec) of columns less their mean over their deviation; a constant column becomes 0.

    A second pass adds up what is left after the first one's mean and variance: such sums stay near 0, so that their
    rounding does not grow with the rows, as that of plain sums does (to some 1e-12 of the mean over 36 million rows).
    """
    rough = df.agg(*[F.avg(c).alias(f"m_{c}") for c in columns], *[F.stddev_pop(c).alias(f"s_{c}") for c in columns])
    off = lambda c: F.col(c) - F.col(f"m_{c}")
    var = lambda c: F.col(f"s_{c}") * F.col(f"s_{c}")
    rest = [F.avg(off(c)).alias(f"e_{c}") for c in columns] + [F.avg(off(c) * off(c) - var(c)).alias(f"v_{c}") for c in columns]
    stats = df.join(F.broadcast(rough), F.lit(True)).agg(*[F.first(x).alias(x) for x in rough.columns], *rest)
    mean = lambda c: F.col(f"m_{c}") + F.col(f"e_{c}")
    deviation = lambda c: F.sqrt(var(c) + F.col(f"v_{c}") - F.col(f"e_{c}") * F.col(f"e_{c}"))
    vec = F.array(*[F.when(F.col(f"s_{c}") > 0, (F.col(c) - mean(c)) / deviation(c)).otherwise(0.0) for c in columns])
    return df.join(F.broadcast(stats), F.lit(True)).select("obj_id", vec.alias("vec"))


MONTHS = [f"m{i}" for i in range(1, 13)]
PART_FEATURES = ["qty", "price", "disc", "tax", "n", "ret", "fin", "qty_sd", *MONTHS]


def part_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = read_table(spark, sf_dir, "lineitem")
    share = lambda hit: F.avg(hit.cast("double"))
    months = [share(F.month("l_shipdate") == i).alias(f"m{i}") for i in range(1, 13)]
    return li.groupBy(F.col("l_partkey").alias("obj_id")).agg(
        F.avg("l_quantity").alias("qty"), F.avg("l_extendedprice").alias("price"), F.avg("l_discount").alias("disc"), F.avg("l_tax").alias("tax"), F.count("*").cast("double").alias("n"),
        share(F.col("l_returnflag") == "R").alias("ret"), share(F.col("l_linestatus") == "F").alias("fin"), F.coalesce(F.stddev_samp("l_quantity"), F.lit(0.0)).alias("qty_sd"), *months,
    )


def part_profiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return standardize(part_features(spark, sf_dir), PART_FEATURES)


def line_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    cols = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
    li = read_table(spark, sf_dir, "lineitem").withColumn("obj_id", F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice"))
    return standardize(li.select("obj_id", *cols), cols)


STAND_INS = {"audio": ("part_profiles", 20), "image": ("embeddings", 64), "wide": ("documents", 960), "text": ("documents", 100), "codes": ("pages", 256)}


def stand_in(spark: SparkSession, sf_dir: str, name: str, d: int | None = None) -> tuple[DataFrame, int]:
    """(vectors, d) of a stand-in for one of the paper's five sets; d can be given for hashed texts."""
    table, size = STAND_INS[name]
    if table == "part_profiles":
        return part_profiles(spark, sf_dir), size
    if table == "embeddings":
        return embeddings(spark, sf_dir), size
    size = d or size
    rows = read_table(spark, sf_dir, table)
    return (hashed_documents(page_texts(rows), size, "page_id") if table == "pages" else hashed_documents(rows, size)), size


def customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = read_table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count("*").alias("n"), F.avg("o_totalprice").alias("avg_price"), F.max("o_totalprice").alias("max_price"))
    c = read_table(spark, sf_dir, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left").na.fill(0.0, ["avg_price", "max_price"]).na.fill(0, ["n"])
    return standardize(c.select(F.col("c_custkey").alias("obj_id"), F.col("c_acctbal").alias("bal"), F.col("n").cast("double").alias("n"), "avg_price", "max_price"), ["bal", "n", "avg_price", "max_price"])


def split_queries(data: DataFrame, every: int) -> tuple[DataFrame, DataFrame]:
    """(data without queries, queries): every `every`-th id leaves the data."""
    asked = F.pmod("obj_id", F.lit(every)) == 0
    return data.where(~asked), data.where(asked).select(F.col("obj_id").alias("qid"), "vec")


def every_nth(data: DataFrame, every: int) -> tuple[DataFrame, DataFrame]:
    """(data, queries): every `every`-th id is asked against all rows; the search is to leave out the query itself."""
    return data, data.where(F.pmod("obj_id", F.lit(every)) == 0).select(F.col("obj_id").alias("qid"), "vec")
