"""Corpus pipeline: language ID, line dedup, near-duplicate join, benchmark decontamination, source mixing.

Every stage is a function (spark, docs, sf_dir) -> DataFrame over all that its predecessor kept. All but the last
return the columns of `documents`; the last returns the mixed documents with how often each is taken.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ringann.llm import decontaminate, jaccard, language, lines, mixing
from ringann.llm.shared import stage

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
MAX_NOISE = 0.5
NUM, DEN, WIDTH = 80, 100, 5  # near duplicates: five words, similarity 0.8 or more


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents in a learned language: neither without letters nor mostly noise. A null lang becomes the inferred one."""
    model = language.fit(docs.select("text", "lang"))
    judged = language.predict(docs.select(COLUMNS), model, [c for c in COLUMNS if c != "doc_id"])
    kept = judged.where((F.col("lang_pred") != "und") & (F.col("noise") <= MAX_NOISE))
    return kept.withColumn("lang", F.coalesce("lang", "lang_pred")).select(COLUMNS)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without lines that three documents or more hold; a document that loses all its lines goes."""
    kept = lines.drop_lines(docs.select(COLUMNS))
    kept = kept.withColumn("n_chars", F.when(F.col("n_dropped") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars")))
    return kept.where("n_dropped < n_lines").select(COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each component stays, that of its smallest doc_id."""
    return jaccard.keep_one(docs.select(COLUMNS), WIDTH, NUM, DEN).select(COLUMNS)


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without any benchmark window."""
    return decontaminate.remove(docs.select(COLUMNS), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def source_mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix: documents with the number of copies it takes."""
    return mixing.mix(docs, quality=mixing.text_quality(F.col("text")))


STAGES = [
    ("language_id", language_id),
    ("line_dedup", line_dedup),
    ("near_duplicates", near_duplicates),
    ("benchmark_decontamination", benchmark_decontamination),
    ("source_mixing", source_mixing),
]
#: No SQL for the whole: a stage infers language mixtures. tests/llm compares the other stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select(COLUMNS)
    for name, step in STAGES[:-1]:
        docs = stage(step(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
