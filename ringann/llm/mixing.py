"""Mixing sources to target weights by Efraimidis-Spirakis sampling, in DataFrame operations only.

A document's key is -ln(u) / quality, u uniform from a hash of its id: the smaller, the earlier, so better
documents tend to come first. A source's target is its share of all words by weight, at most `cap` times its
size, the excess reshared by weight. A target of e.f times the source's size takes e complete epochs, then
documents in key order until their words reach the fraction.

The prefix sum needs no sort of a whole source: keys fall in `slots` slots of equal probability; slots below
the cut are taken whole, and only the one slot that the cut falls in is sorted. A source may thus hold any
share of the rows.

Edge cases: null text has size 0; null is a source of its own, last; null or non-positive quality counts as
1; sources without words get a target of 0; rows that share a doc_id have the same key and are ordered by
size; a null doc_id is hashed as the empty text; empty tables give empty results.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ringann.llm.shared import stage

CAP, SLOTS, CYCLE = 3, 2048, 3
WORD = r"[^\x20\x09-\x0D]+"


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def uniform(ident: Column, seed: str) -> Column:
    """In (0, 1), from 52 bits of a hash; the same in any SQL engine that has md5."""
    bits = F.conv(F.substring(F.md5(F.concat(F.lit(seed + ":"), F.coalesce(ident.cast("string"), F.lit("")))), 1, 13), 16, 10).cast("double")
    return (bits + 0.5) / float(1 << 52)


def targets(sizes: DataFrame, cap: float = CAP, cycle: int = CYCLE) -> DataFrame:
    """sizes(source, source_size) with `target`. One row per source is gathered, never a document.

    With r = cap * size / weight ascending, sources up to some rank stop at the cap and the rest share what is
    left by weight; the rank is the first whose share per weight does not exceed its r.
    """
    every = Window.partitionBy(F.lit(0))
    ranked = sizes.withColumn("__w", (F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1) % cycle + 1.0)
    ranked = ranked.withColumn("__c", cap * F.col("source_size").cast("double"))
    ranked = ranked.withColumn("__r", F.col("__c") / F.col("__w"))
    order = Window.partitionBy(F.lit(0)).orderBy("__r", F.col("source").asc_nulls_last())
    ranked = ranked.withColumn("__capped", F.coalesce(F.sum("__c").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
    ranked = ranked.withColumn("__left", F.sum("__w").over(order.rowsBetween(0, Window.unboundedFollowing)))
    ranked = ranked.withColumn("__unit", (F.sum("source_size").over(every) - F.col("__capped")) / F.col("__left"))
    unit = F.min(F.when(F.col("__unit") <= F.col("__r"), F.struct("__r", "source", "__unit"))).over(every)["__unit"]
    return ranked.withColumn("target", F.least(F.col("__c"), F.coalesce(unit, F.lit(0.0)) * F.col("__w"))).select("source", "source_size", "target")


def mix(docs: DataFrame, quality: Column | None = None, seed: str = "mix", cap: float = CAP, cycle: int = CYCLE, slots: int = SLOTS, targets_df: DataFrame | None = None) -> DataFrame:
    """(doc_id, source, size, source_size, target, copies, taken): how often the mix takes each document."""
    quality = F.lit(1.0) if quality is None else quality.cast("double")
    rows = docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), quality.alias("__q"))
    rows = rows.withColumn("__q", F.when(F.col("__q") > 0, F.col("__q")).otherwise(F.lit(1.0)))
    rows = rows.withColumn("__key", -F.log(uniform(F.col("doc_id"), seed)) / F.col("__q"))
    rows = rows.withColumn("__slot", F.least(F.floor((1 - F.exp(-F.col("__key"))) * slots), F.lit(slots - 1)).cast("int"))
    rows = stage(rows.drop("__q"))
    sums = rows.groupBy("source", "__slot").agg(F.sum("size").alias("__sum"))
    sizes = sums.groupBy("source").agg(F.sum("__sum").alias("source_size"))
    goal = targets(sizes, cap, cycle) if targets_df is None else sizes.join(targets_df, F.expr("source <=> t_source")).select("source", "source_size", "target")
    goal = goal.withColumn("__epochs", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)))
    goal = goal.withColumn("__rest", F.col("target") - F.col("__epochs") * F.col("source_size"))
    order = Window.partitionBy("source").orderBy("__slot").rowsBetween(Window.unboundedPreceding, -1)
    plan = sums.withColumn("__before", F.coalesce(F.sum("__sum").over(order), F.lit(0)))
    plan = plan.join(goal.withColumnRenamed("source", "__s"), F.col("source").eqNullSafe(F.col("__s"))).drop("__s")
    # At most sources * slots rows: Spark broadcasts them while they are small, else joins by shuffle.
    plan = plan.withColumnsRenamed({"source": "__s", "__slot": "__k"})
    placed = rows.join(plan, F.col("source").eqNullSafe(F.col("__s")) & (F.col("__slot") == F.col("__k"))).drop("__s", "__k")
    below = F.col("__before") + F.col("__sum") <= F.col("__rest")
    above = F.col("__before") >= F.col("__rest")
    keep = ["doc_id", "source", "size", "source_size", "target", "copies"]
    whole = placed.where(below | above).withColumn("copies", F.col("__epochs") + F.when(below, 1).otherwise(0)).select(keep)
    within = Window.partitionBy("source", "__slot").orderBy("__key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    edge = placed.where(~(below | above)).withColumn("__prior", F.col("__before") + F.coalesce(F.sum("size").over(within), F.lit(0)))
    edge = edge.withColumn("copies", F.col("__epochs") + F.when(F.col("__prior") + F.col("size") / 2 <= F.col("__rest"), 1).otherwise(0)).select(keep)
    return whole.union(edge).withColumn("copies", F.col("copies").cast("long")).withColumn("taken", (F.col("copies") * F.col("size")).cast("long"))


def materialize(docs: DataFrame, mixed: DataFrame) -> DataFrame:
    """docs repeated as often as the mix takes them, numbered by `copy`, which replaces such a column. doc_id is to be unique here."""
    docs = docs.drop("copy")
    counts = mixed.where("copies > 0").select(F.col("doc_id").alias("__id"), "copies")
    out = docs.join(counts, F.col("doc_id").eqNullSafe(F.col("__id")))
    return out.withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("copies")))).select(*[docs[c] for c in docs.columns], F.col("__copy").cast("int").alias("copy"))


def text_quality(text: Column) -> Column:
    """A cheap quality weight in [0.5, 2]: characters per line / 100, capped; lists and stubs weigh less than prose."""
    lines = F.length(text) - F.length(F.replace(text, F.lit("\n"))) + 1
    return F.coalesce(F.greatest(F.lit(0.5), F.least(F.lit(2.0), F.length(text) / lines / 100)), F.lit(1.0))


def op2_mixing(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return mix(docs, quality=text_quality(F.col("text"))).select("doc_id", "size", "source_size", "target", "taken")


OP2_SQL = r"""
WITH d AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
    coalesce(greatest(0.5::DOUBLE, least(2.0::DOUBLE, length(text) / (length(text) - length(replace(text, chr(10), '')) + 1) / 100)), 1) AS q,
    (('0x' || substr(md5('mix:' || coalesce(doc_id::VARCHAR, '')), 1, 13))::BIGINT + 0.5::DOUBLE) / 4503599627370496::DOUBLE AS u FROM documents
), s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source
), w AS (SELECT *, ((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::DOUBLE AS w, 3.0::DOUBLE * source_size AS c FROM s
), o AS (SELECT *, c / w AS r, (sum(source_size) OVER () - coalesce(sum(c) OVER (ORDER BY c / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
    / sum(w) OVER (ORDER BY c / w, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS unit FROM w
), t AS (SELECT source, source_size, least(c, coalesce((SELECT arg_min(unit, r) FROM o WHERE unit <= r), 0) * w) AS target FROM o
), p AS (
  SELECT d.*, source_size, target, CASE WHEN source_size > 0 THEN floor(target / source_size) ELSE 0 END AS e,
    coalesce(sum(size) OVER (PARTITION BY d.source ORDER BY -ln(u) / q, doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS prior
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source
)
SELECT doc_id, size, source_size, target, (size * (e + CASE WHEN prior + size / 2 <= target - e * source_size THEN 1 ELSE 0 END))::BIGINT AS taken FROM p
"""
