r"""Merkle fingerprints of documents, in DataFrame operations only.

The tree: a document's sections are its parts between blank lines, a section's paragraphs its lines, a
paragraph's leaves its pieces of up to `piece` code points, from its start. A digest is the md5 of the digests
below; the root is the sha256 of the section digests. The fingerprint text is
`root:section,section,...:leaf leaf ...`, sections by 8 and distinct leaves by 8 hex digits, so that two
fingerprints alone tell equality (roots), which sections differ, and how alike the documents are.

Likeness: 1 where roots agree, else the Dice coefficient of the two sets of leaves.

Edge cases: null text is the empty text; equal texts have equal fingerprints whatever their ids; for
neighbours, rows are ordered by descending doc_id, null last, then by text; a lone row is its own neighbour; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


PIECE = 64
SLOTS, SLOT_BYTES = 4096, 16 << 20


def _pieces(text: Column, piece: int) -> Column:
    return F.regexp_extract_all(text, F.lit(f"([^\n]{{1,{piece}}})"), F.lit(1))


def _leaf(piece: Column) -> Column:
    return F.substring(F.md5(piece), 1, 8)


def fingerprint(text: Column, piece: int = PIECE) -> Column:
    """root:sections:leaves as one string. The root covers md5 digests of all whole pieces, not the short leaves."""
    text = F.coalesce(text, F.lit(""))

    def paragraph(p: Column) -> Column:
        return F.md5(F.array_join(F.transform(_pieces(p, piece), F.md5), ","))

    sections = F.transform(F.split(text, "\n\n", -1), lambda s: F.md5(F.array_join(F.transform(F.split(s, "\n", -1), paragraph), ",")))
    short = F.array_join(F.transform(sections, lambda d: F.substring(d, 1, 8)), ",")
    leaves = F.array_join(F.array_sort(F.array_distinct(F.transform(_pieces(text, piece), _leaf))), " ")
    return F.concat(F.sha2(F.array_join(sections, ",").cast("binary"), 256), F.lit(":"), short, F.lit(":"), leaves)


def likeness(a: Column, b: Column) -> Column:
    x, y = (F.filter(F.split(F.substring_index(c, ":", -1), " "), lambda v: v != "") for c in (a, b))
    total = F.size(x) + F.size(y)
    dice = F.when(total > 0, 2.0 * F.size(F.array_intersect(x, y)) / total).otherwise(0.0)
    return F.when(F.substring_index(a, ":", 1) == F.substring_index(b, ":", 1), F.lit(1.0)).otherwise(dice)


def differing_sections(a: Column, b: Column) -> Column:
    """Indexes (0-based) of the sections of a whose digest is not at the same place in b."""
    x, y = (F.split(F.element_at(F.split(c, ":"), 2), ",") for c in (a, b))
    return F.filter(F.transform(x, lambda v, i: F.when(F.get(y, i).eqNullSafe(v), F.lit(None)).otherwise(i)), lambda v: v.isNotNull())


def _slot(cuts: list[int]) -> Column:
    """How many cuts are at least doc_id: first among every 64th cut, then among the 64 before it."""
    if not cuts:
        return F.lit(0)
    high = sorted(cuts, reverse=True)
    groups = [high[i : i + 64] for i in range(0, len(high), 64)]
    heads = F.array(*[F.lit(g[-1]) for g in groups])
    full = F.size(F.filter(heads, lambda c: c >= F.col("doc_id")))
    rest = F.get(F.array(*[F.array(*[F.lit(x) for x in g]) for g in groups]), full)
    return full * 64 + F.coalesce(F.size(F.filter(rest, lambda c: c >= F.col("doc_id"))), F.lit(0))


def with_next(docs: DataFrame, slot_bytes: int = SLOT_BYTES) -> DataFrame:
    """(doc_id, text, next_text): the text of the following row by descending doc_id; the first's after the last.

    Rows are dealt to ranges of doc_id with about as many rows each, as many ranges as the texts have times
    `slot_bytes`, and a window runs in every range; only the last row of a range looks at the first of the next
    range. One shuffle of the texts, no global sort.
    """
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    told = rows.agg(F.percentile_approx("doc_id", [i / SLOTS for i in range(1, SLOTS)], 4 * SLOTS).alias("c"), F.sum(F.octet_length("text")).alias("n")).first()
    slots = min(SLOTS, max(8, -(-(told["n"] or 0) // slot_bytes)))
    found = told["c"] or []
    cuts = sorted({found[i * len(found) // slots] for i in range(1, slots)}) if found else []
    # Slot 0 is the first in descending order; ids up to the lowest cut and null come last.
    ranked = rows.withColumn("__slot", F.when(F.col("doc_id").isNull(), F.lit(len(cuts) + 1)).otherwise(_slot(cuts)))
    order = Window.partitionBy("__slot").orderBy(F.col("doc_id").desc_nulls_last(), "text")
    led = ranked.withColumns({"__next": F.lead("text").over(order)})
    heads = ranked.groupBy("__slot").agg(F.min(F.struct((-F.col("doc_id")).alias("k"), "text")).alias("h")).select("__slot", F.col("h.text").alias("__head"))
    ring = Window.orderBy("__slot")
    first = F.first("__head").over(ring.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    heads = heads.select(F.col("__slot").alias("__k"), F.coalesce(F.lead("__head").over(ring), first).alias("__after"))
    return led.join(heads, F.col("__slot") == F.col("__k")).select("doc_id", "text", F.coalesce("__next", "__after").alias("next_text"))


def op8_fingerprints(spark, sf_dir: str) -> DataFrame:
    docs = with_next(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    n = F.length("text")
    half = F.floor(n / 2).cast("int")
    edited = F.concat(F.substring(F.col("text"), F.lit(1), n - half), F.substring(F.col("next_text"), F.lit(1), half))
    rows = docs.select("doc_id", n.cast("long").alias("n_chars"), "text", edited.alias("edited"), "next_text")
    rows = rows.select("doc_id", "n_chars", F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"), fingerprint(F.col("text")).alias("fingerprint"), fingerprint(F.col("edited")).alias("edited_fingerprint"), fingerprint(F.col("next_text")).alias("__n"))
    return rows.withColumn("near_edited", likeness(F.col("fingerprint"), F.col("edited_fingerprint"))).withColumn("near_next", likeness(F.col("fingerprint"), F.col("__n"))).drop("__n")


def _fingerprint_sql(text: str) -> str:
    return f"""sha256(array_to_string(list_transform(string_split({text}, chr(10) || chr(10)), lambda s: md5(array_to_string(list_transform(string_split(s, chr(10)),
      lambda p: md5(array_to_string(list_transform(regexp_extract_all(p, '[^\\n]{{1,64}}'), lambda x: md5(x)), ','))), ','))), ','))
    || ':' || array_to_string(list_transform(string_split({text}, chr(10) || chr(10)), lambda s: substr(md5(array_to_string(list_transform(string_split(s, chr(10)),
      lambda p: md5(array_to_string(list_transform(regexp_extract_all(p, '[^\\n]{{1,64}}'), lambda x: md5(x)), ','))), ',')), 1, 8)), ',')
    || ':' || array_to_string(list_sort(list_distinct(list_transform(regexp_extract_all({text}, '[^\\n]{{1,64}}'), lambda x: substr(md5(x), 1, 8)))), ' ')"""


def _likeness_sql(a: str, b: str) -> str:
    x, y = (f"list_filter(string_split(string_split({c}, ':')[3], ' '), lambda v: v <> '')" for c in (a, b))
    return f"CASE WHEN string_split({a}, ':')[1] = string_split({b}, ':')[1] THEN 1.0 WHEN len({x}) + len({y}) > 0 THEN 2.0::DOUBLE * len(list_intersect({x}, {y})) / (len({x}) + len({y})) ELSE 0.0 END"


OP8_SQL = f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents
), n AS (
  SELECT doc_id, text, coalesce(lead(text) OVER w, first_value(text) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)) AS next_text FROM d WINDOW w AS (ORDER BY doc_id DESC NULLS LAST, text)
), e AS (SELECT doc_id, text, next_text, length(text) AS n, substr(text, 1, length(text) - length(text) // 2) || substr(next_text, 1, length(text) // 2) AS edited FROM n
), f AS (SELECT doc_id, n::BIGINT AS n_chars, sha256(edited) AS edited_sha256, {_fingerprint_sql('text')} AS fingerprint, {_fingerprint_sql('edited')} AS edited_fingerprint, {_fingerprint_sql('next_text')} AS nf FROM e)
SELECT doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, ({_likeness_sql('fingerprint', 'edited_fingerprint')})::DOUBLE AS near_edited, ({_likeness_sql('fingerprint', 'nf')})::DOUBLE AS near_next FROM f
"""
