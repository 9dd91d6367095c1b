"""Secret scan with a trigram inverted index, in DataFrame operations only.

Each rule is a regular expression, and its Boolean trigram query is derived from the expression alone: an OR of
branches, each an AND of trigrams (of the lower-cased text) that every match of that branch contains. Postings
(trigram, doc_id) are built for the trigrams that the rules ask for; branches intersect postings, rules unite
branches, and only candidate documents are matched. A rule without a mandatory trigram, such as a run of hex
digits, has no query and scans every document.

Base rules: assign, access, hex. The method adds `pem`, the opening line of a private key block.
Matches are leftmost and non-overlapping within a rule; positions are code points, the end exclusive.

Edge cases: null text is empty; rows that share a doc_id share candidates and are matched one by one; a null
doc_id is matched against all rules; empty tables give empty results; other columns are ignored.
"""

from __future__ import annotations

import re._constants as kinds
import re._parser as parser
from dataclasses import dataclass
from functools import reduce
from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Rule:
    """Group `group` of a match of `pattern` has at least `least` characters."""

    kind: str
    pattern: str
    group: int = 0
    least: int = 0
    base: bool = True


def _any_case(word: str) -> str:
    return "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in word)


#: Fixed words of the assign rule; an underscore may stand between api and key.
KEYWORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")
ASSIGN = "(" + "|".join(map(_any_case, KEYWORDS)) + r""")["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""

RULES = (
    Rule("assign", ASSIGN, 2, 12),
    Rule("access", "(AKIA[A-Z0-9]+)", 1, 18),
    Rule("hex", "([0-9a-f]{16,})", 1, 16),
    Rule("pem", "(-----BEGIN [A-Z ]*PRIVATE KEY-----)", 1, 0, False),
)

MOST_STRINGS, MOST_CHARS, MOST_BRANCHES = 64, 16, 64
WORD = 62
Query = frozenset  # of branches; a branch is a frozenset of trigrams
ANY: Query = frozenset([frozenset()])  # holds for every text


def _both(x: Query, y: Query) -> Query:
    """AND of two queries, or one of them where the product is too large: a weaker query is still necessary."""
    if x == ANY or y == ANY:
        return y if x == ANY else x
    if len(x) * len(y) > MOST_BRANCHES:
        return min(x, y, key=len)
    return _least({a | b for a in x for b in y})


def _least(branches) -> Query:
    """Without branches that another one implies."""
    return frozenset(b for b in branches if not any(o < b for o in branches))


def _of_strings(strings) -> Query:
    """Some of these strings occurs."""
    return _least({frozenset(s[i : i + 3] for i in range(len(s) - 2)) for s in strings}) if strings else ANY


@dataclass(frozen=True)
class Part:
    """What is known of every match of a part of an expression: all its strings if they are few, else how it may
    begin and end (2 characters are kept) and a query that it satisfies."""

    exact: frozenset | None
    begins: frozenset = frozenset([""])
    ends: frozenset = frozenset([""])
    query: Query = ANY

    def heads(self):
        return self.begins if self.exact is None else frozenset(x[:2] for x in self.exact)

    def tails(self):
        return self.ends if self.exact is None else frozenset(x[-2:] for x in self.exact)

    def holds(self) -> Query:
        return self.query if self.exact is None else _of_strings(self.exact)


UNKNOWN = Part(None)


def _then(x: Part, y: Part) -> Part:
    if x.exact is not None and y.exact is not None and len(x.exact) * len(y.exact) <= MOST_STRINGS:
        return Part(frozenset(a + b for a in x.exact for b in y.exact))
    border = frozenset(a + b for a in x.tails() for b in y.heads())
    query = _both(_both(x.holds(), y.holds()), _of_strings(border) if len(border) <= MOST_STRINGS else ANY)
    few = lambda found: found if len(found) <= MOST_STRINGS else frozenset([""])
    begins = few(frozenset((a + b)[:2] for a in x.exact for b in y.heads())) if x.exact is not None else x.begins
    ends = few(frozenset((a + b)[-2:] for a in x.tails() for b in y.exact)) if y.exact is not None else y.ends
    return Part(None, begins, ends, query)


def _or(parts: list[Part]) -> Part:
    if all(p.exact is not None for p in parts) and len(every := frozenset().union(*[p.exact for p in parts])) <= MOST_STRINGS:
        return Part(every)
    queries = [p.holds() for p in parts]
    query = ANY if ANY in queries else _least(frozenset().union(*queries))
    begins, ends = frozenset().union(*[p.heads() for p in parts]), frozenset().union(*[p.tails() for p in parts])
    if len(query) > MOST_BRANCHES or len(begins) > MOST_STRINGS or len(ends) > MOST_STRINGS:
        return UNKNOWN
    return Part(None, begins, ends, query)


def _characters(items) -> Part:
    found = set()
    for kind, value in items:
        if kind is kinds.LITERAL:
            found.add(value)
        elif kind is kinds.RANGE and value[1] - value[0] < 2 * MOST_CHARS:
            found.update(range(value[0], value[1] + 1))
        else:
            return UNKNOWN
    if any(v > 127 for v in found):  # lower case of other characters is not the same everywhere
        return UNKNOWN
    lower = frozenset(chr(v).lower() for v in found)
    return Part(lower) if len(lower) <= MOST_CHARS else UNKNOWN


def _part(tree) -> Part:
    """Every kind of node that is not known here counts as any text, which keeps the query necessary."""
    out = Part(frozenset([""]))
    for kind, value in tree:
        if kind is kinds.LITERAL:
            new = _characters([(kind, value)])
        elif kind is kinds.IN:
            new = _characters(value)
        elif kind is kinds.SUBPATTERN:
            new = _part(value[3])
        elif kind is kinds.BRANCH:
            new = _or([_part(x) for x in value[1]])
        elif kind in (kinds.MAX_REPEAT, kinds.MIN_REPEAT, kinds.POSSESSIVE_REPEAT):
            least, most, inner = value
            once, new = _part(inner), Part(frozenset([""]))
            for _ in range(min(least, 4)):
                new = _then(new, once)
            if most == 1 and least == 0:
                new = _or([Part(frozenset([""])), once])
            elif most != least or least > 4:
                # More of the same may follow: the beginning and the query stay, the end is the inner one's if it is repeated.
                new = Part(None, new.heads(), once.tails() if least else frozenset([""]), new.holds()) if least else UNKNOWN
        elif kind is kinds.AT:
            continue
        else:
            new = UNKNOWN
        out = _then(out, new)
    return out


def trigram_query(rule: Rule) -> list[frozenset[str]]:
    """OR of ANDs of trigrams, from the rule's pattern; empty if it has no mandatory trigram, so that all documents are candidates."""
    query = _part(parser.parse(rule.pattern)).holds()
    return [] if any(not b for b in query) else sorted(query, key=sorted)


def postings(docs: DataFrame, trigrams: list[str]) -> DataFrame:
    """(trigram INT, doc_id): the inverted lists of the given trigrams, by their number in the list."""
    low = F.lower("text")
    found = F.array(*[F.when(F.contains("__low", F.lit(t)), F.lit(i)) for i, t in enumerate(trigrams)])
    if not trigrams:
        return docs.select(F.lit(0).alias("trigram"), "doc_id").limit(0)
    return docs.where("doc_id IS NOT NULL").select("doc_id", low.alias("__low")).select("doc_id", F.explode(F.array_compact(found)).alias("trigram")).select("trigram", "doc_id")


def candidates(docs: DataFrame, rules=RULES) -> DataFrame:
    """(doc_id, rules ARRAY<INT>): the queried rules whose trigram query the document satisfies."""
    queries = {i: trigram_query(r) for i, r in enumerate(rules)}
    trigrams = sorted({t for q in queries.values() for s in q for t in s})
    number = {t: i for i, t in enumerate(trigrams)}
    # The lists of one document meet as bits of numbers of WORD bits: an AND is a mask test, an OR a disjunction.
    words = range(-(-len(trigrams) // WORD) or 1)
    bit = F.expr(f"shiftleft(1L, trigram % {WORD})")
    met = postings(docs, trigrams).groupBy("doc_id").agg(*[F.bit_or(F.when(F.floor(F.col("trigram") / WORD) == w, bit).otherwise(F.lit(0).cast("long"))).alias(f"bits{w}") for w in words])
    tests = []
    for i, query in queries.items():
        if query:
            test = F.lit(False)
            for branch in query:
                masks = {w: sum(1 << number[t] % WORD for t in branch if number[t] // WORD == w) for w in words}
                test = test | reduce(lambda x, y: x & y, [F.col(f"bits{w}").bitwiseAND(F.lit(m).cast("long")) == m for w, m in masks.items() if m])
            tests.append(F.when(test, F.lit(i)))
    if not tests:
        return met.select("doc_id", F.array().cast("array<int>").alias("rules")).limit(0)
    return met.select("doc_id", F.array_compact(F.array(*tests)).alias("rules")).where(F.size("rules") > 0)


def matches(text: Column, rule: Rule, number: int) -> Column:
    """Array of structs (start, number, stop), in text order. Gaps and matches of one pattern alternate, so their running lengths are the positions."""
    whole = F.regexp_extract_all(text, F.lit(f"({rule.pattern})"), F.lit(0))
    kept = F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(rule.group))
    gaps = F.split(text, rule.pattern, -1)
    steps = F.transform(whole, lambda m, i: F.struct(F.length(F.get(gaps, i)).alias("gap"), F.length(m).alias("len"), F.length(F.get(kept, i)).alias("own")))
    empty = F.array().cast("array<struct<start:int,number:int,stop:int>>")

    def add(acc: Column, s: Column) -> Column:
        start = acc["at"] + s["gap"]
        span = F.struct(start.alias("start"), F.lit(number).alias("number"), (start + s["len"]).alias("stop"))
        return F.struct((start + s["len"]).alias("at"), F.when(s["own"] >= rule.least, F.concat(acc["out"], F.array(span))).otherwise(acc["out"]).alias("out"))

    spans = F.aggregate(steps, F.struct(F.lit(0).alias("at"), empty.alias("out")), add, lambda acc: acc["out"])
    return F.when(F.regexp_like(text, F.lit(rule.pattern)), spans).otherwise(empty)


def scan(docs: DataFrame, rules=RULES) -> DataFrame:
    """(doc_id, spans ARRAY<STRUCT<start, number, stop>>) for every row; number is the rule's place in `rules`."""
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    found = candidates(rows, rules).withColumnRenamed("doc_id", "__id")
    joined = rows.join(found, F.col("doc_id") == F.col("__id"), "left")
    parts = []
    for i, rule in enumerate(rules):
        hits = matches(F.col("text"), rule, i)
        if trigram_query(rule):
            hits = F.when(F.array_contains("rules", F.lit(i)) | F.col("doc_id").isNull(), hits).otherwise(F.array().cast("array<struct<start:int,number:int,stop:int>>"))
        parts.append(hits)
    return joined.select("doc_id", F.array_sort(F.concat(*parts)).alias("spans"))


def _text(spans: Column, rules) -> Column:
    kinds = F.array(*[F.lit(r.kind) for r in rules])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(kinds, s["number"]), s["start"].cast("string"), s["stop"].cast("string"))), ",")


def _count(number: int) -> Column:
    return F.size(F.filter("spans", lambda s: s["number"] == number)).cast("long")


def op9_secrets(spark, sf_dir: str) -> DataFrame:
    found = scan(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    counts = [_count(i).alias(f"n_{r.kind}") for i, r in enumerate(RULES) if r.base]
    last = max(i for i, r in enumerate(RULES) if r.base)
    base = F.filter("spans", lambda s: s["number"] <= last)
    return found.select("doc_id", *counts, F.sha2(_text(base, RULES).cast("binary"), 256).alias("base_sha256"), _text(F.col("spans"), RULES).alias("spans"))


def _spans_sql(rule: Rule, number: int) -> str:
    p = rule.pattern.replace("'", "''")
    return f"""SELECT doc_id, {number} AS number, (list_sum(list_transform(g[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(m[1:i-1], lambda x: length(x))), 0))::BIGINT AS start, length(m[i]) AS n, length(k[i]) AS own
  FROM (SELECT *, unnest(range(1, len(m) + 1)) AS i FROM (SELECT doc_id, regexp_extract_all(text, '{p}') AS m, regexp_extract_all(text, '{p}', {rule.group}) AS k, string_split_regex(text, '{p}') AS g FROM d))"""


OP9_SQL = f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents
), s AS ({' UNION ALL '.join(f"SELECT *, '{r.kind}' AS kind FROM ({_spans_sql(r, i)}) WHERE own >= {r.least}" for i, r in enumerate(RULES))}
), a AS (
  SELECT doc_id, count(*) FILTER (WHERE number = 0) AS n_assign, count(*) FILTER (WHERE number = 1) AS n_access, count(*) FILTER (WHERE number = 2) AS n_hex,
    string_agg(kind || ':' || start || ':' || (start + n), ',' ORDER BY start, number) FILTER (WHERE number < 3) AS base,
    string_agg(kind || ':' || start || ':' || (start + n), ',' ORDER BY start, number) AS spans FROM s GROUP BY doc_id
)
SELECT d.doc_id, coalesce(n_assign, 0)::BIGINT AS n_assign, coalesce(n_access, 0)::BIGINT AS n_access, coalesce(n_hex, 0)::BIGINT AS n_hex, sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans
FROM d LEFT JOIN a USING (doc_id)
"""
