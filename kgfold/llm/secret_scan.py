"""Secret scan over a trigram inverted index, in DataFrame functions only.

Each rule is a regular expression.  Its trigram query (see trigram_query) decides which documents can match: postings
(trigram, document) of the trigrams that any rule asks for are joined with the rules' clauses, and a document whose
postings cover a clause is a candidate of that rule.  Candidates are verified with the expression itself; rules that
force no trigram scan every text.

Candidate lists go to the scan by broadcast only up to ``broadcast_rows`` documents, otherwise by a shuffled join.
Documents are known by doc_id; where rows repeat a doc_id each is verified on its own text.

Defined results: null or empty text has no spans; null doc_ids are kept; an empty table gives an empty table.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgfold.llm.common import staged
from kgfold.llm.spans import joined, matches, of_kind
from kgfold.llm.trigram_query import trigram_query


@dataclass(frozen=True)
class Rule:
    """``least``: characters a match (or, with ``value``, that group) must have; shorter matches are dropped."""

    kind: str
    pattern: str
    least: int = 0
    value: int = 0
    base: bool = False


#: The contract's three kinds first, in its order, then public credential formats.
RULES = (
    Rule("assign", r"""(?i:(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+))""", 12, 2, True),
    Rule("access", r"AKIA[A-Z0-9]+", 18, 0, True),
    Rule("hex", r"[0-9a-f]{16,}", 16, 0, True),
    Rule("pem", r"-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
    Rule("github", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("slack", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("google", r"AIza[0-9A-Za-z_-]{35}"),
    Rule("stripe", r"[rs]k_live_[0-9A-Za-z]{16,}"),
)


def postings(docs: DataFrame, grams: list[str]) -> DataFrame:
    """The index: one row (gram, doc_id) for each document that has the trigram, any case."""
    folded = F.lower("text")
    held = F.array(*[F.when(F.contains(folded, F.lit(g)), F.lit(i)) for i, g in enumerate(grams)])
    return docs.select("doc_id", F.explode(held).alias("gram")).filter("gram is not null")


def candidates(docs: DataFrame, rules=RULES) -> DataFrame:
    """doc_id, rules: the rules whose trigram query the document satisfies."""
    spark = docs.sparkSession
    clauses = [(r.kind, c) for r in rules for c in sorted(map(sorted, trigram_query(r.pattern) or ()))]
    grams = sorted({g for _, c in clauses for g in c})
    rows = [(i, kind, grams.index(g), 1 << n, (1 << len(c)) - 1) for i, (kind, c) in enumerate(clauses) for n, g in enumerate(c)]
    asked = spark.createDataFrame(rows, "clause int, kind string, gram int, bit long, whole long")
    hits = postings(docs, grams).join(F.broadcast(asked), "gram")  # as many rows as the rules have trigrams
    covered = hits.groupBy("doc_id", "clause", "kind", "whole").agg(F.bit_or("bit").alias("seen")).filter("seen = whole")
    return covered.groupBy("doc_id").agg(F.collect_set("kind").alias("rules"))  # at most one entry a rule


def _long_enough(rule: Rule):
    if rule.value:
        return lambda x: F.char_length(F.regexp_extract(x["v"], rule.pattern, rule.value)) >= rule.least
    return lambda x: x["e"] - x["s"] >= rule.least


def _is(kind: str):
    return lambda x: x["k"] == kind


def scan(docs: DataFrame, rules=RULES, broadcast_rows: int = 500_000) -> DataFrame:
    """``docs`` (doc_id, text) with ``spans``: array of struct(s, o, e, k) ordered by start, then rule."""
    docs = docs.select("doc_id", "text")
    listed = staged(candidates(docs, rules), "candidates").withColumnRenamed("doc_id", "_id")
    listed = F.broadcast(listed) if listed.count() <= broadcast_rows else listed
    text = F.col("text")
    found = []
    for i, r in enumerate(rules):
        spans = matches(text, r.pattern)
        if r.least:
            spans = F.filter(spans, _long_enough(r))
        own = of_kind(spans, r.kind, i)
        if trigram_query(r.pattern) is not None:
            own = F.when(F.array_contains("rules", r.kind), own)
        found.append(F.coalesce(own, F.array().cast("array<struct<s:int,o:int,e:int,k:string>>")))
    rows = docs.join(listed, docs["doc_id"].eqNullSafe(listed["_id"]), "left")
    return rows.select("doc_id", "text", F.array_sort(F.concat(*found)).alias("spans"))


def digest(scanned: DataFrame, rules=RULES) -> DataFrame:
    spans = F.coalesce("spans", F.array().cast("array<struct<s:int,o:int,e:int,k:string>>"))
    base = [r.kind for r in rules if r.base]
    counts = [F.size(F.filter(spans, _is(k))).cast("long").alias(f"n_{k}") for k in base]
    own = F.filter(spans, lambda x: x["k"].isin(base))
    return scanned.select("doc_id", *counts, F.sha2(joined(own), 256).alias("base_sha256"), joined(spans).alias("spans"))
