"""Information-theoretic sanitisation of personal data, in DataFrame functions only.

Protected entities are the values of direct identifiers (e-mail and IP addresses, card and phone numbers).  Every other
word of a text that holds an entity is a candidate; over the whole corpus the pointwise mutual information of term and
entity is set against the information of the entity itself:

    PMI(t; e) = log2( p(e|t) / p(e) )    IC(e) = -log2( p(e) )    p(e) = n(e) / N    p(e|t) = (n(t,e) + p(e)) / (n(t) + 1)

``PMI / IC`` near 1 means that the term alone gives the entity away.  Where it reaches ``remove_at`` the term is
removed from the texts that hold it and the entity, from ``generalise_at`` on it is replaced by its shape class.  All
four counts are of distinct texts, not rows, so a thousand copies of one document are one observation.  Every entity is
judged, however rare: p(e|t) holds one observation at the base rate p(e), so that a single text weighs less the smaller
the corpus is.

Lists go to a scan by broadcast only up to ``broadcast_rows`` entities or terms, otherwise by a shuffled join.  A text
gives one row for each pair of its distinct entities and distinct words.

Defined results: null or empty text has no spans and is returned as it is; null doc_ids are kept; repeated rows give
repeated results; an empty table gives an empty table.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kgfold.llm.common import staged
from kgfold.llm.spans import blanked, joined, masked, matches, of_kind

#: The contract's kinds, in its order.  Same matches as its expressions, written without backtracking.
PATTERNS = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9]){15,}+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
TERM = r"[\p{L}\p{N}_]{3,}+"
SPAN = "array<struct<s:int,o:int,e:int,k:string>>"
HIT = "array<struct<s:int,e:int,v:string>>"


def _digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def luhn(digits: Column) -> Column:
    """The check-digit test; every second digit from the right is doubled."""
    values = F.transform(F.split(F.reverse(digits), ""), lambda d, i: (d.cast("int") * (1 + i % 2)).cast("int"))
    total = F.aggregate(values, F.lit(0), lambda acc, v: acc + F.when(v > 9, v - 9).otherwise(v))
    return total % 10 == 0


def _valid(kind: str, value: Column) -> Column:
    if kind == "ip":
        return F.forall(F.split(value, r"\."), lambda p: (F.char_length(F.ltrim(p, F.lit("0"))) < 3) | ((F.char_length(F.ltrim(p, F.lit("0"))) == 3) & (F.ltrim(p, F.lit("0")) <= "255")))
    if kind == "card":
        digits = _digits(value)
        return F.when(F.char_length(digits).between(16, 19), luhn(digits)).otherwise(False)
    if kind == "phone":
        return F.char_length(_digits(value)).between(8, 15)
    return F.lit(True)


def identifiers(text: Column) -> dict[str, Column]:
    """Valid matches of each kind: array of struct(s, e, v)."""
    out = {}
    needs = {"email": F.contains(text, F.lit("@")), "ip": F.rlike(text, F.lit(r"[0-9]\.[0-9]")), "card": F.rlike(text, F.lit(PATTERNS["card"])), "phone": F.contains(text, F.lit("+"))}
    for kind, pattern in PATTERNS.items():
        found = F.filter(matches(text, pattern), _check(kind))
        found = F.when(needs[kind], found)  # spares most texts the search
        out[kind] = F.coalesce(found, F.array().cast(HIT))
    return out


def _check(kind: str):
    return lambda x: _valid(kind, x["v"])


def _entity(kind: str, value: Column) -> Column:
    return F.concat(F.lit(f"{kind}:"), F.lower(value) if kind in ("email", "ip") else _digits(value))


def _with_entity(kind: str):
    return lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), _entity(kind, x["v"]).alias("v"))


def _seen(text: Column) -> Column:
    """All identifiers of a text: array of struct(s, e, v), v being the entity."""
    return F.concat(*[F.transform(v, _with_entity(k)) for k, v in identifiers(text).items()])


def _plain(text: Column, seen: Column) -> Column:
    return F.when(F.size(seen) > 0, blanked(text, F.array_sort(seen))).otherwise(text)


def _low(text: Column) -> Column:
    """Lower case, one character for one: a text's words are the same lowered before or after they are cut."""
    return F.lower(F.translate(text, "\u0130", "I"))


def observed(docs: DataFrame) -> DataFrame:
    """One row per distinct text: text_key, entities, words (lower case, those of identifiers left out)."""
    texts = docs.select("text").filter("text is not null").distinct().withColumn("seen", _seen(F.col("text")))
    texts = texts.withColumn("plain", _plain(F.col("text"), F.col("seen")))
    words = F.regexp_extract_all(_low(F.col("plain")), F.lit(TERM), F.lit(0))
    return texts.select(F.md5("text").alias("text_key"), F.array_distinct("seen.v").alias("entities"), F.array_distinct(words).alias("words"))


def disclosing_terms(texts: DataFrame, remove_at: float = 0.8, generalise_at: float = 0.6, broadcast_rows: int = 100_000) -> DataFrame:
    """text_key, entity, term, share for every word of ``texts`` that discloses an entity of its text."""
    total = texts.count()
    seen = texts.select(F.explode("entities").alias("entity")).groupBy("entity").agg(F.count("*").alias("n_e"))
    seen = F.broadcast(seen) if seen.count() <= broadcast_rows else seen
    frequent = texts.select(F.explode("words").alias("term")).groupBy("term").agg(F.count("*").alias("n_t"))
    pairs = texts.filter(F.size("entities") > 0).select("text_key", "words", F.explode("entities").alias("entity"))
    rated = pairs.select("text_key", "entity", F.explode("words").alias("term")).join(frequent, "term")  # dealt by term, as is the window
    rated = rated.withColumn("n_te", F.count("*").over(Window.partitionBy("term", "entity"))).join(seen, "entity")
    base = F.col("n_e") / total
    share = F.log2((F.col("n_te") + base) / (F.col("n_t") + 1) / base) / -F.log2(base)
    return rated.filter(F.col("n_e") < total).withColumn("share", share).filter(F.col("share") >= min(remove_at, generalise_at)).select("text_key", "entity", "term", "share")


def _spelt(terms: Column) -> Column:
    """The words of ``_plain`` that are terms, as spelt there, by first letter: array of struct(letter, rest)."""
    lower = F.filter("_forms", lambda form: form == _low(form))  # most are, and meet the terms by hash
    other = F.filter("_forms", lambda form: (form != _low(form)) & F.array_contains(terms, _low(form)))
    own = F.concat(F.array_intersect(lower, terms), other)
    return F.array_sort(F.transform(own, lambda form: F.struct(F.substring(form, 1, 1).alias("letter"), F.substr(form, F.lit(2)).alias("rest"))))


def _term_spans(own: str, kind: str, order: int) -> Column:
    """Spans of the words ``own`` in ``_plain``, by one pattern of whole words that is told apart by first letter."""
    step = lambda acc, x: F.struct(
        x["letter"].alias("letter"),
        F.concat(acc["pattern"], F.when(acc["letter"] == x["letter"], F.lit("|")).when(acc["letter"] == "", F.concat(x["letter"], F.lit("(?:"))).otherwise(F.concat(F.lit(")|"), x["letter"], F.lit("(?:"))), x["rest"]).alias("pattern"),
    )
    built = F.aggregate(own, F.struct(F.lit("").alias("letter"), F.lit(r"(?<![\p{L}\p{N}_])(?:").alias("pattern")), step, lambda acc: F.concat(acc["pattern"], F.lit(r"))(?![\p{L}\p{N}_])")))
    return of_kind(F.when(F.size(own) > 0, matches(F.col("_plain"), built)).otherwise(F.array().cast(HIT)), kind, order)


def sanitise(docs: DataFrame, remove_at: float = 0.8, generalise_at: float = 0.6, broadcast_rows: int = 100_000) -> DataFrame:
    """``docs`` (doc_id, text, any others) with ``spans`` (struct(s, o, e, k) by kind, then start) and ``clean_text``."""
    texts = staged(observed(docs), "texts")
    flagged = disclosing_terms(texts, remove_at, generalise_at, broadcast_rows)
    sure = F.col("share") >= remove_at
    by_text = flagged.groupBy("text_key").agg(F.collect_set(F.when(sure, F.col("term"))).alias("_remove"), F.collect_set(F.when(~sure, F.col("term"))).alias("_generalise"))
    by_text = staged(by_text.withColumn("_generalise", F.array_except("_generalise", "_remove")), "flagged")
    terms = by_text.agg(F.sum(F.size("_remove") + F.size("_generalise"))).first()[0] or 0
    text, found = F.col("text"), identifiers(F.col("text"))
    spans = [of_kind(v, k, i) for i, (k, v) in enumerate(found.items())]
    if terms:
        known = F.broadcast(by_text) if terms <= broadcast_rows else by_text
        held = docs.withColumn("_seen", _seen(text)).filter(F.size("_seen") > 0).join(known, F.md5(text) == known["text_key"], "left")  # texts without identifiers are not moved
        held = held.withColumn("_plain", F.when(F.col("text_key").isNotNull(), _plain(text, F.col("_seen"))))
        held = held.withColumn("_forms", F.array_distinct(F.regexp_extract_all("_plain", F.lit(TERM), F.lit(0))))
        none = F.array().cast("array<string>")
        held = held.withColumn("_own4", _spelt(F.coalesce("_remove", none))).withColumn("_own5", _spelt(F.coalesce("_generalise", none)))
        held = _cleaned(held, docs.columns, [*spans, _term_spans("_own4", "term", 4), _term_spans("_own5", "class", 5)])
        rest = docs.filter(text.isNull() | (F.size(_seen(text)) == 0))
        return held.union(rest.select(*docs.columns, F.array().cast(SPAN).alias("spans"), text.alias("clean_text")))
    return _cleaned(docs, docs.columns, spans)


def _cleaned(rows: DataFrame, columns: list[str], spans: list[Column]) -> DataFrame:
    by_kind = F.array_sort(F.transform(F.concat(*spans), lambda x: F.struct(x["o"].alias("o"), x["s"].alias("s"), x["e"].alias("e"), x["k"].alias("k"))))
    out = rows.withColumn("spans", F.transform(by_kind, lambda x: F.struct(x["s"].alias("s"), x["o"].alias("o"), x["e"].alias("e"), x["k"].alias("k"))))
    return out.withColumn("clean_text", masked(F.col("text"), F.array_sort("spans"))).select(*columns, "spans", "clean_text")


def _is(kind: str):
    return lambda x: x["k"] == kind


def digest(sanitised: DataFrame) -> DataFrame:
    spans = F.coalesce("spans", F.array().cast(SPAN))
    counts = [F.size(F.filter(spans, _is(k))).cast("long").alias(f"n_{k}") for k in PATTERNS]
    own = F.filter(spans, lambda x: x["k"].isin(list(PATTERNS)))
    return sanitised.select("doc_id", *counts, F.sha2(joined(own), 256).alias("base_sha256"), joined(spans).alias("spans"))
