"""Document fingerprints by consistent weighted sampling, in DataFrame functions only.

A document is a weighted set: its words (ASCII letters lower-cased, cut at white space) weighted by how often they
occur.  For each of ``SAMPLES`` independent samples every term draws r and c from Gamma(2, 1) and b from U(0, 1), all
functions of the term and the sample number alone; with t = floor(ln w / r + b) the term's rank is
ln c - r (t - b) - r, and the term of least rank, with its t, is the sample.  Two documents have the same sample with
the probability of their generalised Jaccard similarity, sum of minima over sum of maxima of the weights.

Terms are counted and sampled where the document lies: the exploded words keep the document's hash partitioning, so
nothing but the texts (once) and the borrowed text halves are shuffled.

Defined results: null text counts as empty; an empty text has the all-zero fingerprint, like only to itself; null
doc_id sorts as the smallest (the least 64-bit integer counts as null); rows that repeat a doc_id each get a result, and their neighbours see the one with the
least SHA-256; an empty table gives an empty table.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kgfold.llm.common import next_lower, staged

SAMPLES, PER_ROW = 32, 8
NULL_KEY = -(1 << 63)


def _uniform(bits: Column, shift: int) -> Column:
    """(0, 1) from 21 bits of a hash."""
    return (F.shiftrightunsigned(bits, shift).bitwiseAND(F.lit((1 << 21) - 1)) + F.lit(0.5)) / F.lit(float(1 << 21))


def draw(term: Column, log_weight: Column, sample: Column) -> tuple[Column, Column]:
    """(rank, name) of a term in one sample; the least rank wins."""
    one, two = F.xxhash64(term, sample), F.xxhash64(term, sample + F.lit(1 << 20))
    r = -F.ln(_uniform(one, 0) * _uniform(one, 21))
    c = -F.ln(_uniform(one, 42) * _uniform(two, 0))
    b = _uniform(two, 21)
    t = F.floor(log_weight / r + b)
    return F.ln(c) - r * (t - b) - r, F.hash(term, t)


def signatures(texts: DataFrame, keys: list[str], text: str = "text") -> DataFrame:
    """keys, signature (array of SAMPLES ints) of every row with a word; keys must be unique."""
    words = texts.select(*keys, F.explode(F.split(F.col(text), "[ \t\n\x0b\f\r]+")).alias("word")).filter("word <> ''")
    terms = words.select(*keys, F.xxhash64(F.translate("word", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")).alias("term"))
    weighted = terms.groupBy(*keys, "term").agg(F.ln(F.count("*").cast("double")).alias("lw"))
    spread = weighted.select(*keys, "term", "lw", F.explode(F.array(*[F.lit(i) for i in range(0, SAMPLES, PER_ROW)])).alias("block"))
    drawn = [draw(F.col("term"), F.col("lw"), F.col("block") + k) for k in range(PER_ROW)]
    least = spread.groupBy(*keys, "block").agg(*[F.min_by(name, rank).alias(f"m{k}") for k, (rank, name) in enumerate(drawn)])
    blocks = least.select(*keys, F.struct("block", F.array(*[f"m{k}" for k in range(PER_ROW)]).alias("m")).alias("part"))
    whole = blocks.groupBy(*keys).agg(F.array_sort(F.collect_list("part")).alias("parts"))  # SAMPLES / PER_ROW entries
    return whole.select(*keys, F.flatten(F.transform("parts", lambda p: p["m"])).alias("signature"))


def likeness(a: Column, b: Column) -> Column:
    """Share of equal samples: the estimate of the generalised Jaccard similarity."""
    return F.size(F.filter(F.zip_with(a, b, lambda x, y: x == y), lambda same: same)) / F.lit(float(SAMPLES))


def printed(signature: Column) -> Column:
    """The fingerprint as text: eight hexadecimal digits a sample."""
    return F.array_join(F.transform(signature, lambda x: F.lpad(F.lower(F.hex(x.cast("long").bitwiseAND(F.lit(0xFFFFFFFF)))), 8, "0")), "")


def with_edits(docs: DataFrame) -> DataFrame:
    """key, text, at, next_id, n_chars, edited: the last half of each text replaced by the next document's start.

    All that needs a text takes just (key, text) dealt by key, so Spark moves the texts once and reuses that exchange.
    """
    rows = docs.select(F.coalesce("doc_id", F.lit(NULL_KEY)).alias("key"), F.coalesce("text", F.lit("")).alias("text"))
    half = F.floor(F.char_length("text") / 2).cast("int")
    needs = rows.groupBy("key").agg(F.max(half).alias("need"), F.count("*").alias("n"))
    links = staged(next_lower(needs, "key"), "links")
    begun = rows.join(links.select(F.col("next_id").alias("key"), F.col("key").alias("to"), "need"), "key")
    begun = begun.select(F.col("to").alias("key"), F.substring("text", F.lit(1), F.col("need")).alias("start"), "text")
    if links.filter("n > 1").limit(1).count():
        begun = begun.groupBy("key").agg(F.min_by("start", F.sha2("text", 256)).alias("start"))
    joined = rows.join(begun.select("key", "start"), "key").join(links.select("key", "next_id"), "key")
    n = F.char_length("text")
    edited = F.concat(F.substring("text", F.lit(1), n - half), F.substring("start", F.lit(1), half))
    return joined.select("key", "text", F.xxhash64("text").alias("at"), "next_id", n.cast("long").alias("n_chars"), edited.alias("edited"))


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next."""
    rows = with_edits(docs)
    once = rows.select("key", "at", F.explode(F.array(F.struct(F.lit(0).alias("v"), F.col("text").alias("t")), F.struct(F.lit(1).alias("v"), F.col("edited").alias("t")))).alias("x"))
    once = once.select("key", "at", F.col("x.v").alias("v"), F.col("x.t").alias("text"))
    if docs.select("doc_id").groupBy("doc_id").count().filter("count > 1").limit(1).count():
        once = once.dropDuplicates(["key", "at", "v"])
    signed = signatures(once, ["key", "at", "v"])
    both = signed.groupBy("key", "at").agg(F.max(F.when(F.col("v") == 0, F.col("signature"))).alias("own"), F.max(F.when(F.col("v") == 1, F.col("signature"))).alias("other"))
    zero = F.array_repeat(F.lit(0), SAMPLES)
    facts = rows.select("key", "at", "next_id", "n_chars", F.sha2("text", 256).alias("sha"), F.sha2("edited", 256).alias("edited_sha256"))
    made = facts.join(both, ["key", "at"], "left").withColumn("own", F.coalesce("own", zero)).withColumn("other", F.coalesce("other", zero))
    made = staged(made, "signatures")
    following = made.groupBy("key").agg(F.min_by("own", "sha").alias("following")).withColumnRenamed("key", "next_id")
    out = made.join(following, "next_id")
    return out.select(
        F.when(F.col("key") != NULL_KEY, F.col("key")).alias("doc_id"), "n_chars", "edited_sha256", printed(F.col("own")).alias("fingerprint"), printed(F.col("other")).alias("edited_fingerprint"),
        likeness(F.col("own"), F.col("other")).alias("near_edited"), likeness(F.col("own"), F.col("following")).alias("near_next"),
    )
