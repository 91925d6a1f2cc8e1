"""Canonicalisation: clusters of the merge graph, their best-ranked member, substitution and the unmerged rest."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgfold.config import IntegrationConfig
from kgfold.kernels import components, follow_to_sink
from kgfold.operators.identity import preference_order
from kgfold.schema import source_of
from kgfold.work import written


def clusters(merges: DataFrame) -> DataFrame:
    """node, label of every name that takes part in a merge."""
    return components(merges)


def canonicalise(merges: DataFrame, concept: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    """src, dst: every cluster member goes to the member that is least by (obsolete, vocabulary rank, name)."""
    merges = merges.select("src", "dst")
    if cfg.canonical == "sink":
        return follow_to_sink(merges.distinct())
    label = components(merges, any_label=True)
    ranks = preference_order(concept, cfg)
    flags = concept.filter("is_obsolete").select(F.col("concept").alias("node"), F.lit(1).alias("old"))
    ranked = label.join(flags, "node", "left").withColumn("_s", source_of("node"))
    ranked = ranked.join(F.broadcast(ranks.withColumnRenamed("source", "_s")), "_s", "left")
    place = F.coalesce("old", F.lit(0)).cast("long") * (1 << 32) + F.coalesce("rank", F.lit(1 << 30))
    ranked = written(ranked.select("node", "label", place.alias("place")), "ranked")
    first = ranked.join(ranked.groupBy("label").agg(F.min("place").alias("place")), ["label", "place"])  # names are compared among these only
    best = written(first.groupBy("label").agg(F.min("node").alias("dst")), "best")
    out = ranked.join(best, "label").filter("node <> dst").select(F.col("node").alias("src"), "dst")
    if cfg.same_source == "edge":
        out = out.filter(source_of("src") != source_of("dst"))
    return out


def same_source_edges(merges: DataFrame, concept: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    """Merges inside one vocabulary as hierarchy edges (child, parent)."""
    whole = canonicalise(merges, concept, cfg.with_(same_source="merge"))
    return whole.filter(source_of("src") == source_of("dst")).select(F.col("src").alias("child"), F.col("dst").alias("parent"))


def substitute(df: DataFrame, cols: list[str], merges: DataFrame, drop_self: bool = True) -> DataFrame:
    """``df`` with the names in ``cols`` replaced by their canonical names; duplicates (and self links) go."""
    to = merges.select(F.col("src").alias("_old"), F.col("dst").alias("_new"))
    for c in cols:
        kept = [F.coalesce("_new", x).alias(x) if x == c else F.col(x) for x in df.columns]
        df = df.join(to, df[c] == to["_old"], "left").select(*kept)
    if drop_self and len(cols) == 2:
        df = df.filter(F.col(cols[0]) != F.col(cols[1]))
    return df.distinct()


def domain_concepts(concept: DataFrame, merges: DataFrame) -> DataFrame:
    return substitute(concept.select("concept"), ["concept"], merges).select("concept", source_of("concept").alias("source"))


def unmerged(concept: DataFrame, merges: DataFrame) -> DataFrame:
    """concept, source: neither obsolete nor the left side of a canonical merge."""
    gone = merges.select(F.col("src").alias("concept"))
    return concept.filter("not is_obsolete").join(gone, "concept", "left_anti").select("concept", "source")


def stability_violations(merges: DataFrame) -> DataFrame:
    """concept, reason: names on the left twice, or on both sides."""
    twice = merges.groupBy("src").count().filter("count > 1").select(F.col("src").alias("concept"), F.lit("left twice").alias("reason"))
    right = merges.select(F.col("dst").alias("src")).distinct()
    both = merges.join(right, "src", "left_semi").select(F.col("src").alias("concept"), F.lit("both sides").alias("reason")).distinct()
    return twice.union(both)


def inferred_mappings(mapping: DataFrame, merges: DataFrame) -> DataFrame:
    """src, dst: equalities that the clusters imply and no mapping asserts (either way round)."""
    said = mapping.select("src", "dst").union(mapping.select("dst", "src")).distinct()
    return merges.select("src", "dst").join(said, ["src", "dst"], "left_anti")


def signature(df: DataFrame, left: str, right: str, side: str = "both") -> DataFrame:
    """Names on the left, the right or either side of a set of triples."""
    one, two = df.select(F.col(left).alias("concept")), df.select(F.col(right).alias("concept"))
    return {"left": one, "right": two, "both": one.union(two)}[side].distinct()
