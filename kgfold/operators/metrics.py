"""Cost and accuracy measures: the before/after table, the status table and what they are built of."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgfold.config import IntegrationConfig
from kgfold.kernels import components
from kgfold.schema import KnowledgeGraph, source_of


def subgraphs(edges: DataFrame) -> DataFrame:
    """One row: the number of weakly connected subgraphs of a hierarchy."""
    return components(edges, "child", "parent").agg(F.countDistinct("label").alias("n"))


def _row(name: str, before: DataFrame | None, after: DataFrame) -> DataFrame:
    b = before.select(F.col(before.columns[0]).cast("long").alias("value_in")) if before is not None else None
    a = after.select(F.col(after.columns[0]).cast("long").alias("value_out"))
    joined = a.select(F.lit(None).cast("long").alias("value_in"), "value_out") if b is None else b.crossJoin(a)  # one row each
    return joined.select(F.lit(name).alias("metric"), "value_in", "value_out")


def comparison_table(kg: KnowledgeGraph, result) -> DataFrame:
    """metric, value_in, value_out: sources, concepts, merges, mappings, subgraphs, edges (distinct counts)."""
    n = lambda df: df.agg(F.count("*").alias("n"))
    i = result.identity
    rows = [
        _row("concept sources", kg.concept.agg(F.countDistinct("source")), i.domain_concepts.agg(F.countDistinct("source"))),
        _row("concepts", n(kg.concept), n(i.domain_concepts)),
        _row("concept merges", None, n(i.canonical_merges)),
        _row("mappings", n(kg.mapping), n(i.domain_mappings)),
        _row("connected subgraphs", subgraphs(kg.hier), subgraphs(result.domain_hierarchy)),
        _row("hierarchy edges", n(kg.hier), n(result.domain_hierarchy)),
    ]
    return reduce(DataFrame.union, rows)


def buckets(kg: KnowledgeGraph, result, cfg: IntegrationConfig) -> DataFrame:
    """concept, source, bucket, canonical, attached: disjoint and total buckets of all input names."""
    i = result.identity
    can = i.canonical_merges.select(F.col("src").alias("concept"), F.col("dst").alias("canonical"))
    att = result.attached.select("concept", F.lit(True).alias("attached"))
    rows = kg.concept.join(can, "concept", "left").join(att, "concept", "left")
    bucket = (
        F.when(F.col("canonical").isNull() & (F.col("source") == cfg.seed), "seed")
        .when(F.col("canonical").isNotNull() & (source_of("canonical") == cfg.seed), "to_seed")
        .when(F.col("canonical").isNotNull(), "to_other")
        .when(F.col("is_obsolete"), "obsolete_open")
        .otherwise("unmapped")
    )
    return rows.select("concept", "source", bucket.alias("bucket"), "canonical", F.coalesce("attached", F.lit(False)).alias("attached"))


BUCKETS = ("seed", "to_seed", "to_other", "obsolete_open", "unmapped")


def status_table(kg: KnowledgeGraph, result, cfg: IntegrationConfig) -> DataFrame:
    """status, n, ratio (to the input): identity buckets, then connectivity, then the shares the text reports."""
    rows = buckets(kg, result, cfg)
    count = lambda cond: F.sum(cond.cast("long"))
    b = F.col("bucket")
    totals = rows.agg(
        F.count("*").alias("input"), *[count(b == x).alias(x) for x in BUCKETS], count((b == "seed") | (b == "to_seed")).alias("connected_base"),
        count(F.col("attached")).alias("connected_attached"), count((b == "unmapped") & ~F.col("attached")).alias("disconnected"),
        count(b.isin("seed", "to_seed", "to_other")).alias("merged_share"), count(b.isin("seed", "to_seed") | F.col("attached")).alias("integrated_share"),
    )
    names = totals.columns
    stacked = totals.select(F.col("input").alias("_all"), F.explode(F.array(*[F.struct(F.lit(x).alias("status"), F.coalesce(F.col(x), F.lit(0)).alias("n")) for x in names])).alias("r"))
    return stacked.select("r.status", "r.n", F.round(F.col("r.n").cast("double") / F.col("_all"), 4).alias("ratio"))


def coverage_by_source(kg: KnowledgeGraph, result) -> DataFrame:
    """source, unmerged, attached, ratio."""
    att = result.attached.select("concept", F.lit(1).alias("a"))
    return result.identity.unmerged.join(att, "concept", "left").groupBy("source").agg(F.count("*").alias("unmerged"), F.count("a").alias("attached")).withColumn("ratio", F.round(F.col("attached").cast("double") / F.col("unmerged"), 4))


def cluster_sizes(canonical_merges: DataFrame) -> DataFrame:
    """size, clusters, spanning: clusters by size, and how many of them span several vocabularies."""
    members = canonical_merges.select(F.col("dst").alias("c"), F.col("src").alias("m")).union(canonical_merges.select("dst", "dst").distinct())
    per = members.groupBy("c").agg(F.count("*").alias("size"), F.countDistinct(source_of("m")).alias("k"))
    return per.groupBy("size").agg(F.count("*").alias("clusters"), F.sum((F.col("k") > 1).cast("long")).alias("spanning"))


def growth(kg: KnowledgeGraph, result) -> DataFrame:
    """One row: hierarchy names outside the domain concepts (must be 0)."""
    names = result.domain_hierarchy.select(F.col("child").alias("concept")).union(result.domain_hierarchy.select(F.col("parent").alias("concept"))).distinct()
    return names.join(result.identity.domain_concepts, "concept", "left_anti").agg(F.count("*").alias("n"))


def dag_checks(edges: DataFrame) -> DataFrame:
    """check, n: roots, self loops, names with several parents, components, edges in cycles."""
    from kgfold.kernels import peel

    kids = edges.select(F.col("child").alias("parent")).distinct()
    rows = [
        ("roots", edges.select("parent").distinct().join(kids, "parent", "left_anti").agg(F.count("*").alias("n"))),
        ("self loops", edges.filter("child = parent").agg(F.count("*").alias("n"))),
        ("several parents", edges.groupBy("child").count().filter("count > 1").agg(F.count("*").alias("n"))),
        ("components", subgraphs(edges)),
        ("edges in cycles", peel(edges).agg(F.count("*").alias("n"))),
    ]
    return reduce(DataFrame.union, [df.select(F.lit(k).alias("check"), F.col("n").cast("long").alias("n")) for k, df in rows])
