"""Readers and writers of the four input sets and of result bundles."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from kgfold.schema import CONCEPT, HIER, MAPPING, KnowledgeGraph

SUBCLASS = "http://www.w3.org/2000/01/rdf-schema#subClassOf"
EXACT = "http://www.w3.org/2004/02/skos/core#exactMatch"
DEPRECATED = "http://www.w3.org/2002/07/owl#deprecated"
XREF = "http://www.geneontology.org/formats/oboInOwl#hasDbXref"
TRIPLE = r'^\s*<([^>]*)>\s+<([^>]*)>\s+(?:<([^>]*)>|"((?:[^"\\]|\\.)*)"\S*)\s*\.\s*$'


def read_csv(spark: SparkSession, path: str, schema: StructType, sep: str = ",") -> tuple[DataFrame, DataFrame]:
    """(rows, bad lines): explicit schema, permissive; a line that doesn't parse goes to the second table."""
    full = StructType([*schema.fields]).add("_bad", "string")
    raw = spark.read.schema(full).option("header", True).option("sep", sep).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_bad").csv(path)
    return raw.filter("_bad is null").drop("_bad"), raw.filter("_bad is not null").select("_bad")


def read_parquet(spark: SparkSession, path: str, schema: StructType) -> DataFrame:
    return spark.read.schema(schema).parquet(path)


def read_jdbc(spark: SparkSession, url: str, table: str, column: str, low: int, high: int, parts: int, **options) -> DataFrame:
    """A bounded parallel read over the public JDBC source."""
    return spark.read.jdbc(url, table, column=column, lowerBound=low, upperBound=high, numPartitions=parts, properties=options)


def round_trip(df: DataFrame, kind: str, path: str) -> DataFrame:
    """Written as csv, json, orc or parquet and read back with its schema."""
    spark = df.sparkSession
    if kind == "csv":
        df.write.option("header", True).csv(path)
        return read_csv(spark, path, df.schema)[0]
    getattr(df.write, kind)(path)
    return getattr(spark.read.schema(df.schema), kind)(path)


def bucketed(df: DataFrame, key: str, buckets: int = 8) -> DataFrame:
    """A managed table bucketed by ``key``: later joins on it need no exchange."""
    name = f"kg_{uuid.uuid4().hex}"
    df.write.bucketBy(buckets, key).sortBy(key).saveAsTable(name)
    return df.sparkSession.table(name)


def write_ntriples(kg: KnowledgeGraph, path: str, base: str = "urn:kg:") -> None:
    """Edges, mappings and deprecations as N-Triples lines."""
    iri = lambda c: F.concat(F.lit(f"<{base}"), F.col(c), F.lit(">"))
    rel = F.when(F.col("relation") == "xref", F.lit(f"<{XREF}>")).when(F.col("relation") == "exactMatch", F.lit(f"<{EXACT}>")).otherwise(F.concat(F.lit(f"<{base}rel/"), "relation", F.lit(">")))
    lines = kg.hier.select(F.concat_ws(" ", iri("child"), F.lit(f"<{SUBCLASS}>"), iri("parent"), F.lit(".")).alias("value"))
    lines = lines.union(kg.mapping.select(F.concat_ws(" ", iri("src"), rel, iri("dst"), F.lit("."))))
    lines = lines.union(kg.concept.filter("is_obsolete").select(F.concat_ws(" ", iri("concept"), F.lit(f"<{DEPRECATED}>"), F.lit('"true" .'))))
    lines.write.text(path)


def read_ntriples(spark: SparkSession, path: str, base: str = "urn:kg:") -> tuple[KnowledgeGraph, DataFrame]:
    """(graph, lines that are no triples), with column functions alone."""
    lines = spark.read.text(path)
    part = lambda k: F.regexp_extract("value", TRIPLE, k)
    name = lambda c: F.regexp_replace(c, f"^{base}", "")
    rows = lines.filter(F.col("value").rlike(TRIPLE)).select(name(part(1)).alias("s"), part(2).alias("p"), name(part(3)).alias("o"), part(4).alias("lit"))
    hier = rows.filter(F.col("p") == SUBCLASS).select(F.col("s").alias("child"), F.col("o").alias("parent"))
    old = rows.filter((F.col("p") == DEPRECATED) & (F.col("lit") == "true")).select(F.col("s").alias("concept"), F.lit(True).alias("is_obsolete")).distinct()
    links = rows.filter(~F.col("p").isin(SUBCLASS, DEPRECATED) & (F.col("o") != ""))
    rel = F.when(F.col("p") == XREF, "xref").when(F.col("p") == EXACT, "exactMatch").otherwise(F.regexp_replace("p", f"^{base}rel/", ""))
    mapping = links.select(F.col("s").alias("src"), rel.alias("relation"), F.col("o").alias("dst"))
    names = rows.select(F.col("s").alias("concept")).union(rows.filter("o <> ''").select("o")).distinct()
    concept = names.join(old, "concept", "left").select("concept", F.coalesce("is_obsolete", F.lit(False)).alias("is_obsolete"))
    return KnowledgeGraph.of(concept, mapping, hier), lines.filter(~F.col("value").rlike(TRIPLE) & ~F.col("value").rlike(r"^\s*(#.*)?$"))


def ntriples_round_trip(kg: KnowledgeGraph, path: str) -> DataFrame:
    write_ntriples(kg, path)
    return read_ntriples(kg.hier.sparkSession, path)[0].hier


def write_bundle(result, path: str, max_records: int = 5_000_000) -> None:
    """The four outputs as Parquet; concepts and hierarchy are laid out by vocabulary."""
    i = result.identity
    i.domain_concepts.repartition("source").write.mode("overwrite").option("maxRecordsPerFile", max_records).partitionBy("source").parquet(f"{path}/concepts")
    i.domain_mappings.write.mode("overwrite").option("maxRecordsPerFile", max_records).parquet(f"{path}/mappings")
    i.canonical_merges.write.mode("overwrite").parquet(f"{path}/merges")
    result.domain_hierarchy.repartitionByRange(F.col("parent")).write.mode("overwrite").option("maxRecordsPerFile", max_records).parquet(f"{path}/hierarchy")


def write_graph(kg: KnowledgeGraph, path: str) -> None:
    kg.concept.repartition("source").write.mode("overwrite").partitionBy("source").parquet(f"{path}/concept")
    kg.mapping.write.mode("overwrite").parquet(f"{path}/mapping")
    kg.hier.write.mode("overwrite").parquet(f"{path}/hier")


def read_graph(spark: SparkSession, path: str) -> KnowledgeGraph:
    return KnowledgeGraph(spark.read.schema(CONCEPT).parquet(f"{path}/concept").select(*CONCEPT.names), spark.read.schema(MAPPING).parquet(f"{path}/mapping"), spark.read.schema(HIER).parquet(f"{path}/hier"))


def bundle_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    from kgfold.plans.fixtures import load
    from kgfold.work import work_dir

    path = f"{work_dir(spark)}/{uuid.uuid4().hex}"
    write_graph(load(spark, sf_dir, "k3"), path)
    return read_graph(spark, path).hier
