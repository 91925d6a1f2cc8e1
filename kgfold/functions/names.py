"""Column functions on names, their SQL registrations, and hooks for user matchers."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfold.config import INVERSE
from kgfold.schema import local_of, source_of


def kg_source(name: str | Column) -> Column:
    return source_of(name)


def kg_local(name: str | Column) -> Column:
    return local_of(name)


def kg_flip(relation: str | Column) -> Column:
    """The inverse of a formal relation; symmetric relations stay."""
    col = F.col(relation) if isinstance(relation, str) else relation
    out = col
    for a, b in INVERSE.items():
        out = F.when(col == a, F.lit(b)).otherwise(out)
    return out


def unique_or_null(col: str | Column) -> Column:
    """Aggregate: the only distinct value of a group, else null.  min = max combines map-side and needs no set."""
    return F.when(F.min(col) == F.max(col), F.min(col))


def register(spark: SparkSession) -> None:
    """kg_source, kg_local and kg_flip as temporary SQL functions (expressions, no Python at run time)."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION kg_source(name STRING) RETURNS STRING RETURN split_part(name, ':', 1)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION kg_local(name STRING) RETURNS STRING RETURN substring(name, length(split_part(name, ':', 1)) + 2)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION kg_flip(relation STRING) RETURNS STRING RETURN CASE relation WHEN 'narrower' THEN 'broader' WHEN 'broader' THEN 'narrower' ELSE relation END")


def split_by_sql(concept: DataFrame) -> DataFrame:
    register(concept.sparkSession)
    return concept.selectExpr("concept", "kg_source(concept) AS source", "kg_local(concept) AS local")


def expanded_paths(hier: DataFrame) -> DataFrame:
    """start, n, name: the nodes of one-edge paths, by a table function over arrays."""
    return hier.select(F.col("child").alias("start"), F.array("child", "parent").alias("path")).select("start", F.posexplode("path").alias("n", "name"))


def pandas_matches(rows: DataFrame, match=None) -> DataFrame:
    """Pairs (a, b) that a user's matcher finds inside each block (vocabulary).  ``match`` takes and returns frames;
    the default pairs equal names.  One block is one group: block keys must bound their groups."""

    def equal_names(block: pd.DataFrame) -> pd.DataFrame:
        both = block.merge(block, on="p_name", suffixes=("_a", "_b"))
        both = both[both.p_partkey_a < both.p_partkey_b]
        return pd.DataFrame({"a": both.p_partkey_a.astype("int64"), "b": both.p_partkey_b.astype("int64")})

    return rows.groupBy("p_brand").applyInPandas(match or equal_names, "a long, b long")


def map_batches(df: DataFrame, f, schema: str) -> DataFrame:
    """A user's function over Arrow batches as pandas frames."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield f(b)

    return df.mapInPandas(run, schema)
