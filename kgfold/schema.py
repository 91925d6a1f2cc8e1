"""The tables of a knowledge graph and their schemas."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


def _struct(**cols) -> T.StructType:
    return T.StructType([T.StructField(n, t) for n, t in cols.items()])


S, B, L = T.StringType(), T.BooleanType(), T.LongType()
CONCEPT = _struct(concept=S, source=S, is_obsolete=B)
MAPPING = _struct(src=S, relation=S, dst=S)
HIER = _struct(child=S, parent=S)
MERGE = _struct(src=S, dst=S, origin=S)
METRIC = _struct(metric=S, value_in=L, value_out=L)
QUARANTINE = _struct(table=S, reason=S, c1=S, c2=S, c3=S)


def source_of(name: Column | str) -> Column:
    """A name's vocabulary: what stands before its first colon.  Local to the row, so no lookup join is ever needed."""
    return F.split_part(F.col(name) if isinstance(name, str) else name, F.lit(":"), F.lit(1))


def local_of(name: Column | str) -> Column:
    col = F.col(name) if isinstance(name, str) else name
    return F.substring(col, F.length(source_of(col)) + 2, F.length(col))


def conform(df: DataFrame, schema: T.StructType) -> DataFrame:
    """Exactly the schema's columns with its types; a missing ``source`` or ``is_obsolete`` is derived."""
    if "source" in schema.names and "source" not in df.columns:
        df = df.withColumn("source", source_of("concept"))
    if "is_obsolete" in schema.names and "is_obsolete" not in df.columns:
        df = df.withColumn("is_obsolete", F.lit(False))
    missing = [n for n in schema.names if n not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {missing}")
    return df.select(*[F.col(f.name).cast(f.dataType) for f in schema.fields])


@dataclass
class KnowledgeGraph:
    concept: DataFrame
    mapping: DataFrame
    hier: DataFrame

    @staticmethod
    def of(concept: DataFrame, mapping: DataFrame, hier: DataFrame) -> KnowledgeGraph:
        """Conformed, duplicate-free sets."""
        return KnowledgeGraph(conform(concept, CONCEPT).distinct(), conform(mapping, MAPPING).distinct(), conform(hier, HIER).distinct())
