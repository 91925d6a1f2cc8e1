"""Reference points: unrestricted clusters and the untrimmed union of all hierarchies."""

from __future__ import annotations

from pyspark.sql import DataFrame

from kgfold.config import IntegrationConfig
from kgfold.operators import blocks
from kgfold.operators.canonical import substitute
from kgfold.schema import KnowledgeGraph


def equivalence_components(kg: KnowledgeGraph, cfg: IntegrationConfig) -> DataFrame:
    """node, label: components over every equivalence link, with no rule of multiplicity."""
    return blocks.equivalence_components(kg, cfg)


def naive_union(kg: KnowledgeGraph, merges: DataFrame) -> DataFrame:
    """All hierarchies under canonical names, nothing trimmed."""
    return substitute(kg.hier, ["child", "parent"], merges)
