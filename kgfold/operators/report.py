"""The HTML report: input, intermediate and produced data, profiles with test results, inner metrics.

Only aggregates reach the driver; their size depends on the number of vocabularies, not on the data.
"""

from __future__ import annotations

from html import escape

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgfold.config import IntegrationConfig
from kgfold.operators import metrics, profile, quality
from kgfold.operators.identity import preference_order
from kgfold.schema import KnowledgeGraph

MOST_ROWS = 500


def _sections(kg: KnowledgeGraph, result, cfg: IntegrationConfig) -> list[tuple[str, list[tuple[str, DataFrame]]]]:
    i = result.identity
    return [
        ("Input", [("vocabularies", kg.concept.groupBy("source").agg(F.count("*").alias("names"), F.sum(F.col("is_obsolete").cast("long")).alias("obsolete"))), ("links", profile.link_matrix(kg.mapping, cfg)), ("order", preference_order(kg.concept, cfg))]),
        ("Produced", [("comparison", metrics.comparison_table(kg, result)), ("status", metrics.status_table(kg, result, cfg)), ("coverage", metrics.coverage_by_source(kg, result))]),
        ("Profile and tests", [("concepts", profile.profile(kg.concept)), ("mappings", profile.profile(kg.mapping)), ("input tests", quality.graph_expectations(kg, cfg)), ("result tests", quality.result_expectations(kg, result, cfg))]),
        ("Inner metrics", [("cluster sizes", metrics.cluster_sizes(i.canonical_merges)), ("multiplicity", profile.multiplicity_report(kg.mapping)), ("seconds", kg.concept.sparkSession.createDataFrame(sorted(result.seconds.items()) or [("none", 0.0)], "stage string, seconds double"))]),
    ]


def report_sections(kg: KnowledgeGraph, result, cfg: IntegrationConfig) -> DataFrame:
    """section, tables: what the report holds."""
    rows = [(name, len(tables)) for name, tables in _sections(kg, result, cfg)]
    return kg.concept.sparkSession.createDataFrame(rows, "section string, tables int")


def render_report(kg: KnowledgeGraph, result, cfg: IntegrationConfig, path: str | None = None) -> str:
    """The report as HTML; written to ``path`` if one is given (a driver-side file)."""
    parts = ["<!DOCTYPE html><html><head><meta charset='utf-8'><title>Integration report</title></head><body>"]
    for name, tables in _sections(kg, result, cfg):
        parts.append(f"<h1>{escape(name)}</h1>")
        for title, df in tables:
            parts.append(f"<h2>{escape(title)}</h2><table><tr>" + "".join(f"<th>{escape(c)}</th>" for c in df.columns) + "</tr>")
            parts += ["<tr>" + "".join(f"<td>{escape(str(v))}</td>" for v in row) + "</tr>" for row in df.limit(MOST_ROWS).collect()]
            parts.append("</table>")
    text = "".join(parts) + "</body></html>"
    if path:
        with open(path, "w", encoding="utf-8") as f:
            f.write(text)
    return text
