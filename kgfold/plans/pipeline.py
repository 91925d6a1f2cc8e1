"""The whole integration: identity stage, hierarchy stage, timings."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgfold.config import IntegrationConfig
from kgfold.operators import blocks, canonical, hierarchy
from kgfold.schema import KnowledgeGraph
from kgfold.work import written


@dataclass
class IdentityResult:
    forwards: DataFrame
    make_links: Callable[[], DataFrame]
    merges: DataFrame
    canonical_merges: DataFrame
    domain_concepts: DataFrame
    unmerged: DataFrame

    @cached_property
    def links(self) -> DataFrame:
        """External links under current names, made only for those who ask."""
        return self.make_links()

    @cached_property
    def domain_mappings(self) -> DataFrame:
        return canonical.substitute(self.links.select("src", "relation", "dst"), ["src", "dst"], self.canonical_merges)


@dataclass
class IntegrationResult:
    identity: IdentityResult
    domain_hierarchy: DataFrame
    attached: DataFrame
    seconds: dict[str, float] = field(default_factory=dict)


def resolve_identity(kg: KnowledgeGraph, cfg: IntegrationConfig) -> IdentityResult:
    """Written tables at the two points that later steps read more than once; all else stays lazy."""
    forwards = written(blocks.forwards(kg, cfg), "forwards")
    held = blocks.rewrite(kg, forwards, cfg) if blocks.has_blocks(kg, cfg) else None
    merges = forwards
    if cfg.align:
        elected = written(blocks.elect(kg, forwards, cfg, held).select("src", "dst"), "elected")
        said = forwards.join(elected, ["src", "dst"], "left_semi")  # each is distinct by itself
        merges = merges.union(elected.join(said, ["src", "dst"], "left_anti"))
    can = written(canonical.canonicalise(merges, kg.concept, cfg), "canonical")
    return IdentityResult(
        forwards, lambda: blocks.links(kg, forwards, cfg, held), merges, can,
        canonical.domain_concepts(kg.concept, can),
        canonical.unmerged(kg.concept, can),
    )


def integrate(kg: KnowledgeGraph, cfg: IntegrationConfig, write_tree: bool = True) -> IntegrationResult:
    """Domain concepts, domain mappings, canonical merges and one connected hierarchy, which who doesn't read it need not write."""
    problems = [p for p in cfg.problems() if "moved" not in p]
    if problems:
        raise ValueError("; ".join(problems))
    t = [time.perf_counter()]
    ident = resolve_identity(kg, cfg)
    t.append(time.perf_counter())
    edges = kg.hier
    if cfg.same_source == "edge":
        edges = edges.union(canonical.same_source_edges(ident.merges, kg.concept, cfg)).distinct()
    tree, attached = hierarchy.attach_orphans(kg.concept, edges, ident.unmerged, ident.canonical_merges, cfg, kg.mapping if cfg.promote_subsumption else None)
    tree, attached = written(tree, "tree") if write_tree else tree, written(attached, "attached")
    t.append(time.perf_counter())
    return IntegrationResult(ident, tree, attached, {"identity": t[1] - t[0], "hierarchy": t[2] - t[1]})


def stage_times(kg: KnowledgeGraph, cfg: IntegrationConfig) -> DataFrame:
    """stage, seconds, share: load, identity, hierarchy and analysis of one run."""
    from kgfold.operators import metrics

    a = time.perf_counter()
    kg = KnowledgeGraph(written(kg.concept, "concept"), written(kg.mapping, "mapping"), written(kg.hier, "hier"))
    b = time.perf_counter()
    result = integrate(kg, cfg)
    c = time.perf_counter()
    metrics.comparison_table(kg, result).collect()  # six rows
    metrics.status_table(kg, result, cfg).collect()  # nine rows
    spent = {"load": b - a, **result.seconds, "analysis": time.perf_counter() - c}
    total = sum(spent.values())
    rows = [(k, float(v), float(v / total)) for k, v in spent.items()]
    return kg.concept.sparkSession.createDataFrame(rows, "stage string, seconds double, share double")


def explain_concept(kg: KnowledgeGraph, result: IntegrationResult, name: str, cfg: IntegrationConfig) -> DataFrame:
    """step, detail: links of one name, its chosen target, canonical name and hierarchy edge."""
    ident = result.identity
    n = F.lit(name)
    parts = [
        ident.links.filter((F.col("src") == n) | (F.col("dst") == n)).select(F.lit("link").alias("step"), F.concat_ws(" ", "src", "relation", "dst").alias("detail")),
        ident.merges.filter(F.col("src") == n).select(F.lit("target"), F.col("dst")),
        ident.canonical_merges.filter(F.col("src") == n).select(F.lit("canonical"), F.col("dst")),
        result.domain_hierarchy.filter(F.col("child") == n).select(F.lit("below"), F.col("parent")),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out
