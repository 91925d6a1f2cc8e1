"""Hierarchy stage: unmerged names are hung below the seed hierarchy along their own vocabulary's paths.

With ties broken by (distance, name) every node has one next hop, so a vocabulary's shortest paths form a forest and
one level-synchronous search from the roots settles all names at once: it carries down the nearest kept ancestor and
whether an anchor lies above.  The trimmed path of a name is its edge to that ancestor plus the ancestor's own, so one
edge per attached name is the whole output.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgfold.config import IntegrationConfig
from kgfold.kernels import bfs_down
from kgfold.operators.canonical import substitute
from kgfold.operators.identity import preference_order
from kgfold.schema import source_of
from kgfold.work import written


def usable_edges(hier: DataFrame, mapping: DataFrame | None, cfg: IntegrationConfig) -> DataFrame:
    """child, parent, each once, as in ``hier``."""
    edges = hier.select("child", "parent").filter("child <> parent")
    if cfg.hierarchies is not None:
        edges = edges.filter(source_of("child").isin(list(cfg.hierarchies)))
    if cfg.promote_subsumption and mapping is not None:
        down = mapping.filter("relation = 'narrower'").select(F.col("dst").alias("child"), F.col("src").alias("parent"))
        up = mapping.filter("relation = 'broader'").select(F.col("src").alias("child"), F.col("dst").alias("parent"))
        edges = edges.union(down).union(up).distinct()
    return edges


def seed_edges(hier: DataFrame, merges: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    return substitute(hier.filter(source_of("child") == cfg.seed).select("child", "parent"), ["child", "parent"], merges)


def initial_anchors(hier: DataFrame, merges: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    """concept: names of the seed hierarchy and names merged into the seed (or into any name, by ``anchors``)."""
    own = hier.filter(source_of("child") == cfg.seed)
    named = own.select(F.col("child").alias("concept")).union(own.select(F.col("parent").alias("concept")))
    merged = merges.filter(source_of("dst") == cfg.seed).select(F.col("src").alias("concept"))
    return named.union(merged).distinct()


def fragments(edges: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    """sid, child, parent: edges keyed by their vocabulary."""
    if cfg.fragment_by == "both":
        edges = edges.filter(source_of("child") == source_of("parent"))
    return edges.select(source_of("child").alias("sid"), "child", "parent")


def roots(frag: DataFrame) -> DataFrame:
    """sid, node: parents that are no child within their fragment."""
    above = frag.select("sid", F.col("parent").alias("node")).distinct()
    return above.join(frag.select("sid", F.col("child").alias("node")), ["sid", "node"], "left_anti")


def _marks(frag: DataFrame, anchors: DataFrame, unmerged: DataFrame) -> DataFrame:
    """sid, node, is_anchor, is_open for every node of a fragment; only its own vocabulary's unmerged names are open."""
    nodes = frag.select("sid", F.col("child").alias("node")).union(frag.select("sid", F.col("parent").alias("node"))).distinct()
    held = nodes.join(anchors.select(F.col("concept").alias("node"), F.lit(True).alias("is_anchor")), "node", "left")
    open_ = unmerged.select(F.col("concept").alias("node"), F.col("source").alias("sid"), F.lit(True).alias("is_open"))
    held = held.join(open_, ["sid", "node"], "left")
    return held.select("sid", "node", F.coalesce("is_anchor", F.lit(False)).alias("is_anchor"), F.coalesce("is_open", F.lit(False)).alias("is_open"))


def root_distance(edges: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    """sid, node, dist, next_hop of every node that a root reaches."""
    frag = written(fragments(edges, cfg), "fragments")
    nobody = frag.sparkSession.createDataFrame([], "sid string, node string, is_anchor boolean, is_open boolean")
    return bfs_down(frag, roots(frag), nobody).select("sid", "node", "dist", "next_hop")


def attach(frag: DataFrame, anchors: DataFrame, unmerged: DataFrame, merges: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    """child, parent: one edge per attached name of the given fragments."""
    marks = written(_marks(frag, anchors, unmerged), "marks")
    if cfg.path == "any_anchor":  # search from the anchors: any anchored ancestor will do
        start = marks.filter("is_anchor").select("sid", "node")
        found = bfs_down(frag, start, marks).filter("dist > 0 and is_open").select(F.col("node").alias("child"), F.col("kept").alias("parent"))
    elif cfg.path == "k_shortest":
        return _attach_k(frag, marks, merges, cfg)
    else:
        found = bfs_down(frag, roots(frag), marks).filter("is_open and anchored and not is_anchor").select(F.col("node").alias("child"), F.col("kept").alias("parent"))
    return substitute(found, ["parent"], merges).select("child", "parent")


def k_paths(frag: DataFrame, k: int, max_depth: int = 64) -> DataFrame:
    """sid, node, paths: each node's ``k`` least paths to a root as arrays of names, ordered by (length, names)."""
    start = roots(frag).select("sid", "node", F.array(F.array("node")).alias("paths"))
    state = written(start, "paths")
    for _ in range(max_depth):
        up = state.select("sid", F.col("node").alias("parent"), F.explode("paths").alias("above"))
        longer = frag.join(up, ["sid", "parent"]).filter(~F.array_contains("above", F.col("child"))).select("sid", F.col("child").alias("node"), F.concat(F.array("child"), "above").alias("path"))
        keyed = longer.groupBy("sid", "node").agg(F.array_sort(F.collect_set(F.struct(F.size("path").alias("n"), F.col("path").alias("p")))).alias("ps"))
        new = keyed.select("sid", "node", F.transform(F.slice("ps", 1, k), lambda x: x["p"]).alias("paths")).unionByName(start)
        new = written(new, "paths")
        if not new.select("sid", "node", F.hash("paths").alias("h")).exceptAll(state.select("sid", "node", F.hash("paths").alias("h"))).limit(1).count():
            return new
        state = new
    return state


def _attach_k(frag: DataFrame, marks: DataFrame, merges: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    """Attach along the first of the k least paths that meets an anchor."""
    paths = k_paths(frag, cfg.k)
    steps = paths.select("sid", F.col("node").alias("start"), F.posexplode("paths").alias("rank", "path")).select("sid", "start", "rank", F.posexplode("path").alias("at", "node"))
    seen = steps.filter("at > 0").join(marks, ["sid", "node"])
    per_path = seen.groupBy("sid", "start", "rank").agg(F.max("is_anchor").alias("anchored"), F.min_by(F.col("node"), F.when(F.col("is_anchor") | F.col("is_open"), F.col("at"))).alias("kept"))
    best = per_path.filter("anchored").groupBy("sid", "start").agg(F.min_by("kept", "rank").alias("parent"))
    mine = marks.filter("is_open and not is_anchor").select("sid", F.col("node").alias("start"))
    return substitute(best.join(mine, ["sid", "start"]).select(F.col("start").alias("child"), "parent"), ["parent"], merges).select("child", "parent")


def dependent_sources(frag: DataFrame, cfg: IntegrationConfig) -> list[str]:
    """Vocabularies whose fragment holds names of others: only these must wait for earlier ones."""
    foreign = frag.filter(source_of("parent") != F.col("sid")).select("sid").distinct()
    return [r["sid"] for r in foreign.filter(F.col("sid") != cfg.seed).collect()]  # vocabularies


def attach_orphans(concept: DataFrame, hier: DataFrame, unmerged: DataFrame, merges: DataFrame, cfg: IntegrationConfig, mapping: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(domain hierarchy, attached names): the seed hierarchy and one edge per attached name."""
    edges = usable_edges(hier, mapping, cfg)
    base = seed_edges(edges, merges, cfg)
    frag = written(fragments(edges, cfg).filter(F.col("sid") != cfg.seed), "fragments")
    anchors = initial_anchors(edges, merges, cfg)
    waiting = dependent_sources(frag, cfg)
    if cfg.anchors == "canonical":
        waiting = [r["source"] for r in preference_order(concept, cfg).orderBy("rank").collect()]  # vocabularies
    free = frag.filter(~F.col("sid").isin(waiting)) if waiting else frag
    found = written(attach(free, anchors, unmerged, merges, cfg), "attached")
    if waiting:
        order = {r["source"]: r["rank"] for r in preference_order(concept, cfg).collect()}  # vocabularies
        for sid in sorted(set(waiting) - {cfg.seed}, key=lambda s: order.get(s, 1 << 30)):
            grown = anchors.union(found.select(F.col("child").alias("concept")))
            if cfg.anchors == "canonical":
                known = grown.select(F.col("concept").alias("dst"))
                grown = grown.union(merges.join(known, "dst", "left_semi").select(F.col("src").alias("concept")))
            found = written(found.union(attach(frag.filter(F.col("sid") == sid), grown.distinct(), unmerged, merges, cfg)), "attached")
    return base.union(found).distinct(), found.select(F.col("child").alias("concept")).distinct()
