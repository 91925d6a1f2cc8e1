"""Graph kernels as DataFrame loops: connected components, breadth-first search, peeling, pointer doubling, closure.

Each round is one or two exchanges on node keys and ends in a written table, so lineage stays short and a lost
executor costs one round.  The driver sees only counts.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kgfold.work import written

#: Graphs of at most so many edges (under 2 MB) are settled by one task; larger ones by rounds of exchanges.
ONE_TASK_EDGES = 15_000


def _settle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Components of all the edges (u, v) that one task reads."""
    up: dict = {}

    def top(x):
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    schema = None
    for b in batches:
        schema = b.schema
        for u, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            up.setdefault(u, u)
            up.setdefault(v, v)
            a, b_ = top(u), top(v)
            up[max(a, b_)] = min(a, b_)
    if schema is not None:
        kind = schema.field(0).type
        nodes = list(up)
        yield pa.RecordBatch.from_arrays([pa.array(nodes, kind), pa.array([top(x) for x in nodes], kind)], ["node", "label"])


def components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 60, any_label: bool = False) -> DataFrame:
    """node, label: the least node of each weakly connected component, for every node that has an edge.

    Names with one neighbour only step aside first: they follow it, and lend it their name where theirs is less.  Many
    names are first replaced by numbers.  With ``any_label``, a label is any value that is the component's alone.
    """
    pairs = written(edges.select(F.greatest(src, dst).alias("u"), F.least(src, dst).alias("v")), "cc")
    few = pairs.limit(ONE_TASK_EDGES + 1).count() <= ONE_TASK_EDGES
    if not few and pairs.schema["u"].dataType.simpleString() == "string":
        names = written(pairs.select(F.explode(F.array("u", "v")).alias("node")).distinct().select("node", _digest("node").alias("id")), "cc")
        if names.groupBy("id").count().filter("count > 1").isEmpty():  # each name has its own number: rounds need no strings
            found = components(pairs.select(_digest("u").alias("u"), _digest("v").alias("v")), "u", "v", max_rounds)
            held = names.join(found.withColumnRenamed("node", "id"), "id")
            if any_label:
                return held.select("node", "label")
            held = written(held.select("node", F.col("label").alias("_id")), "cc")
            return held.join(held.groupBy("_id").agg(F.min("node").alias("label")), "_id").select("node", "label")
    pairs = written(pairs.distinct(), "cc")
    if pairs.limit(ONE_TASK_EDGES + 1).count() <= ONE_TASK_EDGES:
        return _contracted(pairs, max_rounds)
    links = pairs.filter("u <> v")
    near = links.select(F.col("u").alias("node"), F.col("v").alias("x")).union(links.select("v", "u")).groupBy("node").agg(F.count("*").alias("n"), F.min("x").alias("hub"))
    near = written(near, "cc")
    leaves = near.filter("n = 1").select(F.col("node").alias("leaf"), "hub")
    core = links
    for end in ("u", "v"):
        core = core.join(leaves.select(F.col("leaf").alias(end)), end, "left_anti")
    core = _contracted(written(core.select("u", "v"), "cc"), max_rounds).withColumnRenamed("label", "_core")
    lent = leaves.groupBy("hub").agg(F.min("leaf").alias("_lent")).withColumnRenamed("hub", "node")
    inner = near.filter("n > 1").select("node").join(core, "node", "left").join(lent, "node", "left").select("node", F.coalesce("_core", "node").alias("_core"), F.least("node", "_lent").alias("_own"))
    inner = written(inner, "cc")
    inner = written(inner.join(inner.groupBy("_core").agg(F.min("_own").alias("label")), "_core").select("node", "label"), "cc")
    outer = leaves.join(inner.select(F.col("node").alias("hub"), "label"), "hub", "left").select(F.col("leaf").alias("node"), F.coalesce("label", F.least("leaf", "hub")).alias("label"))
    loops = pairs.filter("u = v").select(F.col("u").alias("node"), F.col("v").alias("label")).join(near.select("node"), "node", "left_anti")
    return inner.union(outer).union(loops)


def _contracted(pairs: DataFrame, max_rounds: int) -> DataFrame:
    """Alternating star contraction of a written table: every node hooks its larger neighbours, then its smaller ones, to
    the least neighbour it knows, until each component is one star.
    """
    if pairs.limit(ONE_TASK_EDGES + 1).count() <= ONE_TASK_EDGES:
        kind = pairs.schema["u"].dataType.simpleString()
        return pairs.coalesce(1).mapInArrow(_settle, f"node {kind}, label {kind}")
    return _starred(pairs, max_rounds)


def _digest(name: str) -> Column:
    return F.xxhash64(name)


def _starred(pairs: DataFrame, max_rounds: int) -> DataFrame:
    """The rounds of ``_contracted``; u and v may come in either order."""
    seen = None
    for _ in range(max_rounds):
        both = pairs.filter("u <> v").select("u", "v").union(pairs.filter("u <> v").select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.filter("u <> m").select("u", F.col("m").alias("v")))
        large = large.filter("u <> v").distinct()
        lower = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(lower, "u").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        stars = small.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).union(lower.select("u", F.col("m").alias("v")))
        new = written(stars.filter("u <> v").distinct().union(pairs.filter("u = v")), "cc")
        state = new.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        pairs = new
        if state == seen:
            break
        seen = state
    else:
        raise RuntimeError("components did not settle")
    linked = pairs.filter("u <> v").select(F.col("u").alias("node"), F.col("v").alias("label"))
    roots = linked.select(F.col("label").alias("node"), "label").distinct()
    loops = pairs.filter("u = v").select(F.col("u").alias("node"), F.col("v").alias("label")).join(linked.select("node").union(roots.select("node")), "node", "left_anti")
    return linked.union(roots).union(loops)


def follow_to_sink(edges: DataFrame, max_rounds: int = 40) -> DataFrame:
    """src, dst of a functional graph with every chain followed to its end (pointer doubling); cycles end at their least node."""
    hop = written(edges.groupBy("src").agg(F.min("dst").alias("dst")), "sink")
    label = components(hop).withColumnRenamed("node", "src")
    ends = hop.select(F.col("dst").alias("src")).join(hop.select("src"), "src", "left_anti").distinct()
    for _ in range(max_rounds):
        nxt = hop.select(F.col("src").alias("dst"), F.col("dst").alias("further"))
        new = written(hop.join(nxt, "dst", "left").select("src", F.coalesce("further", "dst").alias("dst")), "sink")
        if not new.join(ends.withColumnRenamed("src", "dst"), "dst", "left_anti").join(hop, ["src", "dst"], "left_anti").limit(1).count():
            hop = new
            break
        hop = new
    settled = hop.join(ends.withColumnRenamed("src", "dst"), "dst", "left_semi").select("src", "dst")
    cyclic = hop.join(settled.select("src"), "src", "left_anti").join(label, "src").select("src", F.col("label").alias("dst"))
    return settled.union(cyclic).filter("src <> dst")


def bfs_down(edges: DataFrame, starts: DataFrame, marks: DataFrame, max_rounds: int = 10_000) -> DataFrame:
    """Level-synchronous search from ``starts`` (sid, node) down ``edges`` (sid, child, parent).

    Returns sid, node, dist, next_hop (least parent one step nearer), kept (nearest ancestor that ``marks`` names as
    anchor or unmerged) and anchored (an anchor lies above).  ``marks``: sid, node, is_anchor, is_open.  Every edge is
    relaxed once, all fragments advance in the same rounds, and no path is ever stored.  Names that nothing hangs from
    lead nowhere, so the rounds leave them out and all of them follow in one step.
    """
    upper = written(edges.select("sid", F.col("parent").alias("node")).distinct(), "bfs")
    as_child = upper.withColumnRenamed("node", "child")
    inner, inner_marks = written(edges.join(as_child, ["sid", "child"], "left_semi").select("sid", "child", "parent"), "bfs"), written(marks.join(upper, ["sid", "node"], "left_semi"), "bfs")
    flags = [F.coalesce(c, F.lit(False)).alias(c) for c in ("is_anchor", "is_open")]
    carried = F.struct(F.when(F.col("is_anchor") | F.col("is_open"), F.col("parent")).otherwise(F.col("kept")).alias("kept"), (F.col("is_anchor") | F.col("anchored")).alias("anchored"))
    frontier = written(
        starts.select("sid", "node", F.lit(0).alias("dist"), F.lit(None).cast("string").alias("next_hop"), F.lit(None).cast("string").alias("kept"), F.lit(False).alias("anchored"))
        .join(marks, ["sid", "node"], "left")
        .select("sid", "node", "dist", "next_hop", "kept", "anchored", *flags),
        "bfs",
    )
    layers = [frontier]
    seen = frontier.select("sid", "node")
    for d in range(1, max_rounds + 1):
        up = frontier.select("sid", F.col("node").alias("parent"), "kept", "anchored", "is_anchor", "is_open")
        reached = inner.join(up, ["sid", "parent"]).join(seen.withColumnRenamed("node", "child"), ["sid", "child"], "left_anti")
        best = reached.groupBy("sid", F.col("child").alias("node")).agg(F.min("parent").alias("next_hop"), F.min_by(carried, "parent").alias("c"))
        frontier = best.join(inner_marks, ["sid", "node"], "left").select("sid", "node", F.lit(d).alias("dist"), "next_hop", "c.kept", "c.anchored", *flags)
        frontier = written(frontier, "bfs")
        if frontier.isEmpty():
            break
        layers.append(frontier)
        seen = seen.union(frontier.select("sid", "node"))
    out = layers[0]
    for layer in layers[1:]:
        out = out.unionByName(layer)
    up = out.select("sid", F.col("node").alias("parent"), "dist", "kept", "anchored", "is_anchor", "is_open")
    outer = edges.select("sid", "child", "parent").join(as_child, ["sid", "child"], "left_anti").join(up, ["sid", "parent"]).join(starts.select("sid", F.col("node").alias("child")), ["sid", "child"], "left_anti")
    nearest = F.struct("dist", "parent")
    best = outer.groupBy("sid", F.col("child").alias("node")).agg(F.min(nearest).alias("n"), F.min_by(carried, nearest).alias("c"))
    last = best.join(marks, ["sid", "node"], "left").select("sid", "node", (F.col("n.dist") + 1).alias("dist"), F.col("n.parent").alias("next_hop"), "c.kept", "c.anchored", *flags)
    return out.unionByName(written(last, "bfs"))


def peel(edges: DataFrame, max_rounds: int = 10_000) -> DataFrame:
    """The edges (child, parent) left after roots are taken away again and again: empty if and only if there is no cycle."""
    left = written(edges.select("child", "parent").distinct(), "peel")
    n = left.count()
    for _ in range(max_rounds):
        if not n:
            break
        left = written(left.join(left.select(F.col("child").alias("parent")).distinct(), "parent", "left_semi").select("child", "parent"), "peel")
        m = left.count()
        if m == n:
            break
        n = m
    return left


def closure(edges: DataFrame, max_depth: int = 50, max_rows: int = 50_000_000) -> DataFrame:
    """child, ancestor, dist: least distances of all ancestor pairs, semi-naive; refuses to grow over ``max_rows``."""
    step = written(edges.select("child", F.col("parent").alias("ancestor")).distinct(), "closure")
    known = new = written(step.withColumn("dist", F.lit(1)), "closure")
    for d in range(2, max_depth + 1):
        further = new.join(step.select(F.col("child").alias("ancestor"), F.col("ancestor").alias("_up")), "ancestor").select("child", F.col("_up").alias("ancestor")).distinct()
        new = written(further.join(known, ["child", "ancestor"], "left_anti").withColumn("dist", F.lit(d)), "closure")
        if new.isEmpty():
            break
        known = known.unionByName(new)
        if known.count() > max_rows:
            raise RuntimeError(f"the closure has over {max_rows} rows")
    return known
