"""Identity stage: forwarding of obsolete names and election of one target per duplicate name.

The paper's loop over relation classes and vocabularies collapses into two algebraic aggregations: what a name gets
depends on its own links alone, so its target is the one of its first (class, vocabulary) step that has exactly one
distinct target.  "Exactly one" is ``min = max``, which combines map-side and needs no set of targets.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kgfold.config import INVERSE, IntegrationConfig
from kgfold.schema import source_of
from kgfold.work import written


def preference_order(concept: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    """source, rank: the given order (seed forced first, unnamed vocabularies appended) or descending name count."""
    counts = concept.groupBy("source").agg(F.count("*").alias("n"))
    given = F.lit(None).cast("int")
    for i, s in enumerate(cfg.order or ()):
        given = F.when(F.col("source") == s, F.lit(i)).otherwise(given)
    keyed = counts.select("source", (F.col("source") != cfg.seed).alias("late"), F.coalesce(given, F.lit(1 << 30)).alias("place"), "n")
    w = Window.orderBy("late", "place", F.desc("n"), "source")  # one row per vocabulary
    return keyed.select("source", (F.row_number().over(w) - 1).alias("rank"))


def classified(mapping: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    """Mappings of known relations with class and class_rank; others belong to quarantine."""
    rows = cfg.relation_rows()
    table = mapping.sparkSession.createDataFrame(rows, "relation string, class string, class_rank int")
    return mapping.join(F.broadcast(table), "relation").select("src", "relation", "dst", "class", "class_rank")


def forward_obsolete(mapping: DataFrame, concept: DataFrame, cfg: IntegrationConfig) -> tuple[DataFrame, DataFrame]:
    """(forwards: src, dst; internal links): obsolete names with one current replacement in their own vocabulary."""
    links = classified(mapping, cfg)
    internal = links.filter(source_of("src") == source_of("dst"))
    strong = internal.filter("class_rank = 0").select("src", "dst")
    if cfg.obsolete_symmetric:
        strong = strong.union(strong.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()
    obsolete = concept.filter("is_obsolete").select("concept")
    from_old = strong.join(obsolete, strong["src"] == obsolete["concept"], "left_semi")
    if cfg.follow_obsolete:
        forwards = _follow(from_old, obsolete)
    else:
        forwards = from_old.join(obsolete, from_old["dst"] == obsolete["concept"], "left_anti")
    agreed = forwards.groupBy("src").agg(F.min("dst").alias("dst"), F.max("dst").alias("_hi"))
    if cfg.obsolete_ambiguous == "drop":
        agreed = agreed.filter(F.col("dst") == F.col("_hi"))
    return agreed.select("src", "dst"), internal.select("src", "relation", "dst")


def _follow(edges: DataFrame, obsolete: DataFrame, max_rounds: int = 40) -> DataFrame:
    """Replacements reached through chains of obsolete names (pointer doubling on the least replacement)."""
    hop = written(edges.groupBy("src").agg(F.min("dst").alias("dst")), "chain")
    for _ in range(max_rounds):
        nxt = hop.select(F.col("src").alias("dst"), F.col("dst").alias("further"))
        new = written(hop.join(nxt, "dst", "left").select("src", F.coalesce("further", "dst").alias("dst")), "chain")
        moved = new.exceptAll(hop).limit(1).count()
        hop = new
        if not moved:
            break
    return hop.join(obsolete, hop["dst"] == obsolete["concept"], "left_anti")


def rewrite_links(mapping: DataFrame, forwards: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    """External links under current names (``internal_links`` says which same-vocabulary links go)."""
    links = classified(mapping, cfg)
    same = source_of("src") == source_of("dst")
    if cfg.internal_links == "all":
        links = links.filter(~same)
    elif cfg.internal_links == "used":
        links = links.join(forwards, ["src", "dst"], "left_anti")
    to = forwards.select(F.col("src").alias("_old"), F.col("dst").alias("_new"))
    left = links.join(to, links["src"] == to["_old"], "left").select(F.coalesce("_new", "src").alias("src"), "relation", "dst", "class", "class_rank")
    both = left.join(to, left["dst"] == to["_old"], "left").select("src", "relation", F.coalesce("_new", "dst").alias("dst"), "class", "class_rank")
    return both.filter("src <> dst").distinct()


def point_at(links: DataFrame) -> DataFrame:
    """Every link in both orientations; a formal relation is inverted by the flip."""
    flipped = F.col("relation")
    for a, b in INVERSE.items():
        flipped = F.when(F.col("relation") == a, F.lit(b)).otherwise(flipped)
    ends = F.array(F.struct("src", "relation", "dst"), F.struct(F.col("dst").alias("src"), flipped.alias("relation"), F.col("src").alias("dst")))
    return links.select(F.explode(ends).alias("x"), "class_rank").select("x.src", "x.relation", "x.dst", "class_rank")


def oriented(links: DataFrame, concept: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    """src, dst, class_rank, source_rank (of the target's vocabulary); seed names are never sources."""
    ranks = preference_order(concept, cfg)
    sides = point_at(links).filter(source_of("src") != cfg.seed)
    if cfg.active_classes is not None:
        sides = sides.filter(F.col("class_rank") < cfg.active_classes)
    if cfg.targets == "seed":
        sides = sides.filter(source_of("dst") == cfg.seed)
    named = sides.withColumn("_to", source_of("dst"))
    return named.join(F.broadcast(ranks.withColumnRenamed("source", "_to")), "_to").select("src", "dst", "class_rank", F.col("rank").alias("source_rank"))


def candidates(links: DataFrame, concept: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    """src, class_rank, source_rank, lo, hi: the range of targets in every step of a name."""
    return oriented(links, concept, cfg).groupBy("src", "class_rank", "source_rank").agg(F.min("dst").alias("lo"), F.max("dst").alias("hi"))


def keep_functional(steps: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    return steps if cfg.ambiguous == "least" else steps.filter("lo = hi")


def elect_targets(links: DataFrame, concept: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    """src, dst, class_rank, source_rank: the unique target of each name's first unambiguous step."""
    if cfg.live_targets:
        return elect_targets_loop(links, concept, cfg)
    return elect_of_steps(candidates(links, concept, cfg), cfg)


def elect_of_steps(steps: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    steps = keep_functional(steps, cfg)
    step = F.col("class_rank").cast("long") * (1 << 32) + F.col("source_rank")
    best = steps.groupBy("src").agg(F.min_by("lo", step).alias("dst"), F.min(step).alias("step"))
    return best.select("src", "dst", F.shiftright("step", 32).cast("int").alias("class_rank"), F.col("step").bitwiseAND(F.lit((1 << 32) - 1)).cast("int").alias("source_rank"))


def ambiguous_steps(links: DataFrame, concept: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    """Rejected steps: src, class_rank, source_rank, n_targets."""
    grouped = oriented(links, concept, cfg).distinct().groupBy("src", "class_rank", "source_rank").agg(F.count("*").alias("n_targets"))
    return grouped.filter("n_targets > 1")


def elect_targets_loop(links: DataFrame, concept: DataFrame, cfg: IntegrationConfig) -> DataFrame:
    """The sequential form, class by class and vocabulary by vocabulary: oracle of the collapsed form, and the way to
    run with ``live_targets`` (a target must be unmerged itself).  One written table per step."""
    sides = written(oriented(links, concept, cfg), "sides")
    steps = [(r["class_rank"], r["source_rank"]) for r in sides.select("class_rank", "source_rank").distinct().orderBy("class_rank", "source_rank").collect()]  # classes x vocabularies
    done = None
    for c, s in steps:
        own = sides.filter((F.col("class_rank") == c) & (F.col("source_rank") == s))
        if done is not None:
            own = own.join(done.select("src"), "src", "left_anti")
            if cfg.live_targets:
                own = own.join(done.select(F.col("src").alias("dst")), "dst", "left_anti")
        new = own.groupBy("src").agg(F.min("dst").alias("dst"), F.max("dst").alias("_hi"))
        new = new if cfg.ambiguous == "least" else new.filter(F.col("dst") == F.col("_hi"))
        new = new.select("src", "dst", F.lit(c).alias("class_rank"), F.lit(s).alias("source_rank"))
        if cfg.live_targets:  # two names that elect each other in one step: the greater one moves
            back = new.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
            new = new.join(back.filter("src < dst"), ["src", "dst"], "left_anti")
        done = written(new if done is None else done.unionByName(new), "elected")
    empty = links.sparkSession.createDataFrame([], "src string, dst string, class_rank int, source_rank int")
    return empty if done is None else done
