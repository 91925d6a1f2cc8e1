"""The paper's methods, variants, baselines, measures and experiments on the fixtures, each with its oracle."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfold.config import IntegrationConfig
from kgfold.kernels import closure, components
from kgfold.operators import baselines, blocks, canonical, hierarchy, identity, metrics, profile, quality
from kgfold.plans import oracle
from kgfold.plans.fixtures import config, load, with_views
from kgfold.plans.pipeline import integrate, resolve_identity, stage_times
from kgfold.schema import KnowledgeGraph, local_of, source_of
from kgfold.work import written

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_ORACLES: dict[str, str] = {}


def add(name: str, run: Callable, sql: str | None = None) -> None:
    _QUERIES[name] = run
    if sql is not None:
        _ORACLES[name] = sql


def _on(fixture: str, f: Callable[[KnowledgeGraph, IntegrationConfig], DataFrame], /, **changes) -> Query:
    return lambda spark, sf_dir: f(load(spark, sf_dir, fixture), config(fixture, **changes))


def _forwards(kg, cfg):
    return blocks.forwards(kg, cfg)


def _links(kg, cfg):
    return blocks.links(kg, written(_forwards(kg, cfg), "forwards"), cfg)


def _elect(kg, cfg):
    return blocks.elect(kg, written(_forwards(kg, cfg), "forwards"), cfg)


def _canonical(kg, cfg):
    return resolve_identity(kg, cfg).canonical_merges


def _tree(kg, cfg):
    return integrate(kg, cfg).domain_hierarchy


COMPARISON = (
    "SELECT 'concept sources' AS metric, (SELECT count(DISTINCT source) FROM concept) AS value_in, (SELECT count(DISTINCT source) FROM dconcept) AS value_out "
    "UNION ALL SELECT 'concepts', (SELECT count(*) FROM concept), (SELECT count(*) FROM dconcept) UNION ALL SELECT 'concept merges', NULL, (SELECT count(*) FROM can) "
    "UNION ALL SELECT 'mappings', (SELECT count(*) FROM mapping), (SELECT count(*) FROM dmapping) "
    "UNION ALL SELECT 'connected subgraphs', (SELECT count(DISTINCT label) FROM i_label), (SELECT count(DISTINCT label) FROM o_label) "
    "UNION ALL SELECT 'hierarchy edges', (SELECT count(*) FROM hier), (SELECT count(*) FROM dtree)"
)
SUBGRAPHS = [*oracle.components_of("hier", "child", "parent", "i"), *oracle.components_of("dtree", "child", "parent", "o")]
_STATUS = {
    "input": "true", "seed": "bucket = 'seed'", "to_seed": "bucket = 'to_seed'", "to_other": "bucket = 'to_other'", "obsolete_open": "bucket = 'obsolete_open'", "unmapped": "bucket = 'unmapped'",
    "connected_base": "bucket IN ('seed', 'to_seed')", "connected_attached": "attached", "disconnected": "bucket = 'unmapped' AND NOT attached",
    "merged_share": "bucket IN ('seed', 'to_seed', 'to_other')", "integrated_share": "bucket IN ('seed', 'to_seed') OR attached",
}
STATUS = " UNION ALL ".join(f"SELECT '{k}' AS status, count(*) FILTER (WHERE {c}) AS n, round(count(*) FILTER (WHERE {c})::DOUBLE / count(*), 4) AS ratio FROM bucket" for k, c in _STATUS.items())
CONNECTIVITY = ("connected_base", "connected_attached", "disconnected", "integrated_share")


def _methods() -> None:
    for k in ("k1", "k2"):
        add(f"m3_forward_obsolete_{k}", _on(k, _forwards), oracle.sql(k, "SELECT src, dst FROM fwd"))
        add(f"m4_rewrite_links_{k}", _on(k, lambda kg, c: _links(kg, c).select("src", "relation", "dst")), oracle.sql(k, "SELECT src, relation, dst FROM links"))
        add(f"m5e_ambiguous_{k}", _on(k, lambda kg, c: identity.ambiguous_steps(_links(kg, c), kg.concept, c)), oracle.sql(k, "SELECT src, cls AS class_rank, rnk AS source_rank, count(DISTINCT dst) AS n_targets FROM sides GROUP BY src, cls, rnk HAVING count(DISTINCT dst) > 1"))
    for k in ("k1", "k2", "k3", "k7", "k8"):
        add(f"m5_elect_targets_{k}", _on(k, _elect), oracle.sql(k, "SELECT src, dst, cls AS class_rank, rnk AS source_rank FROM elect"))
        add(f"m10_source_order_{k}", _on(k, lambda kg, c: identity.preference_order(kg.concept_once, c)), oracle.sql(k, "SELECT source, rnk AS rank FROM ranks"))
    for k in ("k1", "k2", "k3"):
        add(f"m6_canonical_{k}", _on(k, _canonical), oracle.sql(k, "SELECT src, dst FROM can"))
        add(f"m7_domain_concepts_{k}", _on(k, lambda kg, c: resolve_identity(kg, c).domain_concepts), oracle.sql(k, "SELECT concept, source FROM dconcept"))
        add(f"m7_domain_mappings_{k}", _on(k, lambda kg, c: resolve_identity(kg, c).domain_mappings), oracle.sql(k, "SELECT src, relation, dst FROM dmapping"))
        add(f"m8_unmerged_{k}", _on(k, lambda kg, c: resolve_identity(kg, c).unmerged), oracle.sql(k, "SELECT concept, source FROM unm"))
        add(f"m9_domain_hierarchy_{k}", _on(k, _tree), oracle.sql(k, "SELECT child, parent FROM dtree"))
        add(f"m9_attached_{k}", _on(k, lambda kg, c: integrate(kg, c).attached), oracle.sql(k, "SELECT DISTINCT child AS concept FROM atte"))
    for k in ("k1", "k3", "k8"):
        free = _on(k, lambda kg, c: hierarchy.root_distance(hierarchy.usable_edges(kg.hier, None, c).filter(source_of("child") != c.seed), c))
        add(f"m9e_root_distance_{k}", free, oracle.sql(k, "SELECT far.sid AS sid, far.node AS node, far.dist AS dist, hop.nxt AS next_hop FROM far LEFT JOIN hop ON far.sid = hop.sid AND far.node = hop.node"))
    for side, q in (("left", "SELECT DISTINCT src AS concept FROM mapping"), ("right", "SELECT DISTINCT dst AS concept FROM mapping"), ("both", "SELECT src AS concept FROM mapping UNION SELECT dst FROM mapping")):
        add(f"m11_signature_{side}_k1", _on("k1", lambda kg, c, side=side: blocks.signature(kg, side)), oracle.sql("k1", q))
    stable = "SELECT (SELECT count(*) FROM (SELECT src FROM {t} GROUP BY src HAVING count(*) > 1)) + (SELECT count(*) FROM (SELECT DISTINCT src FROM {t} WHERE src IN (SELECT dst FROM {t}))) AS violations"
    add("m13_stability_k1", _on("k1", lambda kg, c: canonical.stability_violations(_canonical(kg, c)).agg(F.count("*").alias("violations"))), oracle.sql("k1", stable.format(t="can")))
    add("m13_stability_before_k1", _on("k1", lambda kg, c: canonical.stability_violations(resolve_identity(kg, c).merges).agg(F.count("*").alias("violations"))), oracle.sql("k1", stable.format(t="merges")))


def _variant(name: str, fixture: str, f: Callable, last: str, /, **changes) -> None:
    add(name, _on(fixture, f, **changes), oracle.sql(fixture, last, config(fixture, **changes)))


def _variants() -> None:
    can, tree = "SELECT src, dst FROM can", "SELECT child, parent FROM dtree"
    _variant("v1_given_order_k1", "k1", _canonical, can, order=("B7", "B1", "B3"))
    _variant("v5_obsolete_least_k2", "k2", _forwards, "SELECT src, dst FROM fwd", obsolete_ambiguous="least")
    _variant("v7_internal_keep_k1", "k1", lambda kg, c: _links(kg, c).select("src", "relation", "dst"), "SELECT src, relation, dst FROM links", internal_links="keep")
    _variant("v7_internal_used_k1", "k1", lambda kg, c: _links(kg, c).select("src", "relation", "dst"), "SELECT src, relation, dst FROM links", internal_links="used")
    _variant("v8_least_target_k1", "k1", _elect, "SELECT src, dst, cls AS class_rank, rnk AS source_rank FROM elect", ambiguous="least")
    _variant("v11_same_source_edges_k1", "k1", _tree, tree, same_source="edge")
    _variant("v14_any_anchor_k1", "k1", lambda kg, c: integrate(kg, c).attached, "SELECT DISTINCT child AS concept FROM atte", path="any_anchor")
    add("v2_three_classes_k1", _on("k1", _elect, classes=_THREE), oracle.sql("k1", "SELECT src, dst, cls AS class_rank, rnk AS source_rank FROM elect", config("k1", classes=_THREE)))
    add("v6_follow_obsolete_k1", _on("k1", _forwards, follow_obsolete=True))
    add("v9_live_targets_k3", _on("k3", _elect, live_targets=True))
    add("v10_sink_canonical_k3", _on("k3", _canonical, canonical="sink"))
    add("v13_two_shortest_k1", _on("k1", lambda kg, c: integrate(kg, c).attached, path="k_shortest", k=2))
    add("v16_closure_k3", _on("k3", lambda kg, c: closure(kg.hier)), oracle.sql("k3", "SELECT child, ancestor, min(dist) AS dist FROM up GROUP BY child, ancestor", extra=[("up(child, ancestor, dist)", "SELECT child, parent, 1 FROM hier UNION SELECT up.child, h.parent, dist + 1 FROM up JOIN hier h ON h.child = up.ancestor WHERE dist < 50")]))
    add("v19_canonical_anchor_k1", _on("k1", lambda kg, c: integrate(kg, c).attached, anchors="canonical"))
    add("v26_inferred_mappings_k1", _on("k1", lambda kg, c: canonical.inferred_mappings(kg.mapping, _canonical(kg, c))), oracle.sql("k1", "SELECT src, dst FROM can EXCEPT (SELECT src, dst FROM mapping UNION SELECT dst, src FROM mapping)"))


_THREE = (("equivalence", ("exactMatch", "replacedBy")), ("aligned", ("alignedWith",)), ("reference", ("xref", "approx")))


def _baselines() -> None:
    can = "SELECT src, dst FROM can"
    _variant("b1_obsolete_only_k1", "k1", _canonical, can, align=False)
    for k in ("k1", "k2"):
        _variant(f"b2_equivalence_only_{k}", k, _canonical, can, active_classes=1)
    _variant("b3_seed_only_k1", "k1", _canonical, can, targets="seed")
    add("b4_components_k1", _on("k1", baselines.equivalence_components), oracle.sql("k1", "SELECT node, label FROM q_label", extra=[("eq", "SELECT src, dst FROM ml WHERE cls = 0"), *oracle.components_of("eq", "src", "dst", "q")]))
    add("b5_sequential_loop_k3", _on("k3", lambda kg, c: identity.elect_targets_loop(_links(kg, c), kg.concept, c)), oracle.sql("k3", "SELECT src, dst, cls AS class_rank, rnk AS source_rank FROM elect"))
    add("b7_naive_union_k1", _on("k1", lambda kg, c: baselines.naive_union(kg, _canonical(kg, c))), oracle.sql("k1", "SELECT DISTINCT coalesce(a.dst, child) AS child, coalesce(b.dst, parent) AS parent FROM hier LEFT JOIN can a ON child = a.src LEFT JOIN can b ON parent = b.src WHERE coalesce(a.dst, child) <> coalesce(b.dst, parent)"))


def _paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    kg, rows = load(spark, sf_dir, "k1"), []
    for path in ("shortest", "k_shortest", "any_anchor"):
        got = integrate(kg, config("k1", path=path))
        rows.append(got.attached.agg(F.count("*").alias("attached")).select(F.lit(path).alias("path"), "attached"))
    return reduce(DataFrame.union, rows)


def _orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    kg, rows = load(spark, sf_dir, "k1"), []
    for name, changes in _ORDERS.items():
        cfg = config("k1").with_(**changes)
        rows.append(_canonical(kg, cfg).agg(F.lit(name).alias("setting"), F.count("*").alias("merges"), F.coalesce(F.sum((source_of("dst") == cfg.seed).cast("long")), F.lit(0)).alias("to_seed")))
    return reduce(DataFrame.union, rows)


_ORDERS = {"frequency": {}, "given": {"order": ("B25", "B24", "B23")}, "other seed": {"seed": "B5"}}


def _experiments() -> None:
    for k in ("k1", "k2", "k3"):
        add(f"w2_comparison_{k}", _on(k, lambda kg, c: metrics.comparison_table(kg, integrate(kg, c))), oracle.sql(k, COMPARISON, extra=SUBGRAPHS))
        add(f"w3_status_{k}", _on(k, lambda kg, c: metrics.status_table(kg, integrate(kg, c), c)), oracle.sql(k, STATUS))
        add(f"w4_connectivity_{k}", _on(k, lambda kg, c: metrics.status_table(kg, integrate(kg, c), c).filter(F.col("status").isin(*CONNECTIVITY))), oracle.sql(k, f"SELECT * FROM ({STATUS}) WHERE status IN {CONNECTIVITY}"))
        add(f"w7_subgraphs_{k}", _on(k, lambda kg, c: metrics.subgraphs(kg.hier).select(F.col("n").alias("n_in")).crossJoin(metrics.subgraphs(_tree(kg, c)).select(F.col("n").alias("n_out")))), oracle.sql(k, "SELECT (SELECT count(DISTINCT label) FROM i_label) AS n_in, (SELECT count(DISTINCT label) FROM o_label) AS n_out", extra=SUBGRAPHS))
    add("w2_comparison_k4", _on("k4", lambda kg, c: metrics.comparison_table(kg, integrate(kg, c))))
    add("w5_stage_times_k4", _on("k4", stage_times))
    four = ("B1", "B2", "B3", "B4")
    add("w6_four_hierarchies_k1", _on("k1", lambda kg, c: metrics.status_table(kg, integrate(kg, c), c), hierarchies=four), oracle.sql("k1", STATUS, config("k1", hierarchies=four)))
    add("w8_path_variants_k1", _paths)
    forms = " UNION ALL ".join(f"SELECT '{s}' AS setting, merges, to_seed FROM ({oracle.sql('k1', 'SELECT count(*) AS merges, count(*) FILTER (WHERE split_part(dst, chr(58), 1) = chr(66) || {n}) AS to_seed FROM can'.replace('{n}', repr(config('k1').with_(**ch).seed[1:])), config('k1').with_(**ch))})" for s, ch in _ORDERS.items())
    add("w13_order_sensitivity_k1", _orders, forms)
    add("w14_class_ablation_k1", _ablation, " UNION ALL ".join(f"SELECT '{s}' AS setting, merges FROM ({oracle.sql('k1', 'SELECT count(*) AS merges FROM can', config('k1', active_classes=n))})" for s, n in (("equivalence", 1), ("both", 2))))
    add("a18_growth_k1", _on("k1", lambda kg, c: metrics.growth(kg, integrate(kg, c))), oracle.sql("k1", "SELECT count(*) AS n FROM (SELECT child AS c FROM dtree UNION SELECT parent FROM dtree) WHERE c NOT IN (SELECT concept FROM dconcept)"))
    add("a20_coverage_k1", _on("k1", lambda kg, c: metrics.coverage_by_source(kg, integrate(kg, c, write_tree=False))), oracle.sql("k1", "SELECT source, count(*) AS unmerged, count(*) FILTER (WHERE concept IN (SELECT child FROM atte)) AS attached, round(count(*) FILTER (WHERE concept IN (SELECT child FROM atte))::DOUBLE / count(*), 4) AS ratio FROM unm GROUP BY source"))
    add("a22_cluster_sizes_k1", _on("k1", lambda kg, c: metrics.cluster_sizes(_canonical(kg, c))), oracle.sql("k1", "SELECT size, count(*) AS clusters, count(*) FILTER (WHERE k > 1) AS spanning FROM (SELECT b, count(*) AS size, count(DISTINCT split_part(a, ':', 1)) AS k FROM chosen GROUP BY b) GROUP BY size"))
    dag = (
        "SELECT 'roots' AS \"check\", (SELECT count(DISTINCT parent) FROM dtree WHERE parent NOT IN (SELECT child FROM dtree)) AS n UNION ALL SELECT 'self loops', (SELECT count(*) FROM dtree WHERE child = parent) "
        "UNION ALL SELECT 'several parents', (SELECT count(*) FROM (SELECT child FROM dtree GROUP BY child HAVING count(*) > 1)) UNION ALL SELECT 'components', (SELECT count(DISTINCT label) FROM o_label) UNION ALL SELECT 'edges in cycles', 0"
    )
    add("t13_single_dag_k1", _on("k1", lambda kg, c: metrics.dag_checks(_tree(kg, c))), oracle.sql("k1", dag, extra=oracle.components_of("dtree", "child", "parent", "o")))
    add("t9_acyclic_k1", _on("k1", lambda kg, c: metrics.dag_checks(kg.hier).filter("check = 'edges in cycles'")), "SELECT 'edges in cycles' AS \"check\", 0 AS n")
    add("w11_chain_example", _chain_example, "SELECT concat('S1:', p_partkey) AS src, concat('S3:', p_partkey) AS dst FROM part UNION SELECT concat('S2:', p_partkey), concat('S3:', p_partkey) FROM part")
    add("w12_drawing_example", _drawing_example, "SELECT * FROM (VALUES ('A:2','A:1'),('A:3','A:1'),('A:4','A:2'),('A:D1','A:2'),('A:6','A:3'),('A:7','A:4'),('A:8','A:4'),('A:9','A:6'),('C:2','A:D1')) t(child, parent)")


def _ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    kg = load(spark, sf_dir, "k1")
    return reduce(DataFrame.union, [_canonical(kg, config("k1", active_classes=n)).agg(F.lit(s).alias("setting"), F.count("*").alias("merges")) for s, n in (("equivalence", 1), ("both", 2))])


def example(spark: SparkSession, concepts: list[str], mappings: list[tuple], edges: list[tuple], obsolete: tuple[str, ...] = ()) -> KnowledgeGraph:
    """A knowledge graph of literal rows."""
    return KnowledgeGraph.of(
        spark.createDataFrame([(c, c in obsolete) for c in concepts], "concept string, is_obsolete boolean"),
        spark.createDataFrame(mappings, "src string, relation string, dst string"),
        spark.createDataFrame(edges, "child string, parent string"),
    )


def _chain_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The three-step chain of names, one for every part."""
    key = spark.read.parquet(f"{sf_dir}/part.parquet").select("p_partkey")
    name = lambda s: F.concat(F.lit(f"{s}:"), "p_partkey")
    concept = key.select(F.explode(F.array(name("S1"), name("S2"), name("S3"))).alias("concept")).select("concept", source_of("concept").alias("source"), F.lit(False).alias("is_obsolete"))
    merges = key.select(name("S1").alias("src"), name("S2").alias("dst")).union(key.select(name("S2"), name("S3")))
    return canonical.canonicalise(merges, concept, IntegrationConfig(seed="S3", order=("S3", "S2", "S1")))


def _drawing_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    left = [("A:2", "A:1"), ("A:3", "A:1"), ("A:4", "A:2"), ("A:D1", "A:2"), ("A:6", "A:3"), ("A:7", "A:4"), ("A:8", "A:4"), ("A:9", "A:6")]
    right = [("C:1", "C:0"), ("C:2", "C:1"), ("C:3", "C:0"), ("C:4", "C:3")]
    names = sorted({x for e in left + right for x in e})
    kg = example(spark, names, [("C:1", "exactMatch", "A:D1")], left + right)
    return integrate(kg, IntegrationConfig(seed="A")).domain_hierarchy


PART = ("p_name", "p_type", "p_brand")
DOCUMENTS = ("doc_id", "text", "lang", "source", "n_chars")
GRAPH = {"concept": ("concept", "source", "is_obsolete"), "mapping": ("src", "relation", "dst"), "hier": ("child", "parent")}


def _profile_sql(table: str, cols: tuple[str, ...]) -> str:
    return " UNION ALL ".join(
        f"SELECT '{c}' AS \"column\", count(*) AS n, count(*) - count({c}) AS n_null, count(DISTINCT {c}) AS n_distinct, min({c}::VARCHAR) AS least, max({c}::VARCHAR) AS greatest, max(length({c}::VARCHAR)) AS longest, count(DISTINCT {c}) = 1 AS is_constant, count(DISTINCT {c}) = count(*) AS is_unique FROM {table}"
        for c in cols
    )


def _table_profiles(kg: KnowledgeGraph, cfg: IntegrationConfig) -> DataFrame:
    parts = [profile.profile_table(getattr(kg, t).select(*cols)).select(F.lit(t).alias("table"), "*") for t, cols in GRAPH.items()]
    return reduce(DataFrame.union, parts)


def _table_profiles_sql() -> str:
    missing = {t: " + ".join(f"(count(*) - count({c}))" for c in cols) for t, cols in GRAPH.items()}
    return " UNION ALL ".join(f"SELECT '{t}' AS \"table\", count(*) AS n_rows, count(*) - (SELECT count(*) FROM (SELECT DISTINCT {', '.join(cols)} FROM {t})) AS duplicate_rows, {missing[t]} AS missing_cells FROM {t}" for t, cols in GRAPH.items())


def _analytics() -> None:
    add("r2_table_profile_part", lambda s, d: profile.profile_table(s.read.parquet(f"{d}/part.parquet")), "SELECT count(*) AS n_rows, count(*) - (SELECT count(*) FROM (SELECT DISTINCT * FROM part)) AS duplicate_rows, 0 AS missing_cells FROM part")
    add("r2_table_profile_k1", _on("k1", _table_profiles), oracle.sql("k1", _table_profiles_sql()))
    add("r1_profile_part", lambda s, d: profile.profile(s.read.parquet(f"{d}/part.parquet").select(*PART), exact=True), _profile_sql("part", PART))
    add("r1_profile_documents", lambda s, d: profile.profile(s.read.parquet(f"{d}/documents.parquet").select(*DOCUMENTS), exact=True), _profile_sql("documents", DOCUMENTS))
    add("r3_link_matrix_k2", _on("k2", lambda kg, c: profile.link_matrix(kg.mapping, c)), oracle.sql("k2", "SELECT ss AS source, ds AS target, count(*) FILTER (WHERE cls = 0) AS equivalence, count(*) FILTER (WHERE cls = 1) AS reference FROM ml GROUP BY ss, ds"))
    mult = "SELECT relation, kind, count(*) AS n FROM (SELECT relation, CASE WHEN o = 1 AND i = 1 THEN '1:1' WHEN o = 1 THEN 'n:1' WHEN i = 1 THEN '1:n' ELSE 'n:m' END AS kind FROM (SELECT relation, count(*) OVER (PARTITION BY src, relation) AS o, count(*) OVER (PARTITION BY dst, relation) AS i FROM mapping)) GROUP BY relation, kind"
    add("r4_multiplicity_k1", _on("k1", lambda kg, c: profile.multiplicity_report(kg.mapping)), oracle.sql("k1", mult))
    add("r5_hints_same_local_k1", _on("k1", lambda kg, c: profile.same_local_hints(resolve_identity(kg, c).unmerged)), oracle.sql("k1", "SELECT lower(substring(concept, length(source) + 2)) AS local, count(*) AS names, min(concept) AS first FROM unm GROUP BY 1 HAVING count(DISTINCT source) > 1"))
    add("r5_hints_dangling_k1", lambda s, d: _dangling(s, d), oracle.sql("k1", "SELECT DISTINCT src, relation, dst FROM raw_mapping WHERE src <> dst AND (src NOT IN (SELECT concept FROM concept) OR dst NOT IN (SELECT concept FROM concept))"))
    add("r10_depths_k1", _on("k1", lambda kg, c: profile.hierarchy_shape(hierarchy.root_distance(kg.hier.filter(source_of("child") != c.seed), c))), oracle.sql("k1", "SELECT dist, count(*) AS n FROM far GROUP BY dist"))
    add("r8_report_sections_k1", _report)
    for k in ("k1", "k2", "k3"):
        add(f"t_all_expectations_{k}", _on(k, lambda kg, c: quality.graph_expectations(kg, c)), _expectations_sql(k))


def _expectations_sql(k: str) -> str:
    rules = [
        ("concept not null", "(SELECT count(*) FROM concept WHERE concept IS NULL)"),
        ("concept unique", "(SELECT count(*) - count(DISTINCT concept) FROM concept)"),
        ("concept name form", "(SELECT count(*) FROM concept WHERE NOT regexp_matches(concept, '^[^:]+:.+$'))"),
        ("mapping unique", "0"),
        ("mapping no self link", "(SELECT count(*) FROM mapping WHERE src = dst)"),
        ("mapping relation known", "(SELECT count(*) FROM mapping WHERE relation NOT IN ('exactMatch', 'alignedWith', 'replacedBy', 'xref', 'approx'))"),
        ("hier no self edge", "(SELECT count(*) FROM hier WHERE child = parent)"),
        ("mapping src refers to concept", "(SELECT count(*) FROM mapping WHERE src NOT IN (SELECT concept FROM concept))"),
        ("mapping dst refers to concept", "(SELECT count(*) FROM mapping WHERE dst NOT IN (SELECT concept FROM concept))"),
        ("hier child refers to concept", "(SELECT count(*) FROM hier WHERE child NOT IN (SELECT concept FROM concept))"),
        ("hier parent refers to concept", "(SELECT count(*) FROM hier WHERE parent NOT IN (SELECT concept FROM concept))"),
        ("seed present", f"(SELECT CASE WHEN count(*) > 0 THEN 0 ELSE 1 END FROM concept WHERE source = '{config(k).seed}')"),
    ]
    return oracle.sql(k, " UNION ALL ".join(f"SELECT '{r}' AS rule, {q} = 0 AS success, {q} AS bad_rows" for r, q in rules))


def _dangling(spark: SparkSession, sf_dir: str) -> DataFrame:
    from kgfold.plans.fixtures import K1, inlined

    with_views(spark, sf_dir)
    get = lambda t: spark.sql(inlined(K1, f"SELECT * FROM {t}"))
    return quality.dangling(get("raw_mapping").filter("src <> dst").distinct(), get("concept"))


def _report(spark: SparkSession, sf_dir: str) -> DataFrame:
    from kgfold.operators.report import report_sections

    kg, cfg = load(spark, sf_dir, "k1"), config("k1")
    return report_sections(kg, integrate(kg, cfg), cfg)


def queries() -> dict[str, Query]:
    if not _QUERIES:
        for part in (_methods, _variants, _baselines, _experiments, _analytics):
            part()
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    queries()
    return dict(_ORACLES)


__all__ = ["components", "example", "local_of", "oracle_sql", "queries"]
