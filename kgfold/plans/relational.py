"""Relational operators around the methods: one query each on the given tables.

``both`` entries are one statement that Spark's and DuckDB's SQL share; ``pair`` entries are built with the DataFrame
API (join strategies, higher-order functions, sketches, round trips) and have an oracle of their own.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kgfold.plans.fixtures import FIXTURES, TABLES, inlined, load
from kgfold.work import work_dir

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_ORACLES: dict[str, str] = {}


def both(name: str, sql: str, fixture: str | None = None, oracle: str | None = None) -> None:
    """The same statement in both engines (``oracle`` where one function has another name)."""
    text = inlined(FIXTURES[fixture], sql) if fixture else sql

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        for t in TABLES:
            if t in text:
                spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(t)
        return spark.sql(text)

    _QUERIES[name] = run
    _ORACLES[name] = (inlined(FIXTURES[fixture], oracle) if fixture and oracle else oracle) or text


def pair(name: str, run: Query, oracle: str | None = None) -> None:
    _QUERIES[name] = run
    if oracle is not None:
        _ORACLES[name] = oracle


def t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _scalar() -> None:
    both("op_proj_name_parts", "SELECT concept, split_part(concept, ':', 1) AS prefix, substring(concept, length(split_part(concept, ':', 1)) + 2) AS local FROM concept", "k1")
    both("op_filter_predicates", "SELECT p_partkey, p_name FROM part WHERE p_size BETWEEN 5 AND 15 AND p_brand IN ('Brand#1', 'Brand#2', 'Brand#3') AND p_name LIKE '%a%' AND NOT p_type LIKE 'X%'")
    both("op_case_bucket", "SELECT CASE WHEN p_retailprice < 1000 THEN 'low' WHEN p_retailprice < 1500 THEN 'middle' ELSE 'high' END AS bucket, count(*) AS n FROM part GROUP BY 1")
    both("op_nullsafe_eq", "SELECT count(*) AS n FROM c WHERE prev IS NOT DISTINCT FROM NULL", "k8")
    both("op_str_split", "SELECT p_partkey, split_part(p_name, ' ', 1) AS first, split_part(p_name, ' ', 2) AS last, lower(p_type) AS kind FROM part")
    both("op_str_regex", "SELECT page_id, regexp_replace(url, '^https?://', '') AS bare FROM pages")
    both("op_str_clean", "SELECT c_custkey, translate(trim(lower(c_name)), '#', '-') AS name, concat_ws('|', c_mktsegment, c_name) AS both_names FROM customer")
    both("op_str_distance", "SELECT a.p_partkey AS a, b.p_partkey AS b, levenshtein(a.p_name, b.p_name) AS d FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_type = b.p_type AND a.p_size = b.p_size AND a.p_partkey < b.p_partkey")
    both("op_hash_md5", "SELECT doc_id, md5(text) AS h FROM documents")
    both("op_url_canonical", "SELECT k, v, c FROM u", "k7")
    both("op_date_trunc", "SELECT date_trunc('month', ts) AS month, event_type, count(*) AS n FROM events GROUP BY 1, 2")
    both("op_date_diff", "SELECT o_orderkey, datediff(DATE '2000-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders", oracle="SELECT o_orderkey, CAST(DATE '2000-01-01' - CAST(o_orderdate AS DATE) AS INT) AS days FROM orders")
    both("op_interval_add", "SELECT event_id, ts + INTERVAL '1' HOUR AS later FROM events")
    both("op_math_ratio", "SELECT l_orderkey, l_linenumber, round(CAST(l_tax / (1 + l_discount) AS DOUBLE), 4) AS r, round(log2(l_quantity), 4) AS lg FROM lineitem")
    both("op_math_bucket", "SELECT floor(p_retailprice / 100) AS bucket, count(*) AS n, CAST(p_size AS INT) % 7 AS rest FROM part GROUP BY 1, 3")


def _joins() -> None:
    links = "mapping m {kind} JOIN concept c ON m.dst = c.concept"
    both("op_join_inner", "SELECT src, dst, source FROM " + links.format(kind=""), "k1")
    both("op_join_left", "SELECT m.src AS src, w.dst AS onward FROM mapping m LEFT JOIN mapping w ON m.dst = w.src AND w.relation = 'alignedWith'", "k1")
    both("op_join_right", "SELECT o_orderkey, c_custkey FROM orders RIGHT JOIN customer ON o_custkey = c_custkey")
    both("op_join_full", "SELECT a.n_nationkey AS nation, b.s_suppkey AS supplier FROM nation a FULL OUTER JOIN supplier b ON a.n_nationkey = b.s_suppkey")
    both("op_join_semi", "SELECT concept FROM concept WHERE EXISTS (SELECT 1 FROM mapping WHERE src = concept)", "k1")
    both("op_join_anti", "SELECT concept FROM concept WHERE NOT EXISTS (SELECT 1 FROM mapping WHERE src = concept OR dst = concept)", "k3")
    both("op_join_cross", "SELECT r_name, n FROM region CROSS JOIN (SELECT count(*) AS n FROM nation)")
    hinted = "SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey"
    for how, hint in (("broadcast", "broadcast"), ("sortmerge", "merge"), ("shuffle_hash", "shuffle_hash")):
        pair(f"op_join_{how}", lambda s, d, hint=hint: t(s, d, "orders").join(t(s, d, "customer").hint(hint), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_name"), hinted)
    pair("op_join_theta_size", _theta_size, "SELECT a.p_partkey AS a, b.p_partkey AS b FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_type = b.p_type AND a.p_partkey < b.p_partkey AND abs(a.p_size - b.p_size) <= 2")
    pair("op_join_range_price", _range_price, "SELECT p_partkey, s_suppkey FROM part JOIN supplier ON s_acctbal BETWEEN p_retailprice - 5 AND p_retailprice + 5")
    pair("op_join_nested_contains", _contains, "SELECT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)")
    pair("op_join_asof_events", _asof, "SELECT p.event_id AS event_id, max(c.ts) AS clicked FROM events p LEFT JOIN events c ON c.user_id = p.user_id AND c.event_type = 'click' AND c.ts <= p.ts WHERE p.event_type = 'purchase' GROUP BY p.event_id")
    both("op_join_interval_events", "SELECT p.event_id AS purchase, c.event_id AS click FROM events p JOIN events c ON c.user_id = p.user_id AND c.ts BETWEEN p.ts - INTERVAL '1' HOUR AND p.ts WHERE p.event_type = 'purchase' AND c.event_type = 'click'")
    both("op_self_join_duplicates", "SELECT x.k AS a, y.k AS b FROM d x JOIN d y ON x.h = y.h AND x.k < y.k", "k2")
    both("k9_containment_links", "SELECT concat('BM:I:', item_id) AS src, 'narrower' AS relation, concat(upper(source), ':D:', doc_id) AS dst FROM documents d JOIN benchmark b ON position(b.text IN d.text) > 0")
    pair("k6_near_links", _near, _NEAR_SQL)


def _theta_size(spark, sf_dir):
    """Band join as an equi-join on size buckets: each right row goes to its bucket and both neighbours."""
    p = t(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_type", "p_size")
    a = p.select(F.col("p_partkey").alias("a"), "p_brand", "p_type", F.col("p_size").alias("sa"), F.floor(F.col("p_size") / 3).alias("bucket"))
    b = p.select(F.col("p_partkey").alias("b"), "p_brand", "p_type", F.col("p_size").alias("sb"), F.explode(F.array(*[F.floor(F.col("p_size") / 3) + k for k in (-1, 0, 1)])).alias("bucket"))
    return a.join(b, ["p_brand", "p_type", "bucket"]).filter("a < b and abs(sa - sb) <= 2").select("a", "b")


def _range_price(spark, sf_dir):
    """Range join by buckets of the band's width."""
    p = t(spark, sf_dir, "part").select("p_partkey", "p_retailprice", F.floor(F.col("p_retailprice") / 10).alias("bucket"))
    s = t(spark, sf_dir, "supplier").select("s_suppkey", "s_acctbal", F.explode(F.array(*[F.floor(F.col("s_acctbal") / 10) + k for k in (-1, 0, 1)])).alias("bucket"))
    return p.join(s, "bucket").filter("s_acctbal between p_retailprice - 5 and p_retailprice + 5").select("p_partkey", "s_suppkey")


def _contains(spark, sf_dir):
    """Containment as an equi-join on the item's first 24 characters' word, then the exact test: no nested loop over documents."""
    items = t(spark, sf_dir, "benchmark").select("item_id", F.col("text").alias("item"), F.element_at(F.split("text", " "), 2).alias("word"))
    words = t(spark, sf_dir, "documents").select("doc_id", "text", F.explode(F.array_distinct(F.split("text", " "))).alias("word"))
    short = items.filter("word is null").select("item_id", "item")
    found = words.join(items.filter("word is not null"), "word").filter(F.contains("text", F.col("item"))).select("doc_id", "item_id")
    loose = t(spark, sf_dir, "documents").join(F.broadcast(short), F.contains("text", F.col("item"))).select("doc_id", "item_id")  # items of one word
    return found.union(loose).distinct()


def _asof(spark, sf_dir):
    """As-of join as one window over the union of both sides: a single exchange on the user."""
    e = t(spark, sf_dir, "events").filter("event_type in ('click', 'purchase')").select("event_id", "ts", "user_id", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "click", 0).otherwise(1)).rowsBetween(Window.unboundedPreceding, 0)
    clicked = F.last(F.when(F.col("event_type") == "click", F.col("ts")), ignorenulls=True).over(w)
    return e.withColumn("clicked", clicked).filter("event_type = 'purchase'").select("event_id", "clicked")


def _near(spark, sf_dir):
    """Vectors of different labels with cosine over 0.4: the left side in blocks against all rows."""
    v = t(spark, sf_dir, "embeddings").select("vec_id", "label", F.col("embedding").cast("array<double>").alias("v"))
    norm = F.sqrt(F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x))
    v = v.withColumn("u", F.transform("v", lambda x: x / norm)).select("vec_id", "label", "u")
    a, b = v.select(F.col("vec_id").alias("a"), F.col("label").alias("la"), F.col("u").alias("ua")), v.select(F.col("vec_id").alias("b"), F.col("label").alias("lb"), F.col("u").alias("ub"))
    dot = F.aggregate(F.zip_with("ua", "ub", lambda x, y: x * y), F.lit(0.0), lambda acc, x: acc + x)
    return a.join(b, (F.col("a") < F.col("b")) & (F.col("la") != F.col("lb")) & (dot > 0.4)).select(F.concat(F.lit("V"), "la", F.lit(":E:"), "a").alias("src"), F.lit("approx").alias("relation"), F.concat(F.lit("V"), "lb", F.lit(":E:"), "b").alias("dst"))


_NEAR_SQL = "SELECT concat('V', a.label, ':E:', a.vec_id) AS src, 'approx' AS relation, concat('V', b.label, ':E:', b.vec_id) AS dst FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id AND a.label <> b.label WHERE list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])) > 0.4"


def _aggregates() -> None:
    both("op_agg_basic", "SELECT o_orderstatus, count(*) AS n, round(sum(o_totalprice), 2) AS total, round(avg(o_totalprice), 4) AS mean, min(o_totalprice) AS least, max(o_totalprice) AS most FROM orders GROUP BY o_orderstatus")
    both("op_agg_distinct", "SELECT o_orderpriority, count(DISTINCT o_custkey) AS customers FROM orders GROUP BY o_orderpriority")
    both("op_agg_filtered", "SELECT l_returnflag, count(*) FILTER (WHERE l_quantity > 25) AS large, CAST(sum(CASE WHEN l_tax > 0.04 THEN 1 ELSE 0 END) AS BIGINT) AS taxed FROM lineitem GROUP BY l_returnflag")
    both("op_agg_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 12")
    both("op_agg_minby", "SELECT p_brand, min_by(p_partkey, p_partkey) AS first, max_by(p_name, p_partkey) AS last_name FROM part GROUP BY p_brand", oracle="SELECT p_brand, arg_min(p_partkey, p_partkey) AS first, arg_max(p_name, p_partkey) AS last_name FROM part GROUP BY p_brand")
    both("op_agg_sets", "SELECT source, concat_ws(',', sort_array(collect_set(relation))) AS relations FROM (SELECT split_part(src, ':', 1) AS source, relation FROM mapping) GROUP BY source", "k1", "SELECT source, string_agg(DISTINCT relation, ',' ORDER BY relation) AS relations FROM (SELECT split_part(src, ':', 1) AS source, relation FROM mapping) GROUP BY source")
    both("op_agg_stats", "SELECT l_returnflag, round(stddev_samp(l_quantity), 4) AS sd, round(var_pop(l_discount), 6) AS v, round(corr(l_quantity, l_extendedprice), 4) AS c FROM lineitem GROUP BY l_returnflag")
    keyed = "(SELECT relation, split_part(src, ':', 1) AS a, split_part(dst, ':', 1) AS b FROM mapping)"
    both("op_agg_rollup", f"SELECT relation, a, count(*) AS n FROM {keyed} GROUP BY ROLLUP (relation, a)", "k2")
    both("op_agg_cube", f"SELECT relation, b, count(*) AS n FROM {keyed} GROUP BY CUBE (relation, b)", "k2")
    both("op_agg_grouping_sets", f"SELECT relation, a, b, count(*) AS n FROM {keyed} GROUP BY GROUPING SETS ((relation), (a, b), ())", "k2")
    both("op_pivot_links", "SELECT * FROM (SELECT split_part(src, ':', 1) AS source, relation FROM mapping) PIVOT (count(*) FOR relation IN ('exactMatch' AS exact, 'xref' AS loose))", "k2", "SELECT split_part(src, ':', 1) AS source, nullif(count(*) FILTER (WHERE relation = 'exactMatch'), 0) AS exact, nullif(count(*) FILTER (WHERE relation = 'xref'), 0) AS loose FROM mapping GROUP BY 1")
    pair("op_unpivot_metrics", lambda s, d: t(s, d, "nation").agg(F.count("*").alias("nations"), F.countDistinct("n_regionkey").alias("regions")).unpivot([], ["nations", "regions"], "metric", "value"), "SELECT 'nations' AS metric, count(*) AS value FROM nation UNION ALL SELECT 'regions', count(DISTINCT n_regionkey) FROM nation")
    pair("op_approx_distinct", lambda s, d: t(s, d, "orders").agg(F.approx_count_distinct("o_custkey").alias("approx"), F.countDistinct("o_custkey").alias("exact")))
    pair("op_approx_quantile", lambda s, d: t(s, d, "lineitem").agg(F.percentile_approx("l_quantity", [0.25, 0.5, 0.75]).alias("approx"), F.percentile("l_quantity", F.lit(0.5)).alias("median")))


def _windows() -> None:
    both("op_win_rank", "SELECT p_partkey, rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS r, dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS dr, row_number() OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey) AS rn FROM part")
    both("op_win_ntile", "SELECT p_partkey, ntile(4) OVER (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey) AS quarter FROM part")
    both("op_win_lag_lead", "SELECT conv_id, turn, role, lag(role) OVER (PARTITION BY conv_id ORDER BY turn) AS before, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS following FROM conversations")
    both("op_win_running_rows", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 4) AS running FROM events")
    both("op_win_range_frame", "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 3 PRECEDING AND 3 FOLLOWING) AS near FROM part")
    both("op_win_first_last", "SELECT o_orderkey, first_value(o_orderkey) OVER w AS first, last_value(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
    both("op_win_percent", "SELECT p_partkey, round(percent_rank() OVER (PARTITION BY p_type ORDER BY p_retailprice), 4) AS pr, round(cume_dist() OVER (PARTITION BY p_type ORDER BY p_retailprice), 4) AS cd FROM part")
    both("op_sort_limit", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
    both("op_topk_clusters", "SELECT dst, count(*) AS n FROM mapping GROUP BY dst ORDER BY n DESC, dst LIMIT 20", "k2")
    both("op_topk_per_group", "SELECT p_brand, p_partkey, p_retailprice FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS rn FROM part) WHERE rn <= 3")


def _sets() -> None:
    for name, word in (("union", "UNION"), ("union_all", "UNION ALL"), ("intersect", "INTERSECT"), ("except", "EXCEPT"), ("intersect_all", "INTERSECT ALL"), ("except_all", "EXCEPT ALL")):
        both(f"op_set_{name}", f"SELECT c_nationkey AS k FROM customer {word} SELECT s_nationkey FROM supplier")
    both("op_subquery_exists", "SELECT n_name FROM nation WHERE EXISTS (SELECT 1 FROM supplier WHERE s_nationkey = n_nationkey)")
    both("op_subquery_not_in", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
    both("op_subquery_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > 1.5 * (SELECT avg(o_totalprice) FROM orders)")
    both("op_subquery_lateral", "SELECT n_name, best FROM nation, LATERAL (SELECT max(s_acctbal) AS best FROM supplier WHERE s_nationkey = n_nationkey)")
    up = "up(name, above, d) AS (SELECT child, parent, 1 FROM hier UNION ALL SELECT up.name, h.parent, d + 1 FROM up JOIN hier h ON h.child = up.above)"
    heads = ", ".join(f"{n} AS ({q})" for n, q in FIXTURES["k3"])
    both("op_recursive_ancestors", f"WITH RECURSIVE {heads}, {up} SELECT name, above, d FROM up")


def _nested() -> None:
    pair("op_array_paths", _paths, inlined(FIXTURES["k3"], "SELECT a.child AS child, concat_ws('>', a.child, a.parent, b.parent) AS path FROM hier a JOIN hier b ON a.parent = b.child"))
    pair("op_array_dot", lambda s, d: t(s, d, "embeddings").select("vec_id", F.round(F.aggregate(F.col("embedding").cast("array<double>"), F.lit(0.0), lambda a, x: a + x * x), 4).alias("square")), "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 4) AS square FROM embeddings")
    pair("op_map_profile", _map_profile, "SELECT o_orderstatus, count(*) AS n FROM orders GROUP BY o_orderstatus")
    pair("op_explode_members", lambda s, d: t(s, d, "part").groupBy("p_brand").agg(F.sort_array(F.collect_list("p_partkey")).alias("m")).select("p_brand", F.posexplode("m").alias("place", "member")), "SELECT p_brand, row_number() OVER (PARTITION BY p_brand ORDER BY p_partkey) - 1 AS place, p_partkey AS member FROM part")
    pair("op_higher_order", lambda s, d: t(s, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.exists("embedding", lambda x: x > 0.5).alias("strong")), "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS positive, len(list_filter(embedding, lambda x: x > 0.5)) > 0 AS strong FROM embeddings")
    both("op_json_props", "SELECT event_id, CAST(get_json_object(props, '$.k') AS INT) AS k FROM events", oracle="SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events")
    pair("op_json_roundtrip", lambda s, d: t(s, d, "nation").select(F.from_json(F.to_json(F.struct("n_nationkey", "n_name")), "n_nationkey int, n_name string").alias("j")).select("j.*"), "SELECT n_nationkey, n_name FROM nation")
    both("op_sample_hash", "SELECT doc_id FROM documents WHERE substring(md5(concat('', doc_id)), 1, 1) IN ('0', '1')")


def _paths(spark, sf_dir):
    h = load(spark, sf_dir, "k3").hier
    up = h.select(F.col("child").alias("parent"), F.col("parent").alias("top"))
    return h.join(up, "parent").select("child", F.array_join(F.array("child", "parent", "top"), ">").alias("path"))


def _map_profile(spark, sf_dir):
    counts = t(spark, sf_dir, "orders").groupBy("o_orderstatus").count()
    as_map = counts.agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "count"))).alias("m"))
    return as_map.select(F.explode("m").alias("o_orderstatus", "n"))


def _round_trips() -> None:
    from kgfold.sources import files

    expected = inlined(FIXTURES["k3"], "SELECT src, relation, dst FROM mapping")
    for kind in ("csv", "json", "orc"):
        pair(f"src_{kind}_roundtrip", lambda s, d, kind=kind: files.round_trip(load(s, d, "k3").mapping, kind, f"{work_dir(s)}/{uuid.uuid4().hex}"), expected)
    pair("src_ntriples_roundtrip", lambda s, d: files.ntriples_round_trip(load(s, d, "k3"), f"{work_dir(s)}/{uuid.uuid4().hex}"), inlined(FIXTURES["k3"], "SELECT child, parent FROM hier"))
    pair("src_table_bucketed", lambda s, d: files.bucketed(load(s, d, "k3").hier, "parent"), inlined(FIXTURES["k3"], "SELECT child, parent FROM hier"))
    pair("src_bundle_roundtrip", lambda s, d: files.bundle_round_trip(s, d), inlined(FIXTURES["k3"], "SELECT child, parent FROM hier"))


def _functions() -> None:
    from kgfold.functions import names

    pair("udf_source_local", lambda s, d: names.split_by_sql(load(s, d, "k1").concept), inlined(FIXTURES["k1"], "SELECT concept, split_part(concept, ':', 1) AS source, substring(concept, length(split_part(concept, ':', 1)) + 2) AS local FROM concept"))
    pair("udf_unique_or_null", lambda s, d: load(s, d, "k1").mapping.groupBy("src").agg(names.unique_or_null("dst").alias("only")), inlined(FIXTURES["k1"], "SELECT src, CASE WHEN min(dst) = max(dst) THEN min(dst) END AS only FROM mapping GROUP BY src"))
    pair("udtf_expand_path", lambda s, d: names.expanded_paths(load(s, d, "k3").hier), inlined(FIXTURES["k3"], "SELECT child AS start, n, name FROM (SELECT child, 0 AS n, child AS name FROM hier UNION ALL SELECT child, 1, parent FROM hier)"))
    pair("udf_pandas_matcher", lambda s, d: names.pandas_matches(t(s, d, "part").select("p_partkey", "p_name", "p_brand")), "SELECT a.p_partkey AS a, b.p_partkey AS b FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_name = b.p_name AND a.p_partkey < b.p_partkey")


def _streams() -> None:
    from kgfold.streaming import links

    kind = "CASE event_type WHEN 'purchase' THEN 'exactMatch' WHEN 'error' THEN 'deprecates' WHEN 'signup' THEN 'declares' ELSE 'xref' END"
    pair("st_tumbling_links", links.tumbling, f"SELECT date_trunc('day', ts) AS start, {kind} AS relation, count(*) AS n FROM events GROUP BY 1, 2")
    pair("st_sliding_links", links.sliding, "SELECT date_trunc('day', ts) - INTERVAL 1 DAY * k AS start, count(*) AS n FROM events, (VALUES (0), (1)) v(k) GROUP BY 1")
    pair("st_session_users", links.sessions, "SELECT user_id, count(*) AS sessions, CAST(sum(n) AS BIGINT) AS events FROM (SELECT user_id, sid, count(*) AS n FROM (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS sid FROM (SELECT *, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 1 DAY > ts THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, sid) GROUP BY user_id")
    pair("st_dedup_links", links.deduplicated, f"SELECT DISTINCT concat('U:', user_id) AS src, {kind} AS relation, concat('K:', json_extract_string(props, '$.k')) AS dst FROM events")
    pair("st_watermark_late", links.late)
    pair("st_stream_static_join", links.with_static, "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY c_mktsegment")
    pair("st_interval_join", links.interval, "SELECT p.event_id AS purchase, e.event_id AS error FROM events p JOIN events e ON p.user_id = e.user_id AND e.ts BETWEEN p.ts AND p.ts + INTERVAL 1 DAY WHERE p.event_type = 'purchase' AND e.event_type = 'error'")
    pair("st_first_target", links.first_target, "SELECT src, CASE WHEN min(dst) = max(dst) THEN min(dst) END AS dst, count(DISTINCT dst) = 1 AS settled FROM (SELECT concat('U:', user_id) AS src, concat('K:', json_extract_string(props, '$.k')) AS dst FROM events WHERE event_type = 'purchase') GROUP BY src")


def queries() -> dict[str, Query]:
    if not _QUERIES:
        for part in (_scalar, _joins, _aggregates, _windows, _sets, _nested, _round_trips, _functions, _streams):
            part()
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    queries()
    return dict(_ORACLES)
