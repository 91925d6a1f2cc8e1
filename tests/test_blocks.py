"""Links kept as blocks against the links themselves."""

import random

import pytest
from kgfold import kernels, ops
from kgfold.operators import blocks, canonical, identity
from kgfold.plans import fixtures
from kgfold.plans.fixtures import config, load
from pyspark.sql import functions as F


def rows(df):
    return sorted(map(tuple, df.collect()), key=str)


@pytest.fixture(scope="module")
def copies(spark, tmp_path_factory):
    """Parts and documents with many copies; doc_id 1 to 5 stand in two sources each."""
    path = tmp_path_factory.mktemp("copies")
    rng = random.Random(7)
    parts = [(k, f"{rng.choice('ab')} {rng.choice('xy')}", f"Brand#{rng.randint(1, 5)}", "T", rng.randint(1, 12), 1.0) for k in range(300)]
    spark.createDataFrame(parts, "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double").write.parquet(f"{path}/part.parquet")
    docs = [(k, f"{rng.choice('ab')}\n{rng.choice('xyz')}", rng.choice(["en", "de"]), f"src{rng.randint(6, 9)}", 3) for k in range(80)]
    docs += [(k, docs[k][1], "en", "src5", 3) for k in range(1, 6)] + [(90, None, "en", "src6", 0), (91, "solo", "en", "src6", 4), (91, "solo", "en", "src7", 4)]
    spark.createDataFrame(docs, "doc_id long, text string, lang string, source string, n_chars int").write.parquet(f"{path}/documents.parquet")
    return str(path)


@pytest.mark.parametrize("name", ["k1", "k2"])
@pytest.mark.parametrize("changes", [{}, {"active_classes": 1}, {"targets": "seed"}, {"ambiguous": "least"}])
def test_election_needs_no_links_spelled_out(spark, copies, name, changes):
    kg, cfg = load(spark, copies, name), config(name, **changes)
    to = blocks.forwards(kg, cfg)
    links, chosen = rows(blocks.links(kg, to, cfg).select("src", "relation", "dst")), rows(blocks.elect(kg, to, cfg))
    assert "mapping" not in kg.__dict__  # the links of all copies were never written
    plain = identity.rewrite_links(kg.mapping, to, cfg)
    assert rows(to) == rows(identity.forward_obsolete(kg.mapping, kg.concept, cfg)[0])
    assert links == rows(plain.select("src", "relation", "dst"))
    assert chosen == rows(identity.elect_targets(plain, kg.concept, cfg)) and chosen


def test_signature_and_components_of_blocks(spark, copies):
    kg, cfg = load(spark, copies, "k1"), config("k1")
    got = [rows(blocks.signature(kg, side)) for side in ("left", "right", "both")]
    label = rows(blocks.equivalence_components(kg, cfg))
    assert "mapping" not in kg.__dict__
    assert got == [rows(canonical.signature(kg.mapping, "src", "dst", side)) for side in ("left", "right", "both")]
    assert label == rows(kernels.components(identity.classified(kg.mapping, cfg).filter("class_rank = 0")))


@pytest.mark.parametrize("bound", [0, 25])
def test_components_with_leaves(spark, monkeypatch, bound):
    rng = random.Random(3)
    edges = [(rng.randint(0, 60), rng.randint(0, 60)) for _ in range(45)] + [(100 + k, 99) for k in range(9)] + [(7, 7), (200, 200), (301, 300), (99, 5)]
    want = rows(kernels.components(spark.createDataFrame(edges, "src long, dst long")))
    monkeypatch.setattr(kernels, "ONE_TASK_EDGES", bound)
    assert rows(kernels.components(spark.createDataFrame(edges, "src long, dst long"))) == want


def test_chain_example_reads_the_parts(spark, sf_dir):
    keys = [r[0] for r in spark.read.parquet(f"{sf_dir}/part.parquet").select("p_partkey").collect()]
    got = ops.queries()["w11_chain_example"](spark, sf_dir)
    assert rows(got.select("src", "dst")) == sorted((f"{s}:{k}", f"S3:{k}") for s in ("S1", "S2") for k in keys)


@pytest.mark.parametrize("digest", ["own", "shared"])
def test_components_of_names_by_number(spark, monkeypatch, digest):
    rng = random.Random(5)
    edges = [(f"n{rng.randint(0, 90)}", f"n{rng.randint(0, 90)}") for _ in range(80)] + [("z", "z"), ("n3", "n3")]
    want = rows(kernels.components(spark.createDataFrame(edges, "src string, dst string")))
    monkeypatch.setattr(kernels, "ONE_TASK_EDGES", 0)
    seen, starred = [], kernels._starred
    monkeypatch.setattr(kernels, "_starred", lambda pairs, n: seen.append(pairs.schema["u"].dataType.simpleString()) or starred(pairs, n))
    if digest == "shared":  # two names of one number: the rounds keep to the names
        monkeypatch.setattr(kernels, "_digest", lambda name: F.length(name).cast("long"))
    assert rows(kernels.components(spark.createDataFrame(edges, "src string, dst string"))) == want
    assert set(seen) == {"bigint" if digest == "own" else "string"}


def test_kept_parts_and_documents_follow_the_shared_rules(spark, copies):
    for name, view in (("k1", "q"), ("k2", "d")):
        fixture = fixtures.FIXTURES[name]
        load(spark, copies, name)
        place = fixtures._KEPT[name][1]
        shared = spark.sql(fixtures.inlined(fixture[: place + 1], f"SELECT * FROM {view}"))
        assert rows(spark.table(f"kept_{view}").select(*shared.columns)) == rows(shared)


def test_links_of_kept_parts_need_no_join_with_all_concepts(spark, copies):
    kg = load(spark, copies, "k1")
    asked, known = [], kg._known
    kg._known = lambda links, concept: asked.append(rows(links)) or known(links, concept)
    assert kg.pairs.filter("relation = 'replacedBy'").count()
    assert not [x for links in asked for x in links if x[1] == "replacedBy"]
    plain = rows(kg.mapping)
    assert set(rows(kg.pairs)) <= set(plain) and {x for x in plain if x[1] not in ("exactMatch", "xref")} <= set(rows(kg.pairs))


@pytest.fixture(scope="module")
def odd_parts(spark, tmp_path_factory):
    """Parts with one key under several names and sizes, repeated rows, names of one word, and nulls."""
    path, rng = tmp_path_factory.mktemp("odd"), random.Random(11)
    rows_ = [(k % 90, f"{rng.choice('ab')} {rng.choice('xy')}", f"Brand#{rng.randint(1, 4)}", rng.choice("TU"), rng.randint(1, 9), 1.0) for k in range(260)]
    rows_ += rows_[:5] + [(500, "solo", "Brand#01", "T", 3, 1.0), (501, "solo", "Brand#1#x", "T", 3, 1.0), (None, "a x", "Brand#2", "T", 3, 1.0), (None, "b x", "Brand#3", "T", None, 1.0)]
    rows_ += [(502, None, "Brand#2", "T", 3, 1.0), (503, "a x", None, "T", 3, 1.0), (504, "a x", "Brand#2", None, 3, 1.0), (505, "a x", "Brand#2", "U", None, 1.0), (506, "a x y", "Brand#3", "T", 4, 1.0)]
    spark.createDataFrame(rows_, "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double").write.parquet(f"{path}/part.parquet")
    return str(path)


def test_parts_are_forwarded_and_listed_by_number(spark, odd_parts):
    kg, cfg = load(spark, odd_parts, "k1"), config("k1")
    order = rows(identity.preference_order(kg.concept_once, cfg))
    to, sides = rows(blocks.forwards(kg, cfg)), [rows(blocks.signature(kg, s)) for s in ("left", "right", "both")]
    label = rows(blocks.equivalence_components(kg, cfg))
    assert not {"concept", "mapping"} & set(kg.__dict__)  # neither all names nor all links were written
    get = lambda t: spark.sql(fixtures.inlined(fixtures.K1, f"SELECT * FROM {t}"))
    mapping, concept = get("mapping"), get("concept")
    assert rows(kg.concept) == rows(concept)
    assert order == rows(identity.preference_order(concept, cfg))
    assert to == rows(identity.forward_obsolete(mapping, concept, cfg)[0]) and to
    assert sides == [rows(canonical.signature(mapping, "src", "dst", s)) for s in ("left", "right", "both")]
    assert label == rows(kernels.components(identity.classified(mapping, cfg).filter("class_rank = 0")))
    chosen = rows(blocks.elect(kg, blocks.forwards(kg, cfg), cfg))
    links = identity.rewrite_links(mapping, blocks.forwards(kg, cfg), cfg)
    assert chosen == rows(identity.elect_targets(links, concept, cfg)) and chosen


def test_merges_of_obsolete_names_alone_need_no_blocks(spark, copies, monkeypatch):
    from kgfold.plans import pipeline

    kg, made = load(spark, copies, "k1"), []
    monkeypatch.setattr(blocks, "written", lambda df, label="step", own=blocks.written: made.append(label) or own(df, label))
    found = pipeline.resolve_identity(kg, config("k1", align=False))
    assert "block" not in made and "mapping" not in kg.__dict__
    assert rows(found.canonical_merges) == rows(canonical.canonicalise(identity.forward_obsolete(kg.mapping, kg.concept, config("k1"))[0], kg.concept, config("k1")))
    both = pipeline.resolve_identity(kg, config("k1"))
    assert len(rows(both.merges)) == len(set(rows(both.merges))) and set(rows(both.merges)) > set(rows(both.forwards))


def test_documents_are_counted_without_texts_and_forwarded_by_number(spark, copies, monkeypatch):
    made, own = [], fixtures.written
    for module in (fixtures, blocks):
        monkeypatch.setattr(module, "written", lambda df, label="step": made.append(label) or own(df, label))
    kg, cfg = load(spark, copies, "k2"), config("k2")
    order = identity.preference_order(kg.concept_once, cfg)
    got, plan = rows(order), order._jdf.queryExecution().executedPlan().toString()
    assert not made and "doc_id:bigint" in plan and "text:string" not in plan
    to = rows(blocks.forwards(kg, cfg))
    assert "concept" not in made and "pairs" not in made
    get = lambda t: spark.sql(fixtures.inlined(fixtures.K2, f"SELECT * FROM {t}"))
    concept = get("concept")
    assert got == rows(identity.preference_order(concept, cfg)) and rows(kg.concept) == rows(concept)
    assert to == rows(identity.forward_obsolete(get("mapping"), concept, cfg)[0]) and to


def test_large_blocks_are_spelled_by_cells(spark, copies, monkeypatch):
    kg, cfg = load(spark, copies, "k2"), config("k2")
    to = blocks.forwards(kg, cfg)
    whole = rows(blocks.links(kg, to, cfg))
    monkeypatch.setattr(blocks, "CHUNK", 4)
    cut = blocks.links(kg, to, cfg)
    assert rows(cut) == whole and len(whole) == len(set(whole))
    assert "REPARTITION_BY_NUM" in cut._jdf.queryExecution().executedPlan().toString()  # small rows are not put into one task


def test_search_leaves_names_without_children_to_one_step(spark, monkeypatch):
    rng = random.Random(9)
    edges = sorted({("s", f"n{a:02}", f"n{b:02}") for a, b in ((rng.randint(1, 60), rng.randint(0, 25)) for _ in range(120)) if a > b} | {("s", "n61", "n03")})
    flags = {f"n{k:02}": (rng.random() < 0.2, rng.random() < 0.4) for k in range(70)}
    starts = [n for n in ("n00", "n01", "n60") if any(n in e for e in edges)]
    level, found = {n: (0, None, None, False) for n in starts}, {}
    while level:  # level by level, each name from its least parent
        found |= level
        up, level = level, {}
        for _, child, parent in sorted(edges, key=lambda e: e[2]):
            if parent in up and child not in found and child not in level:
                level[child] = (up[parent][0] + 1, parent, parent if any(flags[parent]) else up[parent][2], flags[parent][0] or up[parent][3])
    made, own = [], kernels.written
    monkeypatch.setattr(kernels, "written", lambda df, label="step": made.append(own(df, label)) or made[-1])
    marks = spark.createDataFrame([("s", n, *f) for n, f in flags.items()], "sid string, node string, is_anchor boolean, is_open boolean")
    got = kernels.bfs_down(spark.createDataFrame(edges, "sid string, child string, parent string"), spark.createDataFrame([("s", n) for n in starts], "sid string, node string"), marks)
    assert {r["node"]: (r["dist"], r["next_hop"], r["kept"], r["anchored"]) for r in got.collect()} == found and got.count() == len(found)
    leaves = {c for _, c, _ in edges} - {p for _, _, p in edges} - set(starts)
    held = [{r["node"] for r in t.select("node").collect()} for t in made if "dist" in t.columns]
    assert leaves & held[-1] and not any(leaves & names for names in held[:-1])
