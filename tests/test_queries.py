"""Registered queries against their SQL on the smallest tables, and plan shapes."""

import duckdb
import pytest

from kgfold import ops
from kgfold.operators import identity
from kgfold.plans import relational
from kgfold.plans.fixtures import TABLES, config, load

SAMPLE = ["m3_forward_obsolete_k1", "m5_elect_targets_k1", "m6_canonical_k3", "m9_domain_hierarchy_k3", "w3_status_k3", "t_all_expectations_k3", "r3_link_matrix_k2", "v16_closure_k3"]


def rows_of(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    fix = lambda v: round(float(v), 5) if isinstance(v, float) or type(v).__name__ == "Decimal" else v
    return [columns[i] for i in order], sorted((tuple(fix(r[i]) for i in order) for r in rows), key=str)


@pytest.fixture(scope="session")
def duck(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    return con


@pytest.mark.parametrize("name", SAMPLE + [n for n in relational.queries() if n.startswith(("op_join", "op_agg", "op_win", "src_", "st_dedup"))])
def test_matches_oracle(spark, duck, sf_dir, name):
    df = ops.queries()[name](spark, sf_dir)
    got = rows_of(df.columns, df.collect())
    if name not in ops.oracle_sql():
        assert got[1]
        return
    want = duck.execute(ops.oracle_sql()[name])
    assert got == rows_of([d[0] for d in want.description], want.fetchall())


def test_every_name_has_its_ancestors(spark, sf_dir):
    edges = [(r["child"], r["parent"]) for r in load(spark, sf_dir, "k3").hier.select("child", "parent").collect()]
    want, level, d = [], edges, 1
    while level:
        want += [(name, above, d) for name, above in level]
        level, d = [(name, parent) for name, above in level for child, parent in edges if child == above], d + 1
    got = ops.queries()["op_recursive_ancestors"](spark, sf_dir)
    assert sorted(map(tuple, got.select("name", "above", "d").collect())) == sorted(want)
    assert {name.split(":")[0] for name, _, _ in want} == {"CUST", "GEO", "SUPP"}


def test_names_and_oracles_fit():
    assert set(ops.oracle_sql()) <= set(ops.queries())
    assert len(ops.queries()) > 150


def test_election_takes_no_python_and_no_cartesian_product(spark, sf_dir):
    kg, cfg = load(spark, sf_dir, "k1"), config("k1")
    forwards, _ = identity.forward_obsolete(kg.mapping, kg.concept, cfg)
    plan = identity.elect_targets(identity.rewrite_links(kg.mapping, forwards, cfg), kg.concept, cfg)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Cartesian" not in plan and "Pandas" not in plan
    assert "partial_min" in plan  # combined map-side; names are strings, so Spark sorts for these aggregates
