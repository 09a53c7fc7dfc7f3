"""Registered queries against DuckDB. TEST_QUERIES=all runs every one; else those of each kind."""

import glob
import os
import sys

import duckdb
import pytest

import __spark_entry__ as entry
from predtopics import queries as own

SOME = """ontology_stats schema_edges_refined incidence share_patterns connection_patterns_l2 top_predicates density_printed share_scores share_hub_cut chain_scores chain_directed chain_best_path similarity_matrix
dissimilarity_row_euclid neighbours lloyd_fixed silhouette_fixed sibling_width topic_ranking top_table duplicate_concepts weave_fixed share_hosts q1_strict q2_literal q3 q4_strict endpoint_query optional_left
topic_tree tree_sweep tree_ranking tree_readings flat_kmeans q4_pruned_equals_full scale_sweep agg_hll
src_facts_text join_asof join_interval join_range agg_cube win_range_frame fn_array udf_sql cogroup_pandas contract_same stream_session stream_interval_join stream_stateful_degree""".split()
NAMES = list(own.QUERIES) if os.environ.get("TEST_QUERIES") == "all" else SOME


@pytest.fixture(scope="module")
def duck(sf_dir):
    con = duckdb.connect()
    for f in glob.glob(f"{sf_dir}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    return con


def plain(v):
    return round(v, 5) + 0.0 if isinstance(v, float) else v


@pytest.mark.parametrize("name", NAMES)
def test_query(spark, sf_dir, duck, name):
    df = own.QUERIES[name](spark, sf_dir)
    cols = sorted(df.columns)
    got = sorted((tuple(plain(r[c]) for c in cols) for r in df.collect()), key=str)
    if name in own.ORACLES:
        rel = duck.sql(own.ORACLES[name])
        at = [rel.columns.index(c) for c in cols]
        assert sorted(rel.columns) == cols
        assert got == sorted((tuple(plain(r[i]) for i in at) for r in rel.fetchall()), key=str)


def test_llm_oracles(spark, sf_dir, duck):
    for name in entry.oracle_sql().keys() - own.ORACLES.keys():
        df = entry.queries()[name](spark, sf_dir)
        cols = sorted(df.columns)
        rel = duck.sql(entry.oracle_sql()[name])
        at = [rel.columns.index(c) for c in cols]
        assert sorted((tuple(r[c] for c in cols) for r in df.collect()), key=str) == sorted((tuple(r[i] for i in at) for r in rel.fetchall()), key=str)


def test_entry(spark):
    rows = entry.entry(spark).collect()
    assert rows and {r.overall for r in rows} == set(range(1, len(rows) + 1))


def test_every_oracle_has_a_query():
    assert entry.oracle_sql().keys() <= entry.queries().keys()


def test_rest_does_not_know_the_llm_subpackage():
    root = os.path.dirname(os.path.abspath(own.__file__))
    for f in glob.glob(f"{os.path.dirname(root)}/**/*.py", recursive=True):
        if "/llm/" not in f:
            assert ".llm" not in open(f).read(), f
    assert sys.modules


@pytest.mark.parametrize("kind", ["base", "refined", "rooted"])
def test_counting_columns_gives_the_schema_of_the_facts(spark, sf_dir, kind):
    from predtopics.operators import ontology

    facts = ontology.build_facts(spark, sf_dir)
    want = ontology.induce_schema(facts, kind == "refined", kind == "rooted")
    assert sorted(map(tuple, ontology.schema(spark, sf_dir, kind).collect())) == sorted(map(tuple, want.collect()))


def test_costs_are_counted(spark, sf_dir):
    from predtopics.plans import cost

    orders = spark.read.parquet(f"{sf_dir}/orders.parquet")
    told = dict(zip([c.split()[0] for c in cost.SCHEMA.split(", ")], cost.measured(spark, "x", lambda: orders.select("o_custkey").repartition(3).groupBy("o_custkey").count())))
    assert told["rows_read"] == orders.count() and told["rows_shuffled"] >= told["rows_read"] and told["bytes_shuffled"] > 0 and told["jobs"] >= 1 and told["tasks"] >= 3
    assert {r.name for r in own.QUERIES["method_costs"](spark, sf_dir).collect()} == {"schema_edges", "share_scores", "chain_scores", "similarity_matrix", "topic_tree", "tree_ranking"}
