"""Spark against DuckDB for the queries that have SQL, at the smallest scale."""

import duckdb
import pytest

import __spark_entry__ as entry_point
from slicelink.operators import relational
from slicelink.plans import queries as linking_queries

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SAMPLE = [
    "catalog_columns", "correlation_groups", "slice_order", "pack_slices", "pack_slices_group_boundary", "slice_coverage", "qa_split", "difficulty_levels", "examples_sliced_hist", "examples_per_table", "memory_fit", "infer_lexical_once", "infer_lexical_sliced", "link_scores", "vote_of_three", "docs_pack", "passage_link", "dense_link_topk", "conversation_history",
    "budget_gate", "budget_caps", "cap_search", "pack_split_columns", "prune_columns", "infer_lexical_fold", "token_report", "rendered_examples", "examples_neg_sample", "examples_sql_gold", "execution_accuracy", "plan_matches", "logical_match",
    "link_bootstrap", "render_samples", "unique_columns", "fk_inclusion_exact", "nation_groups", "passage_scores", "workload_sizes", "published_saving"]


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def rows(cursor_rows, names):
    order = sorted(range(len(names)), key=lambda i: names[i])
    flat = lambda v: round(float(v), 4) if isinstance(v, float) or hasattr(v, "as_tuple") else int(v) if isinstance(v, bool) else str(v) if not isinstance(v, (int, type(None))) else v
    return sorted((tuple(flat(r[i]) for i in order) for r in cursor_rows), key=repr)


@pytest.mark.parametrize("name", SAMPLE + sorted(relational.S))
def test_against_sql(spark, sf, duck, name):
    every, sql = linking_queries.queries() | relational.queries(), linking_queries.oracle_sql() | relational.oracle_sql()
    df = every[name](spark, sf)
    cur = duck.execute(sql[name])
    names = [c[0] for c in cur.description]
    assert sorted(names) == sorted(df.columns)
    assert rows([tuple(r) for r in df.collect()], df.columns) == rows(cur.fetchall(), names)


def test_entry_is_the_golden_slicing(spark):
    assert [r.slice_tokens for r in entry_point.entry(spark).orderBy("slice_id").collect()] == [84, 93, 98, 39]


def test_pushdown(spark, sf):
    plan = relational.scan_pushdown(spark, sf)._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(l_shipdate)" in plan and "ReadSchema: struct<l_orderkey:bigint,l_quantity:double,l_shipdate:timestamp_ntz>" in plan
