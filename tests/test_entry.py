"""The registry: names, the guard around the optional parts, and agreement with SQL at the smallest scale."""

from __future__ import annotations

import os

import pytest

import __spark_entry__ as entry
from thresher import queries

SF = "/root/testdata/sf0.001"
SAME = ["reg_exact_planted", "reg_multi_losses", "reg_additive_naive_planted", "cls_exact_conv", "gini_exact_conv", "cat_exact_source", "sample_bottom_k", "disj_no", "tree_star_join", "mpc_evaluator", "figure_gini"]


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(queries.queries()) > 50


@pytest.mark.skipif(not os.path.isdir(SF), reason="needs the test tables")
@pytest.mark.parametrize("name", SAME)
def test_queries_equal_sql(spark, name):
    import duckdb

    con = duckdb.connect()
    for t in ("part", "orders", "lineitem", "events", "documents", "embeddings", "labels", "conversations"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    got = queries.queries()[name](spark, SF)
    columns = sorted(got.columns)
    want = con.sql(f"SELECT {', '.join(columns)} FROM ({queries.oracle_sql()[name]})").fetchall()
    value = lambda v: round(float(v), 6) if isinstance(v, (int, float)) and not isinstance(v, bool) else v
    assert sorted(str([value(v) for v in r]) for r in got.select(*columns).collect()) == sorted(str([value(v) for v in r]) for r in want)
