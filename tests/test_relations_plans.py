"""Relational operators against plain versions, and plans that read and move no more than they must."""

from __future__ import annotations

import os
import random

import pytest

from thresher.operators import relations
from thresher.operators.histogram import histogram
from thresher.sources import workloads

SF = "/root/testdata/sf0.001"


def test_as_of_join(spark):
    rng = random.Random(1)
    rows = [(k, rng.randrange(1000)) for k in range(500)]
    points = [(p, f"v{p}") for p in sorted(rng.sample(range(1000), 20))]
    got = {r.k: r.v for r in relations.as_of(spark.createDataFrame(rows, "k long, t long").repartition(5), spark.createDataFrame(points, "t long, v string"), "t", "v").collect()}
    assert got == {k: next((v for p, v in reversed(points) if p <= t), None) for k, t in rows}


def test_sets(spark):
    a, b = spark.createDataFrame([(1,), (2,), (2,), (3,)], "x int"), spark.createDataFrame([(2,), (4,)], "x int")
    assert sorted(r.x for r in relations.without(a, b, "x").collect()) == [1, 3]
    assert [r.x for r in relations.shared(a, b, "x").collect()] == [2]
    assert relations.labelled(a, b, "x").count() == 2 and relations.unlabelled(a, b, "x").count() == 2


def test_interval_join(spark):
    events = spark.createDataFrame([(1, "2024-01-01 00:00:00"), (1, "2024-01-01 05:00:00")], "u int, s string").selectExpr("u", "cast(s as timestamp) t")
    labels = spark.createDataFrame([(1, "2024-01-01 00:30:00")], "u int, s string").selectExpr("u", "cast(s as timestamp) at")
    assert relations.interval_join(events, labels, "u", "t", "at", "1 hour").count() == 1


@pytest.mark.skipif(not os.path.isdir(SF), reason="needs the test tables")
def test_scan_is_pruned_and_sums_are_partial(spark):
    plan = histogram(workloads.qty(spark, SF))._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<" in plan and "l_comment" not in plan
    read = plan.split("ReadSchema: struct<")[1].split(">")[0]
    assert {c.split(":")[0] for c in read.split(",")} == {"l_quantity", "l_extendedprice"}
    assert "partial_sum" in plan and "BatchEvalPython" not in plan and "ArrowEval" not in plan
