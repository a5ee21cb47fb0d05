"""Worked examples, the definition, and cases at the edge for the exact searches."""

from __future__ import annotations

import random

import pytest
from pyspark.sql import functions as F

from thresher.functions import encode
from thresher.operators import baseline, candidates, curves, histogram, metrics
from thresher.operators.prefix import scan
from thresher.sources import workloads


def frame(spark, rows, y="long"):
    return spark.createDataFrame([(int(x), v, k) for k, (x, v) in enumerate(rows)], f"x long, y {y}, id long")


def plain_losses(rows, js):
    def error(side):
        mean = sum(side) / len(side) if side else 0
        return sum((v - mean) ** 2 for v in side)

    return {j: (error([v for x, v in rows if x <= j]), error([v for x, v in rows if x > j])) for j in js}


def noisy(seed, n=300, domain=60):
    rng = random.Random(seed)
    return [(x := rng.randrange(1, domain + 1), (10 if x <= domain // 3 else 25) + rng.randrange(12)) for _ in range(n)]


def test_worked_examples(spark):
    r = curves.exact_split(workloads.figure_regression(spark)).first()
    assert (r.j, r.loss, r.pred_left, r.pred_right) == (4, round(8 / 14, 6), 7.0, 2.0)
    assert baseline.no_split(workloads.figure_regression(spark), "y").first().loss == 6.821429
    obs = workloads.figure_classification(spark)
    assert (lambda r: (r.j, r.loss))(curves.exact_split(obs, "misclassification").first()) == (4, round(3 / 13, 6))
    assert (lambda r: (r.j, r.loss))(curves.exact_split(obs, "gini").first()) == (4, 0.347985)


@pytest.mark.parametrize("method", candidates.METHODS)
def test_moments_equal_the_definition(spark, method):
    rows = noisy(1)
    js = [0, 1, 7, 20, 21, 59, 60, 75]
    want = plain_losses(rows, js)
    got = {r.x: r for r in candidates.losses(frame(spark, rows), js, method=method).collect()}
    assert set(got) == set(js)
    for j, (left, right) in want.items():
        assert abs(got[j].err_left - left) < 1e-6 and abs(got[j].err_right - right) < 1e-6 and got[j].n_left == sum(x <= j for x, _ in rows)


@pytest.mark.parametrize("criterion", ["misclassification", "gini"])
def test_label_methods_agree(spark, criterion):
    rows = [(x, 1 if v % 3 else -1) for x, v in noisy(2)]
    obs, js = frame(spark, rows, "int"), [0, 5, 30, 60]
    by = [sorted((r.x, round(r.loss, 9)) for r in candidates.losses(obs, js, criterion, method=m).collect()) for m in ("bsearch", "arrow", "merge", "naive")]
    assert by[0] == by[1] == by[2] == by[3]


def test_curve_is_monotone_and_neighbours_are_close(spark):
    rows = noisy(3)
    obs = frame(spark, rows)
    c = sorted(curves.loss_curve(obs).collect(), key=lambda r: r.x)
    spread, m = max(v for _, v in rows) - min(v for _, v in rows), len(rows)
    for a, b in zip(c, c[1:]):  # noqa: B905
        assert a.err_left <= b.err_left + 1e-9 and a.err_right >= b.err_right - 1e-9
    for i, a in enumerate(c):
        for b in c[i + 1 :]:
            assert b.loss - a.loss <= 5 * (b.n_left - a.n_left) * spread**2 / (4 * m) + 1e-9


def test_offline_and_brute_force_equal_exact(spark):
    obs = frame(spark, noisy(4))
    exact = curves.exact_split(obs).first()
    assert baseline.offline(obs).first() == exact
    assert curves.best(baseline.brute_force(obs)).first() == exact
    assert curves.exact_split(obs.repartition(7)).first() == exact


def test_edges(spark):
    assert curves.exact_split(frame(spark, [])).count() == 0
    r = curves.exact_split(frame(spark, [(5, 3)])).first()
    assert (r.j, r.loss, r.pred_right, r.n_right) == (5, 0.0, None, 0)
    assert curves.exact_split(frame(spark, [(5, 3), (5, 7)])).first().loss == 4.0
    assert curves.exact_split(frame(spark, [(1, 3), (2, 3)])).first().j == 1
    raw = spark.createDataFrame([(1, 1.0), (None, 2.0), (3, float("nan")), (4, None)], "a long, b double")
    assert encode.observations(raw, F.col("a"), F.col("b")).count() == 1
    assert tuple(encode.dropped_rows(raw, F.col("a"), F.col("b")).first()) == (4, 3)


def test_large_labels_do_not_overflow(spark):
    rows = [(k, 10**12 * (1 if k < 5 else 2)) for k in range(10)]
    assert curves.exact_split(frame(spark, rows)).first().j == 4


def test_prefix_scan(spark):
    rng = random.Random(6)
    rows = [(g, k, rng.randrange(9)) for g in "ab" for k in rng.sample(range(1000), 200)]
    df = spark.createDataFrame(rows, "g string, k long, v long").repartition(3)
    got = {(r.g, r.k): r.v_upto for r in scan(df, "k", ["v"], ["g"]).collect()}
    assert got == {(g, k): sum(v for h, j, v in rows if h == g and j <= k) for g, k, _ in rows}


def test_ranks(spark):
    df = spark.createDataFrame([(v,) for v in (5, 3, 5, 9, 1)], "v int")
    assert sorted((r.v, r.x) for r in encode.dense_rank(df, "v").collect()) == [(1, 1), (3, 2), (5, 3), (5, 3), (9, 4)]


def test_measures(spark):
    obs = workloads.figure_regression(spark)
    found = metrics.compare(obs, spark.createDataFrame([(5,)], "j long"), "mse")
    assert found["excess"] > 0 and found["ratio"] > 1 and metrics.ratio(0, 0) == 1
    assert metrics.success_rate([0.1, 0.2, 0.9], 0.5) == 2 / 3


def test_sums_in_parts_are_exact(spark):
    rng = random.Random(8)
    rows = [(rng.randrange(1, 4), rng.choice((-1, 1)) * rng.randrange(2**rng.choice((5, 30, 42)))) for _ in range(3000)]
    rows += [(1, 2**42 - 1), (2, -(2**42) + 1), (3, 0), (3, -(2**21)), (3, 2**21)]
    obs = frame(spark, rows)
    for r in histogram.histogram(obs).collect():
        ys = [y for x, y in rows if x == r.x]
        assert (r.n, int(r.s), int(r.q)) == (len(ys), sum(ys), sum(y * y for y in ys))
    with pytest.raises(Exception, match="2\\*\\*42"):
        histogram.histogram(frame(spark, [(1, 2**42)])).collect()


def test_value_gaps(spark):
    rng = random.Random(5)
    xs = sorted(rng.sample(range(100_000), 503))
    got = sorted(tuple(r) for r in baseline.value_gaps(frame(spark, [(x, 1) for x in xs]).repartition(7)).collect())
    assert [r[2] for r in got] == [b - a for a, b in zip(xs, xs[1:], strict=False)] + [None]
    assert [r[3] for r in got] == [1] * 126 + [2] * 126 + [3] * 126 + [4] * 125
