"""Trees over several attributes, the SQL surface, planning, and streams."""

from __future__ import annotations

import random

import pytest
from pyspark.sql import functions as F

from thresher.operators import curves, tree
from thresher.operators.domain import resolve
from thresher.plans import choose, sqlapi
from thresher.streaming import splits

from .test_exact import frame, noisy


@pytest.fixture(scope="module")
def table(spark):
    rng = random.Random(4)
    rows = [(a := rng.randrange(1, 100), b := rng.randrange(1, 50), (40 if a <= 30 else 10 if b <= 20 else 25) + rng.randrange(3)) for _ in range(2000)]
    return spark.createDataFrame(rows, "a long, b long, y long").persist()


def test_tree_finds_the_planted_rules(table):
    root = tree.grow(table, ["a", "b"], "y", "mse", 2)
    assert (root.attr, root.split) == ("a", 30) and (root.children[1].attr, root.children[1].split) == ("b", 20)
    scored = tree.score(tree.predict(table, root), "y").first()
    assert scored.mse < 1 and tree.score(tree.predict(table, tree.grow(table, ["a", "b"], "y", "mse", 1)), "y").first().mse > 10


def test_best_attribute_equals_each_alone(table):
    alone = {f: curves.exact_split(table.select(F.col(f).alias("x"), "y")).first() for f in ("a", "b")}
    for r in tree.per_attribute(table, ["a", "b"], "y").collect():
        assert (r.j, r.loss) == (alone[r.attr].j, alone[r.attr].loss)
    assert tree.best_split(table, ["a", "b"], "y").first().attr == "a"


def test_stump_classifies(spark):
    df = frame(spark, [(x, 1 if v < 20 else -1) for x, v in noisy(5)], "int")
    assert tree.score(tree.predict(df, tree.stump(df, ["x"], "y")), "y").first().error < 0.1


def test_sql_surface(spark, table):
    sqlapi.register(spark)
    assert spark.sql("SELECT split_sse(2, 4, 10) AS e").first().e == 2.0
    hist = tree.long_form(table, ["a", "b"], "y").groupBy("attr", "x").agg(F.count("*").alias("n"), F.sum("y").alias("s"), F.sum(F.col("y") * F.col("y")).alias("q"))
    hist.createOrReplaceTempView("hist")
    got = {r.attr: r.j for r in spark.sql("SELECT * FROM best_split(TABLE(hist) PARTITION BY attr ORDER BY x)").collect()}
    assert got == {r.attr: r.j for r in tree.per_attribute(table, ["a", "b"], "y").collect()}


def test_choice(spark):
    obs = frame(spark, noisy(1))
    assert choose.choose(obs, resolve(obs), 0.1).method == "exact"


def test_streams(spark, tmp_path):
    rows = [(k // 100, 1 + k % 37, 1 if (k * 7) % 11 < 5 else -1, k) for k in range(300)]
    df = spark.createDataFrame(rows, "d int, x long, y int, id long").withColumn("ts", F.timestamp_seconds(F.col("d") * 86400 + 5))
    df.repartition(3).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    hist = splits.run_to_table(splits.windowed_histogram(stream, "ts", "1 day", "misclassification"), str(tmp_path / "windows"), str(tmp_path / "marks"))
    shown = splits.run_to_memory(splits.windowed_histogram(stream, "ts", "1 day", "misclassification"), "windowed")
    assert sorted(map(tuple, shown.collect())) == sorted(map(tuple, hist.collect()))
    got = {r.start.day: (r.j, r.loss, r.n) for r in splits.window_splits(hist, "misclassification").collect()}
    for day in range(3):
        want = curves.exact_split(df.where(F.col("d") == day), "misclassification").first()
        assert got[day + 1] == (want.j, want.loss, 100)
    sample, merged = splits.StreamingSample(spark, str(tmp_path / "sample"), ["id"], 60), splits.StreamingHistogram(spark, str(tmp_path / "hist"), "misclassification")
    for sink in (sample, merged):
        stream.writeStream.foreachBatch(sink).trigger(availableNow=True).start().awaitTermination()
    assert 0 < sample.rows.count() <= 60 and sample.p < 1 and sample.split().count() == 1
    assert merged.split().first() == curves.exact_split(df, "misclassification").first()
    with pytest.raises(ValueError):
        splits.check_one_pass(stream, "additive")


def test_replayed_batches_count_once_and_restarts_go_on(spark, tmp_path):
    path = str(tmp_path / "state")
    batches = [frame(spark, noisy(k), "int").select("x", F.when(F.col("y") > 20, 1).otherwise(-1).alias("y")) for k in range(3)]
    sink = splits.StreamingHistogram(spark, path, "misclassification")
    sink(batches[0], 0)
    sink(batches[1], 1)
    sink(batches[1], 1)
    after = splits.StreamingHistogram(spark, path, "misclassification")
    after(batches[2], 2)
    after(batches[2], 2)
    every = batches[0].unionByName(batches[1]).unionByName(batches[2])
    assert after.split().first() == curves.exact_split(every, "misclassification").first()
    assert after.merged.agg(F.sum("pos"), F.sum("neg")).first() == every.agg(F.count_if(F.col("y") > 0), F.count_if(F.col("y") <= 0)).first()


def test_min_gain_and_leaves_predict(spark, table):
    assert tree.grow(table, ["a", "b"], "y", "mse", 2, min_gain=1e9).children == []
    whole = tree.grow(table, ["a", "b"], "y", "mse", 2)
    gains = tree.grow(table, ["a", "b"], "y", "mse", 3, min_gain=1.0)
    assert len(tree.splits_of(gains)) < len(tree.splits_of(tree.grow(table, ["a", "b"], "y", "mse", 3)))
    assert (gains.attr, gains.split) == (whole.attr, whole.split)
    flat = spark.createDataFrame([(1, 4), (1, 6)], "x long, y long")
    root = tree.grow(flat, ["x"], "y")
    assert root.prediction == 5.0 and [r.prediction for r in tree.predict(flat, root).collect()] == [5.0, 5.0]
