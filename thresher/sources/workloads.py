"""Workloads on the given tables: observations (x, y) with the keys that sampling hashes.

Regression labels are fixed-point longs; ``SCALE`` has their factors.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.encode import day_number, fixed_point, observations, second_number, to_pm1
from .tables import table

#: Columns that tell rows of lineitem apart at every scale, as whole numbers.
LINE_KEYS = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "x")
SCALE = {"qty": 100, "price_qty": 1, "ship_discount": 100, "order_total": 100, "event_value": 100, "part": 100, "doc_words": 1, "planted": 1}

#: The points (x, y) of the two worked examples.
FIGURE_REGRESSION = [(1, 6), (1, 7), (2, 8), (3, 8), (3, 6), (2, 7), (4, 7), (5, 2), (6, 2), (6, 1), (7, 3), (8, 2), (9, 3), (9, 1)]
FIGURE_CLASSIFICATION = [(1, 1), (1, -1), (2, 1), (3, 1), (3, 1), (2, -1), (4, 1), (5, -1), (6, -1), (7, -1), (8, -1), (9, -1), (9, 1)]


def _noise() -> Column:
    return F.col("l_orderkey") * 7919 + F.col("l_linenumber") * 104729


def _line(spark: SparkSession, sf_dir: str, x: Column, y: Column) -> DataFrame:
    return observations(table(spark, sf_dir, "lineitem"), x, y, "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")


def price_cents() -> Column:
    return fixed_point("l_extendedprice")


def qty(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quantity against price: 50 values of x."""
    return _line(spark, sf_dir, F.col("l_quantity"), price_cents())


def price_qty(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Price against quantity: nearly as many values of x as rows."""
    return _line(spark, sf_dir, price_cents(), F.col("l_quantity").cast("long"))


def planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A step at a price of 40,000 with noise that is a hash of the row."""
    y = F.when(F.col("l_extendedprice") <= 40000, 10).otherwise(30) + _noise() % 20
    return _line(spark, sf_dir, price_cents(), y.cast("long"))


def ship_discount(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _line(spark, sf_dir, day_number("l_shipdate"), fixed_point("l_discount"))


def order_total(spark: SparkSession, sf_dir: str) -> DataFrame:
    return observations(table(spark, sf_dir, "orders"), day_number("o_orderdate"), fixed_point("o_totalprice"), "o_orderkey")


def event_value(spark: SparkSession, sf_dir: str) -> DataFrame:
    return observations(table(spark, sf_dir, "events"), second_number("ts"), fixed_point("value"), "event_id")


def part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Key against retail price: every row its own x, with structure."""
    return observations(table(spark, sf_dir, "part"), F.col("p_partkey"), fixed_point("p_retailprice"), "p_partkey")


def doc_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return observations(table(spark, sf_dir, "documents"), F.col("n_chars"), F.size(F.split("text", " ")).cast("long"), "doc_id")


def price_class(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _line(spark, sf_dir, price_cents(), to_pm1(F.col("l_quantity") > 25))


def ship_class(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _line(spark, sf_dir, day_number("l_shipdate"), to_pm1(F.col("l_linestatus") == "O"))


def planted_class(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The side of a price of 40,000, a fifth of the labels turned over by a hash of the row."""
    return _line(spark, sf_dir, price_cents(), to_pm1((F.col("l_extendedprice") <= 40000) == (_noise() % 100 < 80)))


def doc_label(spark: SparkSession, sf_dir: str, label: str = "quality") -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "n_chars", "source", "lang")
    joined = docs.join(table(spark, sf_dir, "labels"), "doc_id")
    return joined.select(F.col("n_chars").alias("x"), to_pm1(F.col(label) == 1).alias("y"), "doc_id", "source", "lang")


def event_class(spark: SparkSession, sf_dir: str) -> DataFrame:
    return observations(table(spark, sf_dir, "events"), fixed_point("value"), to_pm1(F.col("event_type") == "purchase"), "event_id")


def conversation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Length of a turn against who speaks."""
    turns = table(spark, sf_dir, "conversations").where("role <> 'system'")
    return observations(turns, F.length("text") + 1, to_pm1(F.col("role") == "assistant"), "conv_id", "turn")


def figure_regression(spark: SparkSession) -> DataFrame:
    """The worked regression example: its best split is 4."""
    return spark.createDataFrame([(x, y, k) for k, (x, y) in enumerate(FIGURE_REGRESSION)], "x long, y long, id long")


def figure_classification(spark: SparkSession) -> DataFrame:
    """The worked classification example: its best split is 4."""
    return spark.createDataFrame([(x, y, k) for k, (x, y) in enumerate(FIGURE_CLASSIFICATION)], "x long, y int, id long")


def line_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five attributes of a line, its order and its part against its price: a star join.

    Dimensions join by their keys; Spark broadcasts a side only under its own size limit.
    """
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_quantity", "l_discount", "l_tax", "l_shipdate", "l_extendedprice")
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_orderdate")
    parts = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_size")
    joined = line.join(orders, "l_orderkey").join(parts, "l_partkey")
    return joined.select(
        F.col("l_quantity").cast("long").alias("qty"), fixed_point("l_discount").alias("discount"), fixed_point("l_tax").alias("tax"), day_number("o_orderdate").alias("order_day"), F.col("p_size").cast("long").alias("size"), price_cents().alias("y")
    )


def embedding_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(attr, x, y): 64 quantised dimensions against label 0."""
    e = table(spark, sf_dir, "embeddings").select(to_pm1(F.col("label") == 0).alias("y"), F.posexplode("embedding").alias("p", "v"))
    return e.select((F.col("p") + 1).cast("long").alias("attr"), F.floor((F.col("v").cast("double") + 2) * 1000).cast("long").alias("x"), "y")


def user_sets(spark: SparkSession, sf_dir: str, disjoint: bool) -> tuple[DataFrame, DataFrame]:
    """Users of clicks and of errors; even and odd ones only, which makes them disjoint."""
    events = table(spark, sf_dir, "events")
    a, b = events.where("event_type = 'click'"), events.where("event_type = 'error'")
    return (a.where("user_id % 2 = 0"), b.where("user_id % 2 = 1")) if disjoint else (a, b)
