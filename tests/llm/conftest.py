from __future__ import annotations

import pytest
from pyspark.sql import SparkSession


@pytest.fixture(scope="session")
def spark():
    made = (
        SparkSession.builder.master("local[4]")
        .config("spark.sql.shuffle.partitions", "4")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "4g")
        .getOrCreate()
    )
    made.sparkContext.setLogLevel("ERROR")
    return made


LONG = "the cat sat on the mat " * 30_000
HARD = [
    (1, None),
    (2, ""),
    (3, "  \n\t "),
    (4, "One two three four five six seven eight nine ten eleven twelve."),
    (5, "One two three four five six seven eight nine ten eleven twelve."),
    (5, "One two three four five six seven eight nine ten eleven twelve."),
    (6, LONG),
    (7, "Étude naïve, ÀÉ ß 日本語 😀 x"),
    (8, "Licensed under the Apache License, Version 2.0. MIT license MIT License cc-by CC BY"),
    (9, "a  b\n\n c\r\nd\x1ce <|endoftext|>"),
    (None, "a row without an id"),
    (10, "x"),
]


@pytest.fixture(scope="session")
def hard(spark):
    """Nulls, empty and long texts, ties, repeated rows, and columns with clashing names."""
    clash = [(i, t, "k", 1, b"z", 2.0, 7) for i, t in HARD]
    return spark.createDataFrame(clash, "doc_id long, text string, key string, row int, fp binary, score double, part int").repartition(3)


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], "doc_id long, text string")
