"""The SQL surface: errors of sides as expressions, and best splits as a table function."""

from __future__ import annotations

import math
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def sse_sql(n: str, s: str, q: str) -> str:
    """Squared error of a side as SQL text, which stays inside the JVM."""
    return f"CASE WHEN {n} > 0 THEN greatest(CAST({q} AS DOUBLE) - CAST({s} AS DOUBLE) * CAST({s} AS DOUBLE) / CAST({n} AS DOUBLE), 0D) ELSE 0D END"


def register(spark: SparkSession) -> None:
    """``split_sse(n, s, q)``, and ``best_split(TABLE(histogram) PARTITION BY attr ORDER BY x)``."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION split_sse(n DOUBLE, s DOUBLE, q DOUBLE) RETURNS DOUBLE RETURN {sse_sql('n', 's', 'q')}")

    @F.udtf(returnType="attr string, j bigint, loss double, n bigint")
    class BestSplit:
        """Rows of one attribute's histogram in order of x; memory holds its distinct values."""

        def __init__(self) -> None:
            self.rows: list[tuple] = []
            self.attr = None

        def eval(self, row) -> Iterator[tuple]:
            self.attr = str(row["attr"])
            self.rows.append((row["x"], row["n"], row["s"], row["q"]))
            return iter(())

        def terminate(self) -> Iterator[tuple]:
            if not self.rows:
                return
            total = [sum(r[k] for r in self.rows) for k in (1, 2, 3)]
            left, best = [0, 0, 0], None
            side = lambda n, s, q: max(0.0, float(q) - float(s) * float(s) / n) if n else 0.0
            for x, *own in sorted(self.rows):
                left = [a + b for a, b in zip(left, own, strict=True)]
                loss = (side(*left) + side(*(a - b for a, b in zip(total, left, strict=True)))) / total[0]
                if best is None or loss < best[0] and not math.isclose(loss, best[0], rel_tol=1e-12):
                    best = loss, x
            yield self.attr, best[1], best[0], total[0]

    spark.udtf.register("best_split", BestSplit)
