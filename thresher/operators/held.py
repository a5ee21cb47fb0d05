"""What searches keep between their passes, so that it can be let go.

Results are lazy and may still read a kept frame after the function that made it has returned; so frames
are only noted here, and ``release`` drops them once their results have been used. Registered queries
release what the query before them kept.
"""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import DataFrame

_kept: list[DataFrame] = []


def hold(df: DataFrame) -> DataFrame:
    """Persists the frame and notes it; blocks of a lost executor are computed again from their source."""
    kept = df.persist(StorageLevel.MEMORY_AND_DISK)
    _kept.append(kept)
    return kept


def release() -> int:
    """Unpersists everything noted so far; gives the number of frames."""
    n = len(_kept)
    while _kept:
        _kept.pop().unpersist()
    return n
