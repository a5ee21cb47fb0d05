"""Helpers that the operators of this subpackage share.

Intermediate tables go to the folder that the cluster names in ``spark.checkpoint.dir``:
all executors see it, and a table that was written there survives the loss of any of them.
"""

from __future__ import annotations

import os
import uuid
from collections.abc import Iterable, Iterator
from pathlib import Path

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Used only where a session on one machine names no shared folder, as in local tests.
LOCAL_SHARED = "/tmp/checkpoints/thresher"

_SEPARATORS = [i for i in range(128) if not (48 <= i <= 57 or 65 <= i <= 90 or 97 <= i <= 122)]
#: Lower-cases A-Z and turns every ASCII byte that is neither digit nor letter into a blank.
WORD_TABLE = bytes(32 if i in _SEPARATORS else i + 32 if 65 <= i <= 90 else i for i in range(256))

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def blank_words(text: str | None) -> list[bytes]:
    """Words between ASCII white space, A-Z lower-cased (``bytes.split`` splits at 0x20 and 0x09-0x0D)."""
    return text.encode("utf-8", "surrogatepass").lower().split() if text else []


def plain_words(text: str | None) -> list[bytes]:
    """Maximal runs of ASCII digits, letters and non-ASCII characters, A-Z lower-cased."""
    return text.encode("utf-8", "surrogatepass").translate(WORD_TABLE).split() if text else []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    prepare(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def prepare(spark: SparkSession) -> None:
    """Lets Python workers import this package even if only the driver's sys.path has it."""
    root = str(Path(__file__).resolve().parents[2])
    env = spark.sparkContext.environment
    have = env.get("PYTHONPATH", "")
    if root not in have.split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (root, have) if x)


def shared_dir(spark: SparkSession) -> str:
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        found = LOCAL_SHARED
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


class SharedTable:
    """A Parquet table in the shared folder. ``drop`` removes it once nothing reads it any more.

    Results are lazy and read the tables that were made for them, so a table stays until ``drop_tables`` is called by
    whoever has stored a result.
    """

    made: list[SharedTable] = []

    def __init__(self, df: DataFrame, name: str, codec: str = "zstd", partition_by: Iterable[str] = ()):
        self.spark = df.sparkSession
        self.path = f"{shared_dir(self.spark)}/{name}-{uuid.uuid4().hex}"
        self.schema = df.schema
        df.write.option("compression", codec).partitionBy(*partition_by).parquet(self.path)
        SharedTable.made.append(self)

    def read(self) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(self.path)

    def drop(self) -> None:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)
        if self in SharedTable.made:
            SharedTable.made.remove(self)


def drop_tables(keep: Iterable[SharedTable] = ()) -> int:
    """Removes every table of this process but those to keep; gives their number."""
    kept = set(keep)
    gone = [t for t in SharedTable.made if t not in kept]
    for t in gone:
        t.drop()
    return len(gone)


def is_trained_on(doc_id: Column, divisor: int, held_out: int) -> Column:
    """Whether crc32 of the id as text leaves another remainder than ``held_out``."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % divisor != held_out


def rows_of(batches: Iterable[pa.RecordBatch], *names: str) -> Iterator[tuple]:
    """Python tuples of the named columns, some rows at a time: a batch may hold ten thousand texts."""
    for some in parts(batches):
        yield from zip(*(some.column(n).to_pylist() for n in names), strict=True)


def parts(batches: Iterable[pa.RecordBatch], size: int = 256) -> Iterator[pa.RecordBatch]:
    """The batches in slices of at most ``size`` rows."""
    for batch in batches:
        for low in range(0, batch.num_rows, size):
            yield batch.slice(low, size)


def batched(rows: Iterable[tuple], schema: pa.Schema, size: int = 2048, max_bytes: int = 8 << 20) -> Iterator[pa.RecordBatch]:
    """Record batches of at most ``size`` rows; they end early when blobs add up."""
    kept: list[tuple] = []
    weight = 0
    for row in rows:
        kept.append(row)
        weight += sum(len(x) for x in row if isinstance(x, bytes))
        if len(kept) >= size or weight >= max_bytes:
            yield _pack(kept, schema)
            kept, weight = [], 0
    if kept:
        yield _pack(kept, schema)


def _pack(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)
