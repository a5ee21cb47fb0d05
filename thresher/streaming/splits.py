"""One-pass searches as Structured Streaming.

Histograms are streaming aggregates: state is a row for each distinct x and window, late rows
beyond the watermark are dropped. Bernoulli samples are stateless filters; samples of an
unknown number of rows keep a cap by halving their rate, which hash samples allow without
loss because they nest. Searches that scan again (two passes or more) need a table: they raise.

The ``foreachBatch`` sinks keep their state as one table for each batch in a folder that all executors
see. A batch that is replayed starts from the state before it and writes the same table again, so
nothing counts twice, and a new process goes on from the last table.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import histogram as H
from ..operators.curves import best, curve_of
from ..operators.sampling import MODULUS, lcg

ONE_PASS = ("exact", "sampled")


def check_one_pass(df: DataFrame, method: str) -> None:
    if df.isStreaming and method not in ONE_PASS:
        raise ValueError(f"{method} scans its input more than once; run it on a stored snapshot")


def windowed_histogram(stream: DataFrame, time: str, window: str, criterion: str = "mse", watermark: str = "1 hour", slide: str | None = None, session_gap: str | None = None) -> DataFrame:
    """(start, x, sums): tumbling windows, sliding ones with ``slide``, sessions with ``session_gap``."""
    at = F.session_window(time, session_gap) if session_gap else F.window(time, window, slide) if slide else F.window(time, window)
    summed = stream.withWatermark(time, watermark).groupBy(at.alias("w"), "x").agg(*H.part_sums(criterion, F.col("y")))
    return summed.select(F.col("w.start").alias("start"), "x", *H.joined(criterion))


def window_splits(hist: DataFrame, criterion: str = "mse", scale: int = 1, digits: int = 6) -> DataFrame:
    """(start, j, loss, n): the best split of each window of a stored histogram."""
    curve = curve_of(hist, criterion, scale, ["start"]).withColumn("loss", F.round("loss", digits))
    chosen = F.min_by(F.struct(F.col("x").alias("j"), "loss", (F.col("n_left") + F.col("n_right")).alias("n")), F.struct("loss", "x")).alias("b")
    return curve.groupBy("start").agg(chosen).select("start", "b.j", "b.loss", "b.n")


def run_to_memory(hist: DataFrame, name: str, mode: str = "complete", checkpoint: str | None = None) -> DataFrame:
    """Runs the stream over what there is into the driver's memory: for looking at small results."""
    writer = hist.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    query = (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()
    query.awaitTermination()
    # The memory sink's rows are the driver's already; a plain frame of them may be joined with itself.
    return hist.sparkSession.createDataFrame(hist.sparkSession.table(name).toArrow())


def run_to_table(hist: DataFrame, path: str, checkpoint: str) -> DataFrame:
    """Runs the stream over what there is and gives its last complete result, a Parquet table under ``path``.

    Each trigger writes a table of its own, named by its number: a replayed trigger overwrites its own.
    """
    store = States(hist.sparkSession, path)
    hist.writeStream.foreachBatch(lambda batch, number: store.write(batch, number)).outputMode("complete").option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return store.latest()


class States:
    """Tables by batch number in one folder; a table counts once its success mark is there."""

    def __init__(self, spark: SparkSession, path: str, schema=None):
        self.spark, self.path, self.schema = spark, path.rstrip("/"), schema
        jvm = spark._jvm
        self._root = jvm.org.apache.hadoop.fs.Path(self.path)
        self._fs = self._root.getFileSystem(spark._jsc.hadoopConfiguration())

    def numbers(self) -> list[int]:
        if not self._fs.exists(self._root):
            return []
        names = [s.getPath().getName() for s in self._fs.listStatus(self._root)]
        done = lambda n: self._fs.exists(self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{n}/_SUCCESS"))
        return sorted(int(n) for n in names if n.isdigit() and done(n))

    def write(self, df: DataFrame, number: int, keep: int = 3) -> None:
        self.schema = df.schema
        df.write.mode("overwrite").parquet(f"{self.path}/{number}")
        for old in [n for n in self.numbers() if n <= number - keep]:
            self._fs.delete(self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{old}"), True)

    def before(self, number: int) -> DataFrame | None:
        """The state that a batch starts from."""
        earlier = [n for n in self.numbers() if n < number]
        return self._read(earlier[-1]) if earlier else None

    def latest(self) -> DataFrame | None:
        found = self.numbers()
        return self._read(found[-1]) if found else None

    def _read(self, number: int) -> DataFrame:
        reader = self.spark.read.schema(self.schema) if self.schema else self.spark.read
        return reader.parquet(f"{self.path}/{number}")


class StreamingHistogram:
    """A ``foreachBatch`` sink that merges sums into a table of at most one row for each distinct x."""

    def __init__(self, spark: SparkSession, path: str, criterion: str = "mse", scale: int = 1):
        self.criterion, self.scale, self.states = criterion, scale, States(spark, path)

    def __call__(self, batch: DataFrame, number: int) -> None:
        names = H.part_names(self.criterion)
        new = batch.groupBy("x").agg(*H.part_sums(self.criterion, F.col("y")))
        if (have := self.states.before(number)) is not None:
            new = have.unionByName(new).groupBy("x").agg(*[F.sum(c).alias(c) for c in names])
        self.states.write(new, number)

    @property
    def merged(self) -> DataFrame:
        return self.states.latest().select("x", *H.joined(self.criterion))

    def split(self, digits: int = 6) -> DataFrame:
        return best(curve_of(self.merged, self.criterion, self.scale), digits)


class StreamingSample:
    """A ``foreachBatch`` sink that keeps a uniform sample of at most ``cap`` rows of an unknown number.

    Rows are kept with the halving level of their hash; the rate is the largest at which at most ``cap`` are left.
    """

    def __init__(self, spark: SparkSession, path: str, keys: Sequence[str], cap: int, seed: int = 0):
        self.keys, self.cap, self.seed, self.states = list(keys), cap, seed, States(spark, path)

    def __call__(self, batch: DataFrame, number: int) -> None:
        h = F.greatest(lcg(self.keys, self.seed), F.lit(1).cast("long"))
        level = F.floor(F.log2(F.lit(float(MODULUS)) / h)).cast("int")
        kept, done = batch.withColumn("_level", level), 0
        if (have := self.states.before(number)) is not None:
            done = have.agg(F.max("_halvings")).first()[0] or 0
            kept = have.drop("_halvings").unionByName(kept.where(F.col("_level") >= done))
        now = max(done, halvings(kept, self.cap))
        self.states.write(kept.where(F.col("_level") >= now).withColumn("_halvings", F.lit(now)), number)

    @property
    def rows(self) -> DataFrame:
        return self.states.latest().drop("_level", "_halvings")

    @property
    def p(self) -> float:
        """The rate at which the kept rows were taken."""
        return 0.5 ** int(self.states.latest().agg(F.max("_halvings")).first()[0] or 0)

    def split(self, criterion: str = "misclassification", digits: int = 6) -> DataFrame:
        from ..operators.curves import exact_split

        return exact_split(self.rows.select("x", "y"), criterion, 1, digits)


def halvings(rows: DataFrame, cap: int) -> int:
    """The least number of halvings that leaves at most ``cap`` rows; 63 levels at most are counted."""
    counts = {int(r["_level"]): r["count"] for r in rows.groupBy("_level").count().collect()}
    found = 0
    while found < 62 and sum(n for lv, n in counts.items() if lv >= found) > cap:
        found += 1
    return found
