"""Reservoirs over streams.

Keyed uniforms make re-delivered rows idempotent: a row's race time depends on its id alone.  The global reservoir lives
in a written table of m rows that each micro-batch merges with its own m best, so state never grows with the stream.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from wsample.functions.times import instant
from wsample.operators.race import KEY, top_m, with_race_key
from wsample.plans.shared import new_path


def state_dir(spark: SparkSession) -> str:
    """A new folder under the cluster's shared checkpoint folder."""
    return new_path(spark, "stream")


#: Layout of a written reservoir; a table of another one is refused.
VERSION = 1


class StreamingRace:
    """A draw-role reservoir of m over an unbounded stream, one written table a batch; ``foreach`` is the batch function.

    All state is in the folder: a new object on the same folder goes on after the last batch that was written to its end.
    """

    def __init__(self, spark: SparkSession, m: int, *, weight: Column | str, id_cols: Sequence[str], folder: str | None = None, **kw):
        self.spark, self.m, self.weight, self.id_cols, self.kw = spark, m, weight, list(id_cols), kw
        self.folder = folder or state_dir(spark)

    def path(self, batch: int) -> str:
        return f"{self.folder}/reservoir/batch={batch}"

    def batches(self) -> list[int]:
        """Batches whose tables are complete, in order."""
        jvm = self.spark._jvm
        pattern = jvm.org.apache.hadoop.fs.Path(f"{self.folder}/reservoir/batch=*/_SUCCESS")
        found = pattern.getFileSystem(self.spark._jsc.hadoopConfiguration()).globStatus(pattern) or []
        return sorted(int(f.getPath().getParent().getName().split("=")[1]) for f in found)

    def read(self, batch: int) -> DataFrame:
        rows = self.spark.read.parquet(self.path(batch))
        if "version" not in rows.columns or rows.where(F.col("version") != VERSION).limit(1).count():
            raise ValueError(f"the reservoir of batch {batch} has another layout than version {VERSION}")
        return rows.select(*self.id_cols, KEY)

    def bound(self, kept: DataFrame) -> float | None:
        """The worst kept time of a full reservoir: no later row enters above it."""
        n, worst = kept.agg(F.count("*"), F.max(KEY)).first()
        return worst if n >= self.m else None

    def foreach(self, rows: DataFrame, batch: int) -> None:
        """Merge a micro-batch; a batch that comes twice, or rows that come twice, give the same table."""
        keyed = with_race_key(rows, weight=self.weight, id_cols=self.id_cols, **self.kw).select(*self.id_cols, KEY)
        earlier = [b for b in self.batches() if b < batch]
        if earlier:
            kept = self.read(earlier[-1])
            keyed = prefilter(keyed, self.bound(kept)).unionByName(kept)
        best = top_m(keyed.dropDuplicates(self.id_cols), self.m, self.id_cols).select(*self.id_cols, KEY, F.lit(VERSION).alias("version"))
        best.write.mode("overwrite").parquet(self.path(batch))

    def sample(self) -> DataFrame:
        """The reservoir after the last batch, with positions."""
        return top_m(self.read(self.batches()[-1]), self.m, self.id_cols).select(*self.id_cols, "position")

    def history(self) -> DataFrame:
        """(batch, ids): the reservoir after every batch."""
        return self.spark.read.parquet(f"{self.folder}/reservoir").select("batch", *self.id_cols)


def drain(stream: DataFrame, state: StreamingRace) -> None:
    """Run a stream until its source has no more."""
    stream.writeStream.foreachBatch(state.foreach).option("checkpointLocation", f"{state.folder}/log").trigger(availableNow=True).start().awaitTermination()


def drain_race(spark: SparkSession, path: str, m: int, *, weight: str, id_cols: Sequence[str], keep: str | None = None, files_per_batch: int = 1, **kw) -> DataFrame:
    """Read files as a stream until none is left; the reservoir then equals the batch sample."""
    schema = spark.read.parquet(path).schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path if not path.endswith(".parquet") else path.rsplit("/", 1)[0] + "/" + path.rsplit("/", 1)[1] + "*")
    if keep:
        stream = stream.where(keep)
    state = StreamingRace(spark, m, weight=weight, id_cols=id_cols, **kw)
    drain(stream, state)
    return state.sample()


def window_winner(stream: DataFrame, *, weight: str, id_col: str, time: str, width: str, late: str = "1 hour", **kw) -> DataFrame:
    """(window_start, id): one weighted draw a window, by built-in aggregates; rows later than ``late`` behind the newest are dropped."""
    keyed = with_race_key(stream, weight=weight, id_cols=[id_col], **kw)
    keyed = keyed.withColumn("__at", instant(time))
    watermarked = keyed.withWatermark("__at", late) if stream.isStreaming else keyed
    best = watermarked.groupBy(F.window("__at", width).alias("w")).agg(F.min_by(id_col, F.struct(KEY, id_col)).alias(id_col))
    return best.select(F.unix_micros(F.col("w.start")).alias("window_start"), id_col)


def file_stream(spark: SparkSession, path: str, *, keep: str | None = None, files_per_batch: int = 1) -> DataFrame:
    stream = spark.readStream.schema(spark.read.parquet(path).schema).option("maxFilesPerTrigger", files_per_batch).parquet(path + "*")
    return stream.where(keep) if keep else stream


def drain_window_winner(spark: SparkSession, path: str, *, keep: str | None = None, **kw) -> DataFrame:
    """Windows of a drained file stream, from the table that a complete-mode query leaves after each batch."""
    folder = state_dir(spark)
    run = window_winner(file_stream(spark, path, keep=keep), **kw).writeStream.outputMode("complete")
    run.foreachBatch(lambda rows, _: rows.write.mode("overwrite").parquet(f"{folder}/winners")).option("checkpointLocation", f"{folder}/log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{folder}/winners")


def drain_window_reservoirs(spark: SparkSession, path: str, m: int, *, keep: str | None = None, **kw) -> DataFrame:
    """(window_start, id, position): the last reservoir of every window of a drained file stream, closed or still open."""
    from wsample.streaming.stateful import window_reservoirs

    folder = state_dir(spark)
    run = window_reservoirs(file_stream(spark, path, keep=keep), m, **kw).writeStream.outputMode("update")
    run.foreachBatch(lambda rows, batch: rows.write.mode("overwrite").parquet(f"{folder}/windows/batch={batch}")).option("checkpointLocation", f"{folder}/log").trigger(availableNow=True).start().awaitTermination()
    every = spark.read.parquet(f"{folder}/windows")
    last = every.groupBy("window_start").agg(F.max("batch").alias("batch"))
    return every.join(last, ["window_start", "batch"]).select("window_start", "id", "position").distinct()


def late_rows(run) -> int:
    """Rows that a query's state has dropped as later than the watermark, over the batches it remembers."""
    return sum(op["numRowsDroppedByWatermark"] for p in run.recentProgress for op in p["stateOperators"])


def prefilter(rows: DataFrame, bound: float | None) -> DataFrame:
    """Drop keyed rows that cannot enter a full reservoir whose worst time is ``bound``, before any shuffle."""
    return rows if bound is None else rows.where(F.col(KEY) <= F.lit(bound))
