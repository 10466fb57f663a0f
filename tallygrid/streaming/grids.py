"""Grids over streams: sums by cell are incremental, so a stream's grid is the batch's."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.density import LogSpline, fit_logconcave
from ..functions.hashing import GridSpec
from ..operators.errors import Law, error_hist, law
from ..operators.estimates import narrowest
from ..operators.grid import CounterGrid, cells_of, probe
from ..operators.variants import raise_cells


def stream_grid(stream: DataFrame, spec: GridSpec) -> DataFrame:
    """(rep, idx, v) of a stream of (item, c); its state has r x k rows at most."""
    spread = stream.select(F.explode(cells_of(F.col("item"), spec)).alias("x"), "c")
    return spread.groupBy("x.rep", "x.idx").agg(F.sum("c").alias("v"))


def window_grids(stream: DataFrame, spec: GridSpec, duration: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """One grid for each event-time window of `ts`; rows later than `late` behind the watermark are dropped."""
    spread = stream.withWatermark("ts", late).select("ts", F.explode(cells_of(F.col("item"), spec)).alias("x"), "c")
    return spread.groupBy(F.window("ts", duration, slide) if slide else F.window("ts", duration), "x.rep", "x.idx").agg(F.sum("c").alias("v"))


def drained(stream: DataFrame, folder: str, *keys: str) -> DataFrame:
    """Run an aggregating stream over all that is there now, and give its table.

    Each micro-batch writes the rows that changed (update mode) to files, by batch id, so a batch that runs twice counts once and nothing gathers on the driver; the last row of
    each key stands. `keys`: those columns, by default all but `v`.
    """
    path = f"{folder}/table_{uuid.uuid4().hex}"
    each_batch(stream, lambda batch, batch_id: batch.write.mode("overwrite").parquet(f"{path}/batch={batch_id}"), folder, f"{path}_log", "update")
    rows = stream.sparkSession.read.schema(T.StructType([*stream.schema.fields, T.StructField("batch", T.LongType())])).parquet(path)
    names = list(keys) or [c for c in stream.columns if c != "v"]
    return rows.groupBy(*names).agg(*[F.max_by(c, "batch").alias(c) for c in stream.columns if c not in names]).select(*stream.columns)


def sessions(stream: DataFrame, gap: str, late: str = "0 seconds") -> DataFrame:
    """(item, start, end, c) of each item's sessions, once closed: no tuple within `gap` of the one before."""
    found = stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "item").agg(F.sum("c").alias("c"))
    return found.select("item", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "c")


def decayed_grid(stream: DataFrame, spec: GridSpec, half_life_days: float, landmark: str, scale: int = 1_000_000) -> DataFrame:
    """(rep, idx, v) with weights that double every half-life after `landmark`, so that no cell has to be touched as time goes on.

    Weights are whole parts of 1 / scale; an answer at time t is divided by the weight of t.
    """
    weight = F.round(F.col("c") * F.lit(scale) * growth(F.col("ts"), half_life_days, landmark)).cast("long")
    return stream_grid(stream.select("item", weight.alias("c")), spec)


def growth(at: Column, half_life_days: float, landmark: str) -> Column:
    days = (F.unix_micros(at) - F.unix_micros(F.lit(landmark).cast("timestamp"))).cast("double") / F.lit(86_400e6)
    return F.pow(F.lit(2.0), days / F.lit(float(half_life_days)))


def interval_join(left: DataFrame, right: DataFrame, within: str, late: str = "1 hour") -> DataFrame:
    """Pairs of equal items of two streams, `right` after `left` and no later than `within`; old state goes with the watermarks."""
    a = left.select(F.col("item"), F.col("ts").alias("left_ts"), F.col("event_id").alias("left_id")).withWatermark("left_ts", late)
    b = right.select(F.col("item").alias("right_item"), F.col("ts").alias("right_ts"), F.col("event_id").alias("right_id")).withWatermark("right_ts", late)
    near = (F.col("right_ts") > F.col("left_ts")) & (F.col("right_ts") <= F.col("left_ts") + F.expr(f"INTERVAL {within}"))
    return a.join(b, (F.col("item") == F.col("right_item")) & near).select("item", "left_id", "right_id")


def drained_to_files(stream: DataFrame, folder: str) -> DataFrame:
    """Run an appending stream over all that is there now; rows go to files, so their number is not bound by the driver."""
    path = f"{folder}/rows_{uuid.uuid4().hex}"
    stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", f"{path}_log").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(path)


def batch_numbers(spark: SparkSession, path: str) -> list[int]:
    """Numbers of the finished folders batch=<n> below `path`, in order; read from the store itself, so a restarted driver finds what is there."""
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    fs = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    if not fs.exists(where):
        return []
    done = [f.getPath() for f in fs.listStatus(where) if f.getPath().getName().startswith("batch=")]
    return sorted(int(p.getName()[6:]) for p in done if fs.exists(jvm.org.apache.hadoop.fs.Path(p, "_SUCCESS")))


def file_sets(spark: SparkSession, path: str, before: int | float = float("inf")) -> list[str]:
    """The file sets below `path` that hold every batch once: the last one merged at a batch earlier than `before`, and the batches after it."""
    merged = [b for b in batch_numbers(spark, f"{path}/merged") if b < before]
    last = merged[-1] if merged else -1
    return [f"{path}/merged/batch={last}"] * bool(merged) + [f"{path}/batches/batch={b}" for b in batch_numbers(spark, f"{path}/batches") if b > last]


class BatchGrids:
    """Grids of micro-batches in a shared folder, one file set for each batch id: a batch that runs twice counts once.

    Late tuples are added like any others, as grids are linear. `keys`: further columns that tell grids apart, such as windows. Every `compact` batches, all so far are
    merged into one file set, named by the last batch that it holds, so a reader meets `compact` small sets and one merged one. All state is in the folder: a
    store made anew with the same `name` goes on where the last one stopped.
    """

    def __init__(self, folder: str, spec: GridSpec, *keys: str, name: str | None = None, compact: int = 16):
        self.path, self.spec, self.keys, self.compact = f"{folder}/grids_{name or uuid.uuid4().hex}", spec, keys, compact

    def absorb(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        spread = batch.select(*self.keys, F.explode(cells_of(F.col("item"), self.spec)).alias("x"), "c")
        spread.groupBy(*self.keys, "x.rep", "x.idx").agg(F.sum("c").alias("v")).write.mode("overwrite").parquet(f"{self.path}/batches/batch={batch_id}")
        if (batch_id + 1) % self.compact == 0:
            self.merged(spark, batch_id).write.mode("overwrite").parquet(f"{self.path}/merged/batch={batch_id}")

    def sets(self, spark: SparkSession, before: int | float = float("inf")) -> list[str]:
        return file_sets(spark, self.path, before)

    def merged(self, spark: SparkSession, before: int | float = float("inf")) -> DataFrame:
        found = self.sets(spark, before)
        if not found:
            return spark.createDataFrame([], "rep int, idx long, v long")
        return spark.read.parquet(*found).groupBy(*self.keys, "rep", "idx").agg(F.sum("v").alias("v"))

    def grid(self, spark: SparkSession) -> CounterGrid:
        return CounterGrid(self.merged(spark).select("rep", "idx", "v"), self.spec)


class ConservativeGrid:
    """Conservative updates batch by batch; a batch reads the grid that the one before wrote, so reruns agree. An empty stream gives an empty grid."""

    def __init__(self, folder: str, spec: GridSpec, name: str | None = None):
        self.path, self.spec = f"{folder}/conservative_{name or uuid.uuid4().hex}", spec

    def absorb(self, batch: DataFrame, batch_id: int) -> None:
        raise_cells(batch, self._before(batch.sparkSession, batch_id), self.spec).df.write.mode("overwrite").parquet(f"{self.path}/batch={batch_id}")

    def _before(self, spark: SparkSession, batch_id: int | float) -> CounterGrid | None:
        done = [b for b in batch_numbers(spark, self.path) if b < batch_id]
        return CounterGrid(spark.read.schema("rep int, idx long, v long").parquet(f"{self.path}/batch={done[-1]}"), self.spec) if done else None

    def grid(self, spark: SparkSession) -> CounterGrid:
        return self._before(spark, float("inf")) or CounterGrid(spark.createDataFrame([], "rep int, idx long, v long"), self.spec)


class TopItems:
    """The `most` items with the largest estimates on the grid of all batches, out of all items that came.

    Later batches raise the cells of items that come no more, so none can be left out before the end: the distinct items of each batch are files, merged every `compact` batches
    as grids are, and ranked when asked.
    """

    def __init__(self, folder: str, spec: GridSpec, most: int, name: str | None = None, compact: int = 16):
        name = name or uuid.uuid4().hex
        self.grids, self.most, self.compact, self.path = BatchGrids(folder, spec, name=name, compact=compact), most, compact, f"{folder}/top_{name}"

    def absorb(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        self.grids.absorb(batch, batch_id)
        batch.select("item").where("item IS NOT NULL").distinct().write.mode("overwrite").parquet(f"{self.path}/batches/batch={batch_id}")
        if (batch_id + 1) % self.compact == 0:
            self._seen(spark, batch_id).write.mode("overwrite").parquet(f"{self.path}/merged/batch={batch_id}")

    def _seen(self, spark: SparkSession, before: int | float = float("inf")) -> DataFrame | None:
        found = file_sets(spark, self.path, before)
        return spark.read.parquet(*found).select("item").distinct() if found else None

    def items(self, spark: SparkSession) -> DataFrame:
        seen = self._seen(spark)
        if seen is None:
            return spark.createDataFrame([], "item long, est long")
        return probe(seen, self.grids.grid(spark)).select("item", F.array_min("v").alias("est")).orderBy(F.desc("est"), "item").limit(self.most)


class AutoEstimator:
    """Every `period` batches, the simple estimator with the narrowest interval on the grid of all batches so far."""

    def __init__(self, folder: str, spec: GridSpec, statistics: dict, period: int = 1, level: float = 0.9, name: str | None = None):
        name = name or uuid.uuid4().hex
        self.grids, self.statistics, self.period, self.level, self.path = BatchGrids(folder, spec, name=name), statistics, period, level, f"{folder}/auto_{name}"

    def absorb(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        self.grids.absorb(batch, batch_id)
        if (batch_id + 1) % self.period == 0:
            name, widths = narrowest(self.grids.grid(spark), self.statistics, self.level)
            spark.createDataFrame([(batch_id, name, float(widths[name]))], self.CHOICE).coalesce(1).write.mode("overwrite").parquet(f"{self.path}/batch={batch_id}")

    CHOICE = "id int, statistic string, width double"

    def choices(self, spark: SparkSession) -> DataFrame:
        found = [f"{self.path}/batch={b}" for b in batch_numbers(spark, self.path)]
        return spark.read.schema(self.CHOICE).parquet(*found).withColumnRenamed("id", "batch") if found else spark.createDataFrame([], self.CHOICE.replace("id", "batch", 1))


def each_batch(stream: DataFrame, absorb: Callable[[DataFrame, int], None], folder: str, log: str | None = None, mode: str = "append") -> None:
    """Run `absorb` on the micro-batches of all that is there now. With a `log` of the caller's, a later run goes on after the batches that this one finished."""
    stream.writeStream.foreachBatch(absorb).outputMode(mode).option("checkpointLocation", log or f"{folder}/log_{uuid.uuid4().hex}").trigger(availableNow=True).start().awaitTermination()


class LazyDensity:
    """A fitted density that is fitted anew only when the law of all batches so far has moved by `delta` since the last fit.

    The law of the last fit and what each batch decided are files in the folder, so a driver that starts again goes on where the last one stopped; a batch that runs twice
    decides the same twice.
    """

    STEP = "id int, ks double, refitted boolean, knots int"

    def __init__(self, folder: str, spec: GridSpec, delta: float = 0.02, trim: float = 0.01, name: str | None = None):
        name = name or uuid.uuid4().hex
        self.grids, self.delta, self.trim, self.path = BatchGrids(folder, spec, name=name), delta, trim, f"{folder}/lazy_{name}"

    def _fitted(self, spark: SparkSession, before: int | float) -> Law | None:
        done = [b for b in batch_numbers(spark, f"{self.path}/laws") if b < before]
        return law(spark.read.parquet(f"{self.path}/laws/batch={done[-1]}")) if done else None

    def absorb(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        self.grids.absorb(batch, batch_id)
        now, last = law(error_hist(self.grids.grid(spark))), self._fitted(spark, batch_id)
        gap = 1.0 if last is None else now.ks(last)
        anew = last is None or gap >= self.delta
        if anew:
            spark.createDataFrame([(float(x), int(m)) for x, m in zip(now.x, now.m, strict=True)], "v double, m long").coalesce(1).write.mode("overwrite").parquet(f"{self.path}/laws/batch={batch_id}")
        knots = len(fit_logconcave(now.x, now.m, self.trim).t) if anew else 0
        spark.createDataFrame([(batch_id, gap, anew, knots)], self.STEP).coalesce(1).write.mode("overwrite").parquet(f"{self.path}/steps/batch={batch_id}")

    def density(self, spark: SparkSession) -> LogSpline:
        """The density as of the last fit."""
        last = self._fitted(spark, float("inf"))
        if last is None:
            raise ValueError("no batch has come")
        return fit_logconcave(last.x, last.m, self.trim).extended()

    def steps(self, spark: SparkSession) -> DataFrame:
        """(batch, ks, refitted, knots) of every batch."""
        found = [f"{self.path}/steps/batch={b}" for b in batch_numbers(spark, f"{self.path}/steps")]
        rows = spark.read.schema(self.STEP).parquet(*found) if found else spark.createDataFrame([], self.STEP)
        return rows.withColumnRenamed("id", "batch")
