"""Reading and writing tables in files of any format and through streams, and a source of power-law counts."""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from .shared import place


def written(df: DataFrame, kind: str) -> str:
    """The folder in which `df` was written as `kind`: parquet, csv, json, orc or text."""
    path = place(df.sparkSession, kind)
    df.write.format(kind).save(path)
    return path


def scan(spark: SparkSession, path: str, kind: str, schema: str) -> DataFrame:
    """A table with a given schema: nothing is inferred, so a scan reads the files once, and a value that doesn't fit is an error in formats of text."""
    reader = spark.read.format(kind).schema(schema)
    return (reader.option("mode", "FAILFAST") if kind in ("csv", "json") else reader).load(path)


def through_files(stream: DataFrame, path: str) -> DataFrame:
    """What an appending stream gives now, by way of a file sink, whose log makes every batch count once."""
    stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", f"{path}_log").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(path)


def by_batch(stream: DataFrame, path: str) -> DataFrame:
    """The same with a function for each batch that writes a folder of its own."""
    stream.writeStream.foreachBatch(lambda batch, k: batch.write.mode("overwrite").parquet(f"{path}/batch={k}")).option("checkpointLocation", f"{path}_log").trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(path)


def in_memory(stream: DataFrame) -> DataFrame:
    """The result table of a stream with few groups, kept by the driver."""
    name = f"stream_{uuid.uuid4().hex}"
    stream.writeStream.format("memory").queryName(name).outputMode("complete").option("checkpointLocation", place(stream.sparkSession, "memory")).trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.table(name)


def rate_rows(spark: SparkSession, rows: int) -> DataFrame:
    """One batch of the rate source: (timestamp, value) with values from 0."""
    stream = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", rows).option("numPartitions", 4).option("startTimestamp", 0).load()
    return through_files(stream, place(spark, "rate"))


def power_law_cum(alpha: float, offset: float, most: int) -> np.ndarray:
    law = np.cumsum((offset + np.arange(1, most + 1)) ** -alpha)
    return law / law[-1]


def power_law_counts(ids: np.ndarray, cum: np.ndarray, seed: str | int) -> pa.RecordBatch:
    u = np.asarray([int(hashlib.md5(f"{seed}:{i}".encode()).hexdigest()[:13], 16) for i in ids], dtype=np.float64)
    return pa.RecordBatch.from_arrays([pa.array(ids), pa.array(np.searchsorted(cum, (u + 0.5) / float(1 << 52)) + 1)], names=["item", "c"])


def power_law_of(items: DataFrame, alpha: float, offset: float = 0.0, most: int = 1_000_000, seed: str | int = 3) -> DataFrame:
    """The counts that the source below gives to the whole numbers `item` of a table."""

    def draw(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cum = power_law_cum(alpha, offset, most)
        for batch in batches:
            yield power_law_counts(batch.column("item").to_numpy(), cum, seed)

    return items.select("item").mapInArrow(draw, "item long, c long")


class Slice(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class PowerLawReader(DataSourceReader):
    def __init__(self, options: dict):
        self.items, self.alpha, self.offset = int(options.get("items", 1000)), float(options.get("alpha", 2.0)), float(options.get("offset", 0.0))
        self.most, self.seed, self.slice = int(options.get("most", 1_000_000)), options.get("seed", "3"), int(options.get("slice", 50_000))

    def partitions(self) -> list[Slice]:
        return [Slice(low, min(self.items, low + self.slice)) for low in range(0, self.items, self.slice)]

    def read(self, partition: Slice) -> Iterator[pa.RecordBatch]:
        yield power_law_counts(np.arange(partition.low, partition.high, dtype=np.int64), power_law_cum(self.alpha, self.offset, self.most), self.seed)


class PowerLaw(DataSource):
    """Counts c of items 0, 1, ... with P(c = x) in proportion to (offset + x)^-alpha for x from 1 to `most`, by the inverse of the law at a hashed uniform.

    Options: items, alpha, offset, most, seed, and slice, the items of one partition.
    """

    @classmethod
    def name(cls) -> str:
        return "tally_power_law"

    def schema(self) -> str:
        return "item long, c long"

    def reader(self, schema) -> PowerLawReader:
        return PowerLawReader(self.options)


def power_law_source(spark: SparkSession, **options) -> DataFrame:
    spark.dataSource.register(PowerLaw)
    return spark.read.format("tally_power_law").options(**{k: str(v) for k, v in options.items()}).load()
