"""Input tables as (item, c) tuples, for batch and stream."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.grid import tuples
from ..operators.relational import once


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The files of a table as a stream, whether it is one file or a folder of them."""
    schema = table(spark, sf_dir, name).schema
    return spark.readStream.schema(schema).option("recursiveFileLookup", "true").option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)


def parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tuples(table(spark, sf_dir, "lineitem"), F.col("l_partkey"))


def part_quantities(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tuples(table(spark, sf_dir, "lineitem"), F.col("l_partkey"), F.col("l_quantity").cast("long"))


def users(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tuples(table(spark, sf_dir, "events"), F.col("user_id"))


def customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tuples(table(spark, sf_dir, "orders"), F.col("o_custkey"))


def flows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(item, element): suppliers of parts."""
    return table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("item"), F.col("l_suppkey").alias("element"))


def words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lower-case runs of letters in documents."""
    tokens = F.explode(F.filter(F.split(F.lower("text"), r"[^\p{L}]+"), lambda w: w != ""))
    return tuples(table(spark, sf_dir, "documents").select(tokens.alias("w")), F.col("w"))


def ngrams(spark: SparkSession, sf_dir: str, n: int, prefix: str = "") -> DataFrame:
    """Runs of n words inside a document, joined by blanks; `prefix`: only those that start with it, which their first word tells before any run is formed."""
    words = F.filter(F.split(F.lower("text"), r"[^\p{L}]+"), lambda x: x != "")

    def runs(w: Column) -> Column:
        starts = F.sequence(F.lit(1), F.size(w) - n + 1)
        if prefix:
            starts = F.filter(starts, lambda i: F.element_at(w, i).startswith(prefix))
        return F.when(F.size(w) >= n, F.transform(starts, lambda i: F.concat_ws(" ", F.slice(w, i, n))))

    return tuples(table(spark, sf_dir, "documents").select(F.explode(once(words, runs)).alias("g")), F.col("g"))


def power_law(spark: SparkSession, items: int, alpha: float = 2.0, offset: float = 0.0, most: int = 1_000_000, seed: int = 3) -> DataFrame:
    """Items with counts x from 1 to `most`, P(x) in proportion to (offset + x)^-alpha, by the inverse of the law at a hashed uniform; the same on every run."""
    u = (F.pmod(F.xxhash64(F.lit(seed), "id"), F.lit(1 << 40)).cast("double") + 0.5) / float(1 << 40)

    def blocks(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        law = np.cumsum((offset + np.arange(1, most + 1)) ** -float(alpha))
        law /= law[-1]
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("item"), pa.array(np.searchsorted(law, batch.column("u").to_numpy()) + 1)], names=["item", "c"])

    return spark.range(items).select(F.col("id").alias("item"), u.alias("u")).mapInArrow(blocks, "item long, c long")
