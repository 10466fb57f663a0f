"""Helpers shared by the training-data operators."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.shared import shared_folder

#: Keys that may be sent to all tasks because they hold more than one in so many of all rows: there can't be more of them.
HOT_KEYS = 10_000

#: Fixed value: the class of characters that the word rule of all operators leaves out.
WORD = r"[^\x20\x09-\x0D]+"

#: Upper-case ASCII letters to lower case; all other bytes stay.
LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def cut(df: DataFrame) -> DataFrame:
    """Write `df` to the shared checkpoint folder and go on from the files, so a lost executor costs no recomputation."""
    context = df.sparkSession.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint(eager=True)


def join_by_key(rows: DataFrame, keyed: DataFrame, key: list[str], many: str, total: int, hot_keys: int = HOT_KEYS, how: str = "inner") -> DataFrame:
    """`rows` joined (`how`: inner or left) to `keyed`, which has one row for each key and in `many` how many of the `total` rows hold it (dropped).

    Keys that hold more than one in `hot_keys` of all rows are `hot_keys` at most, so they are sent to all tasks and their rows stay where they are; the
    others are small, and meet their rows by shuffling. `rows` is read twice and ought to be a kept table.
    """
    least = -(-max(1, total) // hot_keys)
    hot = F.broadcast(keyed.where(F.col(many) > least).drop(many))
    cold = rows.join(hot.select(*key), key, "left_anti").join(keyed.where(F.col(many) <= least).drop(many), key, how)
    return rows.join(hot, key).unionByName(cold)


def held_out(doc_id: Column) -> Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0


def sampled(df: DataFrame, key: Column, most: int, rows: int) -> DataFrame:
    """About `most` of the `rows` rows of `df`, chosen by the hash of `key`: alike on every run and for every partitioning."""
    if rows <= most:
        return df
    return df.where(F.pmod(F.xxhash64(F.lit("sample"), key), F.lit(1 << 40)) < int(most / rows * (1 << 40)))


def texts(column: pa.Array) -> list[bytes | None]:
    """The UTF-8 bytes of a text column, null where it is null."""
    return column.cast(pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()).to_pylist()


def pieces(batches: Iterable[pa.RecordBatch], most_bytes: int = 4_000_000, column: str = "text") -> Iterator[pa.RecordBatch]:
    """The batches, cut so that each piece has about `most_bytes` bytes of text; a single longer row stays whole."""
    for batch in batches:
        if not batch.num_rows:
            continue
        lengths = np.asarray(pc.fill_null(pc.binary_length(batch.column(column)), 0), dtype=np.int64)
        block = np.cumsum(lengths) // most_bytes
        cuts = [0, *(np.flatnonzero(np.diff(block)) + 1).tolist(), batch.num_rows]
        for a, b in zip(cuts, cuts[1:], strict=False):
            yield batch.slice(a, b - a)


class WordHashes(dict):
    """64-bit hashes of words, kept between documents. It empties itself before it can outgrow the worker's memory."""

    def __init__(self, most: int = 200_000):
        super().__init__()
        self.most = most

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.most:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value


class WordIds(dict):
    """Consecutive ids of words; `words` lists them by id. The owner clears it between blocks."""

    def __init__(self):
        super().__init__()
        self.words: list[bytes] = []

    def __missing__(self, word: bytes) -> int:
        value = self[word] = len(self.words)
        self.words.append(word)
        return value


def numbered(df: DataFrame, within: list[str], row: str, name: str, buckets: int = 256) -> DataFrame:
    """Add `name`: the gapless number from 0 of each row inside its group `within`, by hash and value of `row`, which may be a struct.

    Two levels, so that a group of any size is counted by many tasks: numbers inside (group, bucket), plus the rows of
    earlier buckets of the group, of which there are `buckets` at most.
    """
    df = df.withColumn("__bucket", F.pmod(F.xxhash64(F.lit("numbered"), F.col(row)), F.lit(buckets)).cast("int"))
    before = Window.partitionBy(*within).orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = df.groupBy(*within, "__bucket").agg(F.count("*").alias("__rows")).withColumn("__start", F.coalesce(F.sum("__rows").over(before), F.lit(0)))
    inside = F.row_number().over(Window.partitionBy(*within, "__bucket").orderBy(row)) - 1
    return df.withColumn("__inside", inside).join(starts.drop("__rows"), [*within, "__bucket"]).withColumn(name, (F.col("__start") + F.col("__inside")).cast("long")).drop("__bucket", "__inside", "__start")
