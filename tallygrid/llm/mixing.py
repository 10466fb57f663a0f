"""Mixing sources to target weights (native): repetition rates per source, whole copies plus one hash-seeded draw.

A source's rate is target / size; a document is taken floor(rate) times, and once more with probability equal to the rest
of the rate. The draw is a hash of seed and doc_id, so it is the same on every run, machine and partitioning.

Defined results: a null or empty text has size 0 and is taken like any other document of its source, adding no words; a null
source is a source of its own, ordered last; a source without words has target 0 and its documents are taken 0 times; rows
that repeat a doc_id share its draw; a null doc_id draws as the text "null"; an empty table gives an empty result. Only
doc_id, text and source are read, so further columns of any name are left alone (`mix` hands all columns on).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import WORD, cut, table

#: Fixed value: digits of the hash that make a draw in [0, 1).
DRAW_HEX, DRAW_RANGE = 13, float(1 << 52)
#: Sources up to which their table of rates may be broadcast; beyond, it is joined by shuffling.
BROADCAST_SOURCES = 50_000


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def draw(doc_id: Column, seed: str) -> Column:
    key = F.concat(F.lit(f"{seed}:"), F.coalesce(doc_id.cast("string"), F.lit("null")))
    return F.conv(F.substring(F.md5(key.cast("binary")), 1, DRAW_HEX), 16, 10).cast("double") / F.lit(DRAW_RANGE)


def source_targets(sized: DataFrame, weights: tuple[int, ...] = (1, 2, 3), cap: int = 3) -> DataFrame:
    """(source, source_size, target): shares of the total by repeating weights, none above `cap` times the source's size.

    Sources fill up in the order of size by weight. Those before a point stop at their cap and the others share the rest by
    weight; a source is capped just if the share that is left when its turn comes would overfill it. One pass of running
    sums over the sources finds them all, which is where repeated resharing ends.
    """
    by_source = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    order = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*[F.lit(w) for w in weights]), (F.pmod(order, F.lit(len(weights))) + 1).cast("int")).cast("long")
    by_source = by_source.withColumn("weight", weight).withColumn("full", F.col("source_size") * cap)
    turn = Window.orderBy((F.col("full").cast("double") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    before = turn.rowsBetween(Window.unboundedPreceding, -1)
    onward = turn.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    every = turn.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    left = F.sum("source_size").over(every) - F.coalesce(F.sum("full").over(before), F.lit(0))
    by_source = by_source.withColumn("left", left).withColumn("weights_left", F.sum("weight").over(onward))
    by_source = by_source.withColumn("capped", F.col("full") * F.col("weights_left") <= F.col("left") * F.col("weight"))
    level = F.min(F.when(~F.col("capped"), F.struct(F.col("full").cast("double") / F.col("weight"), "left", "weights_left"))).over(Window.partitionBy())
    share = F.col("level.left").cast("double") * F.col("weight").cast("double") / F.col("level.weights_left").cast("double")
    return by_source.withColumn("level", level).select("source", "source_size", F.when(F.col("capped"), F.col("full").cast("double")).otherwise(share).alias("target"))


def plan(docs: DataFrame, seed: str = "mix", weights: tuple[int, ...] = (1, 2, 3), cap: int = 3) -> DataFrame:
    """One row per document: doc_id, size, source_size, target, copies, taken."""
    sized = cut(docs.select("doc_id", "source", word_count(F.col("text")).alias("size")))
    return _copies(sized, _rates(sized, weights, cap), seed).select("doc_id", "size", "source_size", "target", "copies", (F.col("size") * F.col("copies")).alias("taken"))


def _rates(sized: DataFrame, weights: tuple[int, ...], cap: int) -> DataFrame:
    rates = cut(source_targets(sized, weights, cap).withColumnRenamed("source", "__source"))
    return F.broadcast(rates) if rates.count() <= BROADCAST_SOURCES else rates


def _copies(docs: DataFrame, rates: DataFrame, seed: str) -> DataFrame:
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size").cast("double")).otherwise(F.lit(0.0))
    joined = docs.join(rates, F.col("source").eqNullSafe(F.col("__source"))).withColumn("__rate", rate)
    whole = F.floor("__rate")
    return joined.withColumn("copies", whole + (draw(F.col("doc_id"), seed) < F.col("__rate") - whole).cast("long")).drop("__rate", "__source")


def mix(docs: DataFrame, seed: str = "mix", weights: tuple[int, ...] = (1, 2, 3), cap: int = 3) -> DataFrame:
    """The documents themselves, all columns, each as often as the plan says."""
    sized = docs.select("source", word_count(F.col("text")).alias("size"))
    taken = _copies(docs.select(F.col("source"), F.col("doc_id"), F.struct("*").alias("__row")), _rates(sized, weights, cap), seed)
    return taken.where("copies > 0").select(F.explode(F.array_repeat("__row", F.col("copies").cast("int"))).alias("__row")).select("__row.*")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return plan(table(spark, sf_dir, "documents", "doc_id", "text", "source")).drop("copies")


ORACLE_SQL = r"""
WITH sized AS (
  SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size FROM documents
), by_source AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size, 1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 AS weight FROM sized GROUP BY source
), running AS (
  SELECT *, 3 * source_size AS filled,
    CAST(sum(source_size) OVER () AS BIGINT) - CAST(coalesce(sum(3 * source_size) OVER (ORDER BY CAST(3 * source_size AS DOUBLE) / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS remaining,
    CAST(sum(weight) OVER (ORDER BY CAST(3 * source_size AS DOUBLE) / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS BIGINT) AS weights_left
  FROM by_source
), flagged AS (
  SELECT *, filled * weights_left <= remaining * weight AS capped FROM running
), level AS (
  SELECT remaining AS r, weights_left AS w FROM flagged WHERE NOT capped ORDER BY CAST(filled AS DOUBLE) / weight, remaining, weights_left LIMIT 1
), targets AS (
  SELECT source, source_size, CASE WHEN capped THEN CAST(filled AS DOUBLE) ELSE CAST(r AS DOUBLE) * CAST(weight AS DOUBLE) / CAST(w AS DOUBLE) END AS target FROM flagged LEFT JOIN level ON true
), rated AS (
  SELECT d.doc_id, d.size, t.source_size, t.target, CASE WHEN t.source_size > 0 THEN t.target / CAST(t.source_size AS DOUBLE) ELSE 0.0 END AS rate,
    CAST(CAST(concat('0x', substr(md5(concat('mix:', coalesce(CAST(d.doc_id AS VARCHAR), 'null'))), 1, 13)) AS BIGINT) AS DOUBLE) / 4503599627370496.0 AS u
  FROM sized d JOIN targets t ON d.source IS NOT DISTINCT FROM t.source
)
SELECT doc_id, size, source_size, target, CAST(size * (floor(rate) + CASE WHEN u < rate - floor(rate) THEN 1 ELSE 0 END) AS BIGINT) AS taken FROM rated
"""
