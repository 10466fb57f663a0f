"""Connected components of a link table, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import HOT_KEYS, cut, join_by_key


def components(edges: DataFrame, hot_keys: int = HOT_KEYS) -> DataFrame:
    """(node, root) for every node of `edges` (a, b): root is the smallest node that can be reached, itself included.

    Links are kept once, from the larger node u to the smaller v. A round hangs every u on the least neighbour of its v, then every v, and u itself, on the
    least neighbour of its u; the tables are never larger than the link table. Rounds go on until one changes nothing: roots only fall,
    so that comes. A node with very many links is joined by `join_by_key`, so no task holds all links of one node. Loops and
    repeated links do no harm; an empty table gives an empty result.
    """
    links = cut(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    state = _state(links)
    while True:
        low = links.groupBy("u").agg(F.min("v").alias("low")).withColumnRenamed("u", "v")
        inner = links.groupBy("v").agg(F.count("*").alias("many")).join(low, "v", "left").select("v", F.coalesce("low", "v").alias("low"), "many")
        large = cut(join_by_key(links, inner, ["v"], "many", state[0], hot_keys).select("u", F.col("low").alias("v")).distinct())
        least = large.groupBy("u").agg(F.min("v").alias("low"), F.count("*").alias("many"))
        moved = join_by_key(large.where("u <> v"), least.where("many > 1"), ["u"], "many", state[0], hot_keys).where("v <> low").select(F.col("v").alias("u"), F.col("low").alias("v"))
        links = cut(moved.unionByName(least.select("u", F.col("low").alias("v"))).distinct())
        now = _state(links)
        if now == state:
            break
        state = now
    hung = links.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return hung.unionByName(hung.select(F.col("root").alias("node"), "root").distinct())


def _state(links: DataFrame) -> tuple:
    """How many links there are, and a sum of hashes that tells one set of them from another."""
    return tuple(links.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
