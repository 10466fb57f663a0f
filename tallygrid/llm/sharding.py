"""Balanced label propagation (native): documents with equal texts move towards one another's shards under row quotas.

The law kept is `rows`: the shards' row counts differ by one at most. Documents are linked by equal text. Rows of one text are
interchangeable, so the state is a table (text group, shard, rows) and no pair of rows is ever formed. Each round, every part of a
group asks to move to the shard that holds most of the group among those with room; a shard accepts requests, small groups first (they can
be whole; a group larger than a shard can't), until its quota is full, and may split a request. Rounds go on until no row is away from the largest part
of its group, or their number stops falling. Where few rows are without a partner quotas are near 0 and groups stay split; these are then released and placed whole, larger ones first, into the
first shard that has room; the driver plans that on the counts of groups by size, of which there are few. A group is cut only if no shard has room for it; if such a
group would fit in a shard, all groups are placed anew that way, should that cut fewer. Documents without a partner have no edge to cut, so they fill what is left, which makes
the sizes exact.

Defined results: a null text counts as empty, size 1; equal rows are separate rows with slots of their own; a group larger
than a shard fills whole shards and is cut only between them; an empty table gives an empty result.
Only doc_id and text are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import cut, join_by_key, numbered, table

BUCKETS = 256


def _grant(requests: DataFrame, quotas: list[int], shards: int) -> DataFrame:
    """Add `granted`: how many of a request's rows its target takes, by size class of the group, then by hash.

    The running sums are taken in two levels, over the sums of (target, size class, hash bucket) and inside each of them, so that no
    task holds all requests for a shard.
    """
    requests = requests.withColumn("__class", F.floor(F.log2(F.col("group_rows"))).cast("int")).withColumn("__bucket", F.pmod(F.xxhash64(F.lit("grant"), "g", "shard"), F.lit(BUCKETS)).cast("int"))
    key = ["target", "__class", "__bucket"]
    earlier = Window.partitionBy("target").orderBy("__class", "__bucket").rowsBetween(Window.unboundedPreceding, -1)
    sums = requests.groupBy(*key).agg(F.sum("rows").alias("__sum")).withColumn("__start", F.coalesce(F.sum("__sum").over(earlier), F.lit(0))).drop("__sum")
    inside = Window.partitionBy(*key).orderBy("group_rows", "g", "shard").rowsBetween(Window.unboundedPreceding, -1)
    quota = _at(quotas, F.col("target"))
    start = F.col("__start") + F.coalesce(F.sum("rows").over(inside), F.lit(0))
    return requests.join(sums, key).withColumn("granted", F.greatest(F.lit(0), F.least(F.col("rows"), quota - start))).drop("__class", "__bucket", "__start")


def _at(values: list[int], index: Column) -> Column:
    return F.element_at(F.array(*[F.lit(int(v)) for v in values]), (index + 1).cast("int")).cast("long")


def _load(state: DataFrame, shards: int) -> list[int]:
    """Rows per shard: one number for each shard reaches the driver."""
    found = {r["shard"]: r["n"] for r in state.groupBy("shard").agg(F.sum("rows").alias("n")).collect()}
    return [int(found.get(s, 0)) for s in range(shards)]


def _away(state: DataFrame) -> int:
    """Rows that are not in the largest part of their group."""
    return int(state.groupBy("g").agg((F.sum("rows") - F.max("rows")).alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")).first()["n"])


def propagate(state: DataFrame, capacity: list[int], rounds: int | None = None) -> DataFrame:
    """(g, shard, rows) after `rounds` rounds of moves, or by default as many as lessen the cut; only groups with more than one row belong in `state`."""
    shards, away, done = len(capacity), _away(state), 0
    while away and done != rounds:
        load = _load(state, shards)
        quotas = [max(0, c - n) for c, n in zip(capacity, load, strict=True)]
        room = _at(quotas, F.col("shard")) > 0
        best = F.max(F.struct(room.alias("room"), F.col("rows"), F.pmod(F.xxhash64("g", "shard"), F.lit(1 << 20)).alias("tie"), F.col("shard"))).over(Window.partitionBy("g"))
        asked = state.withColumn("best", best).withColumn("target", F.col("best.shard")).withColumn("group_rows", F.sum("rows").over(Window.partitionBy("g")))
        moves = _grant(asked.where("best.room AND target != shard").drop("best"), quotas, shards).where("granted > 0")
        change = moves.select("g", F.explode(F.array(F.struct(F.col("shard"), (-F.col("granted")).alias("rows")), F.struct(F.col("target").alias("shard"), F.col("granted").alias("rows")))).alias("x")).select("g", "x.*")
        moved = cut(state.unionByName(change).groupBy("g", "shard").agg(F.sum("rows").alias("rows")).where("rows > 0"))
        now, done = _away(moved), done + 1
        if now >= away:
            break
        state, away = moved, now
    return state


def plan_whole(sizes: dict[int, int], room: list[int], most: int) -> tuple[list[tuple[int, int, int, int, int]], int]:
    """Runs (group_rows, from, to, shard, rows) for the groups numbered within their size, and how many groups are cut although `most` rows fit in a shard.
    Larger groups first, each whole in the first shard with room; a group that fits nowhere is cut over the shards with most room."""
    room, runs, cuts = list(room), [], 0
    for size in sorted(sizes, reverse=True):
        at, left = 0, sizes[size]
        for shard in range(len(room)):
            if n := min(left, room[shard] // size):
                runs.append((size, at, at + n, shard, size))
                room[shard] -= n * size
                at, left = at + n, left - n
        for at in range(at, at + left):
            cuts, rest = cuts + (size <= most), size
            for shard in sorted(range(len(room)), key=lambda x: -room[x]):
                if part := min(rest, room[shard]):
                    runs.append((size, at, at + 1, shard, part))
                    room[shard], rest = room[shard] - part, rest - part
    return runs, cuts


def _parts(runs: list[tuple[int, int, int, int, int]]) -> list[tuple[int, int, int, int, int]]:
    """The runs that are parts of a cut group."""
    return [r for r in runs if r[4] < r[0]]


def _sizes(groups: DataFrame) -> dict[int, int]:
    return {int(r["group_rows"]): int(r["n"]) for r in groups.groupBy("group_rows").agg(F.count("*").alias("n")).collect()}


def make_whole(state: DataFrame, capacity: list[int]) -> DataFrame:
    """(g, shard, rows): groups that are split, or stand above their shard's capacity, are placed anew."""
    groups = state.groupBy("g").agg(F.count("*").alias("parts"), F.min("shard").alias("shard"), F.sum("rows").alias("rows")).withColumn("group_rows", F.col("rows"))
    kept = _grant(groups.where("parts = 1").withColumn("target", F.col("shard")), capacity, len(capacity)).where("granted = rows").select("g", "shard", "rows")
    kept = cut(kept)
    loose = cut(groups.select("g", "group_rows").join(kept.select("g"), "g", "left_anti"))
    sizes = _sizes(loose)
    if not sizes:
        return kept
    runs, cuts = plan_whole(sizes, [c - n for c, n in zip(capacity, _load(kept, len(capacity)), strict=True)], max(capacity))
    if cuts or max(sizes) > max(capacity):
        again, fewer = plan_whole(_sizes(groups), capacity, max(capacity))
        if (fewer, len(_parts(again))) < (cuts, len(_parts(runs))):
            runs, kept, loose = again, kept.where("false"), groups.select("g", "group_rows")
    plan = state.sparkSession.createDataFrame(runs, "size long, low long, high long, shard int, rows long")
    ranked = numbered(loose, ["group_rows"], "g", "rank")
    placed = ranked.join(F.broadcast(plan), (F.col("group_rows") == F.col("size")) & (F.col("rank") >= F.col("low")) & (F.col("rank") < F.col("high")))
    return cut(kept.unionByName(placed.select("g", "shard", "rows")))


def assign(docs: DataFrame, shards: int = 8, rounds: int | None = None) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row of `docs`, and `group_rows`, the rows of its text."""
    text = F.coalesce(F.col("text"), F.lit(""))
    base = docs.select("doc_id", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.xxhash64(text).alias("g"))
    base = base.withColumn("__row", F.struct("doc_id", "g"))  # rows of one doc_id and text are alike, so any of them may take a place of theirs
    base = cut(base.withColumn("first", F.pmod(F.xxhash64(F.lit("shard"), "__row"), F.lit(shards)).cast("int")))
    total = base.count()
    capacity = [total // shards + (s < total % shards) for s in range(shards)]
    parts = base.groupBy("g", F.col("first").alias("shard")).agg(F.count("*").alias("rows"))
    parts = parts.withColumn("group_rows", F.sum("rows").over(Window.partitionBy("g")))
    linked = cut(parts.where("group_rows > 1"))
    state = make_whole(propagate(linked.select("g", "shard", "rows"), capacity, rounds), capacity)

    # Parts become runs of the group's numbered rows; a row finds its run among the group's, which are as many as shards at most.
    order = Window.partitionBy("g").orderBy(F.desc("rows"), "shard").rowsBetween(Window.unboundedPreceding, 0)
    runs = state.withColumn("end", F.sum("rows").over(order)).groupBy("g").agg(F.sort_array(F.collect_list(F.struct("end", "shard"))).alias("runs"), F.sum("rows").alias("group_rows"))
    with_runs = join_by_key(base.drop("first"), runs.withColumn("many", F.col("group_rows")), ["g"], "many", total, how="left")
    placed = numbered(with_runs.where("runs IS NOT NULL"), ["g"], "__row", "__pos")
    placed = placed.withColumn("shard", F.filter("runs", lambda x: x["end"] > F.col("__pos"))[0]["shard"]).drop("runs", "__pos")
    placed = cut(numbered(placed, ["shard"], "__row", "slot"))

    # What stands above a shard's share is released and, with the unlinked rows, fills the gaps in order.
    load = [min(c, n) for c, n in zip(capacity, _load(placed.groupBy("shard").agg(F.count("*").alias("rows")), shards), strict=True)]
    fits = F.col("slot") < _at(capacity, F.col("shard"))
    free = placed.where(~fits).drop("shard", "slot").unionByName(with_runs.where("runs IS NULL").drop("runs").withColumn("group_rows", F.lit(1).cast("long")))
    free = numbered(free.withColumn("__all", F.lit(0)), ["__all"], "__row", "__pos", buckets=4096)
    ends, at = [], 0
    for c, n in zip(capacity, load, strict=True):
        at += c - n
        ends.append(at)
    shard = F.coalesce(*[F.when(F.col("__pos") < e, F.lit(s)) for s, e in enumerate(ends)], F.lit(shards - 1)).cast("int")
    starts = [e - (c - n) for e, c, n in zip(ends, capacity, load, strict=True)]
    free = free.withColumn("shard", shard).withColumn("slot", F.col("__pos") - _at(starts, F.col("shard")) + _at(load, F.col("shard")))
    whole = placed.where(fits).unionByName(free.drop("__all", "__pos"))
    return whole.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), F.col("shard").cast("int").alias("shard"), "slot", F.lit(None).cast("int").alias("grown_shard"), F.col("group_rows").cast("long").alias("group_rows"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return assign(table(spark, sf_dir, "documents", "doc_id", "text"))
