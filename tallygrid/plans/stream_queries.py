"""Queries over streams that work batch by batch, by sessions, with decay, and by joining streams."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import GridSpec, cell_sql
from ..functions.statistics import t_mean, t_median, t_min, t_trimmed
from ..operators import estimates, grid
from ..sources import tables
from ..sources.shared import place
from ..streaming import grids as streams
from .base import SPEC, TUPLES_SQL, add, sql_grid
from .studies import SMALL, _events, _folder, _window_sql, frame

#: Files, and so micro-batches, that the events are dealt to.
PARTS = 4
LANDMARK = "2024-01-01"


def _in_parts(spark, d, parts: int = PARTS) -> DataFrame:
    """The events as a stream of several files, one for each micro-batch, in the order of time."""
    folder = place(spark, "events")
    rows = tables.table(spark, d, "events").select(F.col("user_id").alias("item"), F.lit(1).cast("long").alias("c"), F.col("ts").cast("timestamp").alias("ts"), "event_id", "event_type")
    rows.repartitionByRange(parts, "ts").write.parquet(folder)
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(folder)


USERS_SQL = f"WITH t AS ({TUPLES_SQL['users']}), {sql_grid('g', 't')}"


@add("stream_grid_batchmerge", f"{USERS_SQL} SELECT rep, idx, v FROM g")
def stream_grid_batchmerge(spark, d):
    """Grids of micro-batches, merged; every batch is handed in twice, and counts once."""
    store = streams.BatchGrids(_folder(spark), SPEC)

    def twice(batch, batch_id):
        store.absorb(batch, batch_id)
        store.absorb(batch, batch_id)

    streams.each_batch(_in_parts(spark, d), twice, _folder(spark))
    return store.merged(spark)


#: The last tuple's time, and how far back tuples still count where late ones are dropped.
LATE_HOURS = 48


def _late_parts(spark, d) -> DataFrame:
    """The events in three files: four fifths of them, a tenth, and another tenth, most of which is late by then: a batch drops what the watermark had passed when the one before it began."""
    folder = place(spark, "late")
    rows = tables.table(spark, d, "events").select(F.col("user_id").alias("item"), F.lit(1).cast("long").alias("c"), F.col("ts").cast("timestamp").alias("ts"), "event_id")
    for k, part in enumerate((rows.where("event_id % 10 > 1"), rows.where("event_id % 10 = 1"), rows.where("event_id % 10 = 0"))):
        part.coalesce(1).write.parquet(f"{folder}/part={k}")
        time.sleep(1.1)  # files come in the order of their times
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).option("latestFirst", "false").parquet(f"{folder}/part=*")


@add("stream_late", _window_sql())
def stream_late(spark, d):
    """Daily grids when a tenth of the tuples comes after all others, added: no window is ever closed, as grids of batches are summed."""
    kept = streams.BatchGrids(_folder(spark), SMALL, "start", compact=2)
    daily = _late_parts(spark, d).withColumn("start", F.unix_timestamp(F.date_trunc("day", "ts")))
    streams.each_batch(daily, kept.absorb, _folder(spark))
    return kept.merged(spark)


def _dropped_sql() -> str:
    last = f"(SELECT max(ts) FROM events WHERE event_id % 10 > 1) - INTERVAL {LATE_HOURS} HOUR"
    return _window_sql().replace("FROM events)", f"FROM events WHERE event_id % 10 <> 0 OR date_trunc('day', ts) + INTERVAL 1 DAY > {last})")


@add("stream_late_drop", _dropped_sql())
def stream_late_drop(spark, d):
    """The same with late tuples dropped: a window counts until the watermark, two days behind the newest tuple, has passed its end."""
    grids = streams.drained(streams.window_grids(_late_parts(spark, d), SMALL, "1 day", late=f"{LATE_HOURS} hours"), _folder(spark))
    return grids.select(F.unix_timestamp("window.start").alias("start"), "rep", "idx", "v")


_SLIDING = _window_sql().replace("SELECT CAST(user_id AS BIGINT) AS item, date_trunc('day', ts) AS w FROM events", "SELECT CAST(user_id AS BIGINT) AS item, date_trunc('day', ts) - back * INTERVAL 1 DAY AS w FROM events, (VALUES (0), (1)) b(back)")


@add("stream_sliding", _SLIDING)
def stream_sliding(spark, d):
    """A grid of two days for every day."""
    grids = streams.drained(streams.window_grids(_events(spark, d), SMALL, "2 days", "1 day", late="3650 days"), _folder(spark))
    return grids.select(F.unix_timestamp("window.start").alias("start"), "rep", "idx", "v")


def _session_sql() -> str:
    each = " UNION ALL ".join(f"SELECT day, {a} AS rep, {cell_sql('item', a, SMALL)} AS idx, c FROM s" for a in range(SMALL.r))
    return (
        "WITH e AS (SELECT CAST(user_id AS BIGINT) AS item, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), "
        "n AS (SELECT item, ts, sum(opens) OVER (PARTITION BY item ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e), "
        "s AS (SELECT item, CAST(epoch(date_trunc('day', min(ts))) AS BIGINT) AS day, count(*) AS c FROM n GROUP BY item, k HAVING max(ts) + INTERVAL 6 HOUR <= (SELECT max(ts) FROM events)) "
        f"SELECT day AS start, CAST(rep AS INTEGER) AS rep, idx, CAST(sum(c) AS BIGINT) AS v FROM ({each}) GROUP BY day, rep, idx"
    )


@add("stream_session", _session_sql())
def stream_session(spark, d):
    """A grid of closed sessions' counts for each day on which they began."""
    closed = streams.drained_to_files(streams.sessions(_events(spark, d), "6 hours"), _folder(spark))
    spread = closed.select(F.unix_timestamp(F.date_trunc("day", "start")).alias("start"), F.explode(grid.cells_of(F.col("item"), SMALL)).alias("x"), "c")
    return spread.groupBy("start", "x.rep", "x.idx").agg(F.sum("c").alias("v"))


@add("stream_auto")
def stream_auto(spark, d):
    """The narrowest simple estimator after each batch."""
    auto = streams.AutoEstimator(_folder(spark), GridSpec(4, 50), {"min": t_min, "mean": t_mean, "median": t_median, "trimmed": t_trimmed(1, 1)})
    streams.each_batch(_in_parts(spark, d), auto.absorb, _folder(spark))
    return auto.choices(spark)


@add("stream_conservative")
def stream_conservative(spark, d):
    """(item, truth, est, plain): conservative and plain minimum after the stream."""
    spec = GridSpec(3, 60, "poly4")
    kept = streams.ConservativeGrid(_folder(spark), spec)
    streams.each_batch(_in_parts(spark, d), kept.absorb, _folder(spark))
    t = tables.users(spark, d)
    truth = t.groupBy("item").agg(F.sum("c").alias("truth"))
    est = lambda g, name: estimates.classical(grid.probe(truth.select("item"), g)).withColumnRenamed("est", name)
    return truth.join(est(kept.grid(spark), "est"), "item").join(est(grid.build_grid(t, spec), "plain"), "item")


@add("stream_decay", f"WITH t AS (SELECT CAST(user_id AS BIGINT) AS item, CAST(round(1000000 * pow(2.0, (epoch_us(ts) - epoch_us(TIMESTAMP '{LANDMARK}')) / 86400e6 / 7.0)) AS BIGINT) AS c FROM events), {sql_grid('g', 't')} SELECT rep, idx, v FROM g")
def stream_decay(spark, d):
    """Weights with a half-life of a week, relative to the landmark."""
    return streams.drained(streams.decayed_grid(_events(spark, d), SPEC, 7, LANDMARK), _folder(spark))


TOP_SQL = f"{USERS_SQL}, i AS (SELECT DISTINCT item FROM t), e AS (" + " UNION ALL ".join(f"SELECT item, {a} AS rep, {cell_sql('item', a, SPEC)} AS idx FROM i" for a in range(SPEC.r)) + ") SELECT item, min(v) AS est FROM e JOIN g USING (rep, idx) GROUP BY item ORDER BY est DESC, item LIMIT 20"


@add("stream_topk", TOP_SQL)
def stream_topk(spark, d):
    """The 20 users with the largest estimates, each user's events in one batch alone: estimates of the first batches' users go on rising with the later ones."""
    folder = place(spark, "by-user")
    rows = tables.table(spark, d, "events").select(F.col("user_id").alias("item"), F.lit(1).cast("long").alias("c"), (F.pmod(F.xxhash64("user_id"), F.lit(PARTS))).alias("part"))
    rows.repartition(PARTS, "part").sortWithinPartitions("part").drop("part").write.parquet(folder)
    top = streams.TopItems(_folder(spark), SPEC, 20)
    streams.each_batch(spark.readStream.schema("item long, c long").option("maxFilesPerTrigger", 1).parquet(folder), top.absorb, _folder(spark))
    return top.items(spark)


@add("stream_stream_join", "SELECT CAST(a.user_id AS BIGINT) AS item, a.event_id AS left_id, b.event_id AS right_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 12 HOUR")
def stream_stream_join(spark, d):
    """Purchases within twelve hours after a view by the same user."""
    rows = lambda kind: tables.stream(spark, d, "events").where(F.col("event_type") == kind).select(F.col("user_id").alias("item"), F.col("ts").cast("timestamp").alias("ts"), "event_id")
    return streams.drained_to_files(streams.interval_join(rows("view"), rows("purchase"), "12 HOURS"), _folder(spark))


GATED = GridSpec(4, 200)


def _lazy(spark, d, delta: float) -> streams.LazyDensity:
    kept = streams.LazyDensity(_folder(spark), GATED, delta)
    streams.each_batch(_in_parts(spark, d, 5), kept.absorb, _folder(spark))
    return kept


@add("stream_lazy_density")
def stream_lazy_density(spark, d):
    """(batch, ks, refitted, knots): the gap between the law now and that of the last fit, batch by batch, and where the gate of 0.1 made a new fit."""
    return _lazy(spark, d, 0.1).steps(spark)


@add("refits")
def refits(spark, d):
    """(delta, checks, refits): what gates of different widths cost over the same stream."""
    rows = []
    for delta in (0.05, 0.5):
        told = _lazy(spark, d, delta).steps(spark).agg(F.count("*").alias("n"), F.sum(F.col("refitted").cast("int")).alias("k")).first()
        rows.append((delta, told["n"], told["k"]))
    return frame(spark, rows, "delta double, checks long, refits long")


@add("ks_gate")
def ks_gate(spark, d):
    """(batch, ks): the law of each batch's end against the one before: a gate of 0 fits every time."""
    return _lazy(spark, d, 0.0).steps(spark).select("batch", "ks")
