"""Operations around the methods, as functions of tables: what feeds, ranks, checks and queries counts. Columns have defaults from the example tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

# --- Projections and predicates


def sel_columns(df: DataFrame, *columns: str) -> DataFrame:
    return df.select(*columns)


def sel_expr(df: DataFrame, **named: str) -> DataFrame:
    return df.select(*[F.expr(e).alias(n) for n, e in named.items()])


def flt_range(df: DataFrame, column: str, low, high) -> DataFrame:
    return df.where(F.col(column).between(low, high))


def flt_in(df: DataFrame, column: str, *values) -> DataFrame:
    return df.where(F.col(column).isin(*values))


def flt_like_prefix(df: DataFrame, column: str, prefix: str) -> DataFrame:
    return df.where(F.col(column).startswith(prefix))


def flt_null(df: DataFrame, *columns: str) -> DataFrame:
    """Rows that have a value in all of the columns."""
    return df.dropna(subset=list(columns))


def flt_bool(df: DataFrame, either: str, unless: str) -> DataFrame:
    """Rows for which `either` holds and `unless` does not; unknown counts as not."""
    return df.where(F.coalesce(F.expr(either), F.lit(False)) & ~F.coalesce(F.expr(unless), F.lit(False)))


def case_when(df: DataFrame, column: str, *bounds: tuple[float, str], rest: str, name: str) -> DataFrame:
    """Add `name`: the label of the first bound that the column is below, else `rest`."""
    out = None
    for bound, label in bounds:
        out = F.when(F.col(column) < bound, label) if out is None else out.when(F.col(column) < bound, label)
    return df.withColumn(name, out.otherwise(rest))


# --- Joins


def jn_hash(a: DataFrame, b: DataFrame, on: Column) -> DataFrame:
    """Both sides dealt by key; the second, whose partitions must fit in memory, is hashed."""
    return a.join(b.hint("shuffle_hash"), on)


def jn_broadcast(a: DataFrame, small: DataFrame, on: Column, most_rows: int = 1_000_000) -> DataFrame:
    """`small` goes to all tasks if it is, by a count, no larger than `most_rows`; else the sides meet by shuffling."""
    return a.join(F.broadcast(small) if small.limit(most_rows + 1).count() <= most_rows else small, on)


def jn_sortmerge(a: DataFrame, b: DataFrame, on: Column) -> DataFrame:
    """Both sides dealt and sorted by key, for partitions of any size; the session splits skewed ones."""
    return a.join(b.hint("merge"), on)


def jn_left_zero(items: DataFrame, cells: DataFrame, on: list[str], value: str = "v") -> DataFrame:
    """All items; a value that has no row is 0."""
    return items.join(cells, on, "left").fillna(0, [value])


def jn_right(a: DataFrame, b: DataFrame, on: Column) -> DataFrame:
    return a.join(b, on, "right")


def jn_full_ks(a: DataFrame, b: DataFrame, key: str) -> DataFrame:
    """(key, na, nb): counts of both sides, 0 where one has none."""
    return a.select(key, F.col("n").alias("na")).join(b.select(key, F.col("n").alias("nb")), key, "full_outer").fillna(0, ["na", "nb"])


def jn_self_cells(incidence: DataFrame) -> DataFrame:
    """(rep, pairs): pairs of items of a small set that share a cell."""
    a, b = (incidence.select("rep", "idx", F.col("item").alias(n)) for n in ("a", "b"))
    return a.join(b, ["rep", "idx"]).where("a < b").groupBy("rep").agg(F.count("*").alias("pairs"))


def jn_cross_constants(df: DataFrame, one_row: DataFrame) -> DataFrame:
    """Every row with the columns of a table of one row."""
    return df.crossJoin(F.broadcast(one_row.limit(1)))


def jn_semi_set(df: DataFrame, chosen: DataFrame, on: Column) -> DataFrame:
    return df.join(chosen, on, "left_semi")


def jn_anti_noise(df: DataFrame, own: DataFrame, on: Column) -> DataFrame:
    return df.join(own, on, "left_anti")


def jn_range_bin(df: DataFrame, ranges: DataFrame, column: str, width: int) -> DataFrame:
    """Rows with the (low, high, label) ranges that hold them. Ranges are cut at multiples of `width`, so both sides meet by an equal bin and only then compare."""
    cut = ranges.withColumn("__bin", F.explode(F.sequence(F.floor(F.col("low") / width), F.floor(F.col("high") / width))))
    return df.withColumn("__bin", F.floor(F.col(column) / width)).join(cut, "__bin").where(F.col(column).between(F.col("low"), F.col("high"))).drop("__bin")


def jn_dyadic_cover(df: DataFrame, cover: DataFrame, column: str, levels: int) -> DataFrame:
    """(low, high, n): rows in ranges given as dyadic items (low, high, item): a row meets the items that hold it, one for each level, by equality."""
    own = df.select(F.explode(F.transform(F.sequence(F.lit(0), F.lit(levels - 1)), lambda l: l * (1 << levels) + F.floor(F.col(column) / F.pow(F.lit(2.0), l)).cast("long"))).alias("item"))
    return own.groupBy("item").agg(F.count("*").alias("n")).join(F.broadcast(cover), "item").groupBy("low", "high").agg(F.sum("n").alias("n"))


def jn_theta_bnl(a: DataFrame, small: DataFrame, on: Column) -> DataFrame:
    """Any condition, with a side of few rows."""
    return a.join(F.broadcast(small), on)


def jn_asof_snapshot(events: DataFrame, snapshots: DataFrame, key: str, at: str) -> DataFrame:
    """Each event with the latest snapshot of its key at or before it (null before the first): one sorted pass over both, without a range join."""
    both = events.withColumn("snapshot", F.lit(None).cast(dict(snapshots.dtypes)["snapshot"])).withColumn("__side", F.lit(1))
    both = both.unionByName(snapshots.select(key, at, "snapshot").withColumn("__side", F.lit(0)), allowMissingColumns=True)
    last = F.last("snapshot", ignorenulls=True).over(Window.partitionBy(key).orderBy(at, "__side").rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn("snapshot", last).where("__side = 1").drop("__side")


def jn_interval(a: DataFrame, b: DataFrame, key: str, seconds: int) -> DataFrame:
    """Pairs (a.id, b.id) of a key with `b.at` after `a.at` and no more than `seconds` later: each row of a looks into its own bin of time and the next."""
    left = a.select(key, F.col("id").alias("a_id"), F.col("at").alias("a_at"), F.explode(F.array(F.floor(F.col("at") / seconds), F.floor(F.col("at") / seconds) + 1)).alias("__bin"))
    right = b.select(key, F.col("id").alias("b_id"), F.col("at").alias("b_at"), F.floor(F.col("at") / seconds).alias("__bin"))
    return left.join(right, [key, "__bin"]).where((F.col("b_at") > F.col("a_at")) & (F.col("b_at") <= F.col("a_at") + seconds)).select("a_id", "b_id")


# --- Aggregates


def agg_truth(df: DataFrame, item: str) -> DataFrame:
    return df.groupBy(F.col(item).alias("item")).agg(F.count("*").alias("c"))


def agg_hash(df: DataFrame, key: str, value: str) -> DataFrame:
    """Numbers, whose buffers change in place: the hash form."""
    return df.groupBy(key).agg(F.sum(value).alias("total"), F.count("*").alias("n"))


def agg_sort(df: DataFrame, key: str, value: str) -> DataFrame:
    """Texts, whose buffers don't: rows are sorted by key."""
    return df.groupBy(key).agg(F.min(value).alias("low"), F.max(value).alias("high"))


def agg_partial_final(df: DataFrame, key: str, parts: int = 8) -> DataFrame:
    """Counts in two steps by a salt, so that one key's rows are spread over `parts` tasks before they meet."""
    salted = df.withColumn("__salt", F.pmod(F.xxhash64(*df.columns), F.lit(parts)))
    return salted.groupBy(key, "__salt").agg(F.count("*").alias("n")).groupBy(key).agg(F.sum("n").alias("n"))


def agg_distinct(df: DataFrame, item: str, element: str) -> DataFrame:
    return df.groupBy(F.col(item).alias("item")).agg(F.countDistinct(element).alias("flows"))


def agg_multi_distinct(df: DataFrame, **columns: str) -> DataFrame:
    return df.agg(*[F.countDistinct(c).alias(n) for n, c in columns.items()])


def agg_grouping_sets(df: DataFrame, a: str, b: str) -> DataFrame:
    return df.groupingSets([(a, b), (a,), ()], a, b).agg(F.count("*").alias("n"))


def agg_rollup(df: DataFrame, a: str, b: str) -> DataFrame:
    return df.rollup(a, b).agg(F.count("*").alias("n"))


def agg_cube(df: DataFrame, a: str, b: str) -> DataFrame:
    return df.cube(a, b).agg(F.count("*").alias("n"))


def agg_filter(df: DataFrame, key: str, condition: str) -> DataFrame:
    return df.groupBy(key).agg(F.count_if(F.expr(condition)).alias("high"), F.count("*").alias("n"))


def agg_stats(df: DataFrame, key: str, value: str) -> DataFrame:
    return df.groupBy(key).agg(F.round(F.avg(value), 6).alias("mean"), F.round(F.stddev_samp(value), 6).alias("sd"), F.min(value).alias("low"), F.max(value).alias("high"))


def agg_percentile(df: DataFrame, key: str, value: str) -> DataFrame:
    return df.groupBy(key).agg(*[F.round(F.percentile(value, p), 6).alias(n) for n, p in (("q10", 0.1), ("q50", 0.5), ("q90", 0.9))])


def agg_pivot(df: DataFrame, key: str, by: str, values: list[str]) -> DataFrame:
    """A column of counts for each of the values, 0 where there is none."""
    return df.groupBy(key).pivot(by, values).agg(F.count(F.lit(1))).fillna(0, values)


def agg_collect(df: DataFrame, key: str, value: str) -> DataFrame:
    """The distinct values of each key, sorted, as one text; for values of which a key has few."""
    return df.groupBy(key).agg(F.array_join(F.sort_array(F.collect_set(value)), ",").alias("found"))


def agg_max_by(df: DataFrame, key: str, value: str, by: str) -> DataFrame:
    """The value of the row with the largest `by`; of ties, the smallest value."""
    return df.groupBy(key).agg(F.max(F.struct(F.col(by), (-F.col(value)).alias("v"))).alias("x")).select(key, (-F.col("x.v")).alias(value))


def agg_approx_distinct(df: DataFrame, key: str, value: str, error: float = 0.02) -> DataFrame:
    """(key, n, close): the true number, and whether the bounded sketch is within five of its standard errors."""
    return df.groupBy(key).agg(F.countDistinct(value).alias("n"), F.approx_count_distinct(value, error).alias("a")).select(key, "n", (F.abs(F.col("a") - F.col("n")) <= 5 * error * F.col("n") + 1).alias("close"))


def agg_approx_percentile(df: DataFrame, key: str, value: str, accuracy: int = 1000) -> DataFrame:
    """(key, n, close): whether the share of rows below the sketched median is within its accuracy of one half."""
    middle = df.groupBy(key).agg(F.percentile_approx(value, 0.5, accuracy).alias("m"))
    joined = df.join(F.broadcast(middle), key)
    return joined.groupBy(key).agg(F.count("*").alias("n"), F.avg((F.col(value) < F.col("m")).cast("double")).alias("b"), F.avg((F.col(value) <= F.col("m")).cast("double")).alias("e")).select(key, "n", ((F.col("b") <= 0.5 + 2 / accuracy) & (F.col("e") >= 0.5 - 2 / accuracy)).alias("close"))


# --- Windows, order, sets, samples


def over(key: str, *order) -> Window:
    return Window.partitionBy(key).orderBy(*order)


def win_row_number(df: DataFrame, key: str, *order, most: int) -> DataFrame:
    return df.withColumn("place", F.row_number().over(over(key, *order))).where(F.col("place") <= most)


def win_rank(df: DataFrame, key: str, *order) -> DataFrame:
    return df.withColumn("place", F.rank().over(over(key, *order)))


def win_dense_rank(df: DataFrame, key: str, *order) -> DataFrame:
    return df.withColumn("place", F.dense_rank().over(over(key, *order)))


def win_percent_rank(df: DataFrame, key: str, *order) -> DataFrame:
    return df.withColumn("share", F.round(F.percent_rank().over(over(key, *order)), 9))


def win_cume_dist(df: DataFrame, key: str, *order) -> DataFrame:
    return df.withColumn("f", F.round(F.cume_dist().over(over(key, *order)), 9))


def win_ntile(df: DataFrame, key: str, parts: int, *order) -> DataFrame:
    return df.withColumn("part", F.ntile(parts).over(over(key, *order)))


def win_running_sum(df: DataFrame, key: str, value: str, *order) -> DataFrame:
    return df.withColumn("seen", F.sum(value).over(over(key, *order).rowsBetween(Window.unboundedPreceding, 0)))


def win_range_frame(df: DataFrame, key: str, at: str, reach: int) -> DataFrame:
    """How many rows of the key lie within `reach` before each, itself and its equals included."""
    return df.withColumn("n", F.count("*").over(over(key, at).rangeBetween(-reach, 0)))


def win_lag_lead(df: DataFrame, key: str, value: str, *order) -> DataFrame:
    return df.withColumn("before", F.lag(value).over(over(key, *order))).withColumn("after", F.lead(value).over(over(key, *order)))


def win_first_last(df: DataFrame, key: str, value: str, *order) -> DataFrame:
    whole = over(key, *order).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return df.select(key, F.first(value).over(whole).alias("first"), F.last(value).over(whole).alias("last")).distinct()


def win_moving_avg(df: DataFrame, key: str, value: str, rows: int, *order) -> DataFrame:
    return df.withColumn("mean", F.round(F.avg(value).over(over(key, *order).rowsBetween(-rows, 0)), 6))


def top_per_group(df: DataFrame, key: str, most: int, *order) -> DataFrame:
    """The first rows of each key; only `most` of a key leave a task."""
    return df.withColumn("__place", F.row_number().over(over(key, *order))).where(F.col("__place") <= most).drop("__place")


def ord_first(df: DataFrame, most: int, *order, skip: int = 0) -> DataFrame:
    """The first rows of an order, or those after the first `skip`."""
    return df.orderBy(*order).offset(skip).limit(most)


def hashed(key: Column, seed: str) -> Column:
    """52 bits of a digest of seed and key, the same in every engine."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), key.cast("string")).cast("binary")), 1, 13), 16, 10).cast("long")


def smp_hash_bernoulli(df: DataFrame, key: str, share: float, seed: str = "7") -> DataFrame:
    """Each row by a draw of its own key: the same on every run and in every layout."""
    return df.where(hashed(F.col(key), seed) < F.lit(int(share * (1 << 52))))


def smp_coord(df: DataFrame, keys: list[str], share: float, seed: str = "7") -> DataFrame:
    """All rows of a key or none, by a draw of the key: tables sampled alike keep the same keys, so they can still be joined. Rows with a null in a key go."""
    return df.where(hashed(F.concat_ws("/", *keys), seed) < F.lit(int(share * (1 << 52)))).dropna(subset=keys)


def smp_bottomk(df: DataFrame, key: str, most: int, seed: str = "7") -> DataFrame:
    """All rows of the `most` keys with the smallest hashes; fewer keys, all of them."""
    chosen = ord_first(df.where(F.col(key).isNotNull()).select(F.col(key).alias("__key")).distinct().withColumn("__h", hashed(F.col("__key"), seed)), most, "__h", "__key")
    return df.join(chosen, F.col(key) == F.col("__key"), "left_semi")


def smp_stratified(df: DataFrame, stratum: str, key: str, most: int, seed: str = "7") -> DataFrame:
    """Of each stratum, the `most` rows with the smallest hashes."""
    return top_per_group(df.withColumn("__h", hashed(F.col(key), seed)), stratum, most, "__h", key).drop("__h")


# --- Texts, times, numbers, arrays, maps


def fn_normalize(text: Column) -> Column:
    """Lower case, runs of blanks as one, none at the ends."""
    return F.trim(F.regexp_replace(F.lower(text), "[ \t\n\r]+", " "))


def fn_tokenize(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), r"[^\p{L}]+"), lambda w: w != "")


def once(value: Column, of) -> Column:
    """`of` at `value`, which is worked out a single time however often `of` uses it: an expression that is named inside a lambda runs anew for each element."""
    return F.get(F.transform(F.array(value), of), F.lit(0))


def fn_ngrams(words: Column, n: int) -> Column:
    """Runs of n words, joined by blanks; none in a shorter array."""
    runs = lambda w: F.transform(F.sequence(F.lit(1), F.size(w) - n + 1), lambda i: F.concat_ws(" ", F.slice(w, i, n)))
    return once(words, lambda w: F.when(F.size(w) >= n, runs(w)).otherwise(F.array().cast("array<string>")))


def fn_html_text(html: Column) -> Column:
    """The text of a page: scripts, styles and tags out, runs of blanks as one."""
    bare = F.regexp_replace(F.regexp_replace(html, "(?is)<(script|style)[^>]*>.*?</(script|style)>", " "), "<[^>]*>", " ")
    return F.trim(F.regexp_replace(bare, "[ \t\n\r]+", " "))


def fn_url_host(url: Column) -> Column:
    return F.lower(F.regexp_extract(url, "^[A-Za-z][A-Za-z0-9+.-]*://([^/:?#]+)", 1))


def fn_concat_key(*parts: Column) -> Column:
    """One text key of several parts; the mark between them can't be in a number."""
    return F.concat_ws("|", *[p.cast("string") for p in parts])


def fn_age_weight(at: Column, now: str, half_life_days: float) -> Column:
    return F.pow(F.lit(2.0), -F.datediff(F.lit(now).cast("date"), at.cast("date")) / F.lit(half_life_days))


def fn_beta_closed(level: float, r: Column) -> Column:
    """The level's quantile of the least of r uniforms."""
    return F.lit(1.0) - F.pow(F.lit(1.0 - level), F.lit(1.0) / r)


def fn_ceil_rank(p: float, n: Column) -> Column:
    return F.greatest(F.lit(1), F.ceil(F.lit(p) * n)).cast("long")


def fn_map_counts(values: Column) -> Column:
    """value -> how often the array holds it."""
    return F.map_from_arrays(F.sort_array(F.array_distinct(values)), F.transform(F.sort_array(F.array_distinct(values)), lambda x: F.size(F.filter(values, lambda y: y == x))))


def fn_sign_bits(vector: Column, bits: int) -> Column:
    """The signs of the first numbers as bits, the first one lowest: a bucket of directions."""
    return F.aggregate(F.transform(F.slice(vector, 1, bits), lambda x, i: F.when(x > 0, F.pow(F.lit(2.0), i)).otherwise(0.0)), F.lit(0.0), lambda a, x: a + x).cast("long")
