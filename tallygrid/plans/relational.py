"""Queries of the relational operations, sources and sinks over the example tables, each beside the SQL of another engine."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.hashing import GridSpec, cell_sql
from ..operators import grid, relational as ops, store
from ..sources import formats, tables
from ..sources.shared import keep, place
from .base import SPEC, TUPLES_SQL, Setting, add, sql_base, sql_grid

COUNTS_SQL = "(SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2)"


def op(name: str, sql: str | None, *names: str):
    """Register f(*tables) under `name`."""

    def keep(f):
        add(name, sql)(lambda spark, d: f(*[tables.table(spark, d, t) for t in names]))
        return f

    return keep


c = F.col
by_type = lambda e: e.groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
flagged = lambda df, flag: df.where(c("l_returnflag") == flag)

# --- Projections and predicates
op("sel_columns", "SELECT l_orderkey, l_partkey, l_quantity FROM lineitem", "lineitem")(lambda df: ops.sel_columns(df, "l_orderkey", "l_partkey", "l_quantity"))
op("sel_expr", "SELECT o_orderkey, CAST(round(o_totalprice * 100) AS BIGINT) AS cents FROM orders", "orders")(lambda df: ops.sel_expr(df, o_orderkey="o_orderkey", cents="CAST(round(o_totalprice * 100) AS BIGINT)"))
op("flt_range", "SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_discount < 0.05", "lineitem")(lambda df: ops.flt_range(df, "l_quantity", 10, 20).where("l_discount < 0.05").select("l_orderkey", "l_linenumber"))
op("flt_in", "SELECT o_orderkey, o_orderpriority FROM orders WHERE o_orderstatus IN ('F', 'O')", "orders")(lambda df: ops.flt_in(df, "o_orderstatus", "F", "O").select("o_orderkey", "o_orderpriority"))
op("flt_like_prefix", "SELECT p_partkey, p_type FROM part WHERE p_type LIKE 'S%'", "part")(lambda df: ops.flt_like_prefix(df, "p_type", "S").select("p_partkey", "p_type"))
op("flt_null", "SELECT doc_id FROM documents WHERE text IS NOT NULL AND lang IS NOT NULL", "documents")(lambda df: ops.flt_null(df, "text", "lang").select("doc_id"))
op("flt_bool", "SELECT l_orderkey, l_linenumber FROM lineitem WHERE (l_returnflag = 'R' OR l_quantity > 45) AND NOT l_linestatus = 'O'", "lineitem")(lambda df: ops.flt_bool(df, "l_returnflag = 'R' OR l_quantity > 45", "l_linestatus = 'O'").select("l_orderkey", "l_linenumber"))
op("case_when", "SELECT l_returnflag, CASE WHEN l_quantity < 10 THEN 'small' WHEN l_quantity < 30 THEN 'middle' ELSE 'large' END AS size, count(*) AS n FROM lineitem GROUP BY 1, 2", "lineitem")(lambda df: ops.case_when(df, "l_quantity", (10, "small"), (30, "middle"), rest="large", name="size").groupBy("l_returnflag", "size").agg(F.count("*").alias("n")))

# --- Joins
SQL_ORDERS = "SELECT o_custkey, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_custkey"
per_customer = lambda df: df.groupBy("o_custkey").agg(F.count("*").alias("n"))
op("jn_hash", SQL_ORDERS, "lineitem", "orders")(lambda l, o: per_customer(ops.jn_hash(l.select("l_orderkey"), o.select("o_orderkey", "o_custkey"), c("l_orderkey") == c("o_orderkey"))))
op("jn_sortmerge", SQL_ORDERS, "lineitem", "orders")(lambda l, o: per_customer(ops.jn_sortmerge(l.select("l_orderkey"), o.select("o_orderkey", "o_custkey"), c("l_orderkey") == c("o_orderkey"))))
op("jn_broadcast", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name", "customer", "nation")(lambda a, b: ops.jn_broadcast(a.select("c_nationkey"), b.select("n_nationkey", "n_name"), c("c_nationkey") == c("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n")))
op("jn_left_zero", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey", "customer", "orders")(lambda a, b: ops.jn_left_zero(a.select("c_custkey"), b.groupBy(c("o_custkey").alias("c_custkey")).agg(F.count("*").alias("n")), ["c_custkey"], "n"))
op("jn_right", "SELECT s_suppkey, count(c_custkey) AS n FROM (SELECT * FROM customer WHERE c_acctbal > 9000) c RIGHT JOIN supplier ON c_nationkey = s_nationkey GROUP BY s_suppkey", "customer", "supplier")(lambda a, b: ops.jn_right(a.where("c_acctbal > 9000"), b, c("c_nationkey") == c("s_nationkey")).groupBy("s_suppkey").agg(F.count("c_custkey").alias("n")))
op("jn_full_ks", "SELECT coalesce(a.k, b.k) AS k, coalesce(a.n, 0) AS na, coalesce(b.n, 0) AS nb FROM (SELECT l_partkey AS k, count(*) AS n FROM lineitem WHERE l_returnflag = 'R' GROUP BY 1) a FULL OUTER JOIN (SELECT l_partkey AS k, count(*) AS n FROM lineitem WHERE l_returnflag = 'A' GROUP BY 1) b ON a.k = b.k", "lineitem")(lambda df: ops.jn_full_ks(*[flagged(df, f).groupBy(c("l_partkey").alias("k")).agg(F.count("*").alias("n")) for f in ("R", "A")], "k"))
op("jn_semi_set", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 200000)", "customer", "orders")(lambda a, b: ops.jn_semi_set(a.select("c_custkey"), b.where("o_totalprice > 200000"), c("c_custkey") == c("o_custkey")))
op("jn_anti_noise", "SELECT p_partkey FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity > 49)", "part", "lineitem")(lambda a, b: ops.jn_anti_noise(a.select("p_partkey"), b.where("l_quantity > 49"), c("p_partkey") == c("l_partkey")))
op("jn_theta_bnl", "SELECT a.n_nationkey AS a, count(*) AS n FROM nation a JOIN region b ON a.n_nationkey > b.r_regionkey * 5 GROUP BY 1", "nation", "region")(lambda a, b: ops.jn_theta_bnl(a, b, c("n_nationkey") > c("r_regionkey") * 5).groupBy(c("n_nationkey").alias("a")).agg(F.count("*").alias("n")))
op("jn_cross_constants", "SELECT o_custkey, round(sum(o_totalprice) / (SELECT sum(o_totalprice) FROM orders), 9) AS share FROM orders GROUP BY o_custkey", "orders")(lambda df: ops.jn_cross_constants(df.groupBy("o_custkey").agg(F.sum("o_totalprice").alias("s")), df.agg(F.sum("o_totalprice").alias("t"))).select("o_custkey", F.round(c("s") / c("t"), 9).alias("share")))

CELLS = GridSpec(2, 40, "poly4")
add("jn_self_cells", "WITH i AS (SELECT DISTINCT CAST(user_id AS BIGINT) AS item FROM events), x AS (" + " UNION ALL ".join(f"SELECT item, CAST({a} AS INTEGER) AS rep, {cell_sql('item', a, CELLS)} AS idx FROM i" for a in range(CELLS.r)) + ") SELECT a.rep, count(*) AS pairs FROM x a JOIN x b ON a.rep = b.rep AND a.idx = b.idx AND a.item < b.item GROUP BY a.rep")(lambda spark, d: ops.jn_self_cells(grid.incidence(tables.users(spark, d).select("item").distinct(), CELLS)))

BINS = [(0, 9, "low"), (10, 29, "middle"), (25, 45, "wide"), (46, 60, "high")]


@add("jn_range_bin", f"SELECT label, count(*) AS n FROM lineitem JOIN (VALUES {', '.join(map(str, BINS))}) r(low, high, label) ON l_quantity BETWEEN low AND high GROUP BY label")
def jn_range_bin(spark, d):
    ranges = spark.createDataFrame(BINS, "low int, high int, label string")
    return ops.jn_range_bin(tables.table(spark, d, "lineitem").select("l_quantity"), ranges, "l_quantity", 16).groupBy("label").agg(F.count("*").alias("n"))


COVERED = [(1, 10), (5, 37), (0, 63)]


@add("jn_dyadic_cover", f"SELECT CAST(low AS BIGINT) AS low, CAST(high AS BIGINT) AS high, count(*) AS n FROM lineitem JOIN (VALUES {', '.join(map(str, COVERED))}) r(low, high) ON l_quantity BETWEEN low AND high GROUP BY low, high")
def jn_dyadic_cover(spark, d):
    cover = spark.createDataFrame([(a, b, x) for a, b in COVERED for x in grid.dyadic_cover(a, b, 6)], "low long, high long, item long")
    return ops.jn_dyadic_cover(tables.table(spark, d, "lineitem"), cover, "l_quantity", 6)


@add("jn_asof_snapshot", "SELECT e.event_id, (SELECT o_orderkey FROM orders WHERE o_custkey = e.user_id AND o_orderdate <= e.at ORDER BY o_orderdate DESC, o_orderkey DESC LIMIT 1) AS snapshot FROM (SELECT event_id, user_id, ts - INTERVAL 9000 DAY AS at FROM events) e")
def jn_asof_snapshot(spark, d):
    """Each event, moved back to the orders' years, with its user's latest order."""
    events = tables.table(spark, d, "events").select("event_id", c("user_id").alias("key"), F.expr("ts - INTERVAL 9000 DAYS").alias("at"))
    orders = tables.table(spark, d, "orders").groupBy(c("o_custkey").alias("key"), c("o_orderdate").alias("at")).agg(F.max("o_orderkey").alias("snapshot"))
    return ops.jn_asof_snapshot(events, orders, "key", "at").select("event_id", "snapshot")


@add("jn_interval", "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR")
def jn_interval(spark, d):
    rows = tables.table(spark, d, "events").select("user_id", "event_type", c("event_id").alias("id"), F.unix_micros(c("ts").cast("timestamp")).alias("at"))
    return ops.jn_interval(*[rows.where(c("event_type") == k) for k in ("view", "purchase")], "user_id", 6 * 3600 * 1_000_000)


# --- Aggregates
op("agg_truth", "SELECT l_partkey AS item, count(*) AS c FROM lineitem GROUP BY l_partkey", "lineitem")(lambda df: ops.agg_truth(df, "l_partkey"))
op("agg_hash", "SELECT l_suppkey, sum(l_quantity) AS total, count(*) AS n FROM lineitem GROUP BY l_suppkey", "lineitem")(lambda df: ops.agg_hash(df, "l_suppkey", "l_quantity"))
op("agg_sort", "SELECT l_partkey, min(l_linestatus) AS low, max(l_linestatus) AS high FROM lineitem GROUP BY l_partkey", "lineitem")(lambda df: ops.agg_sort(df, "l_partkey", "l_linestatus"))
op("agg_partial_final", "SELECT l_returnflag, count(*) AS n FROM lineitem GROUP BY l_returnflag", "lineitem")(lambda df: ops.agg_partial_final(df.select("l_returnflag", "l_orderkey", "l_linenumber"), "l_returnflag"))
op("agg_distinct", "SELECT l_partkey AS item, count(DISTINCT l_suppkey) AS flows FROM lineitem GROUP BY l_partkey", "lineitem")(lambda df: ops.agg_distinct(df, "l_partkey", "l_suppkey"))
op("agg_multi_distinct", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem", "lineitem")(lambda df: ops.agg_multi_distinct(df, parts="l_partkey", suppliers="l_suppkey"))
for _name, _sql in (("agg_grouping_sets", "GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())"), ("agg_rollup", "ROLLUP (l_returnflag, l_linestatus)"), ("agg_cube", "CUBE (l_returnflag, l_linestatus)")):
    op(_name, f"SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY {_sql}", "lineitem")(lambda df, f=getattr(ops, _name): f(df, "l_returnflag", "l_linestatus"))
op("agg_filter", "SELECT event_type, count(*) FILTER (WHERE value > 50) AS high, count(*) AS n FROM events GROUP BY event_type", "events")(lambda df: ops.agg_filter(df, "event_type", "value > 50"))
op("agg_stats", "SELECT l_returnflag, round(avg(l_quantity), 6) AS mean, round(stddev_samp(l_quantity), 6) AS sd, min(l_quantity) AS low, max(l_quantity) AS high FROM lineitem GROUP BY l_returnflag", "lineitem")(lambda df: ops.agg_stats(df, "l_returnflag", "l_quantity"))
op("agg_percentile", "SELECT o_orderpriority, round(quantile_cont(o_totalprice, 0.1), 6) AS q10, round(quantile_cont(o_totalprice, 0.5), 6) AS q50, round(quantile_cont(o_totalprice, 0.9), 6) AS q90 FROM orders GROUP BY o_orderpriority", "orders")(lambda df: ops.agg_percentile(df, "o_orderpriority", "o_totalprice"))
op("agg_pivot", "SELECT l_linestatus, count(*) FILTER (WHERE l_returnflag = 'A') AS A, count(*) FILTER (WHERE l_returnflag = 'N') AS N, count(*) FILTER (WHERE l_returnflag = 'R') AS R FROM lineitem GROUP BY l_linestatus", "lineitem")(lambda df: ops.agg_pivot(df, "l_linestatus", "l_returnflag", ["A", "N", "R"]))
op("agg_collect", "SELECT user_id, array_to_string(list_sort(list(DISTINCT event_type)), ',') AS found FROM events GROUP BY user_id", "events")(lambda df: ops.agg_collect(df, "user_id", "event_type"))
op("agg_max_by", "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders) WHERE k = 1", "orders")(lambda df: ops.agg_max_by(df, "o_custkey", "o_orderkey", "o_totalprice"))
op("agg_approx_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS n, true AS close FROM lineitem GROUP BY l_returnflag", "lineitem")(lambda df: ops.agg_approx_distinct(df, "l_returnflag", "l_partkey"))
op("agg_approx_percentile", "SELECT l_returnflag, count(*) AS n, true AS close FROM lineitem GROUP BY l_returnflag", "lineitem")(lambda df: ops.agg_approx_percentile(df, "l_returnflag", "l_quantity"))

# --- Windows, order, sets, samples
op("win_row_number", "SELECT * FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS place FROM orders) t WHERE place <= 3", "orders")(lambda df: ops.win_row_number(df, "o_custkey", F.desc("o_totalprice"), "o_orderkey", most=3).select("o_custkey", "o_orderkey", "place"))
for _name, _f in (("win_rank", "rank()"), ("win_dense_rank", "dense_rank()")):
    op(_name, f"SELECT user_id, event_type, n, {_f} OVER (PARTITION BY event_type ORDER BY n DESC) AS place FROM {COUNTS_SQL}", "events")(lambda e, f=getattr(ops, _name): f(by_type(e), "event_type", F.desc("n")))
op("win_percent_rank", f"SELECT user_id, event_type, n, round(percent_rank() OVER (PARTITION BY event_type ORDER BY n), 9) AS share FROM {COUNTS_SQL}", "events")(lambda e: ops.win_percent_rank(by_type(e), "event_type", "n"))
op("win_cume_dist", f"SELECT user_id, event_type, n, round(cume_dist() OVER (PARTITION BY event_type ORDER BY n), 9) AS f FROM {COUNTS_SQL}", "events")(lambda e: ops.win_cume_dist(by_type(e), "event_type", "n"))
op("win_ntile", f"SELECT user_id, event_type, n, ntile(4) OVER (PARTITION BY event_type ORDER BY n, user_id) AS part FROM {COUNTS_SQL}", "events")(lambda e: ops.win_ntile(by_type(e), "event_type", 4, "n", "user_id"))
op("win_running_sum", "SELECT event_id, CAST(sum(1) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS seen FROM events", "events")(lambda e: ops.win_running_sum(e.withColumn("one", F.lit(1).cast("long")), "user_id", "one", "ts", "event_id").select("event_id", "seen"))
op("win_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY CAST(epoch_us(ts) AS BIGINT) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS n FROM events", "events")(lambda e: ops.win_range_frame(e.select("event_id", "user_id", F.unix_micros(c("ts").cast("timestamp")).alias("at")), "user_id", "at", 86_400_000_000).select("event_id", "n"))
op("win_lag_lead", "SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)", "events")(lambda e: ops.win_lag_lead(e, "user_id", "event_type", "ts", "event_id").select("event_id", "before", "after"))
op("win_first_last", "SELECT DISTINCT user_id, first_value(event_id) OVER w AS first, last_value(event_id) OVER w AS last FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)", "events")(lambda e: ops.win_first_last(e, "user_id", "event_id", "ts", "event_id"))
op("win_moving_avg", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS mean FROM events", "events")(lambda e: ops.win_moving_avg(e, "user_id", "value", 4, "ts", "event_id").select("event_id", "mean"))
op("top_heavy", "SELECT l_partkey AS item, count(*) AS c FROM lineitem GROUP BY l_partkey ORDER BY c DESC, item LIMIT 20", "lineitem")(lambda df: ops.ord_first(ops.agg_truth(df, "l_partkey"), 20, F.desc("c"), "item"))
op("top_per_group", f"SELECT user_id, event_type, n FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY n DESC, user_id) AS k FROM {COUNTS_SQL}) WHERE k <= 5", "events")(lambda e: ops.top_per_group(by_type(e), "event_type", 5, F.desc("n"), "user_id"))
op("ord_multi", "SELECT o_orderkey FROM orders ORDER BY o_orderpriority, o_totalprice DESC, o_orderkey LIMIT 100", "orders")(lambda df: ops.ord_first(df, 100, "o_orderpriority", F.desc("o_totalprice"), "o_orderkey").select("o_orderkey"))
op("ord_nulls", "SELECT c_custkey, o_orderkey FROM customer LEFT JOIN (SELECT * FROM orders WHERE o_totalprice > 300000) ON c_custkey = o_custkey ORDER BY o_orderkey NULLS FIRST, c_custkey LIMIT 60", "customer", "orders")(lambda a, b: ops.ord_first(a.join(b.where("o_totalprice > 300000"), c("c_custkey") == c("o_custkey"), "left").select("c_custkey", "o_orderkey"), 60, F.asc_nulls_first("o_orderkey"), "c_custkey"))
op("lim_offset", "SELECT l_partkey AS item, count(*) AS c FROM lineitem GROUP BY l_partkey ORDER BY c DESC, item LIMIT 20 OFFSET 15", "lineitem")(lambda df: ops.ord_first(ops.agg_truth(df, "l_partkey"), 20, F.desc("c"), "item", skip=15))
_keys = lambda df, f: flagged(df, f).select(c("l_partkey").alias("k"))
for _name, _word, _how in (("set_union", "UNION", lambda a, b: a.union(b).distinct()), ("set_union_all", "UNION ALL", lambda a, b: a.unionAll(b)), ("set_intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)), ("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b))):
    op(_name, f"SELECT l_partkey AS k FROM lineitem WHERE l_returnflag = 'R' {_word} SELECT l_partkey FROM lineitem WHERE l_returnflag = 'A'", "lineitem")(lambda df, how=_how: how(_keys(df, "R"), _keys(df, "A")))
op("set_except", "SELECT p_partkey AS k FROM part EXCEPT SELECT l_partkey FROM lineitem WHERE l_quantity > 45", "part", "lineitem")(lambda a, b: a.select(c("p_partkey").alias("k")).subtract(b.where("l_quantity > 45").select("l_partkey")))
_H = lambda key: f"CAST(concat('0x', substr(md5(concat('7:', CAST({key} AS VARCHAR))), 1, 13)) AS BIGINT)"
op("smp_hash_bernoulli", f"SELECT o_orderkey FROM orders WHERE {_H('o_orderkey')} < {int(0.1 * (1 << 52))}", "orders")(lambda df: ops.smp_hash_bernoulli(df, "o_orderkey", 0.1).select("o_orderkey"))
op("smp_coord", f"SELECT l_orderkey, l_linenumber, o_custkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE {_H('l_orderkey')} < {int(0.1 * (1 << 52))}", "lineitem", "orders")(lambda lines, orders: ops.smp_coord(lines, ["l_orderkey"], 0.1).join(ops.smp_coord(orders, ["o_orderkey"], 0.1), c("l_orderkey") == c("o_orderkey")).select("l_orderkey", "l_linenumber", "o_custkey"))
op("smp_bottomk", f"SELECT user_id, event_id FROM events WHERE user_id IN (SELECT user_id FROM (SELECT DISTINCT user_id FROM events WHERE user_id IS NOT NULL) ORDER BY {_H('user_id')}, user_id LIMIT 20)", "events")(lambda df: ops.smp_bottomk(df, "user_id", 20).select("user_id", "event_id"))
op("smp_stratified", f"SELECT o_orderpriority, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY {_H('o_orderkey')}, o_orderkey) AS k FROM orders) WHERE k <= 30", "orders")(lambda df: ops.smp_stratified(df, "o_orderpriority", "o_orderkey", 30).select("o_orderpriority", "o_orderkey"))

# --- Texts, times, numbers
WORDS = r"list_filter(regexp_split_to_array(lower(text), '[^\p{L}]+'), lambda x: x <> '')"
op("fn_tokenize", f"SELECT doc_id, len({WORDS}) AS n, md5(array_to_string({WORDS}, ' ')) AS h FROM documents WHERE text IS NOT NULL", "documents")(lambda df: df.where("text IS NOT NULL").select("doc_id", F.size(ops.fn_tokenize(c("text"))).cast("long").alias("n"), F.md5(F.array_join(ops.fn_tokenize(c("text")), " ")).alias("h")))
op("fn_ngrams", f"SELECT doc_id, greatest(0, len(w) - 2) AS n, CASE WHEN len(w) >= 3 THEN array_to_string(w[1:3], ' ') END AS first FROM (SELECT doc_id, {WORDS} AS w FROM documents WHERE text IS NOT NULL)", "documents")(lambda df: df.where("text IS NOT NULL").select("doc_id", ops.fn_ngrams(ops.fn_tokenize(c("text")), 3).alias("g")).select("doc_id", F.size("g").cast("long").alias("n"), F.get("g", F.lit(0)).alias("first")))
op("fn_normalize", r"SELECT doc_id, md5(trim(regexp_replace(lower(text), '[ \t\n\r]+', ' ', 'g'))) AS h FROM documents", "documents")(lambda df: df.select("doc_id", F.md5(ops.fn_normalize(c("text"))).alias("h")))
op("fn_prefix", "SELECT substr(lower(event_type), 1, 2) AS prefix, count(*) AS n FROM events GROUP BY 1", "events")(lambda e: e.groupBy(F.substring(F.lower("event_type"), 1, 2).alias("prefix")).agg(F.count("*").alias("n")))
op("fn_html_text", r"SELECT page_id, md5(trim(regexp_replace(regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g'), '[ \t\n\r]+', ' ', 'g'))) AS h FROM pages", "pages")(lambda p: p.select("page_id", F.md5(ops.fn_html_text(c("html"))).alias("h")))
op("fn_url_host", "SELECT lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://([^/:?#]+)', 1)) AS host, count(*) AS n FROM pages GROUP BY 1", "pages")(lambda p: p.groupBy(ops.fn_url_host(c("url")).alias("host")).agg(F.count("*").alias("n")))
op("fn_md5_key", "SELECT doc_id, md5(concat(source, ':', lang)) AS h FROM documents", "documents")(lambda df: df.select("doc_id", F.md5(F.concat("source", F.lit(":"), "lang")).alias("h")))
op("fn_concat_key", "SELECT concat(l_partkey, '|', l_suppkey) AS item, count(*) AS c FROM lineitem GROUP BY 1", "lineitem")(lambda df: df.groupBy(ops.fn_concat_key(c("l_partkey"), c("l_suppkey")).alias("item")).agg(F.count("*").alias("c")))
op("fn_trunc_hour", "SELECT date_trunc('hour', ts) AS h, count(*) AS n FROM events GROUP BY 1", "events")(lambda e: e.groupBy(F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("h")).agg(F.count("*").alias("n")))
op("fn_day_bucket", "SELECT CAST(floor(date_diff('day', DATE '2020-01-01', CAST(ts AS DATE)) / 7.0) AS BIGINT) AS week, count(*) AS n FROM events GROUP BY 1", "events")(lambda e: e.groupBy(F.floor(F.datediff(c("ts").cast("date"), F.lit("2020-01-01").cast("date")) / 7).cast("long").alias("week")).agg(F.count("*").alias("n")))
op("fn_datediff", "SELECT o_orderkey, CAST(date_diff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE)) AS INTEGER) AS days FROM orders JOIN lineitem ON l_orderkey = o_orderkey", "orders", "lineitem")(lambda o, l: o.join(l, c("l_orderkey") == c("o_orderkey")).select("o_orderkey", F.datediff(c("l_shipdate").cast("date"), c("o_orderdate").cast("date")).alias("days")))
op("fn_age_weight", "SELECT o_orderkey, round(pow(2.0, -date_diff('day', CAST(o_orderdate AS DATE), DATE '2000-01-01') / 365.0), 9) AS w FROM orders", "orders")(lambda o: o.select("o_orderkey", F.round(ops.fn_age_weight(c("o_orderdate"), "2000-01-01", 365.0), 9).alias("w")))
op("fn_interval_add", "SELECT o_orderkey, CAST(CAST(o_orderdate AS DATE) + INTERVAL 45 DAY AS DATE) AS due FROM orders", "orders")(lambda o: o.select("o_orderkey", (c("o_orderdate").cast("date") + F.make_interval(days=F.lit(45))).cast("date").alias("due")))
op("fn_log_exp", "SELECT o_orderkey, round(ln(o_totalprice), 6) AS l, round(exp(-o_totalprice / 100000), 6) AS e FROM orders", "orders")(lambda o: o.select("o_orderkey", F.round(F.log("o_totalprice"), 6).alias("l"), F.round(F.exp(-c("o_totalprice") / 100000), 6).alias("e")))
op("fn_beta_closed", "SELECT DISTINCT CAST(l_linenumber AS INTEGER) AS r, round(1 - pow(1 - 0.95, 1.0 / l_linenumber), 9) AS q FROM lineitem", "lineitem")(lambda df: df.select(c("l_linenumber").cast("int").alias("r")).distinct().select("r", F.round(ops.fn_beta_closed(0.95, c("r")), 9).alias("q")))
op("fn_pmod", "SELECT o_orderkey, ((o_custkey - 1000) % 7 + 7) % 7 AS bucket FROM orders", "orders")(lambda o: o.select("o_orderkey", F.pmod(c("o_custkey") - 1000, F.lit(7).cast("long")).alias("bucket")))
op("fn_round", "SELECT o_orderkey, round(o_totalprice / 7, 2) AS r, CAST(floor(o_totalprice / 7) AS BIGINT) AS f FROM orders", "orders")(lambda o: o.select("o_orderkey", F.round(c("o_totalprice") / 7, 2).alias("r"), F.floor(c("o_totalprice") / 7).alias("f")))
op("fn_ceil_rank", "SELECT o_custkey, CAST(greatest(1, ceil(0.25 * count(*))) AS BIGINT) AS place FROM orders GROUP BY o_custkey", "orders")(lambda o: o.groupBy("o_custkey").agg(F.count("*").alias("n")).select("o_custkey", ops.fn_ceil_rank(0.25, c("n")).alias("place")))
op("fn_bit_shift", "SELECT l_orderkey, l_linenumber, l_partkey >> 3 AS prefix, (l_partkey << 2) & 255 AS low FROM lineitem", "lineitem")(lambda df: df.select("l_orderkey", "l_linenumber", F.shiftright("l_partkey", 3).alias("prefix"), F.shiftleft("l_partkey", 2).bitwiseAND(F.lit(255).cast("long")).alias("low")))

# --- Arrays, maps, JSON
per_order = lambda df: df.groupBy("l_orderkey").agg(F.sort_array(F.collect_list(c("l_quantity").cast("long"))).alias("q"))
LISTS = "(SELECT l_orderkey, list_sort(list(CAST(l_quantity AS BIGINT))) AS q FROM lineitem GROUP BY l_orderkey)"
op("fn_array_sort_slice", f"SELECT l_orderkey, array_to_string(list_reverse_sort(q)[1:2], ',') AS top FROM {LISTS}", "lineitem")(lambda df: per_order(df).select("l_orderkey", F.array_join(F.slice(F.sort_array("q", asc=False), 1, 2).cast("array<string>"), ",").alias("top")))
op("fn_zip_with", f"SELECT l_orderkey, CAST(list_sum(list_transform(range(1, len(q) + 1), lambda i: q[i] * q[len(q) + 1 - i])) AS BIGINT) AS s FROM {LISTS}", "lineitem")(lambda df: per_order(df).select("l_orderkey", F.aggregate(F.zip_with("q", F.reverse("q"), lambda x, y: x * y), F.lit(0).cast("long"), lambda a, x: a + x).alias("s")))
op("fn_aggregate", f"SELECT l_orderkey, CAST(list_sum(list_transform(q, lambda x: x * x)) AS BIGINT) AS s FROM {LISTS}", "lineitem")(lambda df: per_order(df).select("l_orderkey", F.aggregate("q", F.lit(0).cast("long"), lambda a, x: a + x * x).alias("s")))
op("fn_filter_exists", f"SELECT l_orderkey, len(list_filter(q, lambda x: x > 30)) AS large, len(list_filter(q, lambda x: x = 1)) > 0 AS has_one FROM {LISTS}", "lineitem")(lambda df: per_order(df).select("l_orderkey", F.size(F.filter("q", lambda x: x > 30)).cast("long").alias("large"), F.exists("q", lambda x: x == 1).alias("has_one")))
op("fn_map_counts", "SELECT user_id, count(*) FILTER (WHERE event_type = 'view') AS views FROM events GROUP BY user_id HAVING count(*) FILTER (WHERE event_type = 'view') > 0", "events")(lambda e: e.groupBy("user_id").agg(ops.fn_map_counts(F.collect_list("event_type")).alias("m")).select("user_id", F.try_element_at("m", F.lit("view")).cast("long").alias("views")).where("views IS NOT NULL"))
op("fn_map_entries", "SELECT user_id, event_type AS key, count(*) AS value FROM events GROUP BY 1, 2", "events")(lambda e: e.groupBy("user_id").agg(ops.fn_map_counts(F.collect_list("event_type")).alias("m")).select("user_id", F.explode(F.map_entries("m")).alias("x")).select("user_id", "x.key", c("x.value").cast("long").alias("value")))
op("fn_struct_key", "SELECT l_partkey AS part, l_suppkey AS supplier, count(*) AS c FROM lineitem GROUP BY 1, 2", "lineitem")(lambda df: df.groupBy(F.struct(c("l_partkey").alias("part"), c("l_suppkey").alias("supplier")).alias("item")).agg(F.count("*").alias("c")).select("item.*", "c"))
op("fn_json_props", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events", "events")(lambda e: e.select("event_id", F.from_json("props", "k long")["k"].alias("k")))
op("fn_embedding_bucket", f"SELECT bucket, count(*) AS n FROM (SELECT CAST({' + '.join(f'CASE WHEN embedding[{i + 1}] > 0 THEN {1 << i} ELSE 0 END' for i in range(10))} AS BIGINT) AS bucket FROM embeddings) GROUP BY bucket", "embeddings")(lambda e: e.groupBy(ops.fn_sign_bits(c("embedding"), 10).alias("bucket")).agg(F.count("*").alias("n")))

# --- Sources: every format is written and read again
ORDERS_SQL = "SELECT o_orderkey, o_custkey, o_orderstatus, round(o_totalprice, 2) AS price FROM orders"
ORDERS = "o_orderkey long, o_custkey long, o_orderstatus string, price double"
some_orders = lambda spark, d: tables.table(spark, d, "orders").select("o_orderkey", "o_custkey", "o_orderstatus", F.round("o_totalprice", 2).alias("price"))
for _kind in ("parquet", "csv", "json", "orc"):
    add(f"scan_{_kind}", ORDERS_SQL)(lambda spark, d, kind=_kind: formats.scan(spark, formats.written(some_orders(spark, d), kind), kind, ORDERS))


@add("scan_text", "SELECT line, count(*) AS n FROM (SELECT concat(o_orderstatus, ' ', o_orderpriority) AS line FROM orders) GROUP BY line")
def scan_text(spark, d):
    lines = tables.table(spark, d, "orders").select(F.concat_ws(" ", "o_orderstatus", "o_orderpriority").alias("value"))
    return formats.scan(spark, formats.written(lines, "text"), "text", "value string").groupBy(c("value").alias("line")).agg(F.count("*").alias("n"))


@add("scan_view", "SELECT o_orderstatus, count(*) AS n FROM orders WHERE o_totalprice > 100000 GROUP BY o_orderstatus")
def scan_view(spark, d):
    tables.table(spark, d, "orders").createOrReplaceTempView("tally_orders")
    return spark.sql("SELECT o_orderstatus, count(*) AS n FROM tally_orders WHERE o_totalprice > 100000 GROUP BY o_orderstatus")


@add("src_range", "WITH b AS (SELECT min(CAST(o_orderdate AS DATE)) AS low, max(CAST(o_orderdate AS DATE)) AS high FROM orders), n AS (SELECT date_diff('day', low, CAST(o_orderdate AS DATE)) AS day, count(*) AS n FROM orders, b GROUP BY 1) SELECT CAST(i AS BIGINT) AS day, coalesce(n, 0) AS n FROM (SELECT unnest(range(0, (SELECT date_diff('day', low, high) + 1 FROM b))) AS i) LEFT JOIN n ON day = i")
def src_range(spark, d):
    """Orders of each day from the first to the last, by a range of days: those without orders too."""
    days = keep(tables.table(spark, d, "orders").groupBy(c("o_orderdate").cast("date").alias("date")).agg(F.count("*").alias("n")), "days")
    low, high = days.agg(F.min("date"), F.max("date")).first()
    every = spark.range(0 if low is None else (high - low).days + 1).select(c("id").alias("day"))
    return every.join(days.select(F.datediff("date", F.lit(low)).cast("long").alias("day"), "n"), "day", "left").select("day", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


_HOUR = "CAST(epoch(date_trunc('hour', ts)) AS BIGINT) // 3600"


@add("src_rate", f"WITH h AS (SELECT {_HOUR} AS hour, count(*) AS n FROM events WHERE ts IS NOT NULL GROUP BY 1), b AS (SELECT min(hour) AS low, max(hour) AS high FROM h) SELECT CAST(i AS BIGINT) AS value, coalesce(n, 0) AS n FROM (SELECT unnest(range(0, (SELECT high - low + 1 FROM b))) AS i) LEFT JOIN (SELECT hour - low AS tick, n FROM h, b) ON tick = i")
def src_rate(spark, d):
    """The rate source as a clock: each tick tells how many events came in its hour, from the first hour to the last."""
    hour = (F.unix_seconds(F.date_trunc("hour", c("ts").cast("timestamp"))) / 3600).cast("long")
    hours = keep(tables.table(spark, d, "events").where("ts IS NOT NULL").groupBy(hour.alias("hour")).agg(F.count("*").alias("n")), "hours")
    low, high = hours.agg(F.min("hour"), F.max("hour")).first()
    if low is None:
        return spark.createDataFrame([], "value long, n long")
    told = hours.select((c("hour") - F.lit(low)).alias("value"), "n")
    return formats.rate_rows(spark, high - low + 1).select("value").join(told, "value", "left").select("value", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


add("src_file_stream", "SELECT event_id, user_id FROM events")(lambda spark, d: formats.through_files(tables.stream(spark, d, "events").select("event_id", "user_id"), place(spark, "file-stream")))
add("sink_file_stream", "SELECT event_id, event_type FROM events WHERE value > 50")(lambda spark, d: formats.through_files(tables.stream(spark, d, "events").where("value > 50").select("event_id", "event_type"), place(spark, "file-sink")))
add("sink_memory", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")(lambda spark, d: formats.in_memory(tables.stream(spark, d, "events").groupBy("event_type").agg(F.count("*").alias("n"))))
add("sink_foreach_batch", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")(lambda spark, d: formats.by_batch(tables.stream(spark, d, "events").select("event_type"), place(spark, "batches")).groupBy("event_type").agg(F.count("*").alias("n")))
_U = "(CAST(CAST(concat('0x', substr(md5(concat('3:', CAST(i AS VARCHAR))), 1, 13)) AS BIGINT) AS DOUBLE) + 0.5) / 4503599627370496.0"
add("src_power_law", f"WITH p AS (SELECT x, sum(pow(2.0 + x, -2.5)) OVER (ORDER BY x) / sum(pow(2.0 + x, -2.5)) OVER () AS f FROM range(1, 2001) t(x)), u AS (SELECT i, {_U} AS u FROM (SELECT DISTINCT CAST(o_custkey AS BIGINT) AS i FROM orders WHERE o_custkey IS NOT NULL)) SELECT i AS item, CAST(x AS BIGINT) AS c FROM u ASOF JOIN p ON u.u <= p.f")(lambda spark, d: formats.power_law_of(tables.customers(spark, d).select(c("item").cast("long").alias("item")).distinct(), 2.5, 2.0, 2000))

# --- Sinks of grids and estimates


@add("save_grid", f"{sql_base()} SELECT rep, count(*) AS n, CAST(sum(v) AS BIGINT) AS total FROM g GROUP BY rep")
def save_grid(spark, d):
    """What the files hold: cells and total of each replicate's folder."""
    path = place(spark, "saved")
    store.save_grid(grid.build_grid(tables.parts(spark, d), SPEC), path, "bigint")
    return spark.read.schema(store.CELLS).parquet(f"{path}/cells").groupBy("rep").agg(F.count("*").alias("n"), F.sum("v").alias("total"))


@add("load_grid", f"WITH t AS ({TUPLES_SQL['parts']} UNION ALL {TUPLES_SQL['users']}), {sql_grid('g', 't')} SELECT rep, idx, v FROM g")
def load_grid(spark, d):
    """Two grids that were kept apart, loaded and added."""
    paths = [place(spark, "saved") for _ in range(2)]
    for path, source in zip(paths, (tables.parts, tables.users), strict=True):
        store.save_grid(grid.build_grid(source(spark, d), SPEC), path, "bigint")
    return grid.merge(*[store.load_grid(spark, path, SPEC, "bigint") for path in paths]).df


@add("save_estimates", f"{sql_base()} SELECT item, s[1] * 1.0 AS est, 'min' AS method FROM p UNION ALL SELECT item, (s[2] + s[3]) / 2.0, 'median' FROM p")
def save_estimates(spark, d):
    from ..functions.statistics import t_median, t_min
    from ..operators.estimates import classical

    probed, path = Setting(spark, d).probed, place(spark, "estimates")
    for method, statistic in (("min", t_min), ("median", t_median)):
        store.save_estimates(classical(probed, statistic).withColumn("method", F.lit(method)), path, "method", "append")
    return spark.read.schema("item long, est double, method string").parquet(path)
