"""What all queries are registered with and built from: their names, the SQL of other engines in parts, and a grid over a source.

The SQL works with the portable hash families only; doubles are rounded alike on both sides.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.density import LogSpline
from ..functions.hashing import GridSpec, cell_sql
from ..functions.statistics import t_mean, t_median, t_min, t_order, t_quantile, t_trimmed
from ..operators import grid, store
from ..sources import tables
from ..sources.shared import keep

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}

SPEC = GridSpec(4, 250, "poly4")
WORD_SPEC = GridSpec(4, 4096, "md5")
LINE = GridSpec(1, 1000, "poly4")
LEVEL = 0.9
#: A fixed density for tests of the estimators alone.
PINNED = LogSpline(np.asarray([0.0, 100.0, 200.0, 400.0]), np.asarray([-6.0, -2.0, -4.0, -12.0]))
PINNED_SQL = "CASE WHEN x <= 100 THEN -6 + 0.04 * x WHEN x <= 200 THEN -2 - 0.02 * (x - 100) ELSE -4 - 0.04 * (x - 200) END"

TUPLES_SQL = {
    "parts": "SELECT CAST(l_partkey AS BIGINT) AS item, CAST(1 AS BIGINT) AS c FROM lineitem",
    "quantities": "SELECT CAST(l_partkey AS BIGINT) AS item, CAST(l_quantity AS BIGINT) AS c FROM lineitem",
    "users": "SELECT CAST(user_id AS BIGINT) AS item, CAST(1 AS BIGINT) AS c FROM events",
    "words": r"SELECT item, CAST(1 AS BIGINT) AS c FROM (SELECT unnest(regexp_split_to_array(lower(text), '[^\p{L}]+')) AS item FROM documents) WHERE item <> ''",
}


def add(name: str, sql: str | None = None):
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLE_SQL[name] = sql
        return f

    return keep


def r6(c: str | Column) -> Column:
    return F.round(c, 6)


# --- SQL parts -------------------------------------------------------------------------------------------------------------------------


def sql_grid(name: str, source: str, spec: GridSpec = SPEC, value: str = "c") -> str:
    each = " UNION ALL ".join(f"SELECT CAST({a} AS INTEGER) AS rep, {cell_sql('item', a, spec)} AS idx, {value.replace('{rep}', str(a))} AS c FROM {source}" for a in range(spec.r))
    return f"{name} AS (SELECT rep, idx, CAST(sum(c) AS BIGINT) AS v FROM ({each}) GROUP BY rep, idx)"


def sql_probe(name: str, items: str, of: str = "g", spec: GridSpec = SPEC) -> str:
    cols = ", ".join(f"coalesce(g{a}.v, 0) AS v{a}" for a in range(spec.r))
    joins = " ".join(f"LEFT JOIN {of} g{a} ON g{a}.rep = {a} AND g{a}.idx = {cell_sql('i.item', a, spec)}" for a in range(spec.r))
    return f"{name} AS (SELECT i.*, {cols}, list_sort([{', '.join(f'coalesce(g{a}.v, 0)' for a in range(spec.r))}]) AS s FROM {items} i {joins})"


def sql_base(source: str = "parts", spec: GridSpec = SPEC) -> str:
    return f"WITH t AS ({TUPLES_SQL[source]}), items AS (SELECT DISTINCT item FROM t), {sql_grid('g', 't', spec)}, {sql_probe('p', 'items', 'g', spec)}"


SQL_HIST = f"h AS (SELECT v, CAST(sum(m) AS BIGINT) AS m FROM (SELECT v, count(*) AS m FROM g GROUP BY v UNION ALL SELECT 0, {SPEC.cells} - count(*) FROM g) GROUP BY v HAVING sum(m) > 0), hc AS (SELECT v, m, CAST(sum(m) OVER (ORDER BY v) AS BIGINT) AS cum FROM h)"


def sql_rank(p: float, n: int = SPEC.cells, of: str = "hc") -> str:
    return f"(SELECT min(v) FROM {of} WHERE cum >= least({n}, greatest(1, ceil(CAST({p!r} AS DOUBLE) * {n} - 1e-9))))"


def sql_columns(spec: GridSpec = SPEC) -> str:
    cols = ", ".join(f"coalesce(sum(CASE WHEN rep = {a} THEN v END), 0) AS v{a}" for a in range(spec.r))
    listed = ", ".join(f"coalesce(sum(CASE WHEN rep = {a} THEN v END), 0)" for a in range(spec.r))
    return f"k AS (SELECT r.i AS idx, {cols}, list_sort([{listed}]) AS s FROM range({spec.k}) r(i) LEFT JOIN g ON g.idx = r.i GROUP BY r.i)"


#: Statistics: as a column function, and as SQL over the sorted list s.
STATS: dict[str, tuple] = {
    "min": (t_min, "s[1] * 1.0"),
    "mean": (t_mean, "list_sum(s) / 4.0"),
    "median": (t_median, "(s[2] + s[3]) / 2.0"),
    "order": (t_order(2), "s[2] * 1.0"),
    "quantile": (t_quantile(0.4), "s[2] * 1.0"),
    "trimmed": (t_trimmed(1, 1), "(s[2] + s[3]) / 2.0"),
}


def sql_law(stat: str) -> str:
    return f"{sql_columns()}, l AS (SELECT v, count(*) AS m FROM (SELECT {stat} AS v FROM k) GROUP BY v), lc AS (SELECT v, m, sum(m) OVER (ORDER BY v) AS cum FROM l), mu AS (SELECT sum(v * m) / sum(m) AS mu FROM l)"


# --- Fixtures ----------------------------------------------------------------------------------------------------------------------------


class Setting:
    """A grid over one source, its items probed. The source is read once: counts by item are kept as files, and so is the grid, which is linear in them."""

    def __init__(self, spark: SparkSession, sf_dir: str, source=tables.parts, spec: GridSpec = SPEC):
        self.truth = keep(source(spark, sf_dir).groupBy("item").agg(F.sum("c").alias("c")), "counts")
        self.tuples = self.truth
        self.grid = store.kept(grid.build_grid(self.truth, spec))
        self.items = self.truth.select("item")
        self.spec = spec

    @property
    def probed(self) -> DataFrame:
        return grid.probe(self.items, self.grid)
