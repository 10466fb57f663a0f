"""The law of a counter's error, read off the grid itself."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .grid import CounterGrid, incidence

#: Atoms up to which a law may be held on the driver, 16 bytes each; more are gathered to so many of equal mass.
MOST_ATOMS = 10_000_000
#: Steps of the running sums' coarse level in each factor of two.
STEPS = 1024


def cumulated(df: DataFrame, *sums: str, order: str = "v") -> DataFrame:
    """Add `cum` (one column), or cum_<name> of each column: its running sum by `order`, in two levels.

    The coarse level is the logarithm of the value, which keeps the order; it has STEPS rows for each factor of two, a bounded number. So no task holds
    all rows however many there are.
    """
    level = (F.signum(order) * F.floor(F.log2(F.abs(F.col(order).cast("double")) + 1) * STEPS)).cast("long")
    rows = df.withColumn("__level", level)
    earlier = Window.orderBy("__level").rowsBetween(Window.unboundedPreceding, -1)
    starts = rows.groupBy("__level").agg(*[F.sum(c).alias(f"__{c}") for c in sums]).select("__level", *[F.coalesce(F.sum(f"__{c}").over(earlier), F.lit(0)).alias(f"__{c}") for c in sums])
    inside = Window.partitionBy("__level").orderBy(order).rowsBetween(Window.unboundedPreceding, 0)
    name = lambda c: "cum" if len(sums) == 1 else f"cum_{c}"
    found = rows.select("*", *[F.sum(c).over(inside).alias(f"__in_{c}") for c in sums]).join(F.broadcast(starts), "__level")
    return found.select(*df.columns, *[(F.col(f"__in_{c}") + F.col(f"__{c}")).alias(name(c)) for c in sums])


def error_hist(grid: CounterGrid, without: DataFrame | None = None) -> DataFrame:
    """(v, m, cum): how many of the r x k counters have each value, empty cells included; `without`: leave out the own cells of these items."""
    spec, cells = grid.spec, grid.df
    total = F.lit(spec.cells)
    if without is not None:
        own = incidence(without, spec).select("rep", "idx").distinct()
        cells = cells.join(own, ["rep", "idx"], "left_anti")
        n = own.agg(F.count("*").alias("own"))
        zero = cells.agg(F.count("*").alias("n")).join(n).select(F.lit(0).cast("long").alias("v"), (total - F.col("n") - F.col("own")).alias("m"))
    else:
        zero = cells.agg(F.count("*").alias("n")).select(F.lit(0).cast("long").alias("v"), (total - F.col("n")).alias("m"))
    by_value = cells.groupBy("v").agg(F.count("*").alias("m")).unionByName(zero).groupBy("v").agg(F.sum("m").cast("long").alias("m")).where("m > 0")
    return cumulated(by_value, "m")


@dataclass(frozen=True)
class Law:
    """A weighted empirical law: rising values x with multiplicities m."""

    x: np.ndarray
    m: np.ndarray

    @property
    def n(self) -> int:
        return int(self.m.sum())

    def quantile(self, p: float) -> float:
        """The ceil(p n)-th smallest value."""
        rank = min(self.n, max(1, int(np.ceil(p * self.n - 1e-9))))
        return float(self.x[np.searchsorted(np.cumsum(self.m), rank)])

    def cdf(self, y: float, left: bool = False) -> float:
        return float(self.m[: np.searchsorted(self.x, y, side="left" if left else "right")].sum() / self.n)

    def mean(self) -> float:
        return float(self.x @ self.m / self.n)

    def order_mean(self, i: int, r: int, mode: str = "exact") -> float:
        """Mean of the i-th smallest of r draws: `exact`, `plugin` (quantile i / (r + 1)) or `rank` (quantile i / r)."""
        if mode != "exact":
            return self.quantile(i / (r + 1) if mode == "plugin" else i / r)
        at = np.cumsum(self.m) / self.n
        g = sum(math.comb(r, j) * at**j * (1 - at) ** (r - j) for j in range(i, r + 1)) if i > 1 else 1 - (1 - at) ** r
        return float(self.x @ np.diff(g, prepend=0.0))

    def without(self, values: np.ndarray) -> Law:
        """The law without some of its atoms, one for each value."""
        m = self.m.copy()
        np.subtract.at(m, np.searchsorted(self.x, values), 1)
        return Law(self.x[m > 0], m[m > 0])

    def draws(self, size: tuple[int, ...], seed: int) -> np.ndarray:
        return np.random.default_rng(seed).choice(self.x, size=size, p=self.m / self.n)

    def ks(self, other: Law) -> float:
        at = np.union1d(self.x, other.x)
        f = lambda law: np.append(0, np.cumsum(law.m))[np.searchsorted(law.x, at, side="right")] / law.n
        return float(np.abs(f(self) - f(other)).max())


def law(hist: DataFrame, most: int = MOST_ATOMS) -> Law:
    """The histogram (v, m) on the driver. It has one row for each distinct value; beyond `most` of them, neighbours are gathered on the cluster to about
    `most` means of equal mass, which moves no quantile by more than the share of one."""
    hist = hist.select("v", "m")
    rows, total = hist.agg(F.count("*"), F.sum("m")).first()
    if rows > most:
        part = F.floor((F.col("cum") - F.col("m")).cast("double") / F.lit(float(total)) * most)
        hist = cumulated(hist, "m").groupBy(part.alias("part")).agg((F.sum(F.col("v").cast("double") * F.col("m")) / F.sum("m")).alias("v"), F.sum("m").alias("m"))
    found = hist.select(F.col("v").cast("double").alias("v"), F.col("m").cast("long").alias("m")).toArrow()
    x, m = (found.column(c).to_numpy() for c in ("v", "m"))
    order = np.argsort(x, kind="stable")
    return Law(x[order], m[order])


def columns(grid: CounterGrid) -> DataFrame:
    """(idx, v): the r counters at each place, empty ones included: k samples of r counters."""
    spec = grid.spec
    wide = grid.df.groupBy("idx").agg(*[F.sum(F.when(F.col("rep") == a, F.col("v")).otherwise(0)).alias(f"v{a}") for a in range(spec.r)])
    every = grid.df.sparkSession.range(spec.k).select(F.col("id").alias("idx")).join(wide, "idx", "left")
    return every.select("idx", F.array(*[F.coalesce(F.col(f"v{a}"), F.lit(0)).cast("long") for a in range(spec.r)]).alias("v"))


def column_hist(grid: CounterGrid, statistic) -> DataFrame:
    """(v, m, cum): the law of a statistic over the grid's columns."""
    values = columns(grid).select(statistic(F.col("v")).alias("v")).groupBy("v").agg(F.count("*").alias("m"))
    return cumulated(values, "m")


def hist_quantile(hist: DataFrame, p: Column) -> DataFrame:
    """(p, q): the value of rank ceil(p n)."""
    n = F.broadcast(hist.agg(F.sum("m").alias("n")))
    return hist.crossJoin(n).where(F.col("cum") >= F.ceil(p * F.col("n"))).agg(F.min("v").alias("q"))


def ks(self, other: Law) -> float:
        at = np.union1d(self.x, other.x)
        f = lambda law: np.append(0, np.cumsum(law.m))[np.searchsorted(law.x, at, side="right")] / law.n
        return float(np.abs(f(self) - f(other)).max())


def law(hist: DataFrame, most: int = MOST_ATOMS) -> Law:
    """The histogram (v, m) on the driver. It has one row for each distinct value; beyond `most` of them, neighbours are gathered on the cluster to about
    `most` means of equal mass, which moves no quantile by more than the share of one."""
    hist = hist.select("v", "m")
    rows, total = hist.agg(F.count("*"), F.sum("m")).first()
    if rows > most:
        part = F.floor((F.col("cum") - F.col("m")).cast("double") / F.lit(float(total)) * most)
        hist = cumulated(hist, "m").groupBy(part.alias("part")).agg((F.sum(F.col("v").cast("double") * F.col("m")) / F.sum("m")).alias("v"), F.sum("m").alias("m"))
    found = hist.select(F.col("v").cast("double").alias("v"), F.col("m").cast("long").alias("m")).toArrow()
    x, m = (found.column(c).to_numpy() for c in ("v", "m"))
    order = np.argsort(x, kind="stable")
    return Law(x[order], m[order])


def columns(grid: CounterGrid) -> DataFrame:
    """(idx, v): the r counters at each place, empty ones included: k samples of r counters."""
    spec = grid.spec
    wide = grid.df.groupBy("idx").agg(*[F.sum(F.when(F.col("rep") == a, F.col("v")).otherwise(0)).alias(f"v{a}") for a in range(spec.r)])
    every = grid.df.sparkSession.range(spec.k).select(F.col("id").alias("idx")).join(wide, "idx", "left")
    return every.select("idx", F.array(*[F.coalesce(F.col(f"v{a}"), F.lit(0)).cast("long") for a in range(spec.r)]).alias("v"))


def column_hist(grid: CounterGrid, statistic) -> DataFrame:
    """(v, m, cum): the law of a statistic over the grid's columns."""
    values = columns(grid).select(statistic(F.col("v")).alias("v")).groupBy("v").agg(F.count("*").alias("m"))
    return cumulated(values, "m")


def hist_quantile(hist: DataFrame, p: Column) -> DataFrame:
    """(p, q): the value of rank ceil(p n)."""
    n = F.sum("m").over(Window.partitionBy())
    return hist.withColumn("n", n).where(F.col("cum") >= F.ceil(p * F.col("n"))).agg(F.min("v").alias("q"))


def ks(a: DataFrame, b: DataFrame) -> DataFrame:
    """(ks): the largest gap between two histograms' distribution functions."""
    both = a.select("v", F.col("m").alias("ma")).join(b.select("v", F.col("m").alias("mb")), "v", "full_outer").fillna(0, ["ma", "mb"])
    every = F.broadcast(both.agg(F.sum("ma").alias("na"), F.sum("mb").alias("nb")))
    gap = F.col("cum_ma") / F.col("na") - F.col("cum_mb") / F.col("nb")
    return cumulated(both, "ma", "mb").crossJoin(every).select(F.abs(gap).alias("gap")).agg(F.max("gap").alias("ks"))
