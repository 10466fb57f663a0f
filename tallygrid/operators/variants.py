"""Earlier estimators to compare with, and grids of other kinds."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.density import convolved
from ..functions.hashing import GridSpec, cell, sign
from ..functions.statistics import t_median, t_min
from .grid import CounterGrid, cell_load, cells_of, incidence, probe


def zero_probe_min(probed: DataFrame, absent: DataFrame) -> DataFrame:
    """The minimum less the mean minimum of items known to be absent."""
    bias = absent.agg(F.avg(t_min(F.col("v"))).alias("bias"))
    return probed.crossJoin(F.broadcast(bias)).select("item", F.greatest(F.lit(0.0), t_min(F.col("v")) - F.col("bias")).alias("est"))


def noise_debiased(probed: DataFrame, statistic, noise: float) -> DataFrame:
    """The statistic of own counters less that of plain noise counters."""
    return probed.select("item", F.greatest(F.lit(0.0), statistic(F.col("v")) - F.lit(noise)).alias("est"))


def collision_debiased(items: DataFrame, universe: DataFrame, grid: CounterGrid, statistic=t_median, beta: float | None = None) -> DataFrame:
    """Each own counter less beta for every other item of the universe in it; beta: the mean count of an item, unless given."""
    if beta is None:
        n_total, d = grid.df.where("rep = 0").agg(F.sum("v")).first()[0], universe.count()
        beta = n_total / d
    load = cell_load(universe, grid.spec)
    own = incidence(items, grid.spec).join(grid.df, ["rep", "idx"], "left").join(load, ["rep", "idx"], "left")
    cleared = F.coalesce(F.col("v"), F.lit(0)).cast("double") - F.lit(float(beta)) * (F.coalesce(F.col("load"), F.lit(1)) - 1)
    return own.groupBy("item").agg(F.collect_list(cleared).alias("v")).select("item", statistic(F.col("v")).alias("est"))


def build_signed(df: DataFrame, spec: GridSpec) -> CounterGrid:
    """A second hash gives each item +1 or -1, so that errors are even around 0."""
    spread = df.select(F.explode(F.array(*[F.struct(F.lit(a).alias("rep"), cell(F.col("item"), a, spec).alias("idx"), (sign(F.col("item"), a, spec) * F.col("c")).alias("v")) for a in range(spec.r)])).alias("x"))
    return CounterGrid(spread.groupBy("x.rep", "x.idx").agg(F.sum("x.v").alias("v")), spec)


def probe_signed(items: DataFrame, grid: CounterGrid) -> DataFrame:
    """Own counters, each times the item's sign."""
    signs = F.array(*[sign(F.col("item"), a, grid.spec) for a in range(grid.spec.r)])
    return probe(items, grid).withColumn("v", F.zip_with("v", signs, lambda v, s: v * s))


def conservative_batches(df: DataFrame, spec: GridSpec, batches: int) -> CounterGrid:
    """Conservative updates, batch by batch (column `batch`, from 0): a batch raises an item's cells no higher than its smallest cell plus its batch count.

    Inside a batch all items see the grid as it was before, so a batch is one probe and one grouping; every cell stays at or above the true count of each of its
    items.
    """
    grid = None
    for b in range(batches):
        grid = raise_cells(df.where(F.col("batch") == b), grid, spec)
    return grid


def raise_cells(df: DataFrame, grid: CounterGrid | None, spec: GridSpec) -> CounterGrid:
    """The grid (None: empty) after one batch of conservative updates."""
    own = df.groupBy("item").agg(F.sum("c").alias("c"))
    low = own.withColumn("low", F.lit(0).cast("long")) if grid is None else probe(own, grid).withColumn("low", F.array_min("v")).drop("v")
    raised = low.select(F.explode(cells_of(F.col("item"), spec)).alias("x"), (F.col("low") + F.col("c")).alias("v")).select("x.rep", "x.idx", "v")
    raised = raised if grid is None else raised.unionByName(grid.df)
    return CounterGrid(raised.groupBy("rep", "idx").agg(F.max("v").alias("v")), spec)


def build_decayed(df: DataFrame, spec: GridSpec, age_days: Column, half_life: float, scale: int = 1_000_000) -> CounterGrid:
    """Counts weighted by 2^(-age / half-life), in whole parts of 1 / scale so that sums don't depend on their order."""
    weight = F.round(F.col("c") * F.lit(scale) * F.pow(F.lit(2.0), -age_days / F.lit(float(half_life)))).cast("long")
    spread = df.select(F.explode(cells_of(F.col("item"), spec)).alias("x"), weight.alias("w"))
    return CounterGrid(spread.groupBy("x.rep", "x.idx").agg(F.sum("w").alias("v")), spec)


def build_distinct(df: DataFrame, spec: GridSpec, exact: bool = True) -> CounterGrid:
    """Cells count the distinct values of `element` of their items: exactly, or by Spark's cardinality sketch with bounded cells."""
    spread = df.select(F.explode(cells_of(F.col("item"), spec)).alias("x"), F.struct("item", "element").alias("e"))
    many = F.countDistinct("e") if exact else F.approx_count_distinct("e", 0.02)
    return CounterGrid(spread.groupBy("x.rep", "x.idx").agg(many.alias("v")), spec)


def conservative_serial(df: DataFrame, spec: GridSpec) -> CounterGrid:
    """The order-dependent original, tuple by tuple in the order of `seq`; for small inputs, as it can't be split."""
    import pandas as pd

    placed = df.select(F.lit(0).alias("one"), "seq", "c", *[cell(F.col("item"), a, spec).alias(f"i{a}") for a in range(spec.r)])

    def run(part: pd.DataFrame) -> pd.DataFrame:
        grid: dict[tuple[int, int], int] = {}
        for row in part.drop(columns="one").sort_values("seq").itertuples(index=False):
            own = list(enumerate(row[2:]))
            to = min(grid.get(x, 0) for x in own) + row[1]
            for x in own:
                grid[x] = max(grid.get(x, 0), to)
        return pd.DataFrame([(a, i, v) for (a, i), v in grid.items()], columns=["rep", "idx", "v"])

    return CounterGrid(placed.groupBy("one").applyInPandas(run, "rep int, idx long, v long"), spec)


def inner_products(u: CounterGrid, v: CounterGrid) -> DataFrame:
    """(rep, product, unbiased) for two grids of one spec: U V, and k / (k - 1) (U V - sum U sum V / k)."""
    k = u.spec.k
    both = u.df.withColumnRenamed("v", "u").join(v.df, ["rep", "idx"], "full_outer").fillna(0, ["u", "v"])
    sums = both.groupBy("rep").agg(F.sum(F.col("u") * F.col("v")).alias("product"), F.sum("u").alias("su"), F.sum("v").alias("sv"))
    unbiased = F.lit(k / (k - 1)) * (F.col("product").cast("double") - F.col("su").cast("double") * F.col("sv").cast("double") / F.lit(float(k)))
    return sums.select("rep", "product", unbiased.alias("unbiased"))


def surrogate_products(u: CounterGrid, v: CounterGrid, shifts: int) -> DataFrame:
    """(rep, shift, product): sums over cells of U_i V_(i+s), which hold no common item: draws of the error of U V."""
    k = u.spec.k
    moved = v.df.select("rep", "idx", "v", F.explode(F.sequence(F.lit(1), F.lit(shifts))).alias("shift")).withColumn("idx", F.pmod(F.col("idx") - F.col("shift"), F.lit(k)))
    return u.df.withColumnRenamed("v", "u").join(moved, ["rep", "idx"]).groupBy("rep", "shift").agg(F.sum(F.col("u") * F.col("v")).alias("product"))


def product_law(x: np.ndarray, m: np.ndarray, y: np.ndarray, n: np.ndarray, bins: int = 4096) -> tuple[float, np.ndarray, np.ndarray]:
    """(share of zero, values, shares) of the product of two independent non-negative laws: logs add, so their histograms are convolved."""
    zero = 1 - m[x > 0].sum() / m.sum() * n[y > 0].sum() / n.sum()
    (a, p), (b, q) = ((np.log(v[v > 0]), w[v > 0] / w[v > 0].sum()) for v, w in ((x, m), (y, n)))
    if not len(a) or not len(b):
        return 1.0, np.zeros(0), np.zeros(0)
    step = max(np.ptp(a), np.ptp(b), 1e-9) / (bins - 1)
    h, g = (np.bincount(np.rint((v - v.min()) / step).astype(int), weights=w) for v, w in ((a, p), (b, q)))
    both = convolved(h, g)
    return float(zero), np.exp(a.min() + b.min() + step * np.arange(len(both))), (1 - zero) * both


def coordinated_sample(df: DataFrame, share: float, seed: int = 5) -> DataFrame:
    """All tuples of the items whose hash is in the share: the items' number falls, their counts stay."""
    digest = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col("item").cast("string")).cast("binary")), 1, 13), 16, 10).cast("long")
    return df.where(digest < F.lit(int(share * (1 << 52))))


def bottom_k_sample(df: DataFrame, k: int, seed: int = 5) -> DataFrame:
    """All tuples of the k items with the smallest hashes."""
    digest = F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col("item").cast("string")).cast("binary")), 1, 13)
    chosen = df.select("item").distinct().withColumn("h", digest).orderBy("h", "item").limit(k).select("item")
    return df.join(chosen, "item", "left_semi")


def top_items(df: DataFrame, most: int) -> DataFrame:
    """(item, c): the items with the largest counts; ties go to the smaller item."""
    return df.groupBy("item").agg(F.sum("c").alias("c")).orderBy(F.desc("c"), "item").limit(most)


def running(df: DataFrame, value: str, order: str) -> DataFrame:
    return df.withColumn("cum", F.sum(value).over(Window.orderBy(order).rowsBetween(Window.unboundedPreceding, 0)))
