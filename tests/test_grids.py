import numpy as np
import pytest
from pyspark.sql import functions as F

from tallygrid.functions.hashing import GridSpec
from tallygrid.functions.statistics import t_median, t_min
from tallygrid.operators import errors, estimates, grid, variants
from tallygrid.sources import tables


def counts(spark, rows):
    return spark.createDataFrame(rows, "item long, c long")


def as_dict(g):
    return {(r["rep"], r["idx"]): r["v"] for r in g.df.collect() if r["v"]}


@pytest.mark.parametrize("family", ["xx64", "poly4", "md5"])
def test_hash_spread(spark, family):
    spec = GridSpec(2, 512, family)
    load = grid.cell_load(spark.range(2000).withColumnRenamed("id", "item"), spec).collect()
    for rep in range(2):
        own = np.zeros(512)
        for r in load:
            if r["rep"] == rep:
                own[r["idx"]] = r["load"]
        assert 0.8 < own.var() / own.mean() < 1.2


def test_empty_single_and_absent(spark):
    spec = GridSpec(3, 1, "poly4")
    empty = grid.build_grid(counts(spark, []), spec)
    assert grid.probe(counts(spark, [(5, 1)]).select("item"), empty).first()["v"] == [0, 0, 0]
    one = grid.build_grid(counts(spark, [(7, 2), (7, 3)]), spec)
    assert as_dict(one) == {(0, 0): 5, (1, 0): 5, (2, 0): 5}


def test_linear(spark, sf):
    t, spec = tables.parts(spark, sf), GridSpec(4, 50)
    whole = as_dict(grid.build_grid(t, spec))
    low, high = (grid.build_grid(t.where(c), spec) for c in ("item % 2 = 0", "item % 2 = 1"))
    assert as_dict(grid.merge(low, high)) == whole
    assert as_dict(grid.subtract(grid.build_grid(t, spec), t.where("item % 2 = 1"))) == as_dict(low)
    assert as_dict(grid.build_grid(t.repartition(7), spec)) == whole == as_dict(grid.build_grid_dense(t.repartition(3), spec))
    assert sum(v for (rep, _), v in whole.items() if rep == 2) == t.count()
    with pytest.raises(ValueError):
        grid.merge(low, grid.build_grid(t, GridSpec(4, 51)))


def test_probe_plan_is_native(spark, sf):
    t, spec = tables.parts(spark, sf), GridSpec(4, 50)
    plan = estimates.classical(grid.probe(t.select("item"), grid.build_grid(t, spec)))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("BroadcastHashJoin") == 4 and "SortMergeJoin" not in plan and "Python" not in plan


def test_probe_by_shuffle_agrees(spark, sf, monkeypatch):
    t, spec = tables.parts(spark, sf), GridSpec(4, 50)
    g, items = grid.build_grid(t, spec), t.select("item").distinct()
    near = {r["item"]: r["v"] for r in grid.probe(items, g).collect()}
    monkeypatch.setattr(grid, "BROADCAST_CELLS", 1)
    assert {r["item"]: r["v"] for r in grid.probe(items, g).collect()} == near


def test_unbiased_and_covering(spark):
    """Mean error of the estimate that is not cut off is near 0, and intervals cover, over many salts."""
    rng = np.random.default_rng(0)
    c = np.minimum(rng.zipf(2.0, 2000), 2000)
    df = counts(spark, [(i, int(x)) for i, x in enumerate(c)]).cache()
    bias, covered = [], []
    for seed in range(12):
        g = grid.build_grid(df, GridSpec(4, 200, "xx64", seed))
        f = estimates.grid_law(g)
        e = estimates.debiased_min(grid.probe(df, g), f, 4, 0.9, "exact", truncate=False).join(df, "item").toPandas()
        bias.append((e.est - e.c).mean())
        covered.append(((e.lo <= e.c) & (e.c <= e.hi)).mean())
        assert (e.hi >= e.c).all()
    assert abs(np.mean(bias)) < 3 * np.std(bias) / np.sqrt(12) + 0.3
    assert np.mean(covered) > 0.9 - 3 * np.std(covered) / np.sqrt(12) - 0.005


def test_translation(spark):
    v = spark.createDataFrame([(1, [5, 9, 2, 7]), (2, [3, 3, 8, 1])], "item int, v array<long>")
    for statistic in (t_min, t_median):
        a = [r["est"] for r in estimates.classical(v, statistic).orderBy("item").collect()]
        b = [r["est"] for r in estimates.classical(v.withColumn("v", F.transform("v", lambda x: x + 10)), statistic).orderBy("item").collect()]
        assert b == [x + 10 for x in a]


def test_dyadic_cover():
    for low, high in ((0, 63), (1, 1), (5, 37), (31, 32)):
        found = []
        for x in grid.dyadic_cover(low, high, 6):
            level, prefix = divmod(x, 64)
            found += range(prefix << level, (prefix + 1) << level)
        assert sorted(found) == list(range(low, high + 1))


def test_best_markov_width():
    from tallygrid.operators.estimates import markov_best, markov_width

    k, width = markov_best(1e6, 10_000, 0.95)
    assert width == pytest.approx(min(markov_width(1e6, 10_000 / x, x, 0.95) for x in np.linspace(100, 9_000, 20_000)), rel=1e-5)
    assert markov_width(1e6, 10_000 / k, k, 0.95) == pytest.approx(width)


def test_conservative_is_an_upper_bound(spark, sf):
    t = tables.table(spark, sf, "events").select(F.col("user_id").alias("item"), F.lit(1).cast("long").alias("c"), (F.col("event_id") % 3).alias("batch"))
    g = variants.conservative_batches(t, GridSpec(3, 20), 3)
    plain = grid.build_grid(t, GridSpec(3, 20))
    truth = t.groupBy("item").agg(F.sum("c").alias("c"))
    rows = grid.probe(truth, g).join(grid.probe(truth, plain).select("item", F.col("v").alias("w")), "item").collect()
    assert all(r["c"] <= min(r["v"]) <= min(r["w"]) for r in rows)


def test_law_without_own():
    law = errors.Law(np.asarray([0.0, 1.0, 5.0]), np.asarray([3, 2, 1]))
    left = law.without(np.asarray([0.0, 5.0]))
    assert left.x.tolist() == [0, 1] and left.m.tolist() == [2, 2] and left.quantile(0.5) == 0 and left.quantile(0.51) == 1
