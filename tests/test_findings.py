"""What a review found: whole jobs at size, and queries that read their tables."""

import tracemalloc

import numpy as np
import pytest
from pyspark.sql import functions as F

from tallygrid.functions.hashing import GridSpec
from tallygrid.operators import grid, joint, relational as ops, tuning
from tallygrid.operators.errors import Law
from tallygrid.plans.registry import QUERIES
from tallygrid.sources import formats, tables
from tallygrid.streaming import grids as streams


def test_widths_take_no_room_for_large_counters():
    g = np.random.default_rng(0)
    x, m = np.unique(g.negative_binomial(3, 0.05, 5000), return_counts=True)
    f = Law(x.astype(float), m)
    told = {(d, p): w for d, p, w in tuning.depth_widths(tuning.mass(f, 64 * (int(x.max()) + 1)), [1, 2, 4], [0.9, 0.95])}
    assert tuning.split_widths(f, [1, 2, 4], [0.9, 0.95]) == told
    steps = tuning.split_widths(f, [1, 2, 4], [0.9, 0.95], most=200)
    assert all(0.9 * told[k] - 8 <= steps[k] <= told[k] for k in told)
    tracemalloc.start()
    heavy = Law(np.append(f.x, 5e7), np.append(f.m, 1))
    assert all(abs(w - told[k]) <= 2 for k, w in tuning.split_widths(heavy, [1, 2, 4], [0.9, 0.95]).items())
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 20_000_000


def test_a_text_is_split_once_for_all_its_ngrams(spark, sf):
    df = spark.createDataFrame([("a b c d",), ("a b",), (None,), ("",)], "text string")
    found = df.select("text", ops.fn_ngrams(F.split("text", " "), 3).alias("g"))
    assert [r["g"] for r in found.collect()] == [["a b c", "b c d"], [], [], []]
    for plan in (found.select(F.size("g"), F.get("g", F.lit(0))), tables.ngrams(spark, sf, 2), tables.ngrams(spark, sf, 2, "th")):
        assert plan._jdf.queryExecution().optimizedPlan().toString().count("split(") == 1


def test_top_items_that_fell_behind_come_back(spark, tmp_path):
    """Two cells: the first batch's many small items share one with what the last batch makes largest. A merging batch may run twice."""
    spec = GridSpec(1, 2, "poly4")
    rows = spark.range(1, 400).select(F.col("id").alias("item"), grid.cell(F.col("id"), 0, spec).alias("x"))
    ones, zeros = ([r["item"] for r in rows.where(F.col("x") == x).orderBy("item").collect()] for x in (1, 0))
    batches = [[(i, 1) for i in ones[1:]] + [(i, 9) for i in zeros], [(zeros[0], 5)], [(ones[0], 10_000)], [(zeros[0], 1)]]
    top = streams.TopItems(str(tmp_path), spec, 3, compact=2)
    for k, batch in enumerate(batches):
        for _ in range(2):
            top.absorb(spark.createDataFrame(batch, "item long, c long"), k)
    est = 10_000 + len(ones) - 1
    assert [tuple(r) for r in top.items(spark).collect()] == [(i, est) for i in ones[:3]]


def test_least_squares_are_exact_for_more_items_than_one_grid_has_cells(spark):
    counts = spark.range(3000).select(F.col("id").alias("item"), (F.pmod(F.xxhash64("id"), F.lit(1000)) + 1).alias("c"))
    rows = joint.least_squares_blocks(counts, GridSpec(4, 200, "poly4")).join(counts, "item").collect()
    assert len(rows) == 3000 and all(abs(r["est"] - r["c"]) < 1e-7 for r in rows)
    assert joint.least_squares_blocks(counts.where("item < 0"), GridSpec(4, 200, "poly4")).count() == 0


def bytes_read(spark) -> int:
    return sum(e.totalInputBytes() for e in [spark.sparkContext._jsc.sc().statusStore().executorList(False).apply(0)])


#: Queries that once worked on data of their own.
READING = ["w09_shapes", "regimes", "growth_study", "src_rate", "src_range", "src_power_law", "space_cells", "size_classic", "logconcave_condition", "beta_quantile", "ci_classic_guarantee"]


@pytest.mark.parametrize("name", READING)
def test_reads_a_table(spark, name):
    before = bytes_read(spark)
    assert QUERIES[name](spark, "/root/testdata/sf0.01").count() > 0 and bytes_read(spark) > before


def test_the_power_law_source_and_a_tables_items_have_the_same_counts(spark):
    source = formats.power_law_source(spark, items=300, alpha=2.5, offset=2.0, most=2000, seed=3, slice=70)
    own = formats.power_law_of(spark.range(300).withColumnRenamed("id", "item"), 2.5, 2.0, 2000)
    assert sorted(map(tuple, source.collect())) == sorted(map(tuple, own.collect()))


def test_the_minimum_wins_where_the_density_starts_high(spark):
    rows = {(r["a"], r["r"]): r for r in QUERIES["regimes"](spark, "/root/testdata/sf0.01").collect()}
    assert len(rows) == 9 and all(rows[a, 64]["min"] < rows[a, 64]["mean"] for a in (0.5, 1.0))
    fall = [rows[a, 4]["min"] / rows[a, 64]["min"] for a in (0.5, 1.0, 2.0)]  # about 16^(1 / a)
    assert fall[0] > 2 * fall[1] > 4 * fall[2] and 1.5 < rows[1.0, 4]["mean"] / rows[1.0, 64]["mean"] < 8


def test_heavy_tails_spoil_the_mean_alone(spark):
    rows = {(r["shape"], r["offset"], r["r"], r["method"]): r["rel_eff"] for r in QUERIES["w09_shapes"](spark, "/root/testdata/sf0.01").collect()}
    assert len(rows) == 96 and rows["words", 0.0, 16, "mean"] > 2 and rows["parts", 3.0, 16, "mean"] < 1.3 < rows["parts", 3.0, 16, "min"]
