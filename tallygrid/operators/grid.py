"""Counter grids: building, adding, weighing, folding, probing."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import GridSpec, cell

#: Cells up to which a grid may be broadcast for probing. A joined cell takes about 40 bytes in the hash table of its replicate, so all tables together are 160 MB.
BROADCAST_CELLS = 4_000_000
#: Cells of one chunk of a dense partial grid.
CHUNK = 1 << 16
#: Chunks that one task adds up at a time.
FAN = 64


@dataclass(frozen=True)
class CounterGrid:
    """Long form (rep, idx, v); cells that are absent hold 0."""

    df: DataFrame
    spec: GridSpec


def tuples(df: DataFrame, item: Column, count: Column | None = None) -> DataFrame:
    """(item, c) of the rows with an item; a null count counts as 0."""
    return df.select(item.alias("item"), (F.lit(1) if count is None else F.coalesce(count, F.lit(0))).cast("long").alias("c")).where("item IS NOT NULL")


def cells_of(item: Column, spec: GridSpec) -> Column:
    """Array of (rep, idx), one for each replicate."""
    return F.array(*[F.struct(F.lit(a).alias("rep"), cell(item, a, spec).alias("idx")) for a in range(spec.r)])


def build_grid(df: DataFrame, spec: GridSpec) -> CounterGrid:
    """Grid of (item, c) rows: sums by cell, combined in each task before the one shuffle."""
    spread = df.select(F.explode(cells_of(F.col("item"), spec)).alias("x"), "c").select("x.rep", "x.idx", "c")
    return CounterGrid(spread.groupBy("rep", "idx").agg(F.sum("c").alias("v")), spec)


def build_grid_dense(df: DataFrame, spec: GridSpec) -> CounterGrid:
    """The same grid by dense partial sums: a task holds r x k numbers and sends chunks once, whatever its rows.

    With many rows for each cell and task, rows sent shrink from rows x r to r x k / CHUNK per task.
    """
    indexed = df.select(*[cell(F.col("item"), a, spec).alias(f"i{a}") for a in range(spec.r)], "c")
    schema = "rep int, at long, task long, cells binary"

    def add_up(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = np.zeros((spec.r, spec.k), dtype=np.int64)
        for batch in batches:
            c = batch.column("c").to_numpy()
            for a in range(spec.r):
                np.add.at(sums[a], batch.column(f"i{a}").to_numpy(), c)
        task = TaskContext.get().partitionId()
        for a in range(spec.r):
            for at in range(0, spec.k, CHUNK):
                part = sums[a, at : at + CHUNK]
                if part.any():
                    yield pa.RecordBatch.from_arrays([pa.array([a], pa.int32()), pa.array([at], pa.int64()), pa.array([task], pa.int64()), pa.array([part.tobytes()], pa.binary())], names=["rep", "at", "task", "cells"])

    def merged(group: pa.Table) -> pa.Table:
        total = sum(np.frombuffer(b, dtype=np.int64) for b in group.column("cells").to_pylist())
        return group.slice(0, 1).set_column(3, "cells", pa.array([total.tobytes()], pa.binary()))

    def spread(group: pa.Table) -> pa.Table:
        total = sum(np.frombuffer(b, dtype=np.int64) for b in group.column("cells").to_pylist())
        idx = np.flatnonzero(total)
        return pa.table({"rep": pa.array(np.full(len(idx), group.column("rep")[0].as_py()), pa.int32()), "idx": idx + group.column("at")[0].as_py(), "v": total[idx]})

    partial = indexed.mapInArrow(add_up, schema)
    # Chunks of FAN tasks are added at a time, so a task holds FAN chunks whatever the number of tasks.
    tasks = indexed.rdd.getNumPartitions()
    while tasks > FAN:
        partial = partial.withColumn("task", F.floor(F.col("task") / FAN)).groupBy("rep", "at", "task").applyInArrow(merged, schema)
        tasks = -(-tasks // FAN)
    return CounterGrid(partial.groupBy("rep", "at").applyInArrow(spread, "rep int, idx long, v long"), spec)


def merge(*grids: CounterGrid) -> CounterGrid:
    """The grid of all inputs together: grids are linear."""
    if len({g.spec for g in grids}) != 1:
        raise ValueError("only grids of one spec can be added")
    df = grids[0].df
    for g in grids[1:]:
        df = df.unionByName(g.df)
    return CounterGrid(df.groupBy("rep", "idx").agg(F.sum("v").alias("v")), grids[0].spec)


def scale(grid: CounterGrid, weight: int) -> CounterGrid:
    return CounterGrid(grid.df.withColumn("v", F.col("v") * F.lit(weight)), grid.spec)


def subtract(grid: CounterGrid, known: DataFrame) -> CounterGrid:
    """The grid without the (item, c) rows of `known`."""
    return merge(grid, scale(build_grid(known, grid.spec), -1))


def fold(grid: CounterGrid, factor: int) -> CounterGrid:
    """The grid of width k / factor over the same data."""
    if grid.spec.k % factor:
        raise ValueError("the factor must divide the width")
    narrow = replace(grid.spec, k=grid.spec.k // factor)
    return CounterGrid(grid.df.groupBy("rep", F.pmod("idx", F.lit(narrow.k)).alias("idx")).agg(F.sum("v").alias("v")), narrow)


def probe(items: DataFrame, grid: CounterGrid) -> DataFrame:
    """`items` and `v`, the array of an item's own counters in the order of replicates.

    One broadcast join per replicate while the grid's size, r x k by its spec, is bounded; else rows meet cells by shuffling.
    """
    spec = grid.spec
    if spec.cells <= BROADCAST_CELLS:
        out = items
        for a in range(spec.r):
            own = grid.df.where(F.col("rep") == a).select(F.col("idx").alias(f"__i{a}"), F.col("v").alias(f"__v{a}"))
            out = out.withColumn(f"__i{a}", cell(F.col("item"), a, spec)).join(F.broadcast(own), f"__i{a}", "left")
        v = F.array(*[F.coalesce(F.col(f"__v{a}"), F.lit(0).cast("long")) for a in range(spec.r)])
        return out.select(*items.columns, v.alias("v"))
    met = incidence(items.select("item").distinct(), spec).join(grid.df, ["rep", "idx"], "left")
    v = F.transform(F.sort_array(F.collect_list(F.struct("rep", F.coalesce("v", F.lit(0)).alias("v")))), lambda x: x["v"])
    return items.join(met.groupBy("item").agg(v.alias("v")), "item")


def incidence(items: DataFrame, spec: GridSpec) -> DataFrame:
    """(item, rep, idx): the ones of the projection matrix."""
    return items.select("item", F.explode(cells_of(F.col("item"), spec)).alias("x")).select("item", "x.rep", "x.idx")


def cell_load(items: DataFrame, spec: GridSpec) -> DataFrame:
    """(rep, idx, load): how many of `items` share each cell."""
    return incidence(items, spec).groupBy("rep", "idx").agg(F.count("*").alias("load"))


def true_errors(grid: CounterGrid, truth: DataFrame) -> DataFrame:
    """(item, rep, error): own counters less the true count."""
    probed = probe(truth, grid).select("item", "c", F.posexplode("v").alias("rep", "v"))
    return probed.select("item", "rep", (F.col("v") - F.col("c")).alias("error"))


def dyadic(df: DataFrame, levels: int) -> DataFrame:
    """(item, c) of all dyadic ranges that hold each integer item: item = level * 2^levels + prefix."""
    spread = df.select(F.explode(F.sequence(F.lit(0), F.lit(levels - 1))).alias("l"), "item", "c")
    return spread.select((F.col("l") * (1 << levels) + F.expr("shiftright(item, l)")).cast("long").alias("item"), "c")


def dyadic_cover(low: int, high: int, levels: int) -> list[int]:
    """Dyadic items whose disjoint union is [low, high]: at most two per level."""
    found, level = [], 0
    while low <= high:
        if level == levels - 1:
            found += [level * (1 << levels) + x for x in range(low, high + 1)]
            break
        if low & 1:
            found.append(level * (1 << levels) + low)
            low += 1
        if low <= high and not high & 1:
            found.append(level * (1 << levels) + high)
            high -= 1
        low, high, level = low >> 1, high >> 1, level + 1
    return found
