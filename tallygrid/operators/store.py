"""Grids and estimates kept as files: a grid is written once, by replicate, beside its spec, and read by all that follows."""

from __future__ import annotations

from dataclasses import asdict

from pyspark.sql import DataFrame, SparkSession

from ..functions.hashing import GridSpec
from ..sources.shared import place
from .grid import CounterGrid

CELLS = "rep int, idx long, v long"
SPEC = "r int, k long, family string, seed long, item_type string, version int"
VERSION = 1


def save_grid(grid: CounterGrid, path: str, item_type: str = "", mode: str = "errorifexists") -> None:
    """Cells as Parquet in one folder for each replicate; the spec is written last, so a grid without one wasn't finished."""
    spark = grid.df.sparkSession
    grid.df.selectExpr("CAST(rep AS INT) AS rep", "CAST(idx AS LONG) AS idx", "CAST(v AS LONG) AS v").write.mode(mode).partitionBy("rep").parquet(f"{path}/cells")
    row = asdict(grid.spec) | {"item_type": item_type, "version": VERSION}
    names = [c.split()[0] for c in SPEC.split(", ")]
    spark.createDataFrame([tuple(row[n] for n in names)], SPEC).coalesce(1).write.mode(mode).json(f"{path}/spec")


def load_grid(spark: SparkSession, path: str, spec: GridSpec | None = None, item_type: str | None = None) -> CounterGrid:
    """The grid at `path`. With `spec` or `item_type`, one that was built otherwise is refused: its cells would mean something else."""
    row = spark.read.schema(SPEC).json(f"{path}/spec").first()
    if row is None or row["version"] != VERSION:
        raise ValueError(f"no grid of version {VERSION} at {path}")
    found = GridSpec(row["r"], row["k"], row["family"], row["seed"])
    if spec is not None and spec != found or item_type is not None and item_type != row["item_type"]:
        raise ValueError(f"the grid at {path} has another spec: {found}, items {row['item_type']!r}")
    return CounterGrid(spark.read.schema(CELLS).parquet(f"{path}/cells"), found)


def kept(grid: CounterGrid) -> CounterGrid:
    """The same grid from files in the shared folder: probes and laws read one replicate's cells, or all, and never its sources again."""
    path = place(grid.df.sparkSession, "grid")
    save_grid(grid, path)
    return load_grid(grid.df.sparkSession, path, grid.spec)


def save_estimates(estimates: DataFrame, path: str, by: str | None = None, mode: str = "errorifexists") -> None:
    """(item, est, lo, hi, ...) as Parquet, in folders by a column such as the method."""
    write = estimates.write.mode(mode)
    (write.partitionBy(by) if by else write).parquet(path)
