"""Accuracy measures over (item, method, truth, est[, lo, hi]) rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def accuracy(df: DataFrame) -> DataFrame:
    """method, n, mse, rmse, bias."""
    off = F.col("est") - F.col("truth")
    return df.groupBy("method").agg(F.count("*").alias("n"), F.avg(off * off).alias("mse"), F.sqrt(F.avg(off * off)).alias("rmse"), F.avg(off).alias("bias"))


def relative_efficiency(df: DataFrame, base: str) -> DataFrame:
    """method, rel_eff: a method's squared error over that of `base`, or how much more data it needs."""
    mse = accuracy(df).select("method", "mse")
    first = mse.where(F.col("method") == base).select(F.col("mse").alias("base"))
    return mse.crossJoin(first).select("method", (F.col("mse") / F.col("base")).alias("rel_eff"))


def coverage(df: DataFrame) -> DataFrame:
    """method, coverage, width."""
    inside = (F.col("lo") <= F.col("truth")) & (F.col("truth") <= F.col("hi"))
    return df.groupBy("method").agg(F.avg(inside.cast("double")).alias("coverage"), F.avg(F.col("hi") - F.col("lo")).alias("width"))


def rmse_by_size(df: DataFrame) -> DataFrame:
    """(items, method, rmse) of rows (items, method, truth, est): error per item against how many are estimated together."""
    off = F.col("est") - F.col("truth")
    return df.groupBy("items", "method").agg(F.sqrt(F.avg(off * off)).alias("rmse"))
