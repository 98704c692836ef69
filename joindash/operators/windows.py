"""Window operators; every window has partition keys, so no single task sees a whole table."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

RANKS = {"row_number": F.row_number, "rank": F.rank, "dense_rank": F.dense_rank, "percent_rank": F.percent_rank, "cume_dist": F.cume_dist}


def rank_within(df: DataFrame, by: list[str], order: list[Column], fn: str = "row_number", alias: str = "rn") -> DataFrame:
    return df.withColumn(alias, RANKS[fn]().over(Window.partitionBy(*by).orderBy(*order)))


def tiles(df: DataFrame, by: list[str], order: list[Column], n: int, alias: str = "tile") -> DataFrame:
    return df.withColumn(alias, F.ntile(n).over(Window.partitionBy(*by).orderBy(*order)))


def top_per_group(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    return rank_within(df, by, order, alias="__rn").filter(F.col("__rn") <= k).drop("__rn")


def framed(df: DataFrame, by: list[str], order: list[Column], frame: tuple[int, int] | None, exprs: dict[str, Column], kind: str = "rows") -> DataFrame:
    w = Window.partitionBy(*by).orderBy(*order)
    if frame:
        w = w.rowsBetween(*frame) if kind == "rows" else w.rangeBetween(*frame)
    return df.withColumns({a: e.over(w) for a, e in exprs.items()})


def share(df: DataFrame, by: list[str], col: str, alias: str = "share") -> DataFrame:
    total = F.sum(col).over(Window.partitionBy(*by)) if by else F.sum(col).over(Window.partitionBy(F.lit(0)))
    return df.withColumn(alias, F.try_divide(F.col(col), total))
