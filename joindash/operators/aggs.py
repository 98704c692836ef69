"""Aggregation: plain, salted, grouping sets, aggregate of aggregates, pivots, histogram quantiles."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def agg(df: DataFrame, keys: list[str], exprs: list[Column]) -> DataFrame:
    return df.groupBy(*keys).agg(*exprs) if keys else df.agg(*exprs)


def salted_sum(df: DataFrame, keys: list[str], sums: dict[str, str], salts: int = 32) -> DataFrame:
    """Sums in two stages, for keys so hot that one task's merge of partial sums would be the bottleneck."""
    first = df.groupBy(*keys, F.spark_partition_id().__mod__(salts).alias("__salt")).agg(*[F.sum(c).alias(a) for a, c in sums.items()])
    return first.groupBy(*keys).agg(*[F.sum(a).alias(a) for a in sums])


def grouping_sets(df: DataFrame, sets: list[list[str]], exprs: list[Column]) -> DataFrame:
    every = list(dict.fromkeys(c for s in sets for c in s))
    return df.groupingSets([[F.col(c) for c in s] for s in sets], *[F.col(c) for c in every]).agg(F.grouping_id().alias("level"), *exprs)


def cube(df: DataFrame, keys: list[str], exprs: list[Column]) -> DataFrame:
    return df.cube(*keys).agg(F.grouping_id().alias("level"), *exprs)


def rollup(df: DataFrame, keys: list[str], exprs: list[Column]) -> DataFrame:
    return df.rollup(*keys).agg(F.grouping_id().alias("level"), *exprs)


def agg_of_agg(df: DataFrame, keys: list[str], inner: Column, outer: list[Column], outer_keys: list[str] = ()) -> DataFrame:
    first = df.groupBy(*keys).agg(inner)
    return first.groupBy(*outer_keys).agg(*outer) if outer_keys else first.agg(*outer)


def pivot(df: DataFrame, keys: list[str], column: str, values: list, expr: Column) -> DataFrame:
    """Values are given, so no extra job looks for them."""
    return df.groupBy(*keys).pivot(column, values).agg(expr)


def weighted_quantile(histogram: DataFrame, keys: list[str], value: str, weight: str, q: float) -> DataFrame:
    """The least value at which the running weight of its group reaches ``q`` of the total: the root's last
    step for percentiles over a tree, after grouping by the value itself."""
    by = Window.partitionBy(*keys) if keys else Window.partitionBy(F.lit(0))
    run = F.sum(weight).over(by.orderBy(value).rowsBetween(Window.unboundedPreceding, 0))
    rows = histogram.withColumn("__run", run).withColumn("__all", F.sum(weight).over(by)).filter(F.col("__run") >= q * F.col("__all"))
    low = F.min(value).alias("quantile")
    return rows.groupBy(*keys).agg(low) if keys else rows.agg(low)
