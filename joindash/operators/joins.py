"""Joins around the engine: equi joins by strategy, semi and anti, outer, range, as-of, multi-way."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

HINTS = {"broadcast": "broadcast", "hash": "shuffle_hash", "merge": "merge", "auto": None}


class UnboundedJoin(ValueError):
    """A join without an equality on inputs too large for a nested loop."""


def equi(left: DataFrame, right: DataFrame, on: list[str], how: str = "inner", strategy: str = "auto", broadcast_rows: int = 1_000_000) -> DataFrame:
    """``strategy='broadcast'`` is honoured only while the right side has at most ``broadcast_rows`` rows."""
    if strategy == "broadcast" and right.limit(broadcast_rows + 1).count() > broadcast_rows:
        strategy = "auto"
    hint = HINTS[strategy]
    return left.join(right.hint(hint) if hint else right, on, how)


def semi(left: DataFrame, right: DataFrame, on: list[str]) -> DataFrame:
    return left.join(right, on, "left_semi")


def anti(left: DataFrame, right: DataFrame, on: list[str]) -> DataFrame:
    return left.join(right, on, "left_anti")


def salted(left: DataFrame, right: DataFrame, on: list[str], salts: int = 16) -> DataFrame:
    """An inner join whose hot keys are spread: left rows draw a salt, right rows are repeated for each.

    Always a sort-merge join: size estimates do not see the repetition, and a broadcast of the repeated side
    would pass through the driver."""
    a = left.withColumn("__salt", F.pmod(F.xxhash64(*[F.col(f"`{c}`") for c in left.columns]), F.lit(salts)))
    b = right.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1)).cast("array<bigint>")))
    return a.join(b.hint("merge"), [*on, "__salt"]).drop("__salt")


def theta(left: DataFrame, right: DataFrame, condition: Column, max_pairs: int = 100_000_000) -> DataFrame:
    """A nested-loop join, refused where the product of the sides is too large; use ``range_join`` there."""
    if left.count() * right.count() > max_pairs:
        raise UnboundedJoin("too many pairs for a join without equality; bin the range and use range_join")
    return left.join(right, condition)


def range_join(points: DataFrame, spans: DataFrame, point: str, low: str, high: str, width: float) -> DataFrame:
    """Rows with low <= point < high: spans are dealt to bins of ``width``, points to theirs, then compared."""
    a = points.withColumn("__bin", F.floor(F.col(point) / width))
    b = spans.withColumn("__bin", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return a.join(b, "__bin").filter((F.col(point) >= F.col(low)) & (F.col(point) < F.col(high))).drop("__bin")


def asof(left: DataFrame, right: DataFrame, on: str, by: list[str], values: list[str], tolerance: float | None = None) -> DataFrame:
    """Each left row with the values of the latest right row of its group at or before it."""
    keep = F.struct(F.col(on).alias("__at"), *values)
    a = left.withColumn("__v", F.lit(None).cast(right.select(keep.alias("x")).schema["x"].dataType)).withColumn("__side", F.lit(1))
    pad = [F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns if c not in (*by, on)]
    b = right.select(*by, on, *pad, keep.alias("__v"), F.lit(0).alias("__side")).select(a.columns)
    w = Window.partitionBy(*by).orderBy(on, "__side").rowsBetween(Window.unboundedPreceding, 0)
    out = a.unionByName(b).withColumn("__hit", F.last("__v", ignorenulls=True).over(w)).filter("__side = 1")
    near = F.lit(True) if tolerance is None else F.col(on) - F.col("__hit.__at") <= tolerance
    return out.select(*left.columns, *[F.when(near, F.col(f"__hit.{v}")).alias(v) for v in values])


def multiway(frames: list[DataFrame], on: list[list[str]]) -> DataFrame:
    """A chain of equi joins; ``on[i]`` joins frame i + 1 to what came before."""
    return reduce(lambda acc, x: acc.join(x[0], x[1]), zip(frames[1:], on, strict=True), frames[0])


def cross(left: DataFrame, right: DataFrame, max_rows: int = 100_000) -> DataFrame:
    """A product of two tables of fixed size."""
    if left.limit(max_rows + 1).count() * right.limit(max_rows + 1).count() > max_rows:
        raise UnboundedJoin("a product is for tables of fixed size")
    return left.crossJoin(right)
