"""Projection, filters, perturbation, scaling, top-k and set operations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def project(df: DataFrame, mapping: dict[str, str]) -> DataFrame:
    return df.select(*[F.expr(e).alias(a) for a, e in mapping.items()])


def where(df: DataFrame, predicate: str) -> DataFrame:
    return df.filter(F.expr(predicate))


def perturb(df: DataFrame, key: str, col: str, every: int, rest: int, change: Column) -> DataFrame:
    """Another version of a table: the cells of ``col`` in every so many-th row changed."""
    return df.withColumn(col, F.when(F.col(key) % every == rest, change).otherwise(F.col(col)))


def scale_out(df: DataFrame, keys: dict[str, int], k: int) -> DataFrame:
    """``k`` copies whose keys are shifted by the given strides, so that copies join with copies."""
    copies = df.withColumn("__k", F.explode(F.sequence(F.lit(0), F.lit(k - 1))))
    return copies.withColumns({c: F.col(c) + F.col("__k") * stride for c, stride in keys.items()}).drop("__k")


def resample_normalised(wide: DataFrame, rows: int, dims: dict[str, list[str]], seed: int = 1) -> dict[str, DataFrame]:
    """Scaled data with the joint distribution of a wide table: its rows are repeated and thinned to the
    asked number, then cut vertically again; each dimension gets a key that digests its columns."""
    have = wide.count()
    copies = max(1, -(-rows // max(have, 1)))
    grown = wide.withColumn("__copy", F.explode(F.sequence(F.lit(1), F.lit(copies))))
    keep = F.pmod(F.xxhash64(F.lit(seed), "__copy", *wide.columns), F.lit(1_000_000)) < int(1_000_000 * rows / max(have * copies, 1))
    grown = grown.filter(keep)
    for name, cols in dims.items():
        grown = grown.withColumn(f"{name}_key", F.xxhash64(F.lit(name), *cols))
    out = {name: grown.select(f"{name}_key", *cols).distinct() for name, cols in dims.items()}
    gone = {c for cols in dims.values() for c in cols} | {"__copy"}
    return {"fact": grown.select(*[c for c in grown.columns if c not in gone])} | out


def top_k(df: DataFrame, order: list[Column], k: int) -> DataFrame:
    """The first k rows; ``order`` ends with a tie-break that makes it total."""
    return df.orderBy(*order).limit(k)


def set_op(left: DataFrame, right: DataFrame, kind: str, keep_all: bool = False) -> DataFrame:
    if kind == "union":
        both = left.unionByName(right)
        return both if keep_all else both.distinct()
    if kind == "intersect":
        return left.intersectAll(right) if keep_all else left.intersect(right)
    if kind == "except":
        return left.exceptAll(right) if keep_all else left.subtract(right)
    raise ValueError(kind)
