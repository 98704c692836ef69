"""Scalar expressions used around the engine; all of them stay in generated code."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def year_month(ts: Column) -> Column:
    return F.year(ts) * 100 + F.month(ts)


def noise(key: Column, i: int) -> Column:
    """A reproducible number in [0, 1): the first 32 bits of a digest of key and index."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", key.cast("string"), F.lit(str(i))).cast("binary")), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def digest(*cols: Column) -> Column:
    return F.sha2(F.concat_ws("|", *cols), 256)


def squared_norm(v: Column) -> Column:
    return F.aggregate(v, F.lit(0.0), lambda t, x: t + x.cast("double") * x.cast("double"))


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda t, x: t + x)


def json_field(col: Column, path: str, kind: str = "string") -> Column:
    return F.get_json_object(col, f"$.{path}").cast(kind)


def bucket(x: Column, width: float) -> Column:
    return F.floor(x / width)
