"""Python extension points, kept off the data path: Arrow functions, grouped maps, a table function."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from joindash.runtime import importable


def vector_udf(fn: Callable[[pd.Series], pd.Series], kind: str) -> Callable[[Column], Column]:
    """A scalar function over Arrow batches."""

    def call(*series: pd.Series) -> pd.Series:
        return fn(*series)

    def batch(s: pd.Series) -> pd.Series:
        return call(s)

    return F.pandas_udf(batch, kind)


def grouped_map(df: DataFrame, keys: list[str], fn: Callable[[pd.DataFrame], pd.DataFrame], schema: str) -> DataFrame:
    """One pandas frame per group, so groups must be of bounded size."""
    importable(df.sparkSession)
    return df.groupBy(*keys).applyInPandas(fn, schema)


def plan_rows(trace_events: list[tuple[str, str, str]]):
    """A table function that lists what an answer did: (step, action, source, target)."""
    rows = [(i, k, u, v) for i, (k, u, v) in enumerate(trace_events)]

    class PlanRows:
        def eval(self):
            yield from rows

    return F.udtf(PlanRows, returnType="step int, action string, source string, target string")
