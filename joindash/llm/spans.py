"""Positions of pattern matches in whole texts, by built-in functions alone."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def bound(value: Column, use) -> Column:
    """``use`` of a value that is evaluated once, however often ``use`` and the optimiser repeat it."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def located(text: Column, pattern: str, needs: str | None) -> Column:
    """array<struct(start, end, value, before)> of the leftmost non-overlapping matches, in code points.

    Splitting and extracting cut the text at the same places, so running lengths give the positions.
    """
    empty = F.expr("cast(array() as array<struct<start:int,end:int,value:string,before:string>>)")
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))

    def spans(parts: Column, values: Column) -> Column:
        def step(acc: Column, i: Column) -> Column:
            start = acc["at"] + F.length(F.get(parts, i))
            end = start + F.length(F.get(values, i))
            span = F.struct(start.alias("start"), end.alias("end"), F.get(values, i).alias("value"), F.get(parts, i).alias("before"))
            return F.struct(end.alias("at"), F.array_append(acc["spans"], span).alias("spans"))

        zero = F.struct(F.lit(0).alias("at"), empty.alias("spans"))
        return F.aggregate(F.sequence(F.lit(0), F.size(values) - 1), zero, step, lambda acc: acc["spans"])

    all_spans = bound(found, lambda v: F.when(F.size(v) > 0, bound(F.split(text, pattern, -1), lambda parts: spans(parts, v))).otherwise(empty))
    return all_spans if needs is None else F.when(F.contains(text, F.lit(needs)), all_spans).otherwise(empty)
