"""Operator 3 – licence scans.

A text is cut into overlapping word windows twice as long as the templates looked for, one window class
per power of two, so that every occurrence lies whole in a window.  MinHash values of a window's word
shingles are bands of one row.  The least similarity s of a window that holds ``threshold`` of a template's
shingles follows from the shingles of both, and each window class gets so many bands b for its least such
template that (1 - s)^b, the probability that a window misses it, is at most ``miss``.  Retrieved templates are verified by exact
containment of their shingles in the window.  Windows that share no shingle with any template cannot
verify and are left out before the bands are computed.

All of it is DataFrame expressions; the templates are a bounded table and the only side broadcast.

Defined results: null, empty and blank texts hold no licence; templates shorter than a shingle are one
shingle of their own length; repeated rows get the same result; an empty table or template list gives
no findings; input columns named like an output column are replaced.
"""

from __future__ import annotations

import math
import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from joindash.llm.common import table, written
from joindash.llm.spans import bound

#: Common licence notices, as their owners ask for them to be given.
TEMPLATES = {
    "all-rights-reserved": "All rights reserved.",
    "apache-2.0-line": "Licensed under the Apache License, Version 2.0.",
    "apache-2.0-notice": 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in '
    "compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0",
    "bsd-3-clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided "
    "that the following conditions are met",
    "cc-by-4.0": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "cc-by-nc-4.0": "Licensed under CC BY-NC 4.0.",
    "gpl-3.0-line": "This work is licensed under the GNU General Public License, version 3.",
    "gpl-notice": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General "
    "Public License as published by the Free Software Foundation",
    "isc": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby "
    "granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "mit-line": "Released under the MIT License.",
    "mit-grant": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated "
    'documentation files (the "Software"), to deal in the Software without restriction',
    "mpl-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "unlicense": "This is free and unencumbered software released into the public domain.",
}
GAP = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


@dataclass(frozen=True)
class LicenseParams:
    width: int = 5
    threshold: float = 0.8
    #: most probability that the bands miss a template that its window holds
    miss: float = 1e-4


def template_words(text: str) -> list[str]:
    return [w for w in re.split(GAP, text.lower()) if w]


def words(text: Column) -> Column:
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), GAP), lambda w: w != "")


def shingle_hashes(ws: Column, width: int) -> Column:
    """One 64-bit hash per shingle; the array's place is the shingle's first word."""
    at = F.sequence(F.lit(0), F.size(ws) - width)  # ``ws`` is a column or a bound value: it is read for each shingle
    each = F.transform(at, lambda i: F.xxhash64(*[F.get(ws, i + k) for k in range(width)]))
    return F.when(F.size(ws) >= width, each).otherwise(F.expr("cast(array() as array<bigint>)"))


def shingle_texts(ws: Column, width: int) -> Column:
    return F.array_distinct(F.transform(F.sequence(F.lit(1), F.size(ws) - width + 1), lambda i: F.array_join(F.slice(ws, i, F.lit(width)), " ")))


def min_hashes(hashes: Column, bands: int) -> Column:
    """array<struct(band, value)>: the least value of the set under each of ``bands`` hash functions."""
    least = lambda i: F.array_min(F.transform(hashes, lambda h: F.xxhash64(h, i)))
    return F.transform(F.sequence(F.lit(1), F.lit(bands)), lambda i: F.struct(i.alias("band"), least(i).alias("value")))


def bands_needed(size: int, counts: list[int], p: LicenseParams) -> int:
    """Bands of a class whose windows have ``size`` shingles and its templates ``counts`` distinct ones."""
    held = [(n, math.ceil(p.threshold * n - 1e-9)) for n in counts]
    least = min(h / (size + n - h) for n, h in held)
    return 1 if least >= 1 else math.ceil(math.log(p.miss) / math.log(1 - least))


def template_table(spark: SparkSession, templates: dict[str, str], p: LicenseParams) -> DataFrame:
    """(name, width, reach, shingles, hashes): ``reach`` is the power of two that bounds the template's words."""
    rows = []
    for name, text in sorted(templates.items()):
        ws = template_words(text)
        if ws:
            rows.append((name, min(p.width, len(ws)), 1 << (len(ws) - 1).bit_length(), ws))
    raw = spark.createDataFrame(rows, "name string, width int, reach int, ws array<string>")
    parts = None
    for width in sorted({r[1] for r in rows}) or [p.width]:
        own = raw.filter(F.col("width") == width).select(
            "name", "width", "reach", shingle_texts(F.col("ws"), width).alias("shingles"), F.array_distinct(shingle_hashes(F.col("ws"), width)).alias("hashes")
        )
        parts = own if parts is None else parts.unionByName(own)
    return parts


def license_matches(docs: DataFrame, templates: dict[str, str], id_col: str = "doc_id", text: str = "text", p: LicenseParams | None = None) -> DataFrame:
    """(id, hash of the text, template, containment, first word of the window): one row per template found."""
    p = p or LicenseParams()
    spark = docs.sparkSession
    known = template_table(spark, templates, p)
    classes: dict[tuple[int, int], set[int]] = {}
    counts: dict[tuple[int, int], list[int]] = {}
    for r in known.select("width", "reach", "hashes").collect():  # the templates, a bounded list
        classes.setdefault((r.width, r.reach), set()).update(r.hashes)
        counts.setdefault((r.width, r.reach), []).append(len(r.hashes))
    widths = sorted({w for w, _ in classes})
    if not widths:
        return spark.createDataFrame([], "hash long, name string, containment double, first_word int").withColumn("id", F.lit(None).cast(docs.schema[id_col].dataType))
    share = lambda col, hashes: F.arrays_overlap(col, F.array(*[F.lit(h) for h in sorted(hashes)]))

    def shingled(ws: Column) -> Column:
        """The words and shingle hashes of a text that shares a shingle with a template, else null."""

        def touched(h: Column) -> Column:
            any_shared = F.lit(False)
            for w in widths:
                any_shared = any_shared | share(h[f"h{w}"], set().union(*[v for (x, _), v in classes.items() if x == w]))
            return F.when(any_shared, F.struct(ws.alias("ws"), *[h[f"h{w}"].alias(f"h{w}") for w in widths]))

        return bound(F.struct(*[shingle_hashes(ws, w).alias(f"h{w}") for w in widths]), touched)

    slim = docs.select(F.col(id_col).alias("id"), F.xxhash64(F.coalesce(F.col(text), F.lit(""))).alias("hash"), bound(words(F.col(text)), shingled).alias("s"))
    near = written(slim).filter("s is not null").select("id", "hash", "s.*")
    found = None
    for (w, reach), hashes in sorted(classes.items()):
        size = 2 * reach - w + 1  # shingles of a window of 2 * reach words
        bands = bands_needed(size, counts[w, reach], p)
        start = F.sequence(F.lit(0), F.greatest(F.size(f"h{w}") - 1, F.lit(0)), F.lit(reach))
        cut = near.select("id", "hash", "ws", f"h{w}", F.explode(start).alias("at"))
        cut = cut.select("id", "hash", "at", F.slice("ws", F.col("at") + 1, F.lit(2 * reach)).alias("ws"), F.slice(f"h{w}", F.col("at") + 1, F.lit(size)).alias("hashes"))
        cut = cut.filter((F.size("hashes") > 0) & share(F.col("hashes"), hashes))
        banded = cut.select("id", "hash", "at", "ws", F.explode(min_hashes(F.col("hashes"), bands)).alias("b")).select("id", "hash", "at", "ws", "b.*")
        own = known.filter((F.col("width") == w) & (F.col("reach") == reach))
        own_bands = own.select("name", "shingles", F.explode(min_hashes(F.col("hashes"), bands)).alias("b")).select("name", "shingles", "b.*")
        met = banded.join(F.broadcast(own_bands), ["band", "value"])  # templates × bands rows
        held = F.size(F.array_intersect(shingle_texts(F.col("ws"), w), F.col("shingles"))) / F.size("shingles")
        checked = met.groupBy("id", "hash", "at", "name").agg(F.first("ws").alias("ws"), F.first("shingles").alias("shingles"))
        checked = checked.select("id", "hash", "name", held.alias("containment"), "at").filter(F.col("containment") >= p.threshold)
        found = checked if found is None else found.unionByName(checked)
    best = F.max(F.struct("containment", (-F.col("at")).alias("back"))).alias("m")
    return found.groupBy("id", "hash", "name").agg(best).select("id", "hash", "name", "m.containment", (-F.col("m.back")).alias("first_word"))


def scan_licenses(docs: DataFrame, templates: dict[str, str] | None = None, id_col: str = "doc_id", text: str = "text", p: LicenseParams | None = None) -> DataFrame:
    """(id, n_licenses, licenses: array<struct(name, containment, first_word)> by name), one row per input row."""
    matches = license_matches(docs, TEMPLATES if templates is None else templates, id_col, text, p)
    per = matches.groupBy("id", "hash").agg(F.array_sort(F.collect_list(F.struct("name", "containment", "first_word"))).alias("licenses"))
    per = written(per)  # narrow; both sides of the join below are then plain shuffles
    rows = docs.select(F.col(id_col).alias("id"), F.xxhash64(F.coalesce(F.col(text), F.lit(""))).alias("hash"))
    out = rows.join(per, rows["id"].eqNullSafe(per["id"]) & (rows["hash"] == per["hash"]), "left")
    none = F.expr("cast(array() as array<struct<name:string,containment:double,first_word:int>>)")
    return out.select(rows["id"].alias(id_col), F.coalesce("licenses", none).alias("licenses")).withColumn("n_licenses", F.size("licenses").cast("long"))


def op3_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan_licenses(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", "n_licenses", F.array_join(F.transform("licenses", lambda s: s["name"]), ",").alias("licenses"))


QUERIES = {"op3_license_scan": op3_license_scan}
ORACLE_SQL: dict[str, str] = {}
