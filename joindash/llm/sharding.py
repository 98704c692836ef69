"""Operator 4 – sharding along a Hilbert curve.

Metadata dimensions are quantised at quantiles (equal-frequency cells that keep the order of values,
whole strings included), each row gets the place of its cell on the Hilbert curve, rows are sorted by that
place across the cluster and cut into runs.  Neighbouring rows agree in all dimensions, so a shard covers
a small box and its file can be skipped by a filter on any of them.  Rows of equal texts take the least of
their places, so they stand together; only a cut between shards can part them.

Laws: ``rows`` (shard sizes at most one row apart) and ``bytes`` (cuts at equal shares of the bytes).

Defined results: null metadata fall in the lowest cell; a null text and an empty one are equal; equal
places are ordered by text and id; repeated rows are interchangeable; more shards than rows leave shards
empty; an empty table gives an empty result; input columns named like an output column are replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from joindash.llm.common import bytes_of, drop_written, global_position, lean, struct_with, table, without, written


@dataclass(frozen=True)
class ShardParams:
    shards: int = 40
    bits: int = 5
    law: str = "rows"
    accuracy: int = 2000
    overhead: int = 16


def string_cuts(df: DataFrame, name: str, cells: int) -> list[str]:
    """At most ``cells`` - 1 values that cut a string column into cells of equal frequency.

    Whole strings are counted and the distinct ones sorted across the cluster; one sum per partition and
    the cuts are all that meets on the driver.
    """
    counted = df.filter(F.col(name).isNotNull()).groupBy(F.col(name).alias("v")).agg(F.count(F.lit(1)).alias("n"))
    dealt = written(counted.repartitionByRange("v").withColumn("part", F.spark_partition_id()))
    starts, total = [], 0
    for part, n in sorted(tuple(r) for r in dealt.groupBy("part").agg(F.sum("n")).collect()):
        starts.append((part, total))
        total += n
    if not total:
        return []
    start = F.broadcast(df.sparkSession.createDataFrame(starts, "part int, start long"))  # one row per partition
    end = F.col("start") + F.sum("n").over(Window.partitionBy("part").orderBy("v"))
    ends = dealt.join(start, "part").select("v", "n", end.alias("end"))
    cell = lambda rows: F.floor(rows * cells / F.lit(total))
    cuts = ends.filter(cell(F.col("end")) > cell(F.col("end") - F.col("n"))).select("v").collect()
    return sorted(r.v for r in cuts)[: cells - 1]


def ordered_number(df: DataFrame, name: str, cells: int) -> Column:
    """A number that keeps the order of a column's values; of a string, the cell it falls in."""
    kind = df.schema[name].dataType
    col = F.col(f"`{name}`")
    if isinstance(kind, T.StringType):
        above = [(col > F.lit(c)).cast("double") for c in string_cuts(df, name, cells)]
        return F.when(col.isNotNull(), sum(above, F.lit(0.0)))
    if isinstance(kind, (T.DateType, T.TimestampType, T.TimestampNTZType)):
        return F.unix_micros(col.cast("timestamp")).cast("double")
    return col.cast("double")


def hilbert_index(cells: np.ndarray, bits: int) -> np.ndarray:
    """Curve places of integer points (rows × dimensions), each coordinate of ``bits`` bits.

    Works from the highest bit down: coordinates are reflected and swapped so that each step's quadrant
    is entered where the last one was left, then bits are read out in Gray order.
    """
    x = cells.astype(np.int64).copy()
    n = x.shape[1]
    q = 1 << (bits - 1)
    while q > 1:
        low = q - 1
        for i in range(n):
            on = (x[:, i] & q) > 0
            swap = np.where(on, 0, (x[:, 0] ^ x[:, i]) & low)
            x[:, 0] = np.where(on, x[:, 0] ^ low, x[:, 0] ^ swap)
            x[:, i] ^= swap
        q >>= 1
    for i in range(1, n):
        x[:, i] ^= x[:, i - 1]
    flip = np.zeros(len(x), np.int64)
    q = 1 << (bits - 1)
    while q > 1:
        flip ^= np.where(x[:, n - 1] & q, q - 1, 0)
        q >>= 1
    x ^= flip[:, None]
    out = np.zeros(len(x), np.int64)
    for b in range(bits - 1, -1, -1):
        for i in range(n):
            out = (out << 1) | ((x[:, i] >> b) & 1)
    return out


def curve_places(df: DataFrame, dims: list[Column], p: ShardParams) -> DataFrame:
    """``df`` with ``__jd_place``; the quantiles are the only thing that meets on the driver."""
    cells = (1 << p.bits) - 1
    shares = [(i + 1) / (cells + 1) for i in range(cells)]
    named = df.select("*", *[d.alias(f"__jd_d{i}") for i, d in enumerate(dims)])
    found = named.agg(*[F.percentile_approx(f"__jd_d{i}", shares, p.accuracy).alias(f"q{i}") for i in range(len(dims))]).first()
    cuts = [np.unique(np.array(q or [], float)) for q in found]
    schema = struct_with(df, [("__jd_place", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = [c.to_numpy(zero_copy_only=False).astype(float) for c in batch.columns[-len(cuts) :]]
            points = [np.where(np.isnan(v), 0, np.searchsorted(c, v, side="left")) for v, c in zip(values, cuts, strict=True)]
            place = hilbert_index(np.stack(points, 1), p.bits)
            yield pa.RecordBatch.from_arrays([*batch.columns[: -len(cuts)], pa.array(place)], names=schema.names)

    return named.mapInArrow(lean(run), schema)


def with_equal_texts(placed: DataFrame, text_key: list[str]) -> DataFrame:
    """``placed`` with one place for all rows of a text: the least of theirs.  Only the texts whose rows
    differ in metadata are joined; they are counted per task before they are shuffled."""
    lo, hi = F.min("__jd_place").alias("__jd_lo"), F.max("__jd_place").alias("__jd_hi")
    several = written(placed.groupBy(*text_key).agg(lo, hi).filter("__jd_lo < __jd_hi").drop("__jd_hi"))
    both = placed.join(several, text_key, "left")
    return both.withColumn("__jd_place", F.coalesce("__jd_lo", "__jd_place")).select(*placed.columns)


OUT = ["size", "text_crc32", "law", "shard", "slot", "grown_shard"]


def assign_shards(docs: DataFrame, dims: list[str], id_col: str = "doc_id", text: str = "text", p: ShardParams | None = None) -> DataFrame:
    """(id, the dimensions, size, checksum, law, shard, slot, grown_shard); texts are read, not moved."""
    p = p or ShardParams()
    raw = bytes_of(text)
    length = F.coalesce(F.octet_length(raw), F.lit(0)).cast("long")
    slim = docs.select(
        F.col(id_col).alias("__jd_id"),
        *[F.col(f"`{d}`").alias(f"__jd_v{i}") for i, d in enumerate(dims)],
        (length + p.overhead).alias("size"),
        F.crc32(F.coalesce(raw, F.lit(b""))).alias("text_crc32"),
        F.xxhash64(F.coalesce(raw, F.lit(b""))).alias("__jd_text"),
    )
    slim = written(slim)
    numbers = [*[ordered_number(slim, f"__jd_v{i}", 1 << p.bits) for i in range(len(dims))], F.col("size").cast("double")]
    curve = with_equal_texts(written(curve_places(slim, numbers, p)), ["size", "text_crc32", "__jd_text"])
    placed = global_position(curve, ["__jd_place", "text_crc32", "__jd_text", "__jd_id"], "__jd_pos")
    drop_written(slim)
    n, k = placed.count(), p.shards
    pos = F.col("__jd_pos")
    if p.law == "rows":
        big, small = n % k, n // k  # the first ``big`` shards hold one row more
        head = big * (small + 1)
        first = F.when(pos < head, F.floor(pos / (small + 1))).otherwise(big + F.floor((pos - head) / max(small, 1)))
        shard = first.cast("int")
        start = shard.cast("long") * small + F.least(shard, F.lit(big))
        out = placed.withColumn("shard", shard).withColumn("slot", pos - start)
    else:
        out = _cut_by_bytes(placed, k)
    return out.select(
        F.col("__jd_id").alias(id_col),
        *[F.col(f"__jd_v{i}").alias(d) for i, d in enumerate(dims) if d.lower() not in {*OUT, id_col.lower()}],
        "size",
        "text_crc32",
        F.lit(p.law).alias("law"),
        "shard",
        F.col("slot").cast("long").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
    )


def _cut_by_bytes(placed: DataFrame, k: int, block: int = 4096) -> DataFrame:
    """Cuts at equal shares of the bytes: running sums inside blocks of rows, then over the blocks."""
    inside = Window.partitionBy("__jd_block").orderBy("__jd_pos")
    rows = written(placed.withColumn("__jd_block", F.floor(F.col("__jd_pos") / block)).withColumn("__jd_sum", F.sum("size").over(inside) - F.col("size")))
    sums = rows.groupBy("__jd_block").agg(F.sum("size").alias("__jd_n"))
    before = Window.partitionBy("__jd_super").orderBy("__jd_block")  # two more levels, so no task sees all blocks
    sums = sums.withColumn("__jd_super", F.floor(F.col("__jd_block") / block))
    tops = sorted(sums.groupBy("__jd_super").agg(F.sum("__jd_n")).collect())
    total, starts = 0, []
    for s, n in tops:  # one row per 16 million rows
        starts.append((s, total))
        total += n
    top = placed.sparkSession.createDataFrame(starts, "__jd_super long, __jd_top long")
    at = sums.withColumn("__jd_at", F.sum("__jd_n").over(before) - F.col("__jd_n")).join(F.broadcast(top), "__jd_super")
    at = at.select("__jd_block", (F.col("__jd_at") + F.col("__jd_top")).alias("__jd_at"))
    middle = 2 * (F.col("__jd_at") + F.col("__jd_sum")) + F.col("size")  # twice the row's middle
    shard = F.least(F.floor(middle * k / F.lit(max(2 * total, 1))), F.lit(k - 1)).cast("int")
    cut = written(rows.join(at, "__jd_block").withColumn("shard", shard))
    first = cut.groupBy("shard").agg(F.min("__jd_pos").alias("__jd_first"))  # one row per shard
    return cut.join(F.broadcast(first), "shard").withColumn("slot", F.col("__jd_pos") - F.col("__jd_first"))


def shard_boxes(assigned: DataFrame, dims: list[str]) -> DataFrame:
    """The manifest: each shard's rows, bytes and value range in every dimension, for file pruning."""
    ranges = [f(d).alias(f"{n}_{d}") for d in dims for n, f in (("min", F.min), ("max", F.max))]
    return assigned.groupBy("shard").agg(F.count(F.lit(1)).alias("n_rows"), F.sum("size").alias("n_bytes"), *ranges)


def write_shards(docs: DataFrame, assigned: DataFrame, path: str, id_col: str = "doc_id") -> None:
    """Write whole rows to one folder per shard, each sorted by slot.  ``id_col`` must be unique."""
    rows = without(docs, ["shard", "slot"]).join(assigned.select(id_col, "shard", "slot"), id_col)
    rows.repartition("shard").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)


def op4_hilbert_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    return assign_shards(docs, ["lang", "source"])


QUERIES = {"op4_hilbert_sharding": op4_hilbert_sharding}
ORACLE_SQL: dict[str, str] = {}
