"""Shared helpers of the training-data operators.

Column clashes: an operator's output columns replace input columns of the same name; scratch
columns start with ``__jd_``, a prefix that callers leave free.
"""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager, nullcontext
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def importable(spark: SparkSession) -> None:
    """Let Python workers that see the driver's folders import this package from them."""
    env, root = spark.sparkContext.environment, str(Path(__file__).resolve().parents[2])
    if root not in env.get("PYTHONPATH", "").split(":"):
        env["PYTHONPATH"] = ":".join(filter(None, [env.get("PYTHONPATH"), root]))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    importable(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


_own: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors share, from the session's ``spark.checkpoint.dir``.

    Where none is named, a session whose executors are threads of the driver gets a folder of its own;
    on a cluster that would be another disk on each machine, so it is refused there.
    """
    sc = spark.sparkContext
    named = sc.getCheckpointDir() or sc.getConf().get("spark.checkpoint.dir")
    if named:
        return named
    if not re.fullmatch(r"local(\[[^\]]*\])?", sc.master):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if sc.applicationId not in _own:
        _own[sc.applicationId] = tempfile.mkdtemp(prefix="joindash-")
    return _own[sc.applicationId]


def _hadoop(spark: SparkSession, path: str):
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    return hadoop, hadoop.getFileSystem(spark._jsc.hadoopConfiguration())


def new_path(spark: SparkSession, kind: str = "t") -> str:
    """A fresh path in the shared folder that goes when the session ends."""
    path = f"{shared_dir(spark)}/{kind}-{uuid.uuid4().hex}"
    hadoop, files = _hadoop(spark, path)
    files.deleteOnExit(hadoop)
    return path


def remove_path(spark: SparkSession, path: str) -> None:
    hadoop, files = _hadoop(spark, path)
    files.delete(hadoop, True)


BATCH_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch"


@contextmanager
def batches_of(spark: SparkSession, most: int) -> Iterator[None]:
    """Arrow batches hold at most ``most`` rows meanwhile, also where the session sets no limit (0 or less)."""
    before = spark.conf.get(BATCH_ROWS)
    spark.conf.set(BATCH_ROWS, str(most if int(before) <= 0 else min(most, int(before))))
    try:
        yield
    finally:
        spark.conf.set(BATCH_ROWS, before)


def written(df: DataFrame, texts: bool = False) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage is cut, a lost executor costs no
    recomputation, and the table goes when the session ends.

    ``texts``: whole texts pass through Python on the way, so batches hold 512 rows at most while it runs."""
    spark = df.sparkSession
    path = new_path(spark)
    with batches_of(spark, 512) if texts else nullcontext():
        df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_written(df: DataFrame) -> None:
    """Remove the files of a table made by ``written`` that nothing reads any more."""
    for name in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/t-" in name:
            remove_path(df.sparkSession, name)


def few(keys: DataFrame, most: int = 2_000_000) -> DataFrame:
    """``keys``, a narrow written table, to be broadcast where its rows were counted and are few enough."""
    return F.broadcast(keys) if keys.count() <= most else keys


def without(df: DataFrame, names) -> DataFrame:
    """``df`` less the columns that an operator is about to add."""
    names = {n.lower() for n in names}
    return df.select(*[F.col(f"`{c}`") for c in df.columns if c.lower() not in names])


def set_aside(df: DataFrame, names) -> tuple[DataFrame, Callable[[DataFrame], DataFrame]]:
    """``df`` with the columns that clash with an operator's under other names, and the way back to ``df``'s own
    columns from the operator's output."""
    names = {n.lower() for n in names}
    other = {c: f"__jd_own_{i}" if c.lower() in names else c for i, c in enumerate(df.columns)}
    own = df.select(*[F.col(f"`{c}`").alias(o) for c, o in other.items()])
    return own, lambda out: out.select(*[F.col(f"`{o}`").alias(c) for c, o in other.items()])


_held: dict = {}


def held(key, make: Callable):
    """What this worker keeps from task to task, made on first use; one thing at a time."""
    if key not in _held:
        _held.clear()
        _held[key] = make()
    return _held[key]


def hand_back(drop: bool = False) -> None:
    """Freed memory of Arrow and of the C library goes back to the system; ``drop``: also what ``held`` keeps."""
    import ctypes

    import pyarrow as pa

    if drop:
        _held.clear()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc only
    if trim:
        trim(0)


def lean(run: Callable, holds: bool = False) -> Callable:
    """An Arrow step that hands freed memory back to the system after each batch: the allocators would keep the
    most that they ever held, in every worker, also while other stages run.

    What a step that ``holds`` keeps for its next tasks goes when the worker comes to a step of another kind."""

    def step(batches: Iterator) -> Iterator:
        hand_back(drop=not holds)
        for made in run(batches):
            yield made
            del made
            hand_back()
        hand_back()

    return step


def local_rows(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    """A few ``rows`` as a table that the JVM reads.  ``createDataFrame`` on a list sends them through Python
    workers of a kind of their own, which stay on each executor beside those of the Arrow steps."""
    import pyarrow as pa
    from pyspark.sql.pandas.types import to_arrow_schema

    fields = to_arrow_schema(T._parse_datatype_string(schema))
    columns = zip(*rows, strict=True) if rows else [[]] * len(fields)
    columns = [pa.array(c, f.type) for c, f in zip(columns, fields, strict=True)]
    with batches_of(spark, 10_000):  # a table is not taken without a limit
        return spark.createDataFrame(pa.Table.from_arrays(columns, schema=fields), schema)


def with_bytes(docs: DataFrame, text: str) -> tuple[DataFrame, int]:
    """``docs`` and the place of its text among the columns; only a text that is no column of its own, or no
    string, goes to Python as one more column."""
    if text in docs.columns and isinstance(docs.schema[text].dataType, T.StringType):
        return docs, docs.columns.index(text)
    return docs.withColumn("__jd_bytes", bytes_of(text)), len(docs.columns)


def slices(batch, at: int, most: int = 2 << 20) -> Iterator:
    """``batch`` in slices of about ``most`` bytes of text, column ``at``; a longer text is a slice of its own."""
    import numpy as np
    import pyarrow.compute as pc

    done = np.cumsum(pc.binary_length(batch.column(at)).fill_null(0).to_numpy(), dtype=np.int64)
    first = 0
    while first < batch.num_rows:
        before = done[first - 1] if first else 0
        last = max(first + 1, int(np.searchsorted(done, before + most, side="right")))
        yield batch.slice(first, last - first)
        first = last


def struct_with(df: DataFrame, fields: list[tuple[str, T.DataType]]) -> T.StructType:
    """The output schema of a Python step over ``df``; sees to it that workers can import this package."""
    importable(df.sparkSession)
    return T.StructType([*df.schema.fields, *[T.StructField(n, t) for n, t in fields]])


def bytes_of(text: str | Column) -> Column:
    return (F.col(text) if isinstance(text, str) else text).cast("binary")


def global_position(df: DataFrame, order: list[Column | str], name: str, first: int = 0) -> DataFrame:
    """Number all rows 0, 1, 2, … in a total order without a single-task window.

    Rows are range-partitioned (sampled bounds, so one hot key is cut by the later sort columns),
    sorted inside each partition and written once; only one count per partition meets on the driver.
    Rows that tie on every sort column are interchangeable.  ``df`` should be narrow.
    """
    spark = df.sparkSession
    tie = F.monotonically_increasing_id()
    df = df.withColumn("__jd_tie", tie)
    keys = [*order, F.col("__jd_tie")]
    placed = written(
        df.repartitionByRange(*keys)
        .sortWithinPartitions(*keys)
        .drop("__jd_tie")
        .withColumn("__jd_part", F.spark_partition_id())
        .withColumn("__jd_row", F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)))
    )
    offsets, at = [], first
    for part, n in sorted(placed.groupBy("__jd_part").count().collect()):
        offsets.append((part, at))
        at += n
    starts = spark.createDataFrame(offsets, "__jd_part int, __jd_start long")
    return (
        placed.join(F.broadcast(starts), "__jd_part")  # one row per partition: bounded by the partition count
        .withColumn(name, F.col("__jd_start") + F.col("__jd_row"))
        .drop("__jd_part", "__jd_row", "__jd_start")
    )
