"""Streams into the engine: appended rows, windows with watermarks, stateful operators, stream joins."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from joindash.plans.calibrate import append_rows, appended_version
from joindash.plans.messages import Engine
from joindash.plans.query import Bound
from joindash.runtime import importable, new_path, path_exists


def stream_table(spark: SparkSession, path: str, files_per_trigger: int | None = None) -> DataFrame:
    """A Parquet file or folder as a stream; NTZ times become times in UTC, which watermarks accept."""
    schema = spark.read.parquet(path).schema
    reader = spark.readStream.schema(schema)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    folder, _, name = path.rpartition("/")
    df = reader.option("pathGlobFilter", name).parquet(folder) if name.endswith(".parquet") else reader.parquet(path)
    for f in schema:
        if f.dataType.typeName() == "timestamp_ntz":
            df = df.withColumn(f.name, F.to_utc_timestamp(F.col(f.name).cast("timestamp"), F.current_timezone()))
    return df


def windowed(df: DataFrame, time: str, kind: str, size: str, slide: str | None = None, watermark: str = "1 hour", by: list[str | Column] = (), exprs: list[Column] = ()) -> DataFrame:
    """Tumbling, sliding or session windows; rows later than the watermark are dropped."""
    w = F.session_window(time, size) if kind == "session" else F.window(time, size, slide) if kind == "sliding" else F.window(time, size)
    exprs = exprs or [F.count(F.lit(1)).alias("n")]
    return df.withWatermark(time, watermark).groupBy(w.alias("w"), *by).agg(*exprs).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *by, *[c for c in _names(exprs)])


def _names(exprs: list[Column]) -> list[str]:
    return [e._jc.toString().rpartition(" AS ")[2].strip("`") for e in exprs]


def deduplicated(df: DataFrame, key: list[str], time: str, watermark: str = "1 hour") -> DataFrame:
    return df.withWatermark(time, watermark).dropDuplicatesWithinWatermark(key)


def with_message(stream: DataFrame, message: DataFrame, on: list[str]) -> DataFrame:
    """Each arriving row meets a stored message, so a chart's contribution is known on arrival."""
    return stream.join(message, on)


def paired(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, within: str) -> DataFrame:
    """Rows of two streams with equal keys, the right one at most ``within`` after the left one."""
    a, b = left.withWatermark(left_time, within), right.withWatermark(right_time, within)
    return a.join(b, F.expr(f"{key} = right_{key} AND {right_time} >= {left_time} AND {right_time} <= {left_time} + interval {within}"))


def latest_per_key(df: DataFrame, key: str, value: str, order: list[str]) -> DataFrame:
    """The current interaction of each session: state holds the last value and the number of changes.

    ``order``: columns by which a batch's rows of one session follow each other."""
    importable(df.sparkSession)

    def update(k: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last, n = state.get if state.exists else ("", 0)
        for v in pd.concat(list(frames)).sort_values(order, kind="stable")[value]:
            n += int(v != last)
            last = v
        state.update((last, n))
        yield pd.DataFrame({key: [k[0]], "latest": [last], "changes": [n]})

    kind = df.schema[key].dataType.simpleString()
    return df.groupBy(key).applyInPandasWithState(update, f"{key} {kind}, latest string, changes int", "latest string, changes int", "update", GroupStateTimeout.NoTimeout)


#: State in files of the workers' own disks, behind a cache that all of a worker's partitions share.
_ROCKSDB = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true",
    "spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB": "256",
}


def drained(df: DataFrame, name: str, mode: str = "append", state_on_disk: bool = False) -> DataFrame:
    """Run a stream over what is there now, into a table in the shared folder, and return the table.

    Executors write the rows, so the driver holds none of them.  In complete mode every batch replaces the one
    before; else each has a folder of its own, which a replay writes again.  ``state_on_disk``: state of one entry
    per row, as of a deduplication, does not lie in the heap."""
    spark = df.sparkSession
    folder = new_path(spark, "stream")
    rows = f"{folder}/rows"

    def keep(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(rows if mode == "complete" else f"{rows}/batch-{batch_id}")

    wanted = _ROCKSDB if state_on_disk else {}
    before = {k: spark.conf.get(k, None) for k in wanted}
    try:
        for k, v in wanted.items():
            spark.conf.set(k, v)
        q = df.writeStream.outputMode(mode).foreachBatch(keep).queryName(name).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start()
    finally:  # the query has a copy of its own
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    q.awaitTermination()
    if not path_exists(spark, rows):  # nothing has arrived
        return spark.createDataFrame([], df.schema)
    return spark.read.schema(df.schema).parquet(rows if mode == "complete" else f"{rows}/batch-*")


def maintain(engine: Engine, stream: DataFrame, relation: str, bounds: list[Bound], versions: list[int], folder: str | None = None) -> StreamingQuery:
    """Append each micro-batch to a relation and bring its messages up to date.

    ``folder``, shared and kept over restarts, holds the stream's checkpoint and one file of rows per batch.
    A batch that is replayed after a failure writes the same file again, so its rows count once; a process
    that starts anew first takes up the batches that earlier ones appended."""
    spark, folder = engine.spark, folder or new_path(engine.spark, "stream")
    rel = engine.tree.graph.relations[relation]
    of = lambda batch_id: f"{folder}/batch-{batch_id}"
    last = last_batch(spark, folder)
    earlier = [of(i) for i in range(last + 1) if of(i) not in rel.appended and path_exists(spark, of(i))]
    if earlier:
        rel.appended += earlier
        versions.append(rel.add_version(appended_version(rel, rel.appended)))

    def apply(batch: DataFrame, batch_id: int) -> None:
        if of(batch_id) in rel.appended:  # replayed: its rows are there
            return
        versions.append(append_rows(engine, relation, batch, bounds, of(batch_id)))

    return stream.writeStream.foreachBatch(apply).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start()


def last_batch(spark: SparkSession, folder: str) -> int:
    """The greatest batch that has a complete file in the folder, or -1."""
    pattern = spark._jvm.org.apache.hadoop.fs.Path(f"{folder}/batch-*/_SUCCESS")
    found = pattern.getFileSystem(spark._jsc.hadoopConfiguration()).globStatus(pattern)
    return max((int(f.getPath().getParent().getName()[6:]) for f in found or []), default=-1)
