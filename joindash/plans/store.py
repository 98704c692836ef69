"""Messages as tables: pointers on the driver, contents in storage, least recently used goes first."""

from __future__ import annotations

import json
import threading
import uuid
from collections import OrderedDict
from dataclasses import dataclass

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession

from joindash.runtime import new_path, path_bytes, path_exists, remove_path


_NARROW = {"tinyint", "smallint", "int", "bigint", "float", "double", "boolean", "date", "timestamp", "timestamp_ntz"}


@dataclass
class MessageRef:
    fingerprint: str
    df: DataFrame
    rows: int
    size: int
    path: str | None
    pins: int = 0
    table: str | None = None

    @property
    def memory(self) -> int:
        """Bytes of the rows as they lie in memory; files are smaller by their encodings."""
        return self.rows * (16 + sum(40 if t == "string" else 24 if t.startswith("decimal") else 16 if t in _NARROW else 256 for _, t in self.df.dtypes))


class MessageStore:
    """``mode``: 'parquet' writes to the shared folder; 'memory' keeps small messages persisted; 'noop'
    computes and forgets (to time calibration without writes).  Safe for the calibrator's thread.

    ``root``: a shared folder in which messages outlive the session; ``save`` puts the catalogue there and
    ``load`` finds the messages again in another process.  Without one, messages go with the session.
    ``bucket_rows``: a larger message is stored as a table in buckets by its separator, so that joins along
    the edge need no shuffle of it."""

    def __init__(self, spark: SparkSession, mode: str = "parquet", max_bytes: int | None = None, bucket_rows: int = 50_000_000, root: str | None = None):
        self.spark, self.mode, self.max_bytes, self.bucket_rows, self.root = spark, mode, max_bytes, bucket_rows, root
        self.refs: OrderedDict[str, MessageRef] = OrderedDict()
        self.lock = threading.RLock()
        self.hits = self.misses = self.evicted = 0

    def get(self, fingerprint: str) -> MessageRef | None:
        with self.lock:
            ref = self.refs.get(fingerprint)
            if ref:
                self.refs.move_to_end(fingerprint)
                self.hits += 1
            else:
                self.misses += 1
            return ref

    def has(self, fingerprint: str) -> bool:
        with self.lock:
            return fingerprint in self.refs

    def put(self, fingerprint: str, df: DataFrame, separator: tuple[str, ...] = ()) -> MessageRef | None:
        """Store a message; it becomes visible only when it is complete."""
        path = table = None
        if self.mode == "noop":
            df.write.format("noop").mode("overwrite").save()
            return None
        if self.mode == "parquet":
            path = f"{self.root}/message-{fingerprint}-{uuid.uuid4().hex[:8]}" if self.root else new_path(self.spark, "message")
            df.write.parquet(path)
            df = self.spark.read.schema(df.schema).parquet(path)
            rows, size = df.count(), path_bytes(self.spark, path)
            if separator and rows > self.bucket_rows:
                table = f"message_{uuid.uuid4().hex}"
                df.write.bucketBy(max(1, 8 * rows // max(self.bucket_rows, 1)), *separator).sortBy(*separator).saveAsTable(table)
                df = self.spark.table(table)
        else:
            df = df.persist(StorageLevel.MEMORY_AND_DISK)
            rows = df.count()
            size = rows * sum(8 if t != "string" else 24 for _, t in df.dtypes)
        ref = MessageRef(fingerprint, df, rows, size, path, table=table)
        with self.lock:
            self.refs[fingerprint] = ref
            self.evict()
        return ref

    def pin(self, fingerprints, step: int = 1) -> None:
        with self.lock:
            for f in fingerprints:
                if f in self.refs:
                    self.refs[f].pins += step

    def drop(self, fingerprint: str) -> None:
        with self.lock:
            ref = self.refs.pop(fingerprint, None)
        if ref and ref.table:
            self.spark.sql(f"DROP TABLE IF EXISTS {ref.table}")
        if ref and ref.path:
            remove_path(self.spark, ref.path)
        elif ref:
            ref.df.unpersist()

    def evict(self) -> None:
        """Drop unpinned messages, least recently used first, until the store fits."""
        if self.max_bytes is None:
            return
        with self.lock:
            for f in [f for f, r in self.refs.items() if not r.pins]:
                if self.bytes() <= self.max_bytes:
                    return
                if f != next(reversed(self.refs)):  # never the one that was just stored
                    self.drop(f)
                    self.evicted += 1

    def bytes(self) -> int:
        return sum(r.size for r in self.refs.values())

    def manifest(self) -> str:
        """The catalogue as JSON."""
        return json.dumps([{"fingerprint": r.fingerprint, "path": r.path, "rows": r.rows, "bytes": r.size} for r in self.refs.values() if r.path])

    def load_manifest(self, text: str) -> int:
        """Take up the messages of a catalogue whose files are still there; returns how many."""
        with self.lock:
            found = [m for m in json.loads(text) if path_exists(self.spark, m["path"])]
            for m in found:
                self.refs[m["fingerprint"]] = MessageRef(m["fingerprint"], self.spark.read.parquet(m["path"]), m["rows"], m["bytes"], m["path"])
            return len(found)

    def save(self) -> None:
        """Write the catalogue beside the messages, for other processes."""
        if not self.root:
            raise ValueError("messages without a root go with the session")
        self.spark.createDataFrame([(self.manifest(),)], "value string").coalesce(1).write.mode("overwrite").text(f"{self.root}/manifest")

    def load(self) -> int:
        """The messages that an earlier process saved; their fingerprints name the contents of all
        relations behind them, so a changed table finds none of its old messages."""
        path = f"{self.root}/manifest"
        return sum(self.load_manifest(r.value) for r in self.spark.read.text(path).collect()) if path_exists(self.spark, path) else 0

    def clear(self) -> None:
        for f in list(self.refs):
            self.drop(f)
