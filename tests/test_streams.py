"""Streams into tables."""

import pytest


@pytest.mark.parametrize("mode", ["append", "complete", "update"])
def test_drained_rows_stay_off_the_driver(spark, tmp_path, mode):
    """Several batches, and none: rows lie in files, and every mode gives what the stream has put out."""
    from pyspark.sql import functions as F

    from joindash.streaming import streams

    for name, first in (("a", 0), ("b", 5)):
        spark.range(first, first + 10).coalesce(1).write.parquet(str(tmp_path / "in" / name))
    stream = spark.readStream.schema("id long").option("recursiveFileLookup", "true").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    df = stream if mode == "append" else stream.groupBy((F.col("id") % 3).alias("k")).agg(F.count(F.lit(1)).alias("n"))
    out = streams.drained(df, f"drained_{mode}", mode)
    plan = out._jdf.queryExecution().analyzed().toString()
    assert "MemoryPlan" not in plan and len(out.inputFiles()) > 0
    got = sorted(map(tuple, out.collect()))
    if mode == "append":
        assert got == sorted([(i,) for i in range(10)] + [(i,) for i in range(5, 15)])
    elif mode == "complete":
        assert got == [(0, 7), (1, 6), (2, 7)]
    else:  # what each of the two batches changed
        assert {(0, 7), (1, 6), (2, 7)} <= set(got) and len(got) == 6
    (tmp_path / "none").mkdir()
    empty = spark.readStream.schema("id long").parquet(str(tmp_path / "none"))
    assert streams.drained(empty, f"drained_none_{mode}", "append").collect() == []


def test_deduplicated_events_are_counted_from_files(spark, sf, monkeypatch):
    from joindash.streaming import streams
    from joindash.workloads import support

    seen, drained = [], streams.drained
    monkeypatch.setattr(streams, "drained", lambda *a: seen.append(drained(*a)) or seen[-1])
    n = spark.read.parquet(f"{sf}/events.parquet").count()
    assert [tuple(r) for r in support.QUERIES["st_dedupe"](spark, sf).collect()] == [(n, n)]
    assert seen[0].inputFiles()


def test_deduplicated_state_lies_on_disk(spark, sf, monkeypatch):
    from pathlib import Path
    from urllib.parse import urlparse

    from joindash.streaming import streams
    from joindash.workloads import support

    provider = "spark.sql.streaming.stateStore.providerClass"
    seen, drained, before = [], streams.drained, spark.conf.get(provider, None)
    monkeypatch.setattr(streams, "drained", lambda *a: seen.append(drained(*a)) or seen[-1])
    support.QUERIES["st_dedupe"](spark, sf)
    folder = urlparse(seen[0].inputFiles()[0]).path.partition("/rows/")[0]
    kinds = {f.suffix for f in Path(folder, "checkpoint", "state").rglob("*") if not f.name.startswith(".")}
    assert ".zip" in kinds and ".delta" not in kinds
    assert spark.conf.get(provider, None) == before
