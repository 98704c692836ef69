"""Operator 6 – quality rules by compression bands.

A text is compressed with zstandard as a whole and in fixed chunks.  Prose of a given length
compresses within a band: far less room means random or encoded content, far more means
repetition.  The band depends on the length, because short texts carry frame overhead and long
ones let the compressor find distant repeats.  The low limits lie between base64 (1.07 at 256 bytes,
1.15 at 400, 1.26 at 1,024, 1.31 at 4,096) and prose (the least of the given texts: 1.08, 1.34, 1.43 and
2.07).  Digits and hex compress as well as prose does, but only by the frequencies of their letters: a
full chunk that needs no less room than these frequencies alone give is odd too.

Defined results: a null text has no words and fails the base rule, as does an empty one; very long
texts are streamed chunk by chunk; repeated rows each get their own verdict; an empty table gives
an empty result; input columns named like an output column are replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from joindash.llm.common import lean, set_aside, slices, struct_with, table, with_bytes, without

WHITE = b" \t\n\r\x0b\x0c"
SYMBOLS = b"#*$%&|<>"


@dataclass(frozen=True)
class CompressionBands:
    """``limits`` holds (bytes up to, least ratio, most ratio); ratio = raw / compressed."""

    limits: tuple[tuple[float, float, float], ...] = (
        (128, 0.60, 2.2),
        (256, 1.05, 2.2),
        (512, 1.25, 3.2),
        (1024, 1.35, 3.2),
        (4096, 1.50, 4.5),
        (16384, 1.60, 5.5),
        (float("inf"), 1.60, 7.0),
    )
    chunk_bytes: int = 4096
    chunk_low: float = 1.60
    chunk_high: float = 4.5
    #: least ratio of a full chunk over that of an ideal code for its single bytes
    chunk_gain: float = 1.0
    #: share of a document's bytes that may lie in odd chunks
    chunk_share: float = 0.10
    level: int = 3
    min_words: int = 10
    repeat_percent: int = 20

    def band(self, n: int) -> tuple[float, float]:
        return next((lo, hi) for most, lo, hi in self.limits if n <= most)


def repeated_window_words(words: list[bytes], width: int = 5) -> int:
    """Words inside any ``width``-word window that the text holds twice or more."""
    n = len(words) - width + 1
    if n < 2:
        return 0
    seen: dict[bytes, int] = {}
    ids = np.fromiter((seen.setdefault(w, len(seen)) for w in words), np.int64, len(words))
    span = len(seen)
    if span == len(words):
        return 0
    key, size = ids[:n].copy(), span
    for k in range(1, width):  # exact: the pair code is made dense again before it could overflow
        if size * span >= 1 << 62:
            _, key = np.unique(key, return_inverse=True)
            size = int(key.max()) + 1
        key = key * span + ids[k : k + n]
        size *= span
    order = np.argsort(key, kind="stable")
    same = key[order[1:]] == key[order[:-1]]
    if not same.any():
        return 0
    twice = np.zeros(n, bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    edge = np.zeros(len(words) + 1, np.int64)
    at = np.flatnonzero(twice)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + width, -1)
    return int((np.cumsum(edge[:-1]) > 0).sum())


def duplicate_lines(data: bytes) -> int:
    lines = [x for x in data.split(b"\n") if x.strip(WHITE)]
    return len(lines) - len(set(lines))


def byte_code_ratio(data: bytes) -> float:
    """The ratio that an ideal code for single bytes reaches."""
    share = np.bincount(np.frombuffer(data, np.uint8)) / len(data)
    share = share[share > 0]
    bits = float(-(share * np.log2(share)).sum())
    return 8 / bits if bits else float("inf")


def odd_chunk(chunk: bytes, ratio: float, bands: CompressionBands) -> bool:
    """A full chunk outside the chunk band or without repeats, or a last part outside the band of its length."""
    if len(chunk) < bands.chunk_bytes:
        low, high = bands.band(len(chunk))
        return not low <= ratio <= high
    return not bands.chunk_low <= ratio <= bands.chunk_high or ratio < bands.chunk_gain * byte_code_ratio(chunk)


def compression(data: bytes, bands: CompressionBands, compressor) -> tuple[float, float, float, float]:
    """Whole ratio, then the least and the most of the full chunks' ratios and the share of bytes in odd chunks.

    A text of less than a chunk is judged as a whole alone.
    """
    if not data:
        return 0.0, 0.0, 0.0, 0.0
    step = bands.chunk_bytes
    whole = len(data) / len(compressor.compress(data))
    if len(data) < step:
        return whole, whole, whole, 0.0
    ratios, odd = [], 0
    for i in range(0, len(data), step):
        chunk = data[i : i + step]
        ratio = len(chunk) / len(compressor.compress(chunk)) if len(data) > step else whole
        if len(chunk) == step:
            ratios.append(ratio)
        if odd_chunk(chunk, ratio, bands):
            odd += len(chunk)
    return whole, min(ratios), max(ratios), odd / len(data)


OUT = [
    ("n_words", T.LongType()),
    ("word_chars", T.LongType()),
    ("n_symbols", T.LongType()),
    ("n_dup_lines", T.LongType()),
    ("n_repeat_words", T.LongType()),
    ("base_failed", T.BooleanType()),
    ("ratio", T.DoubleType()),
    ("chunk_low", T.DoubleType()),
    ("chunk_high", T.DoubleType()),
    ("odd_chunks", T.DoubleType()),
    ("kept", T.BooleanType()),
]


def measure(data: bytes | None, bands: CompressionBands, compressor) -> tuple:
    data = data or b""
    words = data.split()  # on bytes: exactly the six ASCII white-space characters
    n_words = len(words)
    solid = data.translate(None, WHITE)
    chars = len(solid.decode("utf-8", "replace"))
    symbols = len(data) - len(data.translate(None, SYMBOLS))
    repeats = repeated_window_words(words)
    failed = n_words < bands.min_words or 100 * repeats > bands.repeat_percent * n_words
    whole, low, high, odd = compression(data, bands, compressor)
    lo, hi = bands.band(len(data))
    kept = not failed and lo <= whole <= hi and odd <= bands.chunk_share
    return n_words, chars, symbols, duplicate_lines(data), repeats, failed, whole, low, high, odd, kept


def quality_rules(docs: DataFrame, text: str = "text", bands: CompressionBands | None = None) -> DataFrame:
    """``docs`` with the counts, the ratios and ``kept`` for every whole text; no shuffle."""
    bands = bands or CompressionBands()
    docs = without(docs, [n for n, _ in OUT])
    schema = struct_with(docs, OUT)
    arrow = [pa.int64()] * 5 + [pa.bool_()] + [pa.float64()] * 4 + [pa.bool_()]
    own, (docs, at) = len(docs.columns), with_bytes(docs, text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        compressor = zstandard.ZstdCompressor(level=bands.level)
        for batch in batches:
            for part in slices(batch, at):  # what goes back to the JVM at once is small, however large its batches are
                rows = [measure(x.as_py(), bands, compressor) for x in part.column(at).cast(pa.binary())]
                cols = [pa.array(c, t) for c, t in zip(zip(*rows), arrow, strict=True)]
                yield pa.RecordBatch.from_arrays([*part.columns[:own], *cols], names=schema.names)

    return docs.mapInArrow(lean(run), schema)


def passing(docs: DataFrame, text: str = "text", bands: CompressionBands | None = None) -> DataFrame:
    """The documents that pass, with their own columns, whatever their names."""
    own, back = set_aside(docs, [n for n, _ in OUT])
    return back(quality_rules(own, text, bands).filter("kept"))


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = quality_rules(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", *[n for n, _ in OUT])


QUERIES = {"op6_quality_rules": op6_quality_rules}
ORACLE_SQL: dict[str, str] = {}
