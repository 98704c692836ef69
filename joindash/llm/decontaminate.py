"""Operator 2 – benchmark decontamination with an FM-index per training shard.

A shard is a bounded stretch of a partition.  Its words become symbols; only stretches of words that
the benchmark also uses, long enough to hold the shortest phrase, enter the index (a phrase cannot
touch any other word, so nothing is lost).  The index is a suffix array of that sequence, the
transform of its preceding symbols in a wavelet matrix, and suffix positions sampled along the text.
All phrases are searched backwards together; occurrences walk to the next sampled position; hits merge
into spans.  Phrases are a stated query set: they travel to the shards in blocks of checked size.

Defined results: null and empty texts have no words and no hits; an item without words is left out,
one without an id hits and is named nowhere; an empty benchmark leaves every document clean; items that share a phrase all count; repeated rows each
get their own result; input columns named like an output column are replaced.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from joindash.llm.common import bytes_of, lean, set_aside, slices, struct_with, table, with_bytes, without

#: Lower case for A-Z, a space for every other ASCII character that is no letter or digit.
FOLD = bytes(
    c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256)
)
WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


@dataclass(frozen=True)
class DecontamParams:
    window: int = 10
    sample: int = 8
    #: words of one shard index
    shard_words: int = 2_000_000
    #: text bytes of the benchmark that travel to the executors at once
    block_bytes: int = 32 << 20


def words_of(data: bytes | None) -> list[bytes]:
    return (data or b"").translate(FOLD).split()


# ---- the phrases ----------------------------------------------------------------------------


@dataclass
class Phrases:
    """Distinct windows by length, as symbol matrices, and the items that hold each of them."""

    vocab: dict[bytes, int] = field(default_factory=dict)
    matrices: list[np.ndarray] = field(default_factory=list)
    items: list[list[str]] = field(default_factory=list)  # by phrase number, over all matrices

    @staticmethod
    def build(rows: list[tuple[str, bytes]], window: int) -> Phrases:
        out, found = Phrases(), {}
        for item, data in rows:
            ids = [out.vocab.setdefault(w, len(out.vocab) + 1) for w in words_of(data)]
            for i in range(max(1, len(ids) - window + 1) if ids else 0):
                found.setdefault(tuple(ids[i : i + window]), set()).update([item] if item is not None else [])
        for n in sorted({len(k) for k in found}):
            keys = [k for k in found if len(k) == n]
            out.matrices.append(np.array(keys, np.int64))
            out.items += [sorted(found[k]) for k in keys]
        return out

    @property
    def shortest(self) -> int:
        return min((m.shape[1] for m in self.matrices), default=0)


# ---- the index ------------------------------------------------------------------------------


class WaveletMatrix:
    """Ranks over a symbol sequence; one bit vector with running counts a level."""

    def __init__(self, symbols: np.ndarray, top: int):
        self.bits = max(1, int(top).bit_length())
        self.n = len(symbols)
        self.ones, self.zeros = [], []
        for level in range(self.bits - 1, -1, -1):
            bit = (symbols >> level) & 1
            self.ones.append(np.concatenate(([0], np.cumsum(bit))).astype(np.int32))
            self.zeros.append(int(self.n - self.ones[-1][-1]))
            symbols = np.concatenate((symbols[bit == 0], symbols[bit == 1]))

    def place(self, c: np.ndarray, i: np.ndarray) -> np.ndarray:
        """Where the prefix of length ``i`` ends in the last level's order, along the bits of ``c``."""
        i = i.astype(np.int64)
        for level in range(self.bits):
            one = self.ones[level][i]
            bit = (c >> (self.bits - 1 - level)) & 1
            i = np.where(bit == 1, self.zeros[level] + one, i - one)
        return i

    def access(self, i: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The symbol at ``i`` and its place in the last level's order."""
        c = np.zeros(len(i), np.int64)
        for level in range(self.bits):
            ones = self.ones[level]
            one = ones[i]
            bit = ones[i + 1] - one
            i = np.where(bit == 1, self.zeros[level] + one, i - one)
            c = (c << 1) | bit
        return c, i


def suffix_array(text: np.ndarray) -> np.ndarray:
    """Order of the suffixes of ``text``; zeros separate runs and sort by their place, below all words."""
    n = len(text)
    gap = text == 0
    rank = np.where(gap, np.cumsum(gap) - 1, text + int(gap.sum()))
    width = (int(rank.max()) + 1).bit_length() if n else 1
    packed = min(4, 62 // width)
    key = rank.copy()
    for k in range(1, packed):
        ahead = np.zeros(n, np.int64)
        ahead[: max(0, n - k)] = rank[k:] + 1
        key = (key << width) | ahead
    step = packed
    while True:
        order = np.argsort(key, kind="stable")
        ordered = key[order]
        number = np.concatenate(([0], np.cumsum(ordered[1:] != ordered[:-1])))
        if n == 0 or number[-1] == n - 1:
            return order
        rank = np.empty(n, np.int64)
        rank[order] = number
        ahead = np.zeros(n, np.int64)
        ahead[: max(0, n - step)] = rank[step:] + 1
        key = rank * (n + 1) + ahead
        step *= 2


class FMIndex:
    """Backward search and sampled location over a sequence whose zeros separate runs."""

    def __init__(self, text: np.ndarray, sample: int):
        n = len(text)
        order = suffix_array(text)
        before = text[order - 1]  # the first suffix is preceded by the last symbol, a zero
        top = int(text.max())
        self.rank = WaveletMatrix(before, top)
        every = np.arange(top + 2)
        self.first = np.searchsorted(np.sort(text), every)
        self.base = self.rank.place(every[:-1], np.zeros(top + 1, np.int64))
        starts = np.concatenate(([True], text[:-1] == 0))  # so that no walk crosses a separator
        at = np.where(starts[order] | (order % sample == 0), order, -1)
        self.sampled, self.top, self.n = at, top, n

    def search(self, phrases: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rows [low, high) of the suffixes that begin with each phrase."""
        m = len(phrases)
        low, high = np.zeros(m, np.int64), np.full(m, self.n, np.int64)
        high[(phrases > self.top).any(axis=1)] = 0
        alive = np.flatnonzero(low < high)
        for k in range(phrases.shape[1] - 1, -1, -1):
            if not len(alive):
                break
            c = phrases[alive, k]
            low[alive] = self.first[c] + self.rank.place(c, low[alive]) - self.base[c]
            high[alive] = self.first[c] + self.rank.place(c, high[alive]) - self.base[c]
            alive = alive[low[alive] < high[alive]]
        return low, np.maximum(low, high)

    def locate(self, rows: np.ndarray) -> np.ndarray:
        """Text positions of suffix rows, by steps to the preceding suffix until a sampled one."""
        out, rows = np.empty(len(rows), np.int64), rows.copy()
        open_, steps = np.arange(len(rows)), 0
        while len(open_):
            at = self.sampled[rows]
            hit = at >= 0
            out[open_[hit]] = at[hit] + steps
            open_, rows = open_[~hit], rows[~hit]
            if len(open_):
                c, place = self.rank.access(rows)
                rows = self.first[c] + place - self.base[c]
            steps += 1
        return out


def occurrences(symbols: np.ndarray, phrases: Phrases, sample: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(phrase length, positions, phrase numbers) of every occurrence in a shard's symbol sequence."""
    known = symbols > 0
    edge = np.flatnonzero(np.diff(np.concatenate(([False], known, [False])).astype(np.int8)))
    begin, end = edge[::2], edge[1::2]
    long_enough = end - begin >= phrases.shortest
    begin, end = begin[long_enough], end[long_enough]
    if not len(begin):
        return
    size = end - begin + 1  # with a separator after each run
    first = np.concatenate(([0], np.cumsum(size)[:-1]))
    back = np.arange(size.sum()) - np.repeat(first - begin, size)
    text = symbols[np.minimum(back, len(symbols) - 1)].astype(np.int64)
    text[first + size - 1] = 0
    index = FMIndex(text, sample)
    number = 0
    for matrix in phrases.matrices:
        low, high = index.search(matrix)
        n = high - low
        which = np.repeat(np.arange(len(matrix)), n)
        rows = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(low, n)
        if len(rows):
            yield matrix.shape[1], back[index.locate(rows)], which + number
        number += len(matrix)


# ---- documents ------------------------------------------------------------------------------


def shard_hits(datas: list[bytes | None], phrases: Phrases, p: DecontamParams) -> list[tuple[int, list[tuple[int, int]], list[str]]]:
    """(words, merged word spans [start, end), sorted item ids) of each text of one shard."""
    get, sizes, parts = phrases.vocab.get, [], []
    for data in datas:
        ids = [get(w, 0) for w in words_of(data)]
        sizes.append(len(ids))
        ids.append(0)
        parts.append(np.array(ids, np.int32))
    starts = np.concatenate(([0], np.cumsum([len(x) for x in parts])))
    symbols = np.concatenate(parts) if parts else np.zeros(0, np.int32)
    spans: list[list[tuple[int, int]]] = [[] for _ in datas]
    items: list[set[str]] = [set() for _ in datas]
    edge = np.zeros(len(symbols) + 1, np.int64)
    hit = False
    if phrases.matrices:
        for n, at, which in occurrences(symbols, phrases, p.sample):
            hit = True
            np.add.at(edge, at, 1)
            np.add.at(edge, at + n, -1)
            doc = np.searchsorted(starts, at, side="right") - 1
            for d, w in np.unique(np.stack([doc, which], 1), axis=0).tolist():
                items[d].update(phrases.items[w])
    if hit:
        inside = np.concatenate(([False], np.cumsum(edge[:-1]) > 0, [False])).astype(np.int8)
        turns = np.flatnonzero(np.diff(inside))
        for a, b in zip(turns[::2].tolist(), turns[1::2].tolist(), strict=True):
            d = int(np.searchsorted(starts, a, side="right")) - 1
            spans[d].append((a - int(starts[d]), b - int(starts[d])))
    return [(n, s, sorted(i)) for n, s, i in zip(sizes, spans, items, strict=True)]


def merge_spans(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


SPAN = T.ArrayType(T.StructType([T.StructField("start", T.IntegerType()), T.StructField("end", T.IntegerType())]))
OUT = [
    ("n_words", T.LongType()),
    ("hit_spans", SPAN),  # word positions, end exclusive
    ("hit_items", T.ArrayType(T.StringType())),
]


def _shards(batches: Iterator[pa.RecordBatch], at: int, limit: int) -> Iterator[pa.RecordBatch]:
    """Slices with about ``limit`` words (six bytes a word) in column ``at``, and never more than one batch."""
    for batch in batches:
        sizes = pc.fill_null(pc.binary_length(batch.column(at)), 0).to_numpy(zero_copy_only=False)
        cut = np.searchsorted(np.cumsum(sizes), np.arange(1, int(sizes.sum()) // (6 * limit) + 1) * 6 * limit) + 1
        edges = sorted({0, batch.num_rows, *[int(c) for c in cut if c < batch.num_rows]})
        for a, b in zip(edges, edges[1:], strict=False):
            yield batch.slice(a, b - a)


def find_contamination(docs: DataFrame, benchmark: DataFrame, text: str = "text", item_id: str = "item_id", item_text: str = "text",
                       p: DecontamParams | None = None, keep_text: bool = True) -> DataFrame:
    """``docs`` with word counts, merged hit spans and the benchmark items found in each whole text.

    Narrow: no shuffle.  The benchmark is read in as many blocks as its size asks for.
    """
    p = p or DecontamParams()
    spark = docs.sparkSession
    out = without(docs, [n for n, _ in OUT])
    rest = out if keep_text else without(out, [text])
    schema = struct_with(rest, OUT)
    n = len(rest.columns)
    items = benchmark.select(F.col(item_id).cast("string").alias("i"), bytes_of(item_text).alias("t")).filter("t is not null")
    total = items.agg(F.coalesce(F.sum(F.octet_length("t")), F.lit(0))).first()[0]
    blocks = max(1, -(-total // p.block_bytes))
    if keep_text:
        out, at = with_bytes(out, text)
    else:
        out, at = out.select(*[F.col(f"`{c}`") for c in rest.columns], bytes_of(text).alias("__jd_bytes")), n
    for block in range(blocks):
        part = items.filter(F.pmod(F.xxhash64("i"), F.lit(blocks)) == block) if blocks > 1 else items
        shipped = spark.sparkContext.broadcast(Phrases.build([(r.i, bytes(r.t)) for r in part.collect()], p.window))
        last = block == blocks - 1

        def run(batches: Iterator[pa.RecordBatch], shipped=shipped, first=block == 0, last=last) -> Iterator[pa.RecordBatch]:
            phrases = shipped.value
            place = at if at < n or first else n + len(OUT)
            for batch in _shards(batches, place, p.shard_words):
                found = shard_hits(batch.column(place).cast(pa.binary()).to_pylist(), phrases, p)
                counts = pa.array([f[0] for f in found], pa.int64())
                spans, names = [f[1] for f in found], [f[2] for f in found]
                if not first:
                    old = batch.column(n + 1).to_pylist(), batch.column(n + 2).to_pylist()
                    spans = [merge_spans([*s, *[(x["start"], x["end"]) for x in o]]) for s, o in zip(spans, old[0], strict=True)]
                    names = [sorted({*s, *o}) for s, o in zip(names, old[1], strict=True)]
                spans = pa.array([[{"start": a, "end": b} for a, b in s] for s in spans], pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())])))
                cols = [*batch.columns[:n], counts, spans, pa.array(names, pa.list_(pa.string()))]
                tail = [] if last or at < n else [batch.column(place)]
                whole = pa.RecordBatch.from_arrays([*cols, *tail], names=[*schema.names, *(["__jd_bytes"] if tail else [])])
                yield from slices(whole, at) if at < n else [whole]  # kept texts go back to the JVM in small batches

        target = schema if last or at < n else T.StructType([*schema.fields, T.StructField("__jd_bytes", T.BinaryType())])
        out = out.mapInArrow(lean(run), target)
    return out


def removal_text(text: str | None, spans: list[tuple[int, int]]) -> str | None:
    """``text`` without the words of the spans and what stands between them."""
    if not text or not spans:
        return text
    at = [(m.start(), m.end()) for m in WORD.finditer(text)]
    out, last = [], 0
    for a, b in spans:
        out.append(text[last : at[a][0]])
        last = at[b - 1][1]
    return "".join([*out, text[last:]])


def remove_spans(found: DataFrame, text: str = "text", name: str = "clean_text") -> DataFrame:
    """The output of ``find_contamination`` with the text cut free of its hit spans."""
    schema = struct_with(without(found, [name]), [(name, T.StringType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, spans = batch.column(text).to_pylist(), batch.column("hit_spans").to_pylist()
            clean = [removal_text(t, [(x["start"], x["end"]) for x in s or []]) for t, s in zip(texts, spans, strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(clean, pa.string())], names=schema.names)

    return without(found, [name]).mapInArrow(lean(run), schema)


def without_contaminated(docs: DataFrame, benchmark: DataFrame, text: str = "text", p: DecontamParams | None = None) -> DataFrame:
    """The documents that hold no benchmark phrase, with their own columns."""
    own, back = set_aside(docs, [n for n, _ in OUT])
    return back(find_contamination(own, benchmark, text, p=p).filter(F.size("hit_spans") == 0))


def digest(items: list[str]) -> str:
    return hashlib.sha256(",".join(items).encode()).hexdigest()


def op2_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = find_contamination(docs, table(spark, sf_dir, "benchmark"), keep_text=False)
    n_hit = F.aggregate("hit_spans", F.lit(0).cast("long"), lambda t, s: t + s["end"] - s["start"])
    return found.select(
        "doc_id",
        "n_words",
        n_hit.alias("n_hit"),
        F.size("hit_items").cast("long").alias("n_items"),
        F.sha2(F.array_join("hit_items", ","), 256).alias("items_sha256"),
        (n_hit > 0).alias("contaminated"),
    )


QUERIES = {"op2_benchmark_decontamination": op2_benchmark_decontamination}
ORACLE_SQL: dict[str, str] = {}
