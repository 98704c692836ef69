"""Operator 7 – best-fit packing in bulk-synchronous rounds.

Every document becomes token pieces of at most one sequence.  Pieces and the gaps of open sequences are
tables of their own.  A round takes the largest pieces still unplaced and

* sorts them and the gaps that can hold any of them by size, together, over range partitions;
* sweeps every partition from the largest size down: a piece goes to its successor, the least gap at
  hand that holds it, and a gap that shrank comes up again at its new size;
* matches the pieces that found no gap in their partition with gaps left in partitions of larger sizes.
  Pieces that want the same gaps are told apart by rank: partitions report how many they have left,
  and each rank of a piece maps to a rank of a gap;
* updates the gaps.

Sequences are opened only for pieces that no gap holds.  Tables of a round are written, so a lost
executor costs one round; the driver sees two counts per partition.

Defined results: a null or empty text is the end token alone; a text longer than a sequence is cut,
all pieces but its last are full; repeated rows, rows without an id and ties are packed each; an empty
table gives an empty result; the operator returns the id column and its own columns only, so other
columns of the input cannot clash.
"""

from __future__ import annotations

import json
import os
import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from heapq import heappop, heappush

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from joindash.llm.common import held, lean, local_rows, slices, struct_with, table, without, written


@dataclass(frozen=True)
class PackParams:
    tokenizer: str
    capacity: int = 4096
    end_id: int = 1
    #: words and bytes of words whose ids a worker remembers; beyond them it keeps the more frequent ones
    memory: int = 200_000
    memory_bytes: int = 8 << 20
    #: bytes of text that are split at a time
    text_bytes: int = 1 << 20
    #: a round takes pieces longer than the longest one left divided by this
    spread: int = 4
    #: pieces and gaps of a round that one task sweeps; more are dealt over range partitions
    one_task: int = 16_384


# The rules of the vocabulary file for which words can be taken one by one.
WORD_RULES = {
    "normalizer": {
        "type": "Sequence",
        "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}, {"type": "Lowercase"}],
    },
    "pre_tokenizer": {
        "type": "Sequence",
        "pretokenizers": [
            {"type": "Split", "pattern": {"Regex": r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"}, "behavior": "Removed", "invert": True},
            {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False},
        ],
    },
    "post_processor": None,
    "truncation": None,
    "padding": None,
}
CLOSING = ".,;:!?|*#$%&"
#: ASCII letter or digit, closing marks, end of the word
CLOSED = rf"([0-9A-Za-z])([{CLOSING}]+)([ \t-\r]|$)"


def takes_words(rules: dict) -> bool:
    """Whether a vocabulary file's ids of a text are the ids of its words in a row.

    Under ``WORD_RULES`` nothing reaches across white space, which is dropped, and a token never spans
    an ASCII letter or digit and the closing marks behind it: neither composes with the other, and the
    split puts them apart.  An added token is looked up in the raw text first; it must not hold white
    space and must end in a mark that a cut never precedes.
    """
    plain = all(rules.get(k) == v for k, v in WORD_RULES.items()) and rules["model"]["type"] == "BPE" and not rules["model"].get("dropout")
    whole = rf"\S*[^\s0-9A-Za-z{CLOSING}]"
    added = rules.get("added_tokens") or []
    return plain and all(re.fullmatch(whole, t["content"]) and not (t["single_word"] or t["lstrip"] or t["rstrip"] or t["normalized"]) for t in added)


class TextCoder:
    """Token ids of texts.  With a vocabulary file whose rules keep words apart, each distinct word is
    encoded once and looked up afterwards, a batch at a time; with any other file, whole texts are encoded."""

    def __init__(self, p: PackParams):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # tasks are the parallelism; more threads only cost switches
        from tokenizers import Tokenizer

        with open(p.tokenizer, encoding="utf-8") as f:
            rules = json.load(f)
        self.p, self.tokenizer, self.by_word = p, Tokenizer.from_file(p.tokenizer), takes_words(rules)
        self.model, suffix = self.tokenizer.model, rules["model"].get("end_of_word_suffix")
        self.ends = np.zeros(self.tokenizer.get_vocab_size(), bool)
        for token, i in rules["model"]["vocab"].items():
            self.ends[i] = bool(suffix) and token.endswith(suffix)
        self._forget()

    def _forget(self) -> None:
        self.words, self.sizes, self.ids, self.seen = pa.array([], pa.string()), np.zeros(0, np.int32), np.zeros(0, "<u4"), np.zeros(0, np.int64)

    def _gather(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The ids of known words in a row, and where each word's end."""
        size = self.sizes[at]
        begin = (np.cumsum(self.sizes, dtype=np.int64) - self.sizes)[at]
        end = np.cumsum(size, dtype=np.int64)
        total = int(end[-1]) if len(end) else 0
        return self.ids[np.arange(total) + np.repeat(begin - (end - size), size)], end

    def _keep_frequent(self) -> None:
        """Keep the half of the words that was seen most often, as long as they are short enough."""
        often = np.sort(np.argsort(-self.seen, kind="stable")[: self.p.memory // 2])
        words = self.words.take(pa.array(often))
        if words.nbytes > self.p.memory_bytes // 2:
            return self._forget()
        self.ids, _ = self._gather(often)
        self.words, self.sizes, self.seen = words, self.sizes[often], self.seen[often] // 2

    def _encode(self, texts: list[str], at_once: int = 256) -> list[list[int]]:
        """The library's ids; a few texts at a time, because its encodings take far more room than ids."""
        batches = (texts[i : i + at_once] for i in range(0, len(texts), at_once))
        return [e.ids for batch in batches for e in self.tokenizer.encode_batch_fast(batch, add_special_tokens=False)]

    def _encode_letters(self, words: list[str], side: int = 64) -> list:
        """Words of letters, side by side: where each gave one word end, these cut the ids apart."""
        out: list = []
        lines = [words[i : i + side] for i in range(0, len(words), side)]
        for line, ids in zip(lines, self._encode([" ".join(x) for x in lines]), strict=True):
            cut = np.flatnonzero(self.ends[ids]) + 1
            out += [ids[a:b] for a, b in zip([0, *cut], cut, strict=False)] if len(cut) == len(line) else self._encode(line)
        return out

    def _learn(self, words: list[str]) -> None:
        """Ids of new words; a word of ASCII letters is one token sequence of the model once lower-cased."""
        ids: list = [None] * len(words)
        letters, others, model = [], [], self.model.tokenize
        for i, w in enumerate(words):
            if w.isascii() and w.isalpha():
                ids[i] = [t.id for t in model(w.lower())]
            else:
                (letters if w.isalpha() else others).append(i)
        for at, made in ((letters, self._encode_letters([words[i] for i in letters])), (others, self._encode([words[i] for i in others]))):
            for i, x in zip(at, made, strict=True):
                ids[i] = x
        sizes = np.fromiter(map(len, ids), np.int32, len(ids))
        self.sizes = np.concatenate([self.sizes, sizes])
        self.ids = np.concatenate([self.ids, np.fromiter((i for x in ids for i in x), "<u4", int(sizes.sum()))])

    def texts(self, column: pa.Array) -> list[bytes]:
        """Ids of each text, as little-endian 32-bit bytes."""
        column = column.fill_null("")
        if not self.by_word:
            return [np.array(ids, "<u4").tobytes() for ids in self._encode(column.to_pylist())]
        cut = pc.ascii_split_whitespace(pc.replace_substring_regex(column, CLOSED, r"\1 \2\3"))
        words = cut.flatten()
        code = pc.index_in(words, value_set=self.words)
        missing = code.is_null()
        unknown = words.filter(missing)
        new, first = unknown.unique(), len(self.words)
        self._learn(new.to_pylist())
        self.words = pa.concat_arrays([self.words, new])
        at = code.fill_null(0).to_numpy().astype(np.int64)
        at[missing.to_numpy(zero_copy_only=False)] = first + pc.index_in(unknown, value_set=new).to_numpy()
        ids, end = self._gather(at)
        data, bounds = ids.tobytes(), 4 * np.concatenate(([0], end))[cut.offsets.to_numpy() - cut.offsets[0].as_py()]
        self.seen = np.bincount(at, minlength=len(self.words)) + np.concatenate([self.seen, np.zeros(len(new), np.int64)])
        if len(self.words) > self.p.memory or self.words.nbytes > self.p.memory_bytes:
            self._keep_frequent()
        return [data[a:b] for a, b in zip(bounds, bounds[1:], strict=False)]


def coder(p: PackParams) -> TextCoder:
    """This worker's coder; what it remembers lasts over the tasks that the worker runs in a row."""
    return held(p, lambda: TextCoder(p))


PIECE = [
    ("piece", T.IntegerType()),
    ("start", T.LongType()),
    ("length", T.LongType()),
    ("ids_crc32", T.LongType()),
]


def token_pieces(docs: DataFrame, p: PackParams, text: str = "text", keep_ids: bool = False) -> DataFrame:
    """One row per piece: ``docs`` without its text, with the piece's place, length, checksum and ids."""
    rest = without(docs, [n for n, _ in PIECE] + ["ids", text])
    schema = struct_with(rest, PIECE + ([("ids", T.BinaryType())] if keep_ids else []))
    types = [pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary()]
    end, step = np.array([p.end_id], "<u4").tobytes(), 4 * p.capacity

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own_coder = coder(p)
        for batch in batches:
            for part in slices(batch, batch.num_columns - 1, p.text_bytes):
                row, cols = [], [[], [], [], [], []]
                for i, ids in enumerate(own_coder.texts(part.column(part.num_columns - 1))):
                    ids += end
                    for k, at in enumerate(range(0, len(ids), step)):
                        own = ids[at : at + step]
                        row.append(i)
                        for c, v in zip(cols, (k, at // 4, len(own) // 4, zlib.crc32(own), own if keep_ids else None), strict=True):
                            c.append(v)
                made = [pa.array(c, t) for c, t in zip(cols[: 4 + keep_ids], types, strict=False)]
                taken = [c.take(pa.array(row, pa.int64())) for c in part.columns[:-1]]
                yield pa.RecordBatch.from_arrays([*taken, *made], names=schema.names)

    return docs.select(*[F.col(f"`{c}`") for c in rest.columns], F.col(text).alias("__jd_text")).mapInArrow(lean(run, holds=True), schema)


# ---- the rounds -----------------------------------------------------------------------------

#: what became of a row of a sweep; a partition's last row says what it has left: pieces (rank) and the
#: greatest of them (size), gaps (seq) and the least of them (offset)
PLACED, PIECE_LEFT, GAP_LEFT, GAP_BELOW, SUMMARY = range(5)
SWEPT = "kind int, part int, rank long, id long, size long, seq long, offset long"


def sweep(sizes: list[int], ids: list[int], gap: list[bool], capacity: int) -> list[tuple]:
    """One partition, largest size first and gaps before pieces: rows (kind, rank, id, size, seq, offset).

    ``stack`` holds the gaps that take the piece at hand, the least on top; a gap that has become too
    small waits in ``below`` until the sweep has come down to it.  Gaps are left in order from the top.
    """
    out, stack, below, left = [], [], [], 0
    for size, own, is_gap in zip(sizes, ids, gap, strict=True):
        while below and -below[0][0] >= size:
            free, seq = heappop(below)
            stack.append((-free, seq))
        if is_gap:
            stack.append((size, own))
        elif stack:
            free, seq = stack.pop()
            out.append((PLACED, None, own, size, seq, capacity - free))
            if free - size >= size:
                stack.append((free - size, seq))
            elif free > size:
                heappush(below, (size - free, seq))
        else:
            out.append((PIECE_LEFT, left, own, size, None, None))
            left += 1
    out += [(GAP_LEFT, i, None, free, seq, None) for i, (free, seq) in enumerate(reversed(stack))]
    return out + [(GAP_BELOW, None, None, -free, seq, None) for free, seq in below]


def summary(rows: list[tuple]) -> tuple:
    pieces, gaps = ([r for r in rows if r[0] == kind] for kind in (PIECE_LEFT, GAP_LEFT))
    return SUMMARY, len(pieces), None, max((r[3] for r in pieces), default=0), len(gaps), min((r[3] for r in gaps), default=0)


def swept(pieces: DataFrame, gaps: DataFrame, capacity: int, one_task: bool = False) -> DataFrame:
    """The rows of all sweeps over ``pieces`` (id, size) and ``gaps`` (seq, size)."""
    both = pieces.select(F.col("size"), F.col("id"), F.lit(0).alias("gap")).unionByName(
        gaps.select(F.col("size"), F.col("seq").alias("id"), F.lit(1).alias("gap"))
    )
    order = [F.desc("size"), F.desc("gap"), "id"]
    dealt = both.coalesce(1) if one_task else both.repartitionByRange(*order)
    dealt = dealt.sortWithinPartitions(*order).withColumn("part", F.spark_partition_id())
    struct_with(both, [])
    names = [f.split()[0] for f in SWEPT.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        size, own, gap, part = (pa.chunked_array([b.column(i) for b in got]).to_pylist() for i in range(4))
        rows = sweep(size, own, gap, capacity)
        kind, rank, ids, sizes, seq, offset = zip(*rows, summary(rows), strict=True)
        cols = [kind, [part[0]] * len(kind), rank, ids, sizes, seq, offset]
        types = [pa.int32(), pa.int32(), *[pa.int64()] * 5]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=names)

    return dealt.mapInArrow(lean(run), SWEPT)


def rank_plan(left: list[tuple[int, int, int, int, int]]) -> list[tuple[int, int, int, int, int, int]]:
    """Which ranks of pieces left in a partition go to which ranks of gaps left in an earlier one.

    ``left``: (partition, pieces, their greatest size, gaps, their least size), in order of falling sizes.
    Returns (pieces' partition, first rank, end, gaps' partition, first rank, pieces per gap): the last
    partition's gaps are the least that hold a piece, so they are used first.
    """
    plan, open_ = [], []
    for part, pieces, most, gaps, least in left:
        at = 0
        while at < pieces and open_:
            source, first, n, size = open_.pop()
            each = size // most
            take = min(pieces - at, n * each)
            plan.append((part, at, at + take, source, first, each))
            used = -(-take // each)
            if used < n:
                open_.append((source, first + used, n - used, size))
            at += take
        if gaps:
            open_.append((part, 0, gaps, least))
    return plan


def _matched(rows: DataFrame, steps: DataFrame, capacity: int) -> DataFrame:
    """Every gap that the sweeps left, beside the pieces that its rank gets: (id, size, seq, offset), with
    the gap's size after them and whether it is the gap's first row."""
    pieces = rows.filter(F.col("kind") == PIECE_LEFT).join(steps, _in_step(), "inner")
    pieces = pieces.select(F.col("from_part").alias("part"), F.expr("first + (rank - a) div each").alias("rank"), F.col("rank").alias("turn"), "id", "size")
    gaps = rows.filter(F.col("kind") == GAP_LEFT).select("part", "rank", "seq", F.col("size").alias("free"))
    one = Window.partitionBy("part", "rank")  # at most as many pieces as the capacity has tokens
    before = one.orderBy("turn").rowsBetween(Window.unboundedPreceding, -1)
    taken = lambda w: F.coalesce(F.sum("size").over(w), F.lit(0))
    return gaps.join(pieces, ["part", "rank"], "left").select(
        "id", "size", "seq", (F.lit(capacity) - F.col("free") + taken(before)).alias("offset"), (F.col("free") - taken(one)).alias("rest"), (F.count("turn").over(before) == 0).alias("head")
    )


def _in_step():
    return (F.col("part") == F.col("to_part")) & (F.col("rank") >= F.col("a")) & (F.col("rank") < F.col("b"))


def _shares(left: DataFrame | None, gaps: DataFrame, low: int, top: int) -> tuple:
    """Of the pieces left: number, sum and greatest; of the gaps: sum and greatest, and of those that hold a
    piece of this class (``low`` to ``top``) the number, the sum, the most pieces that fit and the least that do."""
    piece, gap = F.when(F.col("piece"), F.col("size")), F.when(~F.col("piece"), F.col("size"))
    both = gaps.select(F.lit(False).alias("piece"), "size")
    if left is not None:
        both = both.unionByName(left.select(F.lit(True).alias("piece"), "size"))
    fits = F.when(gap >= low, gap)
    row = both.agg(F.count(piece), F.sum(piece), F.max(piece), F.sum(gap), F.max(gap), F.count(fits), F.sum(fits), F.sum(F.floor(fits / low)), F.sum(F.floor(fits / top))).first()
    return tuple(x or 0 for x in row)


def best_fit_rounds(pieces: DataFrame, capacity: int, spread: int = 4, one_task: int = 16_384, most_tables: int = 8) -> DataFrame:
    """(id, seq, offset) of every piece (id, size).

    A class of sizes is done with before the next one starts.  The driver holds the number of pieces of
    each size, which the capacity bounds, and two steps per partition."""
    spark = pieces.sparkSession
    many = {r[0]: r[1] for r in pieces.groupBy("size").count().collect()}
    opened, low, top, left, done = 0, capacity + 1, capacity, None, []
    gaps, tables = local_rows(spark, [], "seq long, size long"), 0
    while True:
        n, volume = 0, 0
        if left is not None:
            n, volume, top, free, widest, n_gaps, room, most, least = _shares(left, gaps, low, top)
        if not n:  # the next class of sizes
            top = max((x for x in many if x < low), default=0)
            if not top:
                break
            high, low = low, top // spread + 1
            left = pieces.filter((F.col("size") >= low) & (F.col("size") < high)).select("id", "size")
            of_class = {x: k for x, k in many.items() if low <= x < high}
            n, volume = sum(of_class.values()), sum(x * k for x, k in of_class.items())
            *_, free, widest, n_gaps, room, most, least = _shares(None, gaps, low, top)
        below = sum(x * k for x, k in many.items() if x < low)
        # sequences that the pieces left cannot do without, by size, volume and number; and as many as they
        # could use at once, as long as all that is unplaced needs them
        new = [-(-(volume - room) // capacity), -(-(n - most) // (capacity // low)), min(-(-(n - least) // (capacity // top)), -(-(volume + below - free) // capacity))]
        if widest < top:
            new.append(-(-left.filter(F.col("size") > widest).agg(F.sum("size")).first()[0] // capacity))
        if (new := max(new)) > 0:
            gaps = gaps.unionByName(spark.range(opened, opened + new).select(F.col("id").alias("seq"), F.lit(capacity).cast("long").alias("size")))
            opened, n_gaps = opened + new, n_gaps + new
        rows = written(swept(left, gaps.filter(F.col("size") >= low), capacity, n + n_gaps <= one_task))
        ends = sorted(rows.filter(F.col("kind") == SUMMARY).select("part", "rank", "size", "seq", "offset").collect())  # one row per partition
        plan = rank_plan([tuple(r) for r in ends])
        done.append(rows.filter(F.col("kind") == PLACED).select("id", "seq", "offset"))
        left = rows.filter(F.col("kind") == PIECE_LEFT).select("part", "rank", "id", "size")
        fresh = rows.filter(F.col("kind").isin(GAP_LEFT, GAP_BELOW)).select("seq", "size")
        if plan:
            steps = F.broadcast(local_rows(spark, plan, "to_part int, a long, b long, from_part int, first long, each long"))  # two rows per partition
            met = written(_matched(rows, steps, capacity))
            done.append(met.filter("id is not null").select("id", "seq", "offset"))
            fresh = met.filter("head").select("seq", F.col("rest").alias("size")).unionByName(rows.filter(F.col("kind") == GAP_BELOW).select("seq", "size"))
            left = left.join(steps, _in_step(), "left_anti")
        if sum(r["rank"] for r in ends) == sum(b - a for _, a, b, *_ in plan):
            left = None
        else:
            left = left.select("id", "size")
        gaps, tables = gaps.filter(F.col("size") < low).unionByName(fresh.filter("size > 0")), tables + 1
        if tables == most_tables:  # plans stay short, however many rounds there are
            gaps, tables = written(gaps), 0
    out = local_rows(spark, [], "id long, seq long, offset long")
    for d in done:
        out = out.unionByName(d)
    return out


def pack(pieces: DataFrame, capacity: int, length: str = "length", spread: int = 4, one_task: int = 16_384) -> DataFrame:
    """``pieces`` with sequence_id and offset.  Only a row number and the length take part in the rounds."""
    numbered = written(without(pieces, ["sequence_id", "offset"]).withColumn("__jd_id", F.monotonically_increasing_id()), texts=True)
    narrow = numbered.select(F.col("__jd_id").alias("id"), F.col(length).alias("size"))
    placed = best_fit_rounds(narrow, capacity, spread, one_task).select(F.col("id").alias("__jd_id"), F.col("seq").alias("sequence_id"), "offset")
    return numbered.join(placed, "__jd_id").drop("__jd_id")


def sequences(packed: DataFrame, ids: str = "ids") -> DataFrame:
    """Packed rows with ids, as one row of token bytes per sequence (bounded: at most one capacity each)."""
    part = F.struct("offset", ids)
    joined = F.aggregate(F.array_sort(F.collect_list(part)), F.lit(b""), lambda t, x: F.concat(t, x[ids]))
    return packed.groupBy("sequence_id").agg(joined.alias("ids"), F.sum("length").alias("n_tokens"))


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def pack_documents(docs: DataFrame, id_col: str = "doc_id", text: str = "text", p: PackParams | None = None) -> DataFrame:
    p = p or PackParams(default_tokenizer())
    return pack(token_pieces(docs.select(id_col, text), p, text), p.capacity, spread=p.spread, one_task=p.one_task)


def op7_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"))


QUERIES = {"op7_best_fit_packing": op7_best_fit_packing}
ORACLE_SQL: dict[str, str] = {}
