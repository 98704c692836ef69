"""Operator 1 – SimHash near-duplicates by a binary-trie self-join.

Fingerprints are 64-bit majority sketches of word shingles.  Linking works on distinct fingerprints:

* A *route* orders the 64 bits so that some blocks come first.  Two fingerprints within the error
  budget agree on all leading blocks of at least one route (pigeonhole), so that route's trie keeps
  them below one node at the depth of these blocks.  More rows give longer leading parts.
* Every such node is a subtree that is joined with itself: pairs of nodes descend together, differing
  bits add up, and a pair whose sum exceeds the budget is pruned.  All subtrees of a partition
  descend at once, level by level, in numpy; only two single values are compared directly.
* A node with too many fingerprints is first split, as a distributed table of node pairs, by the same
  rule, until each unit of work is bounded.
* Units return spanning links only; components come from rounds of contraction, all distributed.

Defined results: null, empty and blank texts have fingerprint zero and link like any other; repeated
rows and equal texts share a component; an empty table gives an empty result; a text with fewer words
than a shingle is one shingle; input columns named like an output column are replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from joindash.llm.common import bytes_of, drop_written, few, lean, struct_with, table, without, written

#: BITS[v] holds the eight bits of the byte v, lowest first.
BITS = ((np.arange(256)[:, None] >> np.arange(8)) & 1).astype(np.int64)
PLACES = np.arange(8, dtype=np.int64) * 256


@dataclass(frozen=True)
class SimHashParams:
    width: int = 3
    budget: int = 3
    seed: int = 42
    #: a route's leading part is lengthened while a node would hold more fingerprints on average
    node_fill: int = 256
    #: fingerprints of one unit of work
    unit_rows: int = 8192
    #: trie levels by which an overfull node is split at a time
    split_bits: int = 4


def shingle_digests(data: bytes | None, p: SimHashParams) -> list[int]:
    """Digests of a text's word shingles, in UTF-8; bytes.lower() and bytes.split() know ASCII only."""
    import xxhash

    words = (data or b"").lower().split()
    if not words:
        return []
    digest, seed = xxhash.xxh64_intdigest, p.seed
    flat = b" ".join(words)
    if len(words) <= p.width:
        return [digest(flat, seed)]
    sizes = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(sizes + 1) - 1
    begins = (ends - sizes)[: len(words) - p.width + 1].tolist()
    return [digest(flat[a:b], seed) for a, b in zip(begins, ends[p.width - 1 :].tolist(), strict=True)]


def fingerprint(data: bytes | None, p: SimHashParams) -> int:
    """Signed 64-bit fingerprint of a text in UTF-8."""
    return majority(shingle_digests(data, p))


def majority(hashes: list[int]) -> int:
    """The signed 64-bit number whose bits are set in over half of the digests; zero for none."""
    if not hashes:
        return 0
    counts = np.zeros(64, np.int64)
    for i in range(0, len(hashes), 1 << 16):
        octets = np.array(hashes[i : i + (1 << 16)], "<u8").view(np.uint8).reshape(-1, 8)
        counts += (np.bincount((octets + PLACES).ravel(), minlength=2048).reshape(8, 256) @ BITS).ravel()
    value = sum(1 << int(b) for b in np.flatnonzero(2 * counts > len(hashes)))
    return value - (1 << 64) if value >> 63 else value


def fingerprints(docs: DataFrame, text: str = "text", p: SimHashParams | None = None, name: str = "__jd_fp") -> DataFrame:
    """``docs`` without its text column, with the fingerprint as a signed long."""
    p = p or SimHashParams()
    rest = without(docs, [name, text])
    schema = struct_with(rest, [(name, T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            prints = [fingerprint(x.as_py(), p) for x in batch.column(batch.num_columns - 1)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(prints, pa.int64())], names=schema.names)

    keep = [F.col(f"`{c}`") for c in rest.columns]
    return docs.select(*keep, bytes_of(text).alias("__jd_bytes")).mapInArrow(lean(run), schema)


# ---- routes ---------------------------------------------------------------------------------


@dataclass(frozen=True)
class Routes:
    """Bit orders: ``cuts`` are the blocks (low bit, width), ``orders`` put the chosen ones first."""

    cuts: tuple[tuple[int, int], ...]
    orders: tuple[tuple[int, ...], ...]
    lead: tuple[int, ...]  # leading bits of each order

    @staticmethod
    def plan(rows: int, p: SimHashParams) -> Routes:
        for blocks in range(p.budget + 1, 17):
            edge = [64 * i // blocks for i in range(blocks + 1)]
            cuts = tuple((edge[i], edge[i + 1] - edge[i]) for i in range(blocks))
            chosen = list(combinations(range(blocks), blocks - p.budget))
            lead = tuple(sum(cuts[b][1] for b in c) for c in chosen)
            if rows <= p.node_fill << min(lead) or blocks == p.budget + 4:
                orders = tuple((*c, *[b for b in range(blocks) if b not in c]) for c in chosen)
                return Routes(cuts, orders, lead)
        raise AssertionError

    def column(self, fp: Column, k: int) -> Column:
        """The fingerprint with its bits in the order of route ``k``; the first block is highest."""
        out, top = F.lit(0).cast("long"), 64
        for b in self.orders[k]:
            low, width = self.cuts[b]
            top -= width
            piece = F.shiftrightunsigned(fp, low).bitwiseAND(F.lit((1 << width) - 1 if width < 64 else -1))
            out = out.bitwiseOR(F.shiftleft(piece, top))
        return out

    def undo(self, k: np.ndarray, values: np.ndarray) -> np.ndarray:
        out = np.zeros_like(values)
        for r, order in enumerate(self.orders):
            at = np.flatnonzero(k == r)
            if len(at):
                top = 64
                for b in order:
                    low, width = self.cuts[b]
                    top -= width
                    out[at] |= ((values[at] >> np.uint64(top)) & np.uint64((1 << width) - 1)) << np.uint64(low)
        return out


def _prefix(value: Column, bits: int) -> Column:
    return F.lit(0).cast("long") if bits == 0 else F.shiftrightunsigned(value, 64 - bits)


# ---- joining subtrees -----------------------------------------------------------------------


def trie_links(values: np.ndarray, starts: np.ndarray, ends: np.ndarray, budget: int) -> tuple[np.ndarray, np.ndarray, dict[str, int]]:
    """Spanning links among the sorted distinct ``values`` of each subtree [start, end), as index arrays,
    and how many node pairs were visited, were pruned, and came down to two single values.

    A node is a stretch of values, its children are the stretches with a zero and a one in the next bit.
    Pairs of nodes descend together, all subtrees at once; the bits in which the paths differ add up.  Two
    single values have no branches left, so the rest of their paths is one comparison.
    """
    label = np.arange(len(values))
    keep = ends - starts > 1
    a0, a1 = starts[keep].astype(np.int64), ends[keep].astype(np.int64)
    b0, b1 = a0, a1
    diff = np.zeros(len(a0), np.int64)
    seen = {"visited": len(a0), "pruned": 0, "single": 0}
    for bit in range(63, -1, -1):
        if not len(a0):
            break
        ones = np.concatenate(([0], np.cumsum((values >> np.uint64(bit)) & np.uint64(1)).astype(np.int64)))
        am, bm = a1 - (ones[a1] - ones[a0]), b1 - (ones[b1] - ones[b0])
        same = a0 == b0
        parts = [
            (a0, am, b0, bm, diff),
            (am, a1, bm, b1, diff),
            (a0, am, bm, b1, diff + 1),
            (am[~same], a1[~same], b0[~same], bm[~same], diff[~same] + 1),
        ]
        a0, a1, b0, b1, diff = (np.concatenate(x) for x in zip(*parts, strict=True))
        there = (a1 > a0) & (b1 > b0) & ~((a0 == b0) & (a1 - a0 < 2))
        alive = there & (diff <= budget)
        single = alive & (a1 - a0 == 1) & (b1 - b0 == 1)
        seen["visited"] += int(there.sum())
        seen["pruned"] += int(there.sum() - alive.sum())
        seen["single"] += int(single.sum())
        _compare(values, label, a0[single], b0[single], budget)
        alive &= ~single
        a0, a1, b0, b1, diff = a0[alive], a1[alive], b0[alive], b1[alive], diff[alive]
    at = np.flatnonzero(label != np.arange(len(values)))
    return at, label[at], seen


def _compare(values: np.ndarray, label: np.ndarray, i: np.ndarray, j: np.ndarray, budget: int) -> None:
    """Merge the labels of those pairs of single values that are within the budget."""
    near = np.flatnonzero(np.bitwise_count(values[i] ^ values[j]) <= budget)
    merge(label, i[near], j[near])


def merge(label: np.ndarray, i: np.ndarray, j: np.ndarray) -> None:
    """Union by the least index: hook larger roots below smaller ones, then shorten the paths."""
    while True:
        x, y = label[i], label[j]
        open_ = x != y
        if not open_.any():
            return
        i, j, x, y = i[open_], j[open_], x[open_], y[open_]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while True:
            up = label[label]
            if np.array_equal(up, label):
                break
            label[:] = up


def _join_units(routed: DataFrame, routes: Routes, p: SimHashParams) -> DataFrame:
    """Links (src, dst) of fingerprints from rows (route, unit, value)."""
    rows_at_once = 8 * p.unit_rows

    def links(k, unit, value):
        order = np.lexsort((value, unit, k))
        k, unit, value = k[order], unit[order], value[order]
        new = np.flatnonzero(np.concatenate(([True], (unit[1:] != unit[:-1]) | (k[1:] != k[:-1]))))
        at, root, _ = trie_links(value, new, np.append(new[1:], len(value)), p.budget)
        a, b = routes.undo(k[at], value[at]), routes.undo(k[root], value[root])
        return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["src", "dst"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        for batch in batches:
            k, unit, value = (c.to_numpy() for c in batch.columns)
            held.append((k, unit, value.view(np.uint64)))
            if sum(len(h[0]) for h in held) < rows_at_once:
                continue
            k, unit, value = (np.concatenate(x) for x in zip(*held, strict=True))
            last = (unit == unit[-1]) & (k == k[-1])  # the unit at the end may go on in the next batch
            if not last.all():
                yield links(k[~last], unit[~last], value[~last])
                k, unit, value = k[last], unit[last], value[last]
            held = [(k, unit, value)]
        if held:
            yield links(*(np.concatenate(x) for x in zip(*held, strict=True)))

    return (
        routed.repartition("route", "unit")
        .sortWithinPartitions("route", "unit")
        .select("route", "unit", "value")
        .mapInArrow(lean(run), "src long, dst long")
    )


def _split_units(routed: DataFrame, hot: DataFrame, routes: Routes, p: SimHashParams) -> DataFrame:
    """Rows of overfull nodes, dealt to bounded pairs of deeper nodes within the budget.

    ``hot``: (route, unit).  Works on counts of nodes; the rows are joined once, at the end.
    """
    lead = F.element_at(F.array(*[F.lit(x) for x in routes.lead]), F.col("route") + 1)
    rows = written(routed.join(hot, ["route", "unit"], "left_semi").withColumn("depth", lead))
    pairs = hot.select("route", F.col("unit").alias("a"), F.col("unit").alias("b"), F.lit(0).alias("diff")).withColumn("depth", lead)
    done = []
    while True:
        step = F.least(F.lit(p.split_bits), 64 - F.col("depth"))
        depths = [r[0] for r in pairs.select("depth").distinct().collect()]  # one per route at most
        if not depths:
            break
        by = None
        for d in depths:
            s = min(p.split_bits, 64 - d)
            live = rows.filter(F.col("depth") <= d).groupBy("route", _prefix(F.col("value"), d + s).alias("node")).count()
            live = live.withColumn("parent", F.shiftrightunsigned("node", s)).withColumn("depth", F.lit(d))
            by = live if by is None else by.unionByName(live)
        by = written(by)
        left = by.select("route", "depth", F.col("parent").alias("a"), F.col("node").alias("x"), F.col("count").alias("nx"))
        right = by.select("route", "depth", F.col("parent").alias("b"), F.col("node").alias("y"), F.col("count").alias("ny"))
        grown = (
            pairs.withColumn("step", step)
            .join(left, ["route", "depth", "a"])
            .join(right, ["route", "depth", "b"])
            .filter((F.col("a") != F.col("b")) | (F.col("x") <= F.col("y")))
            .withColumn("diff", F.col("diff") + F.expr("bit_count((x ^ y) & (shiftleft(1L, step) - 1))"))
            .filter(F.col("diff") <= p.budget)
            .withColumn("depth", F.col("depth") + F.col("step"))
        )
        grown = written(grown)
        size = F.when(F.col("x") == F.col("y"), F.col("nx")).otherwise(F.col("nx") + F.col("ny"))
        full = (size > p.unit_rows) & (F.col("depth") < 64)
        done.append(grown.filter(~full & (size > 1)).select("route", "depth", F.col("x").alias("a"), F.col("y").alias("b")))
        pairs = grown.filter(full).select("route", F.col("x").alias("a"), F.col("y").alias("b"), "diff", "depth")
    units = done[0]
    for d in done[1:]:
        units = units.unionByName(d)
    units = units.withColumn("unit", F.xxhash64("route", "depth", "a", "b"))
    sides = units.select("route", "depth", "unit", F.explode(F.array_distinct(F.array("a", "b"))).alias("node"))
    depths = [r[0] for r in sides.select("depth").distinct().collect()]
    ladder = rows.drop("unit", "depth").withColumn(
        "at", F.explode(F.array(*[F.struct(F.lit(d).alias("depth"), _prefix(F.col("value"), d).alias("node")) for d in depths]))
    )
    return ladder.select("route", "value", "at.*").join(sides, ["route", "depth", "node"]).select("route", "unit", "value")


def fingerprint_links(prints: DataFrame, p: SimHashParams) -> DataFrame:
    """Links (src, dst) that span the components of the distinct fingerprints in ``prints`` (column fp)."""
    routes = Routes.plan(prints.count(), p)
    each = [
        F.struct(F.lit(k).alias("route"), routes.column(F.col("fp"), k).alias("value"), _prefix(routes.column(F.col("fp"), k), routes.lead[k]).alias("unit"))
        for k in range(len(routes.orders))
    ]
    routed = prints.select(F.explode(F.array(*each)).alias("r")).select("r.*")
    hot = written(routed.groupBy("route", "unit").count().filter(F.col("count") > p.unit_rows).select("route", "unit"))
    if hot.isEmpty():
        return _join_units(routed, routes, p)
    cold = routed.join(hot, ["route", "unit"], "left_anti").select("route", "unit", "value")
    return _join_units(cold.unionByName(_split_units(routed, hot, routes, p)), routes, p)


# ---- components -----------------------------------------------------------------------------


def components(links: DataFrame) -> DataFrame:
    """(node, root) for every node of the links (src, dst), by rounds of contraction.

    Each round points a node at its least neighbour, follows the pointers to their ends, and redraws
    the links between the ends, so the links shrink; nothing but their count reaches the driver.
    """
    edges = written(links.filter("src != dst").distinct())
    label = written(edges.select(F.explode(F.array("src", "dst")).alias("node")).distinct().withColumn("root", F.col("node")))
    while not edges.isEmpty():
        both = edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
        up = written(both.groupBy("src").agg(F.least(F.col("src"), F.min("dst")).alias("to")).withColumnRenamed("src", "at"))
        while True:  # pointers double in length each time
            ahead = up.select(F.col("at").alias("to"), F.col("to").alias("further"))
            longer = written(up.join(ahead, "to").select("at", F.col("further").alias("to"), (F.col("further") != F.col("to")).alias("moved")))
            moved = not longer.filter("moved").isEmpty()
            drop_written(up)
            up = longer.drop("moved")
            if not moved:
                break
        new_label = written(label.join(up, label["root"] == up["at"], "left").select("node", F.coalesce("to", "root").alias("root")))
        src = up.select(F.col("at").alias("src"), F.col("to").alias("s"))
        dst = up.select(F.col("at").alias("dst"), F.col("to").alias("d"))
        redrawn = written(edges.join(src, "src").join(dst, "dst").select(F.col("s").alias("src"), F.col("d").alias("dst")).filter("src != dst").distinct())
        for old in (label, edges, up):
            drop_written(old)
        label, edges = new_label, redrawn
    return label


def near_classes(docs: DataFrame, id_col: str, text: str, p: SimHashParams) -> tuple[DataFrame, DataFrame]:
    """(id, fp) of every row, and (fp, component_id, root) of every distinct fingerprint."""
    own = written(fingerprints(docs.select(F.col(id_col).alias("id"), text), text, p, "fp"), texts=True)
    prints = written(own.groupBy("fp").agg(F.min("id").alias("first")))
    label = components(fingerprint_links(prints.select("fp"), p))
    linked = written(prints.join(label, prints["fp"] == label["node"]).select("fp", "first", "root"))
    least = linked.groupBy("root").agg(F.min("first").alias("component_id"))
    joined = linked.join(least, "root").select("fp", "component_id", "root")
    component, root = F.coalesce("component_id", "first").alias("component_id"), F.coalesce("root", "fp").alias("root")
    return own, written(prints.join(joined, "fp", "left").select("fp", component, root))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text: str = "text", p: SimHashParams | None = None) -> DataFrame:
    """(id, fingerprint hex, component id = least id reachable), one row per input row."""
    own, classes = near_classes(docs, id_col, text, p or SimHashParams())
    return own.join(classes, "fp").select(
        F.col("id").alias(id_col), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id"
    )


def one_per_group(docs: DataFrame, id_col: str = "doc_id", text: str = "text", p: SimHashParams | None = None) -> DataFrame:
    """``docs`` with one row of every near-duplicate group: the row with the least id, or any row of a
    group in which no row has an id.  Rows carry a number of their own, so ids may repeat."""
    p = p or SimHashParams()
    base = written(docs.withColumn("__jd_uid", F.monotonically_increasing_id()))
    slim = base.select(F.col("__jd_uid").alias("uid"), F.col(f"`{id_col}`").alias("id"), F.col(f"`{text}`").alias("text"))
    own = written(fingerprints(slim, "text", p, "fp"), texts=True)
    first = F.min(F.struct(F.col("id").isNull().alias("bare"), "id", "uid")).alias("first")
    prints = written(own.groupBy("fp").agg(first))
    label = components(fingerprint_links(prints.select("fp"), p))
    rooted = prints.join(label, prints["fp"] == label["node"], "left").select("first", F.coalesce("root", "fp").alias("root"))
    heads = rooted.groupBy("root").agg(F.min("first").alias("first")).select(F.col("first.uid").alias("uid"))
    dropped = written(own.select("uid").join(heads, "uid", "left_anti").select(F.col("uid").alias("__jd_uid")))
    return base.join(few(dropped), "__jd_uid", "left_anti").select(*[F.col(f"`{c}`") for c in docs.columns])


def op1_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


QUERIES = {"op1_simhash_near_dedup": op1_simhash_near_dedup}
ORACLE_SQL: dict[str, str] = {}
