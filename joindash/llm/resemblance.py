"""Near-duplicate groups by SimHash and exact resemblance, for the pipeline.

Two texts are linked where the Jaccard similarity of their sets of five-word shingles is at least four
fifths; groups are the components of these links, and one row of each group is kept.  Equal sets meet by
their digest.  Every other pair is found in one of three rounds, and decided on the sets themselves:

1. SimHash: fingerprints within the budget of the trie self-join of ``simhash``.  Pairs at the threshold
   differ in ten of 64 bits on average, where a trie prunes next to nothing, so two more rounds follow.
2. MinHash: rows with a value in common in one of ``bands`` bands meet in a bucket – a pair at the
   threshold is missed with probability (1 - 0.8^4)^24, about 3 in a million – and each is compared with
   the head of its fullest bucket.
3. What still shares a bucket with another component is joined by rare shingles: in any order of all
   shingles, two sets that are similar enough share one among the first few of each.  With the rarest
   first, shared passages and the common body of unlike copies make no pairs.  Copies with few edits do
   share their body there, so each row is first compared with the head of its shingles, the copy with the
   fewest shingles of its own; this links most of a group in as many comparisons as it has rows.  Then all
   pairs of unlike components that still share such a shingle are compared, and none is left out.

Defined results: null, empty and blank texts are alike; a text with fewer words than a shingle is one
shingle; ids may be null or repeat, because rows carry a number of their own; the row kept is the one
with the least id, or any row of a group in which no row has an id; extra columns pass through, whatever
their names; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from joindash.llm.common import bytes_of, drop_written, few, lean, struct_with, written
from joindash.llm.simhash import SimHashParams, components, fingerprint_links, majority, shingle_digests


@dataclass(frozen=True)
class ResemblanceParams:
    width: int = 5
    #: least similarity as a fraction, so that the comparison is one of whole numbers
    least: tuple[int, int] = (4, 5)
    #: differing bits of the fingerprints of the first round
    budget: int = 3
    bands: int = 24
    rows: int = 4
    #: most rounds of comparisons with the heads of rare shingles; the exact join takes whatever they leave
    head_rounds: int = 3
    seed: int = 42

    def simhash(self) -> SimHashParams:
        return SimHashParams(width=self.width, budget=self.budget, seed=self.seed)


def shingle_set(data: bytes | None, p: ResemblanceParams) -> np.ndarray:
    """The distinct shingle digests of a text in UTF-8, in order."""
    return np.unique(np.array(shingle_digests(data, p.simhash()), np.uint64))


def band_keys(digests: np.ndarray, p: ResemblanceParams) -> list[int]:
    """One signed 64-bit key per band, from the least values under ``bands`` × ``rows`` hash functions."""
    import xxhash

    rng = np.random.default_rng(p.seed)
    times = rng.integers(0, 1 << 64, (p.bands * p.rows, 1), np.uint64) | np.uint64(1)
    plus = rng.integers(0, 1 << 64, (p.bands * p.rows, 1), np.uint64)
    least = np.full(p.bands * p.rows, np.uint64(2**64 - 1))
    for i in range(0, len(digests), 2048):
        least = np.minimum(least, (digests[i : i + 2048] * times + plus).min(axis=1))
    parts = least.astype("<u8").reshape(p.bands, p.rows)
    return np.array([xxhash.xxh64_intdigest(row.tobytes(), k) for k, row in enumerate(parts)], np.uint64).view(np.int64).tolist()


def _over_texts(rows: DataFrame, text: str, fields: list[tuple[str, T.DataType]], make) -> DataFrame:
    """``rows`` without its text column, with the values that ``make`` returns for the text's shingle set."""
    rest = rows.drop(text)
    schema = struct_with(rest, fields)
    arrow = {T.LongType(): pa.int64(), T.ArrayType(T.LongType()): pa.list_(pa.int64())}
    kinds = [arrow[t] for _, t in fields]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made = [make(x.as_py()) for x in batch.column(batch.num_columns - 1)]
            cols = [pa.array(c, t) for c, t in zip(zip(*made) if made else [[]] * len(kinds), kinds, strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], *cols], names=schema.names)

    return rows.select(*rest.columns, bytes_of(text).alias("__jd_bytes")).mapInArrow(lean(run), schema)


def sketches(rows: DataFrame, text: str, p: ResemblanceParams) -> DataFrame:
    """``rows`` without its text, with the fingerprint, and the digest, size and band keys of the shingle set."""

    def make(data):
        import xxhash

        every = shingle_digests(data, p.simhash())
        own = np.unique(np.array(every, np.uint64))
        digest = np.array([xxhash.xxh64_intdigest(own.astype("<u8").tobytes(), p.seed)], np.uint64).view(np.int64)
        return majority(every), int(digest[0]), len(own), band_keys(own, p) if len(own) else []

    fields = [("fp", T.LongType()), ("set_digest", T.LongType()), ("n", T.LongType()), ("keys", T.ArrayType(T.LongType()))]
    return _over_texts(rows, text, fields, make)


def shingle_sets(rows: DataFrame, text: str, p: ResemblanceParams) -> DataFrame:
    return _over_texts(rows, text, [("digests", T.ArrayType(T.LongType()))], lambda data: (shingle_set(data, p).view(np.int64),))


def verified(pairs: DataFrame, sets: DataFrame, p: ResemblanceParams) -> DataFrame:
    """The pairs (src, dst) whose sets are similar enough."""
    num, den = p.least
    one = sets.select(F.col("uid").alias("dst"), F.col("digests").alias("y"))
    two = sets.select(F.col("uid").alias("src"), F.col("digests").alias("x"))
    both = pairs.join(one, "dst").join(two, "src")
    shared = F.size(F.array_intersect("x", "y"))
    return both.filter((num + den) * shared >= num * (F.size("x") + F.size("y"))).select("src", "dst")


def ordered(a: str, b: str):
    return F.least(a, b).alias("src"), F.greatest(a, b).alias("dst")


def print_pairs(rows: DataFrame, p: ResemblanceParams) -> DataFrame:
    """Pairs of ``rows`` (uid, fp) that hold the links between fingerprints within the budget: rows with one
    fingerprint are paired with its least row, and the trie's links are drawn between these."""
    heads = written(rows.groupBy("fp").agg(F.min("uid").alias("head")))
    same = rows.join(heads, "fp").filter("uid != head").select(*ordered("uid", "head"))
    links = fingerprint_links(heads.select("fp"), p.simhash())
    ends = links.join(heads.select(F.col("fp").alias("src"), F.col("head").alias("a")), "src")
    ends = ends.join(heads.select(F.col("fp").alias("dst"), F.col("head").alias("b")), "dst")
    return same.unionByName(ends.select(*ordered("a", "b"))).filter("src != dst").distinct()


def bucket_pairs(open_: DataFrame, p: ResemblanceParams) -> DataFrame:
    """Each row (key, uid, n, count, root) of a bucket with several components, with the head of its fullest one."""
    num, den = p.least
    side = lambda s: F.struct(*[F.col(c).alias(f"{c}_{s}") for c in ("uid", "n", "root")])
    heads = open_.groupBy("key").agg(F.min_by(side("a"), F.xxhash64("uid", "key")).alias("a"))
    fullest = open_.groupBy("uid", "n", "root").agg(F.max(F.struct("count", "key")).alias("m")).select("m.key", side("b").alias("b"))
    pairs = fullest.join(heads, "key").select("a.*", "b.*").filter("root_a != root_b")
    return pairs.filter(den * F.least("n_a", "n_b") >= num * F.greatest("n_a", "n_b")).select(*ordered("uid_a", "uid_b")).distinct()


def rare_rows(sets: DataFrame, p: ResemblanceParams) -> DataFrame:
    """(uid, n, alone, place, digest): the shingles of ``sets`` (uid, digests) by which a pair can be found.

    With the shingles of every set in one order, the rarest first, and ``need`` the least number of shingles
    that similar sets of these sizes share, a similar pair shares one within the first size - need + 1 of both.
    ``alone`` counts the set's shingles that no other set holds.
    """
    num, den = p.least
    each = written(sets.select("uid", F.size("digests").alias("n"), F.explode("digests").alias("digest")))
    shared = each.groupBy("digest").agg(F.count(F.lit(1)).alias("df")).filter("df > 1")
    # a shingle of one set alone comes first and makes no pair; the others follow by how many sets hold them
    held = each.join(shared, "digest").groupBy("uid", "n").agg(F.array_sort(F.collect_list(F.struct("df", "digest"))).alias("rest"))
    alone = F.col("n") - F.size("rest")
    # the longest prefix that any partner asks for: the one of the least size that is similar enough
    longest = F.col("n") - F.ceil(F.col("n") * num / den) + 1
    first = F.slice("rest", 1, F.greatest(longest - alone, F.lit(0)).cast("int"))
    rows = held.select("uid", "n", alone.alias("alone"), F.posexplode(first).alias("i", "t"))
    rows = written(rows.select("uid", "n", "alone", (F.col("alone") + F.col("i")).alias("place"), "t.digest"))
    drop_written(each)
    return rows


def mixed(rows: DataFrame, key: str) -> DataFrame:
    """The ``rows`` (root and others) whose ``key`` is held by rows of several roots."""
    several = rows.groupBy(key).agg(F.min("root").alias("lo"), F.max("root").alias("hi")).filter("lo != hi").select(key)
    return rows.join(several, key, "left_semi")


def head_pairs(rows: DataFrame, p: ResemblanceParams) -> DataFrame:
    """Each of the ``rows`` (uid, root, n, alone, digest) with the head of its shingle: the row with the fewest
    shingles of its own, which stands closest to what the others have in common."""
    num, den = p.least
    side = lambda s: F.struct(*[F.col(c).alias(f"{c}_{s}") for c in ("uid", "n", "root")])
    heads = rows.groupBy("digest").agg(F.min_by(side("a"), F.struct("alone", F.xxhash64("uid"))).alias("a"))
    pairs = rows.select("digest", side("b").alias("b")).join(heads, "digest").select("a.*", "b.*").filter("root_a != root_b")
    return pairs.filter(den * F.least("n_a", "n_b") >= num * F.greatest("n_a", "n_b")).select(*ordered("uid_a", "uid_b")).distinct()


def met_pairs(rows: DataFrame, p: ResemblanceParams) -> DataFrame:
    """All pairs of ``rows`` (uid, root, n, place, digest) of unlike roots that can be similar enough."""
    num, den = p.least
    x, y = (rows.select("digest", *[F.col(c).alias(f"{c}_{s}") for c in ("uid", "root", "n", "place")]) for s in "xy")
    # the shorter set's prefix is the shorter one: its partner has as many shingles at least
    short = x.filter(F.col("place_x") <= F.col("n_x") - F.ceil(F.col("n_x") * 2 * num / (num + den)))
    need = F.ceil((F.col("n_x") + F.col("n_y")) * num / (num + den))
    later = (F.col("n_x") < F.col("n_y")) | ((F.col("n_x") == F.col("n_y")) & (F.col("uid_x") < F.col("uid_y")))
    near = (F.col("place_x") <= F.col("n_x") - need) & (F.col("place_y") <= F.col("n_y") - need)
    met = short.join(y, (short["digest"] == y["digest"]) & later & near & (F.col("root_x") != F.col("root_y")))
    return met.select(*ordered("uid_x", "uid_y")).distinct()


def rare_pairs(sets: DataFrame, p: ResemblanceParams) -> DataFrame:
    """Pairs of ``sets`` (uid, root, digests) of unlike roots that can be similar enough, by shared rare shingles."""
    return met_pairs(mixed(rare_rows(sets, p).join(sets.select("uid", "root"), "uid"), "digest"), p)


def resemblance_links(rows: DataFrame, texts: DataFrame, p: ResemblanceParams) -> DataFrame | None:
    """(node, root) of every row that is linked to another; ``rows``: (uid, n, fp, keys) of distinct sets,
    ``texts``: (uid, text) of all rows."""
    bands = rows.select("uid", "n", F.explode("keys").alias("key"))
    met = bands.groupBy("key").agg(F.count(F.lit(1)).alias("count")).filter(F.col("count") > 1)
    members = written(bands.join(met, "key").select("key", "uid", "n", "count"))
    alike = written(print_pairs(rows.filter("n > 0").select("uid", "fp"), p))
    wanted = written(members.select("uid").unionByName(alike.select(F.explode(F.array("src", "dst")).alias("uid"))).distinct())
    sets = written(shingle_sets(texts.join(few(wanted), "uid", "left_semi"), "text", p), texts=True)
    links = written(verified(alike, sets, p))
    label = components(links)

    def rooted(df: DataFrame) -> DataFrame:
        return df.join(label, df["uid"] == label["node"], "left").select(*df.columns, F.coalesce("root", "uid").alias("root"))

    def still_open() -> DataFrame:
        return mixed(written(rooted(members)), "key")

    links = links.unionByName(written(verified(bucket_pairs(still_open(), p), sets, p)))
    label = components(links)
    unsure = written(still_open().select("uid").distinct())
    meeting = written(mixed(written(rooted(rare_rows(sets.join(few(unsure), "uid", "left_semi"), p))), "digest"))
    for _ in range(p.head_rounds):
        found = written(verified(head_pairs(meeting, p), sets, p))
        if found.isEmpty():
            break
        links = links.unionByName(found)
        label = components(links)
        meeting = written(mixed(written(rooted(meeting.drop("root"))), "digest"))
    pairs = written(met_pairs(meeting, p))
    label = components(links.unionByName(written(verified(pairs, sets, p))))
    for t in (members, alike, wanted):
        drop_written(t)
    return label


def one_of_resembling(docs: DataFrame, id_col: str = "doc_id", text: str = "text", p: ResemblanceParams | None = None) -> DataFrame:
    """``docs`` with one row of every group of texts that resemble each other."""
    p = p or ResemblanceParams()
    base = written(docs.withColumn("__jd_uid", F.monotonically_increasing_id()))
    texts = base.select(F.col("__jd_uid").alias("uid"), F.col(f"`{text}`").alias("text"))
    rows = base.select(F.col("__jd_uid").alias("uid"), F.col(f"`{id_col}`").alias("id"), F.col(f"`{text}`").alias("text"))
    own = written(sketches(rows, "text", p), texts=True)
    first = F.min(F.struct(F.col("id").isNull().alias("bare"), "id", "uid")).alias("first")
    distinct = written(own.groupBy("set_digest").agg(F.min("uid").alias("uid"), first))
    rows = written(own.join(distinct.select("uid"), "uid", "left_semi").select("uid", "n", "fp", "keys"))
    label = resemblance_links(rows, texts, p)
    rooted = distinct.join(label, distinct["uid"] == label["node"], "left").select("first", F.coalesce("root", "uid").alias("root"))
    heads = rooted.groupBy("root").agg(F.min("first").alias("first")).select(F.col("first.uid").alias("uid"))
    dropped = written(own.select("uid").join(heads, "uid", "left_anti").select(F.col("uid").alias("__jd_uid")))
    return base.join(few(dropped), "__jd_uid", "left_anti").select(*[F.col(f"`{c}`") for c in docs.columns])
