"""Operator 9 – personal data: base patterns, and bootstrapped contextual extraction.

Base entities (mail and network addresses, card and phone numbers) are found by patterns and checks.
Every base span is a seed of a graph of instances – the identifiers – and lexical patterns: the two words
before, a label (one word at the start of the text or that ends in a colon and the like) before, and the
two words after, with words that hold digits written as ``#``.  A pattern's score is the mean score of its
known instances, in which an unknown one weighs little; an instance's score is the noisy-or of its trusted
patterns.  Each round counts support anew from the seeds and the instances accepted so far, so trust
spreads to patterns that hold discovered identifiers.  Everything is DataFrame expressions and joins.

The patterns are written without backtracking into repeated groups, so very long digit or letter runs
cost linear time and no stack; ``\\G`` keeps what a search that goes on after a match would find.

Rows carry a number of their own, so ids may be null or repeat; identifiers and contexts are of any length.

Defined results: null texts count as empty, and stay null where texts are masked; empty texts have no spans; repeated rows each get their
spans; overlapping spans of different kinds all count, and are masked as one stretch; an empty table
gives an empty result; input columns named like an output column are replaced.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from joindash.llm.common import drop_written, table, written
from joindash.llm.spans import bound, located

#: kind -> (a fixed substring that every match holds, pattern)
BASE = {
    "email": ("@", r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"),
    "ip": (".", r"(?:(?<![0-9])|\G)[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++"),
    "card": (None, r"[0-9](?:[\x20-]?+[0-9])++"),
    "phone": ("+", r"\+[0-9][\x20().0-9-]+[0-9]"),
}
KINDS = [*BASE, "contextual"]
#: An identifier: a stretch of word characters and joiners with a digit in it.
CANDIDATE = r"(?<![A-Za-z0-9@._%+-])(?=[A-Za-z@._%+-]*+[0-9])[A-Za-z0-9@._%+-]++"


@dataclass(frozen=True)
class PiiParams:
    #: rounds of scoring
    rounds: int = 3
    #: distinct instances, seeds or accepted ones, that a pattern needs
    support: int = 10
    #: weight of an unknown instance against a known one in a pattern's score
    unknown_weight: float = 0.05
    #: least score of a pattern, and of an instance that is added
    pattern_score: float = 0.9
    instance_score: float = 0.95
    #: shape of an unseen identifier; seeds have the shape of their kind
    least_chars: int = 6
    least_digits: int = 1
    #: characters beside a span that are read first; the whole text is where they hold too few words
    near_chars: int = 64


def _digits(m: Column) -> Column:
    return F.regexp_replace(m, "[^0-9]", "")


def _luhn(digits: Column) -> Column:
    back = F.reverse(digits)

    def add(total: Column, i: Column) -> Column:
        d = F.ascii(F.substring(back, i, F.lit(1))) - 48
        twice = d * 2
        return total + F.when(i % 2 == 1, d).otherwise(F.when(twice > 9, twice - 9).otherwise(twice))

    return F.aggregate(F.sequence(F.lit(1), F.length(back)), F.lit(0), add) % 10 == 0


def _small_parts(m: Column) -> Column:
    part = lambda x: F.regexp_replace(x, "^0+", "")
    return F.forall(F.split(m, r"\."), lambda x: (F.length(part(x)) < 3) | ((F.length(part(x)) == 3) & (part(x) <= "255")))


def valid(kind: str, m: Column) -> Column:
    if kind == "ip":
        return _small_parts(m)
    if kind == "card":
        n = F.length(_digits(m))
        return F.when(n.between(14, 19), _luhn(_digits(m))).otherwise(False)
    if kind == "phone":
        return F.length(_digits(m)).between(10, 15)
    return F.lit(True)


def _base_spans(found: Column, kind: str, number: int) -> Column:
    ok = F.filter(found, lambda s: valid(kind, s["value"]))
    return F.transform(ok, lambda s: F.struct(s["start"].alias("start"), F.lit(number).alias("kind"), s["end"].alias("end")))


def _of_kind(number: int) -> Column:
    return F.filter("base", lambda s: s["kind"] == number)


def _words(text: Column) -> Column:
    return F.filter(F.split(text, r"\s+"), lambda w: w != "")


def _pattern(mark: str, words: Column) -> Column:
    """Words as a pattern: in lower case, with ``#`` for those that hold digits."""
    plain = F.transform(words, lambda w: F.when(w.rlike("[0-9]"), "#").otherwise(F.lower(w)))
    return F.concat(F.lit(mark), F.array_join(plain, " "))


def contexts(text: Column, start: Column, end: Column, p: PiiParams) -> Column:
    """The patterns in which the span stands.  Three words are enough: the outer one may be cut."""
    near, empty = p.near_chars, F.expr("cast(array() as array<string>)")
    rest = lambda after: _words(F.regexp_replace(after, r"^[\s,;.]++", ""))
    close_by = _words(F.substring(text, F.greatest(start - near, F.lit(0)) + 1, F.least(start, F.lit(near))))
    before = bound(close_by, lambda w: F.when((F.size(w) > 2) | (start <= near), w).otherwise(_words(F.substring(text, F.lit(1), start))))
    close_by = rest(F.substring(text, end + 1, F.lit(near)))
    to_end = lambda: rest(F.substring(text, end + 1, F.length(text)))
    after = bound(close_by, lambda w: F.when((F.size(w) > 2) | (F.length(text) <= end + near), w).otherwise(to_end()))

    def left(w: Column) -> Column:
        label = F.slice(w, -1, 1)
        two = _pattern("<", F.when(F.size(w) > 1, F.slice(w, F.greatest(F.size(w) - 1, F.lit(1)), F.lit(2))).otherwise(empty))
        one = F.size(w) == 1
        return F.array(two, _pattern("-", F.when(one | F.exists(label, lambda x: x.rlike("[:=#]$")), label).otherwise(empty)))

    right = bound(after, lambda w: F.array(_pattern(">", F.when(F.size(w) > 1, F.slice(w, 1, 2)).otherwise(empty))))
    sides = F.concat(bound(before, lambda w: F.when(F.size(w) > 0, left(w)).otherwise(empty)), right)
    return F.array_distinct(F.filter(sides, lambda c: F.rlike(c, F.lit(r"\p{L}"))))


def extract(docs: DataFrame, text: str, p: PiiParams) -> DataFrame:
    """``docs`` with __jd_row, __jd_base (base spans by start and kind) and __jd_words (instances: base spans
    and unseen candidates with their contexts)."""
    body = F.coalesce(F.col(f"`{text}`"), F.lit(""))
    own = [F.col(f"`{c}`") for c in docs.columns]
    slim = docs.select(*own, F.monotonically_increasing_id().alias("__jd_row"), body.alias("__jd_t"))
    for k, (kind, (needs, pattern)) in enumerate(BASE.items()):
        slim = slim.withColumn(f"__jd_{kind}", _base_spans(located(F.col("__jd_t"), pattern, needs), kind, k))
    candidates = F.filter(
        located(F.col("__jd_t"), CANDIDATE, None),
        lambda s: (F.length(s["value"]) >= p.least_chars) & (F.length(_digits(s["value"])) >= p.least_digits),
    )
    base = F.array_sort(F.concat(*[f"__jd_{kind}" for kind in BASE]))
    slim = slim.select(*own, "__jd_row", "__jd_t", base.alias("__jd_base"), candidates.alias("__jd_c"))
    known = lambda s: F.exists("__jd_base", lambda b: (b["start"] < s["end"]) & (s["start"] < b["end"]))
    t = F.col("__jd_t")

    def instance(s: Column, seed: bool) -> Column:
        value = F.substring(t, s["start"] + 1, s["end"] - s["start"])
        return F.struct(s["start"].alias("start"), s["end"].alias("end"), value.alias("value"), contexts(t, s["start"], s["end"], p).alias("contexts"), F.lit(seed).alias("seed"))

    seeds = F.transform("__jd_base", lambda s: instance(s, True))
    unseen = F.transform(F.filter("__jd_c", lambda s: ~known(s)), lambda s: instance(s, False))
    each = F.filter(F.concat(seeds, unseen), lambda s: F.size(s["contexts"]) > 0)
    return slim.select(*own, "__jd_row", "__jd_base", each.alias("__jd_words"))


def score_graph(edges: DataFrame, p: PiiParams) -> DataFrame:
    """Instances (value) that are no seeds and that high-confidence patterns introduce.

    ``edges``: (context, value, seed).  One row per distinct edge; joins by pattern and by instance.
    """
    own = written(edges.groupBy("context", "value").agg(F.max("seed").alias("seed")))
    enough = own.groupBy("context").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") >= p.support).select("context")
    first = F.when(F.col("seed"), F.lit(1.0)).otherwise(F.lit(0.0))  # an instance counts as known from a score above zero
    graph = written(own.join(enough, "context", "left_semi").withColumn("score", first))
    drop_written(own)
    known = F.col("score") > 0
    for _ in range(p.rounds):
        counted = graph.groupBy("context").agg(F.sum(known.cast("int")).alias("n"), F.sum((~known).cast("int")).alias("unknown"), F.sum("score").alias("total"))
        patterns = counted.filter(F.col("n") >= p.support).select("context", (F.col("total") / (F.col("n") + p.unknown_weight * F.col("unknown"))).alias("trust"))
        patterns = patterns.filter(F.col("trust") >= p.pattern_score)
        doubt = F.exp(F.sum(F.log(F.greatest(1 - F.col("trust"), F.lit(1e-9)))))
        belief = graph.filter(~known).join(patterns, "context").groupBy("value").agg((1 - doubt).alias("belief"))
        belief = written(belief.filter(F.col("belief") >= p.instance_score))
        if belief.isEmpty():
            break
        scored = F.when(known, F.col("score")).otherwise(F.coalesce("belief", F.lit(0.0)))
        new = written(graph.join(belief, "value", "left").select("context", "value", "seed", scored.alias("score")))
        drop_written(graph)
        graph = new
    return graph.filter(~F.col("seed") & known).select("value").distinct()


def discovered(found: DataFrame, p: PiiParams) -> DataFrame | None:
    """(__jd_row, __jd_added) of the rows with contextual spans; ``found`` is a written ``extract``."""
    each = found.select("__jd_row", F.explode("__jd_words").alias("w")).select("__jd_row", "w.*")
    accepted = written(score_graph(each.select(F.explode("contexts").alias("context"), "value", "seed"), p))
    if accepted.isEmpty():
        return None
    span = F.struct(F.col("start").alias("start"), F.lit(len(BASE)).alias("kind"), F.col("end").alias("end"))
    hits = each.filter(~F.col("seed")).join(accepted, "value", "left_semi")
    return written(hits.groupBy("__jd_row").agg(F.collect_set(span).alias("__jd_added")))


NO_SPANS = "cast(array() as array<struct<start:int,kind:int,end:int>>)"


def find_personal_data(docs: DataFrame, id_col: str = "doc_id", text: str = "text", p: PiiParams | None = None) -> DataFrame:
    """(id, base, added): spans as array<struct(start, kind number, end)>, one row per input row."""
    p = p or PiiParams()
    found = written(extract(docs.select(id_col, text), text, p).drop(text))
    added = discovered(found, p)
    found = found.drop("__jd_words")
    found = found.withColumn("__jd_added", F.expr(NO_SPANS)) if added is None else found.join(added, "__jd_row", "left")
    return found.select(F.col(id_col).alias("id"), F.col("__jd_base").alias("base"), F.array_sort(F.coalesce("__jd_added", F.expr(NO_SPANS))).alias("added"))


def spans_text(spans: Column) -> Column:
    name = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(name, s["kind"]), s["start"], s["end"])), ",")


def masked(text: Column, spans: Column) -> Column:
    """``text`` with every span, or stretch of overlapping spans, replaced by its kind in brackets."""
    name = F.array(*[F.lit(f"[{k.upper()}]") for k in KINDS])

    def step(acc: Column, s: Column) -> Column:
        fresh = s["start"] >= acc["at"]
        piece = F.concat(F.substring(text, acc["at"] + 1, s["start"] - acc["at"]), F.get(name, s["kind"]))
        parts = F.when(fresh, F.array_append(acc["parts"], piece)).otherwise(acc["parts"])
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), parts.alias("parts"))

    zero = F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<string>)").alias("parts"))
    done = lambda acc: F.concat(F.array_join(acc["parts"], ""), F.substring(text, acc["at"] + 1, F.length(text)))
    return F.when(F.size(spans) > 0, F.aggregate(spans, zero, step, done)).otherwise(text)


def mask_personal_data(docs: DataFrame, text: str = "text", p: PiiParams | None = None) -> DataFrame:
    """``docs`` with all found spans masked in the text.  Base spans are masked in their row; only rows that
    hold unseen candidates are joined, by row number, to the contextual spans."""
    p = p or PiiParams()
    found = written(extract(docs, text, p))
    added = discovered(found, p)
    columns = [F.col(f"`{c}`") for c in docs.columns]

    def done(rows: DataFrame, spans: Column) -> DataFrame:
        own = F.when(F.col(f"`{text}`").isNotNull(), masked(F.col(f"`{text}`"), spans))
        return rows.withColumn("__jd_masked", own).select(*[F.col("__jd_masked").alias(c) if c == text else F.col(f"`{c}`") for c in docs.columns])

    if added is None:
        return done(found.select(*columns, "__jd_base"), F.col("__jd_base"))
    unseen = F.exists("__jd_words", lambda w: ~w["seed"])
    plain = found.filter(~unseen).select(*columns, "__jd_base")
    joined = found.filter(unseen).select(*columns, "__jd_base", "__jd_row").join(added, "__jd_row", "left")
    both = F.array_sort(F.concat("__jd_base", F.coalesce("__jd_added", F.expr(NO_SPANS))))
    return done(plain, F.col("__jd_base")).unionByName(done(joined, both))


def op9_contextual_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_personal_data(table(spark, sf_dir, "documents").select("doc_id", "text"))
    counts = [F.size(_of_kind(k)).cast("long").alias(f"n_{kind}") for k, kind in enumerate(BASE)]
    return found.select(
        F.col("id").alias("doc_id"),
        *counts,
        F.sha2(spans_text(F.col("base")), 256).alias("base_sha256"),
        spans_text(F.array_sort(F.concat("base", "added"))).alias("spans"),
    )


QUERIES = {"op9_contextual_pii": op9_contextual_pii}
ORACLE_SQL: dict[str, str] = {}
