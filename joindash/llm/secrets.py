"""Operator 10 – secret scans with a random forest against false findings.

A pattern proposes candidates; a random forest, trained from labelled findings, keeps those that look
like secrets by their length, character transitions, dictionary coverage, the document's path and the
words around them.  Features and trees are DataFrame expressions evaluated inside each row, so a scan
is narrow: no shuffle and no Python.  Training reads a bounded table of labelled findings.

Defined results: null and empty texts have no candidates; repeated rows get the same result; a null path
counts as empty; an empty table gives an empty result; input columns named like an output column are
replaced.
"""

from __future__ import annotations

import random
import string
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from joindash.llm.common import table, without
from joindash.llm.spans import located

CANDIDATE = r"(?<![A-Za-z0-9_+/=-])[A-Za-z0-9_+/=-]{16,}+"

#: Word lists of the features.
SECRET_WORDS = "token|secret|passw(?:or)?d|passwd|pwd|api.?key|apikey|access.?key|private.?key|auth|bearer|credential|client.?secret|session"
HARMLESS_WORDS = "commit|sha1|sha256|sha512|md5|checksum|digest|hash|uuid|guid|revision|integrity|etag|fingerprint|version|example|sample|dummy|placeholder"
DOC_PATHS = "test|example|sample|fixture|mock|demo|spec|doc|tutorial|vendor|lock"
DICTIONARY = (
    "the and for with that this from have able ation ing tion ment ness ible ous ent ance ally ity est ers con pro pre com inter over under "
    "key value name user data test file path http https www com org net index main class public function return string number list table "
    "image static assets content header footer button style color width height default example sample config build version release"
).split()

FEATURES = ["length", "digits", "uppers", "symbols", "variety", "changes", "rare_pairs", "words", "vowels", "hexish", "assigned", "quoted", "near_secret", "near_harmless", "doc_path", "sentence"]


def features(value: Column, before: Column, after: Column, path: Column) -> Column:
    """The feature struct of a candidate: doubles named as in FEATURES."""
    n = F.length(value).cast("double")
    count = lambda pattern, of=value: F.regexp_count(of, F.lit(pattern)).cast("double")
    low = F.lower(value)
    flag = lambda c: F.when(c, 1.0).otherwise(0.0)
    changes = F.length(F.regexp_replace(F.regexp_replace(F.regexp_replace(F.regexp_replace(value, "[0-9]+", "0"), "[a-z]+", "a"), "[A-Z]+", "A"), "[_+/=-]+", "_")).cast("double")
    vals = {
        "length": F.least(n, F.lit(256.0)),
        "digits": count("[0-9]") / n,
        "uppers": count("[A-Z]") / n,
        "symbols": count("[_+/=-]") / n,
        "variety": F.size(F.array_distinct(F.split(value, ""))) / F.least(n, F.lit(64.0)),
        "changes": changes / n,
        "rare_pairs": count("[bcdfghjklmnpqrstvwxz]{2}[bcdfghjkmpqtvwxz]|q[^u]|[jvwxz][bcdfgjkmpqvwxz]", low) / n,
        "words": 1 - F.length(F.regexp_replace(low, "|".join(sorted(set(DICTIONARY), key=lambda w: (-len(w), w))), "")) / n,
        "vowels": count("[aeiou]", low) / n,
        "hexish": flag(value.rlike("^[0-9a-f]+$") | value.rlike("^[0-9A-F]+$")),
        "assigned": flag(before.rlike("[=:]\\s*[\"']?$")),
        "quoted": flag(before.rlike("[\"']$") & after.rlike("^[\"']")),
        "near_secret": flag(F.lower(before).rlike(SECRET_WORDS)),
        "near_harmless": flag(F.lower(before).rlike(HARMLESS_WORDS)),
        "doc_path": flag(F.lower(path).rlike(DOC_PATHS)),
        "sentence": flag(before.rlike("[a-z]{2,}[,.;]? $") & ~before.rlike("[=:] *$")),
    }
    return F.struct(*[vals[f].alias(f) for f in FEATURES])


@dataclass(frozen=True)
class ForestParams:
    trees: int = 15
    depth: int = 6
    least_rows: int = 3
    seed: int = 7
    #: training rows that are read at most
    most_rows: int = 50_000
    threshold: float = 0.5
    context_chars: int = 40


def train_forest(x: np.ndarray, y: np.ndarray, p: ForestParams) -> list:
    """Trees as nested (feature, limit, low side, high side) tuples with probabilities as leaves."""
    rng = np.random.default_rng(p.seed)
    n, m = x.shape
    tried = max(1, int(np.sqrt(m)) + 1)

    def grow(rows: np.ndarray, depth: int):
        share = float(y[rows].mean())
        if depth == 0 or share in (0.0, 1.0) or len(rows) < 2 * p.least_rows:
            return round(share, 6)
        best = None
        for f in rng.permutation(m)[:tried]:
            order = rows[np.argsort(x[rows, f], kind="stable")]
            v, t = x[order, f], y[order].astype(float)
            left = np.arange(1, len(order))
            ones = np.cumsum(t)[:-1]
            a, b = ones / left, (t.sum() - ones) / (len(order) - left)
            impurity = left * a * (1 - a) + (len(order) - left) * b * (1 - b)
            impurity[(v[1:] <= v[:-1]) | (left < p.least_rows) | (len(order) - left < p.least_rows)] = np.inf
            k = int(np.argmin(impurity))
            if np.isfinite(impurity[k]) and (best is None or impurity[k] < best[0]):
                best = (impurity[k], int(f), float((v[k] + v[k + 1]) / 2))
        if best is None:
            return round(share, 6)
        _, f, limit = best
        low = x[rows, f] <= limit
        return f, limit, grow(rows[low], depth - 1), grow(rows[~low], depth - 1)

    return [grow(rng.integers(0, n, n), p.depth) for _ in range(p.trees)]


def forest_score(forest: list, feature: Column) -> Column:
    def tree(node) -> Column:
        if not isinstance(node, tuple):
            return F.lit(float(node))
        f, limit, low, high = node
        return F.when(feature[FEATURES[f]] <= limit, tree(low)).otherwise(tree(high))

    total = tree(forest[0])
    for t in forest[1:]:
        total = total + tree(t)
    return total / len(forest)


def labelled_findings(spark: SparkSession, rows: int = 4000, seed: int = 11) -> DataFrame:
    """(value, before, after, path, label): findings of known kinds, drawn by rule.

    Secrets are random strings behind assignments; the others are what scanners report by mistake:
    digests, identifiers, long words, numbers, paths, placeholders, encoded prose.
    """
    r = random.Random(seed)
    pick = lambda chars, a, b: "".join(r.choices(chars, k=r.randint(a, b)))
    syllables = ["".join((c, v, e)) for c in "bcdfglmnprst" for v in "aeiou" for e in ("", "n", "r", "st")]
    word = lambda k: "".join(r.choices(syllables, k=k))
    hex_, b64 = "0123456789abcdef", string.ascii_letters + string.digits
    secret_keys = ["token", "secret", "password", "api_key", "apiKey", "access_key", "auth", "client_secret", "Authorization: Bearer", "private_key", "session"]
    plain_keys = ["commit", "sha256", "md5", "checksum", "uuid", "revision", "integrity", "etag", "id", "name", "file", "path"]
    code_paths = ["src/app.py", "config/prod.env", "deploy/settings.yml", "web1", "src3", "notes.txt"]
    doc_paths = ["tests/fixtures/a.json", "docs/example.md", "vendor/package.lock", "samples/demo.txt"]
    out = []
    for i in range(rows):
        if i % 2:
            value = r.choice([lambda: pick(hex_, 32, 64), lambda: pick(b64, 20, 48), lambda: pick(b64 + "+/", 38, 64) + "=", lambda: "sk_live_" + pick(b64, 20, 32), lambda: pick(string.ascii_uppercase + string.digits, 20, 20), lambda: "gh_" + pick(b64, 36, 36)])()
            before = f"{word(2)} {word(3)} {r.choice(secret_keys)}" + r.choice([' = "', "='", ": ", "=", ' := "', " "])
            label, path = 1, r.choice(code_paths + doc_paths[:1])
        else:
            kind = r.randrange(7)
            value = [
                lambda: word(r.randint(6, 12)), lambda: pick(hex_, 40, 40), lambda: "-".join((pick(hex_, 8, 8), pick(hex_, 4, 4), pick(hex_, 4, 4), pick(hex_, 4, 4), pick(hex_, 12, 12))),
                lambda: pick("0123456789", 16, 24), lambda: "/".join(word(2) for _ in range(r.randint(3, 6))), lambda: r.choice("x0a*-_=").replace("*", "x") * r.randint(16, 40), lambda: "_".join(word(2) for _ in range(r.randint(3, 6))),
            ][kind]()
            before = f"{word(2)} {word(2)} " + (r.choice(plain_keys) + r.choice([": ", " ", ' = "', "="]) if kind in (1, 2) or r.random() < 0.2 else r.choice(["", "", ", ", ". "]) + word(2) + " ")
            label, path = 0, r.choice(code_paths + doc_paths)
        out.append((value, before[-40:], r.choice(['"', "'"]) if before[-1:] in "\"'" else r.choice([" ", "\n", ".", ""]), path, label))
    return spark.createDataFrame(out, "value string, before string, after string, path string, label int")


def fit(findings: DataFrame, p: ForestParams | None = None) -> list:
    """A forest from labelled findings; at most ``most_rows`` of them are read, chosen by hash."""
    p = p or ForestParams()
    empty = F.lit("")
    f = features(F.col("value"), F.coalesce("before", empty), F.coalesce("after", empty), F.coalesce("path", empty))
    rows = findings.orderBy(F.xxhash64("value", "before")).limit(p.most_rows).select(f.alias("f"), "label").select("f.*", "label").collect()
    data = np.array([tuple(r) for r in rows], float)
    return train_forest(data[:, :-1], data[:, -1].astype(int), p)


def scan_secrets(docs: DataFrame, forest: list, text: str = "text", path: str | None = "source", p: ForestParams | None = None) -> DataFrame:
    """``docs`` with ``candidates``: array<struct(start, end, value, score, secret)> of every whole text."""
    p = p or ForestParams()
    out = without(docs, ["candidates"])
    body = F.coalesce(F.col(text), F.lit(""))
    where = F.coalesce(F.col(path).cast("string"), F.lit("")) if path and path in docs.columns else F.lit("")
    found = out.withColumn("__jd_path", where).withColumn("__jd_text", body).withColumn("__jd_c", located(F.col("__jd_text"), CANDIDATE, None))
    keep = F.transform("__jd_c", lambda c: F.struct(
        c["start"].alias("start"), c["end"].alias("end"), c["value"].alias("value"),
        features(c["value"], F.right(c["before"], F.lit(p.context_chars)), F.substring("__jd_text", c["end"] + 1, F.lit(2)), F.col("__jd_path")).alias("f")))
    scored = F.transform("__jd_f", lambda c: F.struct(c["start"].alias("start"), c["end"].alias("end"), c["value"].alias("value"), F.round(forest_score(forest, c["f"]), 6).alias("score")))
    final = F.transform("__jd_s", lambda c: F.struct(c["start"].alias("start"), c["end"].alias("end"), c["value"].alias("value"), c["score"].alias("score"), (c["score"] >= p.threshold).alias("secret")))
    # most texts have no candidate: the tree expressions run only where there is one
    found = found.withColumn("__jd_f", keep).withColumn("__jd_s", scored).withColumn("candidates", final)
    return found.select(*out.columns, "candidates")


def op10_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "source")
    found = scan_secrets(docs, fit(labelled_findings(spark)))
    secrets = F.filter("candidates", lambda c: c["secret"])
    return found.select(
        "doc_id",
        F.size("candidates").cast("long").alias("n_candidates"),
        F.size(secrets).cast("long").alias("n_secrets"),
        F.array_join(F.transform(secrets, lambda c: F.concat_ws(":", c["start"], c["end"])), ",").alias("spans"),
    )


QUERIES = {"op10_secret_scan": op10_secret_scan}
ORACLE_SQL: dict[str, str] = {}
