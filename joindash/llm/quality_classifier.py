"""Operator 5 – a quality classifier from trusted positives and unlabelled text.

Training sees documents labelled good and a sample of all documents without labels.  The class prior is
estimated from the two (a set of scores that holds a share of the positives holds at least prior × share
of the unlabelled), then a small network minimises the non-negative unbiased risk: the negative part,
unlabelled risk less prior × positive risk, is never let below zero.  With the logistic loss its output
estimates the probability of label 1.

Inputs of a score are shape statistics of the whole text alone.  The training sample is bounded by
documented parameters and chosen by hash; every document is scored.

Defined results: null and empty texts get the score of the empty text's features; repeated rows get equal
scores; without positives or documents to learn from every score is the prior 0.5; an empty table gives an
empty result; input columns named like an output column are replaced.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from joindash.llm.common import bytes_of, importable, lean, struct_with, table, without
from joindash.llm.quality_rules import SYMBOLS, duplicate_lines, repeated_window_words


@dataclass(frozen=True)
class PuParams:
    #: documents read for training at most: trusted positives, and unlabelled ones
    most_positives: int = 12_000
    most_unlabelled: int = 24_000
    hidden: int = 24
    epochs: int = 40
    #: small samples are passed over more often, until so many steps are done
    least_steps: int = 300
    batch: int = 512
    rate: float = 3e-3
    decay: float = 1e-4
    seed: int = 5
    threshold: float = 0.3


UPPER = bytes(range(65, 91))
LETTERS = UPPER + bytes(range(97, 123))
N_FEATURES = 22


def text_features(data: bytes | None, compressor) -> list[float]:
    data = data or b""
    words = data.split()
    n, size = len(words), len(data)
    if not n:
        return [0.0] * N_FEATURES
    share = lambda chars: (size - len(data.translate(None, chars))) / size
    letters = share(LETTERS)
    counts = Counter(words)
    lengths = np.fromiter(map(len, words), np.float64, n)
    lines = data.count(b"\n") + 1
    again = sum(a == b for a, b in zip(words, words[1:], strict=False)) / n
    marked = sum(c for w, c in counts.items() if w.translate(None, SYMBOLS) != w) / n
    shouting = sum(c for w, c in counts.items() if w.isupper() and len(w) > 1) / n
    bare = sum(c for w, c in counts.items() if not w.strip(b"|#*$%&<>!.,-")) / n
    return [
        math.log1p(n),
        float(lengths.mean()),
        float(lengths.std()),
        math.log1p(float(lengths.max())),
        share(UPPER) / letters if letters else 0.0,
        letters,
        share(b"0123456789"),
        share(SYMBOLS),
        share(b"!"),
        share(b".,;:?"),
        counts.most_common(1)[0][1] / n,
        len(counts) / n,
        again,
        marked,
        shouting,
        bare,
        float((lengths <= 3).mean()),
        duplicate_lines(data) / lines,
        math.log1p(size / lines),
        repeated_window_words(words) / n,
        min(20.0, size / len(compressor.compress(data))),
        1 - len(data.translate(None, bytes(range(128, 256)))) / size,
    ]


def feature_rows(datas: list[bytes | None]) -> np.ndarray:
    import zstandard

    compressor = zstandard.ZstdCompressor(level=3)
    return np.array([text_features(d, compressor) for d in datas], float).reshape(-1, N_FEATURES)


# ---- learning -------------------------------------------------------------------------------


@dataclass
class Network:
    mean: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float

    def logits(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.mean) / self.scale, -8, 8)
        return np.tanh(z @ self.w1 + self.b1) @ self.w2 + self.b2

    def scores(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logits(x), -30, 30)))


def _train(xp: np.ndarray, xu: np.ndarray, prior: float | None, p: PuParams) -> Network:
    """Non-negative PU risk for a given prior; positives against unlabelled where it is None."""
    rng = np.random.default_rng(p.seed)
    both = np.vstack([xp, xu])
    mean, scale = both.mean(0), both.std(0) + 1e-6
    norm = lambda x: np.clip((x - mean) / scale, -8, 8)
    zp, zu, m = norm(xp), norm(xu), both.shape[1]
    theta = [rng.normal(0, 1 / math.sqrt(m), (m, p.hidden)), np.zeros(p.hidden), rng.normal(0, 1 / math.sqrt(p.hidden), p.hidden), np.zeros(1)]
    m1, m2, t = [np.zeros_like(w) for w in theta], [np.zeros_like(w) for w in theta], 0
    sig = lambda g: 1 / (1 + np.exp(-np.clip(g, -30, 30)))
    soft = lambda g: np.logaddexp(0, g)
    steps = max(1, len(zu) // p.batch)
    for _ in range(max(p.epochs, -(-p.least_steps // steps))):
        order_u, order_p = rng.permutation(len(zu)), rng.permutation(len(zp))
        for s in range(steps):
            u = zu[order_u[s * p.batch : (s + 1) * p.batch]]
            k = max(1, len(zp) // steps)
            q = zp[order_p[s * k : (s + 1) * k]]
            x = np.vstack([q, u])
            h = np.tanh(x @ theta[0] + theta[1])
            g = h @ theta[2] + theta[3]
            gp, gu = g[: len(q)], g[len(q) :]
            if prior is None:
                d = np.concatenate([-sig(-gp) / len(q), sig(gu) / len(u)])
            else:
                negative = soft(gu).mean() - prior * soft(gp).mean()
                d_neg = np.concatenate([-prior * sig(gp) / len(q), sig(gu) / len(u)])
                d_pos = np.concatenate([-prior * sig(-gp) / len(q), np.zeros(len(u))])
                d = d_pos + d_neg if negative >= 0 else -d_neg
            dh = np.outer(d, theta[2]) * (1 - h * h)
            grads = [x.T @ dh, dh.sum(0), h.T @ d, np.array([d.sum()])]
            t += 1
            for i, (w, gr) in enumerate(zip(theta, grads, strict=True)):
                gr = gr + p.decay * w
                m1[i] = 0.9 * m1[i] + 0.1 * gr
                m2[i] = 0.999 * m2[i] + 0.001 * gr * gr
                w -= p.rate * (m1[i] / (1 - 0.9**t)) / (np.sqrt(m2[i] / (1 - 0.999**t)) + 1e-8)
    return Network(mean, scale, theta[0], theta[1], theta[2], float(theta[3][0]))


def estimate_prior(xp: np.ndarray, xu: np.ndarray, p: PuParams) -> float:
    """The least ratio of unlabelled to positive share over the upper score sets; the ranking is learnt on
    one half of each sample and the ratio taken on the other."""
    rng = np.random.default_rng(p.seed + 1)
    ip, iu = rng.permutation(len(xp)), rng.permutation(len(xu))
    hp, hu = len(xp) // 2, len(xu) // 2
    if min(hp, hu) < 20:
        return 0.5
    net = _train(xp[ip[:hp]], xu[iu[:hu]], None, p)
    sp, su = np.sort(net.logits(xp[ip[hp:]])), np.sort(net.logits(xu[iu[hu:]]))
    cuts = np.quantile(sp, np.linspace(0.02, 0.5, 25))
    share_p = 1 - np.searchsorted(sp, cuts) / len(sp)
    share_u = 1 - np.searchsorted(su, cuts) / len(su)
    return float(np.clip(np.min(share_u / np.maximum(share_p, 1e-9)), 0.05, 0.98))


def learn(xp: np.ndarray, xu: np.ndarray, p: PuParams) -> tuple[Network | None, float]:
    if len(xp) < 5 or len(xu) < 5:
        return None, 0.5
    prior = estimate_prior(xp, xu, p)
    return _train(xp, xu, prior, p), prior


# ---- on tables ------------------------------------------------------------------------------


def held_out(doc_id: str) -> Column:
    """Whether a document is kept from learning; one without an id is neither held out nor learnt from."""
    return F.col(doc_id).isNotNull() & (F.crc32(F.col(doc_id).cast("string").cast("binary")) % 5 == 0)


def _collect_features(docs: DataFrame, ids: DataFrame, id_col: str, text: str, extra: int) -> np.ndarray:
    """Features of the documents with the given ids, a set of at most ``extra`` rows."""
    importable(docs.sparkSession)
    chosen = docs.join(F.broadcast(ids), id_col, "left_semi").select(bytes_of(text).alias("b"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = feature_rows(batch.column(0).to_pylist())
            yield pa.RecordBatch.from_arrays([pa.array(rows.tolist(), pa.list_(pa.float64()))], names=["f"])

    got = chosen.mapInArrow(lean(run), "f array<double>").limit(2 * extra).toArrow()
    rows = np.array(got.column("f").to_pylist(), float).reshape(-1, N_FEATURES)
    return rows[np.lexsort(rows.T)]  # an order that does not depend on how the tasks ended


def fit_quality(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text: str = "text", p: PuParams | None = None) -> tuple[Network | None, float]:
    """(network, class prior) from documents that are not held out; negatives are never read as such."""
    p = p or PuParams()
    own = ~held_out(id_col) & F.col(id_col).isNotNull()
    some = lambda df, n: df.select(id_col).distinct().orderBy(F.xxhash64(id_col), id_col).limit(n)
    good = some(labels.filter(own & (F.col("quality") == 1)), p.most_positives)
    any_ = some(docs.filter(own), p.most_unlabelled)
    return learn(_collect_features(docs, good, id_col, text, p.most_positives), _collect_features(docs, any_, id_col, text, p.most_unlabelled), p)


def score_quality(docs: DataFrame, model: tuple[Network | None, float], text: str = "text", name: str = "score") -> DataFrame:
    """``docs`` less its text, with the score of every whole text; narrow."""
    rest = without(docs, [name, text])
    schema = struct_with(rest, [(name, T.DoubleType())])
    network, prior = model

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = feature_rows(batch.column(batch.num_columns - 1).to_pylist())
            scores = network.scores(x) if network else np.full(len(x), prior)
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(scores, pa.float64())], names=schema.names)

    return docs.select(*[F.col(f"`{c}`") for c in rest.columns], bytes_of(text).alias("__jd_bytes")).mapInArrow(lean(run), schema)


def op5_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, p = table(spark, sf_dir, "documents").select("doc_id", "text"), PuParams()
    model = fit_quality(docs, table(spark, sf_dir, "labels").select("doc_id", "quality"), p=p)
    scored = score_quality(docs, model)
    return scored.select("doc_id", held_out("doc_id").alias("held_out"), "score", (F.col("score") >= p.threshold).cast("int").alias("predicted"))


QUERIES = {"op5_quality_classifier": op5_quality_classifier}
ORACLE_SQL: dict[str, str] = {}
