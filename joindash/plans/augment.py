"""Feature augmentation: linear regression from one Gram matrix, and new tables scored one message away."""

from __future__ import annotations

import random
import time
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F

from joindash.functions.semiring import Measure, MomentRing, gram_ring
from joindash.plans.baselines import wide_join
from joindash.plans.calibrate import calibrate
from joindash.plans.graph import JoinGraph, Relation
from joindash.plans.messages import Engine, Trace
from joindash.plans.query import SpjaQuery, bind


@dataclass
class Fit:
    features: list[str]
    beta: np.ndarray
    r2: float
    rows: int


def solve(row: Row, features: list[str], target: str) -> Fit:
    """Least squares with intercept from sums and products; features are centred and scaled first."""
    c = float(row["cnt"])
    names = [*features, target]
    s = np.array([row[f"s_{n}"] or 0.0 for n in names], float)
    q = np.empty((len(names), len(names)))
    for i, a in enumerate(names):
        for j, b in enumerate(names):
            key = f"q_{a}_{b}" if f"q_{a}_{b}" in row.__fields__ else f"q_{b}_{a}"
            q[i, j] = row[key] or 0.0
    cov = q / c - np.outer(s, s) / c**2
    sd = np.sqrt(np.maximum(np.diag(cov), 0))
    sd[sd == 0] = 1.0
    z = cov / np.outer(sd, sd)
    beta, *_ = np.linalg.lstsq(z[:-1, :-1], z[:-1, -1], rcond=1e-10)
    sst = z[-1, -1]
    sse = sst - 2 * beta @ z[:-1, -1] + beta @ z[:-1, :-1] @ beta
    slope = beta * sd[-1] / sd[:-1]
    intercept = (s[-1] - slope @ s[:-1]) / c
    return Fit(features, np.concatenate(([intercept], slope)), float(1 - sse / sst) if sst > 0 else 0.0, int(c))


class Augmenter:
    """A calibrated training join; every candidate table costs a message at most and one small absorption."""

    def __init__(self, engine: Engine, features: list[Measure], target: Measure):
        self.engine, self.features, self.target = engine, features, target
        self.query = SpjaQuery(gram_ring([*features, target]))

    def calibrate(self, trace: Trace | None = None) -> float:
        began = time.perf_counter()
        calibrate(self.engine, bind(self.engine.tree, self.query), trace=trace)
        return time.perf_counter() - began

    def base_gram(self) -> DataFrame:
        root = min(self.engine.tree.bags, key=lambda b: (self.engine.bag_rows(b), b))
        return self.engine.absorb(bind(self.engine.tree, self.query, root), root)

    def base(self) -> Fit:
        return solve(self.base_gram().first(), [m.name for m in self.features], self.target.name)

    def _with(self, table: Relation, column: str, scale: int | None):
        tree = self.engine.tree.attach(table)
        engine = Engine(self.engine.spark, tree, self.engine.store, self.engine.elide)
        engine._rows = dict(self.engine._rows)
        new = Measure(column, table.name, column, scale)
        return engine, SpjaQuery(gram_ring([*self.features, self.target, new])), new

    def gram(self, table: Relation, column: str = "v", scale: int | None = 3, trace: Trace | None = None) -> DataFrame:
        """The Gram matrix with one more feature; the message beside the new table is kept, so that other
        tables with the same key share it."""
        engine, query, _ = self._with(table, column, scale)
        bound = bind(engine.tree, query, table.name)
        host = engine.tree.neighbours(table.name)[0]
        trace = trace if trace is not None else Trace()
        engine.message(bound, host, table.name, trace, keep=True)
        return engine.absorb(bound, table.name, trace)

    def evaluate(self, table: Relation, column: str = "v", scale: int | None = 3, trace: Trace | None = None) -> Fit:
        return solve(self.gram(table, column, scale, trace).first(), [*[m.name for m in self.features], column], self.target.name)

    def evaluate_all(self, tables: list[Relation], scale: int | None = 3, trace: Trace | None = None) -> list[Fit]:
        """Every table (key, v) on its own, in one absorption for each key: the candidates of a key lie below
        each other in one table beside the key's message, and the Gram matrix is grouped by candidate."""
        groups: dict[frozenset[str], list[Relation]] = {}
        for t in tables:
            groups.setdefault(t.attrs - {"v"}, []).append(t)
        fits: dict[str, Fit] = {}
        trace = trace if trace is not None else Trace()
        names = [*[m.name for m in self.features], "v"]
        for key, group in groups.items():
            rows = None
            for t in group:
                part = t.df.select(*sorted(key), F.lit(t.name).alias("candidate"), F.col("v").cast("double").alias("v"))
                rows = part if rows is None else rows.unionByName(part)
            joint = Relation(f"candidates_{'_'.join(sorted(key))}", rows)
            engine, query, _ = self._with(joint, "v", scale)
            bound = bind(engine.tree, query.add_group("candidate"), joint.name)
            engine.message(bound, engine.tree.neighbours(joint.name)[0], joint.name, trace, keep=True)
            for row in engine.absorb(bound, joint.name, trace).collect():  # one row per candidate
                fits[row["candidate"]] = solve(row, names, self.target.name)
        empty = Fit(names, np.zeros(len(names) + 1), 0.0, 0)  # a table that joins with nothing
        return [fits.get(t.name, empty) for t in tables]

    def rank(self, tables: list[Relation]) -> list[tuple[str, float, float, float]]:
        """(table, R², gain over the base, cumulative seconds), best first; duplicates in a key multiply rows.

        Tables of one key are fitted by one job, so they share its end as their time."""
        base, began, out = self.base(), time.perf_counter(), []
        for key in dict.fromkeys(t.attrs for t in tables):
            group = [t for t in tables if t.attrs == key]
            fits = self.evaluate_all(group)
            took = time.perf_counter() - began
            out += [(t.name, f.r2, f.r2 - base.r2, took) for t, f in zip(group, fits, strict=True)]
        return sorted(out, key=lambda r: (-r[1], r[0]))


def sparse_block(engine: Engine, measures: list[Measure], categories: list[str], scale_alias: str = "s") -> DataFrame:
    """Count and sums per value of each categorical feature and per pair of values of two of them.

    This is the part of the Gram matrix (and of a factorisation machine's pairwise moments) that belongs to
    categorical features, with only the values and pairs that occur: each feature is a carried group
    attribute instead of one column per value.  Rows: (feature_a, value_a, feature_b, value_b, cnt, sums);
    a feature with itself is the diagonal."""
    ring = MomentRing(tuple(measures), 1, (("count", "cnt", ()), *[("sum", f"{scale_alias}_{m.name}", (m.name,)) for m in measures]))
    out = None
    for i, a in enumerate(categories):
        for b in categories[i:]:
            rows = engine.factorized(SpjaQuery(ring, (a,) if a == b else (a, b)))
            sums = [c for c in rows.columns if c not in (a, b)]
            rows = rows.select(F.lit(a).alias("feature_a"), F.col(a).cast("string").alias("value_a"), F.lit(b).alias("feature_b"), F.col(b).cast("string").alias("value_b"), *sums)
            out = rows if out is None else out.unionByName(rows)
    return out


def train_factorized(aug: Augmenter, table: Relation, column: str = "v", scale: int | None = 3) -> Fit:
    """One training from the base tables, nothing shared: the baseline for each augmentation."""
    engine, query, _ = aug._with(table, column, scale)
    return solve(engine.factorized(query).first(), [*[m.name for m in aug.features], column], aug.target.name)


def train_batched(aug: Augmenter, tables: list[Relation], scale: int | None = 3) -> list[Fit]:
    """Stand-in for a specialised factorized learner: one aggregation batch per key, all candidate columns of
    that key side by side in one pass over cached lifted scans, but no messages kept between keys."""
    out: list[Fit] = []
    keys: dict[frozenset[str], list[Relation]] = {}
    for t in tables:
        keys.setdefault(t.attrs - {"v"}, []).append(t)
    for key, group in keys.items():
        on, df = sorted(key), None
        for t in group:
            part = t.df.withColumnRenamed("v", t.name)
            df = part if df is None else df.join(part, on)
        joint = Relation("candidates", df, (key,))
        tree = aug.engine.tree.attach(joint)
        engine = Engine(aug.engine.spark, tree, None, aug.engine.elide)
        engine._rows = dict(aug.engine._rows)
        cols = [Measure(t.name, "candidates", t.name, scale) for t in group]
        row = engine.factorized(SpjaQuery(gram_ring([*aug.features, aug.target, *cols]))).first()
        out += [solve(row, [*[m.name for m in aug.features], t.name], aug.target.name) for t in group]
    return out


def train_materialised(graph: JoinGraph, features: list[Measure], target: Measure) -> Fit:
    """Join everything, then fit directly on the wide rows' Gram matrix."""
    ring = gram_ring([*features, target])
    df, names = wide_join(graph, ring=ring)
    aggs = ring.plus(names)
    out = df.agg(*aggs)
    return solve(out.select(*ring.finalise(set(names))).first(), [m.name for m in features], target.name)


def mixing_weights(n: int = 10, seed: int = 3, mean: float = 10.0) -> list[float]:
    """How much of each synthetic table follows the target: min(1, 1/e) for exponential draws e."""
    r = random.Random(seed)
    return [round(min(1.0, 1.0 / r.expovariate(1 / mean)), 6) for _ in range(n)]
