"""Calibration: messages in both directions, whole or in part, now or in think-time."""

from __future__ import annotations

import threading
import time
import uuid
from dataclasses import replace

from pyspark import InheritableThread
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from joindash.plans.graph import Relation
from joindash.plans.messages import Engine, Trace
from joindash.plans.planner import message_cost, plan_cost
from joindash.plans.query import Bound
from joindash.runtime import new_path


def default_root(engine: Engine, bound: Bound) -> str:
    live = [b for b in sorted(bound.tree.bags) if bound.active(b) and b not in bound.tree.optional_bags()]
    return min(live, key=lambda b: (plan_cost(engine, bound, b), b))


def ordered_edges(engine: Engine, bound: Bound, root: str, policy: str = "tree") -> list[tuple[str, str]]:
    """All directed edges, each after those it needs.  'tree': toward the root, then away from it;
    'cheap': always the cheapest whose inputs are ready; 'useful': first what leads into small bags."""
    up = bound.tree.toward(root)
    outer = bound.tree.optional_bags()  # nothing flows into the outer side of an outer join
    every = [*up, *[(v, u) for u, v in reversed(up) if u not in outer]]
    if policy == "tree":
        return every
    done, out = set(), []
    rank = (lambda e: message_cost(engine, bound, *e)) if policy == "cheap" else (lambda e: engine.bag_rows(e[1]))
    while len(out) < len(every):
        ready = [e for e in every if e not in done and all((w, e[0]) in done for w in bound.tree.neighbours(e[0]) if w != e[1])]
        e = min(ready, key=lambda e: (rank(e), e))
        done.add(e)
        out.append(e)
    return out


def missing(engine: Engine, bound: Bound, edges) -> list[tuple[str, str]]:
    return [e for e in edges if not bound.is_one(*e, engine.elide) and not engine.store.has(bound.fingerprint(*e, engine.elide))]


def calibrate(engine: Engine, bound: Bound, root: str | None = None, trace: Trace | None = None, policy: str = "tree", limit: int | None = None) -> Trace:
    """Store every missing message of both directions; ``limit`` stops after so many new ones."""
    trace = trace if trace is not None else Trace()
    root = root or default_root(engine, bound)
    for n, (u, v) in enumerate(missing(engine, bound, ordered_edges(engine, bound, root, policy))):
        if limit is not None and n >= limit:
            break
        engine.message(bound, u, v, trace, keep=True)
    return trace


def calibrate_shared_scan(engine: Engine, bound: Bound, trace: Trace | None = None) -> Trace:
    """Full calibration in which a bag's messages to several plain dimensions come from one scan of it."""
    trace = trace if trace is not None else Trace()
    for u in sorted(bound.tree.bags, key=lambda b: (-engine.bag_rows(b), b)):
        plain = [w for w in bound.tree.neighbours(u) if bound.is_one(w, u, engine.elide) and (u, w) in missing(engine, bound, [(u, w)])]
        if len(plain) > 1:
            engine.fanout(bound, u, plain, trace)
    return calibrate(engine, bound, trace=trace)


def calibrate_all_roots(engine: Engine, bound: Bound, trace: Trace | None = None) -> Trace:
    """The plain alternative: an upward pass for every root, nothing shared between them."""
    trace = trace if trace is not None else Trace()
    for root in sorted(bound.tree.bags):
        for w in bound.tree.neighbours(root):
            m = engine.message(bound, w, root, trace, use_store=False)
            if m:
                m[0].write.format("noop").mode("overwrite").save()
    return trace


def check_calibrated(engine: Engine, bound: Bound) -> DataFrame:
    """(edge, rows that differ): both ends of each edge must add up to the same table on its separator."""
    out = None
    for u, v in sorted(tuple(sorted(e)) for e in bound.tree.links):
        keys = tuple(sorted(bound.tree.separator(u, v)))
        a, b = (engine.absorb(bound, x, keys=keys, raw=True) for x in (u, v))
        cols = sorted(set(a.columns) & set(b.columns))
        gap = a.select(cols).exceptAll(b.select(cols)).unionByName(b.select(cols).exceptAll(a.select(cols)))
        one = gap.agg(F.count(F.lit(1)).alias("differing_rows")).select(F.lit(f"{u}-{v}").alias("edge"), "differing_rows")
        out = one if out is None else out.unionByName(one)
    return out


class Calibrator:
    """Calibration in think-time: one background thread, halted at the next interaction.

    Jobs carry a tag and are cancelled by it; a message is visible only once it is complete, so what was
    finished is kept and a cancelled write is never read."""

    def __init__(self, engine: Engine, policy: str = "cheap"):
        self.engine, self.policy = engine, policy
        self.thread: threading.Thread | None = None
        self.stop = threading.Event()
        self.tag = f"calibration-{uuid.uuid4().hex[:8]}"
        self.trace = Trace()

    def start(self, bound: Bound, root: str | None = None, budget_s: float | None = None) -> None:
        self.halt()
        self.stop.clear()
        sc, deadline = self.engine.spark.sparkContext, time.monotonic() + (budget_s if budget_s is not None else 1e9)

        def work() -> None:
            sc.addJobTag(self.tag)
            sc.setInterruptOnCancel(True)
            try:
                for e in missing(self.engine, bound, ordered_edges(self.engine, bound, root or default_root(self.engine, bound), self.policy)):
                    if self.stop.is_set() or time.monotonic() > deadline:
                        return
                    self.engine.message(bound, *e, self.trace, keep=True)
            except Exception:
                if not self.stop.is_set():  # a cancelled job is no failure
                    raise
            finally:
                sc.removeJobTag(self.tag)

        self.thread = InheritableThread(target=work, daemon=True)
        self.thread.start()

    def wait(self, seconds: float | None = None) -> None:
        if self.thread:
            self.thread.join(seconds)

    def halt(self) -> None:
        if self.thread and self.thread.is_alive():
            self.stop.set()
            self.engine.spark.sparkContext.cancelJobsWithTag(self.tag)
            self.thread.join()
        self.thread = None


def appended_version(rel: Relation, paths: list[str]) -> DataFrame:
    """The relation's rows with those of all appended files: one more scan, however many batches there were."""
    return rel.df.unionByName(rel.df.sparkSession.read.schema(rel.df.schema).parquet(*paths))


def append_rows(engine: Engine, relation: str, delta: DataFrame, bounds: list[Bound], path: str | None = None) -> int:
    """A version of the relation with rows appended, and its messages as old message + message over the new
    rows alone; returns the version.  For rings whose sums merge (all of ours do under union).

    The new rows are written first, to ``path`` where one is given, so that no later step depends on how
    they arrived; writing the same path again replaces them."""
    rel = engine.tree.graph.relations[relation]
    spark, path = engine.spark, path or new_path(engine.spark, "append")
    delta.select(rel.df.columns).write.mode("overwrite").parquet(path)
    base_version = max(rel.versions, default=0)
    before = [p for p in rel.appended if p != path]
    only = rel.add_version(spark.read.schema(rel.df.schema).parquet(path))
    rel.appended = [*before, path]
    full = rel.add_version(appended_version(rel, rel.appended))
    for bound in bounds:
        at = lambda n, bound=bound: replace(bound, versions=tuple(sorted({**dict(bound.versions), relation: n}.items())), memo={})
        old, new, part = at(base_version), at(full), at(only)
        bag = bound.tree.mapping[relation]
        for u, v in bound.tree.directed():
            if bag in bound.tree.upstream(u, v) and engine.store.has(old.fingerprint(u, v, engine.elide)):
                a = engine.store.get(old.fingerprint(u, v, engine.elide)).df
                m = engine.message(part, u, v, Trace())
                keys = list(bound.keys(u, v))
                both = a.unionByName(m[0], allowMissingColumns=True)
                df, _ = engine._add_up(bound, both, [c for c in a.columns if c.startswith("__")], keys)
                engine.store.put(new.fingerprint(u, v, engine.elide), df, tuple(sorted(bound.tree.separator(u, v) & set(keys))))
    return full
