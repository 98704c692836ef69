"""Cost and accuracy measures: theory, what was done, and time."""

from __future__ import annotations

import math
import statistics
import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from joindash.plans.baselines import naive, wide_join
from joindash.plans.calibrate import calibrate, default_root
from joindash.plans.graph import fractional_edge_cover
from joindash.plans.messages import Engine, Trace
from joindash.plans.planner import ReusePlan, plan_cost
from joindash.plans.query import Bound, SpjaQuery, bind
from joindash.plans.session import Session


def seconds(make) -> float:
    began = time.perf_counter()
    out = make()
    if isinstance(out, DataFrame):
        out.collect()
    return time.perf_counter() - began


@dataclass
class Timings:
    """Latencies by strategy."""

    values: dict[str, list[float]] = field(default_factory=dict)

    def add(self, strategy: str, s: float) -> None:
        self.values.setdefault(strategy, []).append(s)

    def share_below(self, strategy: str, limit: float = 1.0) -> float:
        v = self.values[strategy]
        return sum(x < limit for x in v) / len(v)

    def speedup(self, slow: str, fast: str) -> float:
        return statistics.median(self.values[slow]) / max(statistics.median(self.values[fast]), 1e-9)

    def fits(self, strategy: str, think_s: float = 10.0) -> bool:
        return max(self.values[strategy]) <= think_s

    def cumulative(self, strategy: str) -> list[float]:
        out, total = [], 0.0
        for v in self.values[strategy]:
            total += v
            out.append(total)
        return out


def offline_overhead(engine: Engine, query: SpjaQuery) -> float:
    """Calibration time over the time of the query by message passing without sharing."""
    root = default_root(engine, bind(engine.tree, query))
    plain = seconds(lambda: engine.factorized(query, root))
    return seconds(lambda: calibrate(engine, bind(engine.tree, query, root), root)) / max(plain, 1e-9)


def sensitivity(make_session, chart: str, first, second, budgets: list[int]) -> list[tuple[int, float, int]]:
    """(messages calibrated after the first interaction, seconds of the second, messages it computed)."""
    out = []
    for b in budgets:
        s: Session = make_session()
        s.interact(chart, first).rows.collect()
        s.calibrate_online(chart, limit=b)
        a = s.interact(chart, second)
        out.append((b, seconds(lambda a=a: a.rows), a.trace.count("computed")))
    return out


def case_study(session: Session, chart: str, edit) -> dict:
    a = session.interact(chart, edit)
    took = seconds(lambda: a.rows)
    return {"seconds": took, "pivot": a.pivot, "root": a.plan.root, "reused": a.trace.edges("reused"), "computed": a.trace.edges("computed"), "left_out": a.trace.edges("elided")}


def storage_report(engine: Engine, base_bytes: int) -> dict:
    return {"messages": len(engine.store.refs), "bytes": engine.store.bytes(), "ratio": engine.store.bytes() / max(base_bytes, 1)}


def bag_size_curve(engine: Engine, pivot: Bound, filters: dict[str, str]) -> list[tuple[str, int, float]]:
    """(bag, its rows, seconds) for one filter per bag on a calibrated pivot; latency should follow size."""
    from joindash.plans.planner import answer

    out = []
    for bag, expr in filters.items():
        q = SpjaQuery(pivot.ring, pivot.group, tuple(e for _, e, _ in pivot.selects)).with_filter(expr)
        rows, plan = answer(engine, pivot, q)
        out.append((plan.root, engine.bag_rows(bag), seconds(lambda rows=rows: rows)))
    return out


def empty_bag_report(engine: Engine, bound: Bound, bag: str, fact: str) -> dict:
    """Build seconds, size and shrink factor of an empty bag's view, and query seconds with and without."""
    u = next(w for w in bound.tree.neighbours(bag) if fact in bound.tree.upstream(w, bag))
    build = seconds(lambda: engine.message(bound, u, bag, Trace(), keep=True))
    ref = engine.store.get(bound.fingerprint(u, bag, engine.elide))
    return {"build_s": build, "rows": ref.rows, "shrink": engine.rows(fact) / max(ref.rows, 1), "query_s": seconds(lambda: engine.absorb(bound, bag)), "without_s": seconds(lambda: engine.absorb(bound, fact, use_store=False))}


# ---- theory ---------------------------------------------------------------------------------


def cost_naive(engine: Engine) -> float:
    """Bags × attributes × cover number × log of the largest bound, plus one scan of every relation."""
    tree = engine.tree
    n_attrs = len(frozenset().union(*tree.bags.values()))
    rho = fractional_edge_cover(tree.graph.hyperedges())
    rows = {r: engine.rows(r) for r in tree.graph.relations}
    largest = max(rows.values())
    return len(tree.bags) * n_attrs * rho * math.log2(max(largest, 2)) + sum(rows.values())


def cost_messages(engine: Engine, bound: Bound, root: str) -> float:
    return plan_cost(engine, bound, root) + sum(engine.rows(r) for r in bound.tree.graph.relations)


def cost_with_pivot(engine: Engine, plan: ReusePlan) -> float:
    """Only messages inside the reuse subtree and absorption count."""
    return plan_cost(engine, plan.bound, plan.root, plan.subtree)


def bound_vs_actual(engine: Engine, bound: Bound) -> list[tuple[str, str, int, int]]:
    """(u, v, rows of the message, its bound: the bag's relation × the domains carried into it)."""
    out = []
    for u, v in bound.tree.directed():
        if bound.is_one(u, v, engine.elide):
            continue
        m = engine.message(bound, u, v, Trace())
        limit = max((engine.rows(r) for r in bound.active(u)), default=None) if bound.active(u) else math.prod(engine.distinct(a) for a in bound.keys(u, v))
        for a in bound.carried(u, v) - bound.tree.bags[u]:
            limit *= engine.distinct(a) + engine.distinct(a) // 10 + 1  # the domain size is a sketch
        out.append((u, v, m[0].count(), limit))
    return out


def intermediate_report(engine: Engine, query: SpjaQuery) -> dict:
    """Rows of the full join against the largest message."""
    full, _ = wide_join(engine.tree.graph, query.exclude, query.versions)
    bound = bind(engine.tree, query)
    root = default_root(engine, bound)
    sizes = [m[0].count() for e in bound.tree.toward(root) if (m := engine.message(bound, *e, Trace()))]
    return {"full_join": full.count(), "largest_message": max(sizes, default=0)}


def advise_empty_bags(engine: Engine, fact: str, candidates: list[tuple[str, ...]], least_shrink: float = 2.0) -> list[tuple[tuple[str, ...], float, bool]]:
    """(attributes, estimated shrink, worth it): rows of the fact over the sketched distinct combinations."""
    rel = engine.tree.graph.relations[fact]
    counts = rel.df.agg(*[F.approx_count_distinct(F.struct(*c), 0.02).alias(f"c{i}") for i, c in enumerate(candidates)]).first()
    rows = engine.rows(fact)
    return sorted(((c, rows / max(counts[i], 1), rows / max(counts[i], 1) >= least_shrink) for i, c in enumerate(candidates)), key=lambda r: -r[1])


def spark_work(engine: Engine, run) -> dict:
    """Stages, tasks and jobs that an action took, from the status tracker."""
    sc, tag = engine.spark.sparkContext, f"measure-{time.monotonic_ns()}"
    sc.setJobGroup(tag, "measured")
    took = seconds(run)
    jobs = sc.statusTracker().getJobIdsForGroup(tag)
    stages = [s for j in jobs if (i := sc.statusTracker().getJobInfo(j)) for s in i.stageIds]
    tasks = sum(i.numTasks for s in stages if (i := sc.statusTracker().getStageInfo(s)))
    return {"seconds": took, "jobs": len(jobs), "stages": len(stages), "tasks": tasks}


def same_answers(engine: Engine, query: SpjaQuery, *frames: DataFrame) -> bool:
    want = sorted(map(str, naive(engine, query).collect()))
    return all(sorted(map(str, f.collect())) == want for f in frames)


