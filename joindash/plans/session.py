"""Dashboards, sessions and interactions over an engine."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame

from joindash.plans.calibrate import Calibrator, calibrate, default_root, missing
from joindash.plans.graph import Relation
from joindash.plans.messages import Engine, Trace
from joindash.plans.planner import ReusePlan, answer, init_placement, plan_reuse
from joindash.plans.query import Bound, SpjaQuery, bind


@dataclass
class Chart:
    name: str
    query: SpjaQuery
    bound: Bound | None = None
    root: str | None = None


@dataclass
class Answer:
    rows: DataFrame
    trace: Trace
    plan: ReusePlan | None = None
    pivot: str = ""


class Dashboard:
    """Charts over one engine; ``calibrate_offline`` makes each chart's query a pivot, pinned in the store."""

    def __init__(self, engine: Engine):
        self.engine, self.charts = engine, {}

    def chart(self, name: str, query: SpjaQuery) -> Chart:
        probe = bind(self.engine.tree, query)
        root = default_root(self.engine, probe)
        self.charts[name] = Chart(name, query, bind(self.engine.tree, query, root), root)
        return self.charts[name]

    def calibrate_offline(self, names=None) -> float:
        began = time.perf_counter()
        for name in names or self.charts:
            c = self.charts[name]
            calibrate(self.engine, c.bound, c.root)
            edges = [e for e in c.bound.tree.directed() if not c.bound.is_one(*e, self.engine.elide)]
            self.engine.store.pin(c.bound.fingerprint(*e, self.engine.elide) for e in edges)
        return time.perf_counter() - began

    def show(self, name: str, trace: Trace | None = None) -> DataFrame:
        c = self.charts[name]
        return self.engine.absorb(c.bound, c.root, trace)


@dataclass
class Session:
    """One user's state: the latest interaction of each chart, which is the next pivot.

    ``online`` off keeps the dashboard's query as the only pivot."""

    dashboard: Dashboard
    online: bool = True
    latest: dict[str, tuple[SpjaQuery, Bound, str]] = field(default_factory=dict)
    calibrator: Calibrator | None = None
    history: dict[str, list[SpjaQuery]] = field(default_factory=dict)

    @property
    def engine(self) -> Engine:
        return self.dashboard.engine

    def query(self, chart: str) -> SpjaQuery:
        return self.latest[chart][0] if chart in self.latest else self.dashboard.charts[chart].query

    def pivot(self, chart: str) -> tuple[Bound, str]:
        """The latest interaction while sessions calibrate online, else the dashboard's query."""
        if self.online and chart in self.latest:
            return self.latest[chart][1], "interaction"
        return self.dashboard.charts[chart].bound, "dashboard"

    def interact(self, chart: str, *edits, query: SpjaQuery | None = None) -> Answer:
        """Apply edits (functions of the query), answer from the pivot, and remember the state."""
        if self.calibrator:
            self.calibrator.halt()
        new = query or self.query(chart)
        for e in edits:
            new = e(new)
        pivot, kind = self.pivot(chart)
        trace = Trace()
        rows, plan = answer(self.engine, pivot, new, trace)
        self.latest[chart] = (new, plan.bound, plan.root)
        self.history.setdefault(chart, []).append(new)
        return Answer(rows, trace, plan, kind)

    def calibrate_online(self, chart: str, limit: int | None = None) -> Trace:
        """Store the latest interaction's missing messages, here and now; ``limit`` bounds their number."""
        _, bound, root = self.latest[chart]
        return calibrate(self.engine, bound, root, policy="cheap", limit=limit)

    def think(self, chart: str, budget_s: float = 10.0) -> Calibrator:
        """The same in the background, until the budget is spent or the next interaction."""
        self.calibrator = self.calibrator or Calibrator(self.engine)
        _, bound, root = self.latest[chart]
        self.calibrator.start(bound, root, budget_s)
        return self.calibrator

    def update_relation(self, chart: str, name: str, df: DataFrame, sql: str = "") -> Answer:
        version = self.engine.tree.graph.relations[name].add_version(df, sql)
        return self.interact(chart, lambda q: q.update_table(name, version))

    def join_table(self, chart: str, relation: Relation, *edits) -> Answer:
        """Attach a new relation beside the pivot's tree and answer over both; all of the pivot's messages
        that do not contain the new bag stay valid."""
        bound, kind = self.pivot(chart)
        tree = bound.tree.attach(relation)
        engine = Engine(self.engine.spark, tree, self.engine.store, self.engine.elide)
        wide = Bound(tree, bound.ring, bound.group, bound.groups, bound.selects, bound.drops, bound.exclude, bound.versions)
        new = self.query(chart)
        for e in edits:
            new = e(new)
        trace = Trace()
        placed, movable = init_placement(engine, wide, new)
        rows = engine.absorb(placed, relation.name, trace)
        return Answer(rows, trace, ReusePlan(placed, relation.name, tree.steiner({relation.name, *movable.values()}), frozenset(movable.values()) | {relation.name}), kind)

    def explain(self, chart: str, *edits) -> dict:
        """What an interaction would reuse and compute, without running it."""
        new = self.query(chart)
        for e in edits:
            new = e(new)
        pivot, kind = self.pivot(chart)
        plan = plan_reuse(self.engine, pivot, new)
        edges = plan.bound.tree.toward(plan.root)
        todo = set(missing(self.engine, plan.bound, edges))
        ones = {e for e in edges if plan.bound.is_one(*e, self.engine.elide)}
        need, stack = set(), [plan.root]
        while stack:  # a stored message needs nothing behind it
            x = stack.pop()
            for u, v in edges:
                if v == x and (u, v) not in ones:
                    need.add((u, v))
                    if (u, v) in todo:
                        stack.append(u)
        return {
            "pivot": kind, "root": plan.root, "subtree": sorted(plan.subtree), "differing": sorted(plan.diff_bags),
            "computed": sorted(need & todo), "reused": sorted(need - todo), "left_out": sorted(ones),
            "statements": [self.engine.to_sql(plan.bound, u, v) for u, v in sorted(need & todo)],
        }

