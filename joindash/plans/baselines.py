"""What calibrated answers are compared with."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from joindash.operators.joins import cross, theta
from joindash.plans.graph import JoinGraph, JoinTree
from joindash.plans.messages import Engine, Trace
from joindash.plans.planner import answer
from joindash.plans.query import SpjaQuery, attributes_in, bind


def wide_join(graph: JoinGraph, exclude=frozenset(), versions=(), ring=None) -> tuple[DataFrame, list[str]]:
    """The join of all relations, connected ones in a row; lifted columns ride along."""
    todo = [n for n in graph.relations if n not in exclude]
    version, done = dict(versions), set(todo[:1])
    compared = lambda n: next((c for p, c in graph.conditions.items() if n in p and p - {n} <= done), None)

    def rows(n: str):
        df = graph.relations[n].at(version.get(n, 0))
        lift = (ring.lift(n) or {}) if ring else {}
        return df.select("*", *[v.alias(k) for k, v in lift.items()]), list(lift)

    df, names = rows(todo.pop(0))
    while todo:
        inner = [n for n in todo if not any(b == n for _, b in graph.optional)] or todo
        n = next((n for n in inner if set(graph.relations[n].df.columns) & set(df.columns) or compared(n)), inner[0])
        todo.remove(n)
        right, more = rows(n)
        for k in more:
            if k in names:
                right = right.withColumnRenamed(k, f"{k}__r")
        on = sorted(c for c in set(right.columns) & set(df.columns) if not c.startswith("__"))
        if condition := compared(n):
            df = df.join(right, on).filter(F.expr(condition.expr)) if on else theta(df, right, F.expr(condition.expr))
        elif any(b == n and a in done for a, b in graph.optional):
            absent = ring.absent(more) if ring else {}
            df = df.join(right, on, "left")
            here = {f"{k}__r" if k in names else k: k for k in more}
            df = df.select(*[F.coalesce(c, absent[here[c]]).alias(c) if here.get(c) in absent else F.col(c) for c in df.columns])
        else:
            df = df.join(right, on) if on else cross(df, right)
        done.add(n)
        if ring and names and more:
            x, y = {k: F.col(k) for k in names}, {k: F.col(f"{k}__r" if k in names else k) for k in more}
            product = ring.times(x, y)
            df = df.select(*[c for c in df.columns if not c.startswith("__")], *[v.alias(k) for k, v in product.items()])
            names = list(product)
        else:
            names = names or more
    return df, names


def naive(engine: Engine, query: SpjaQuery) -> DataFrame:
    """The query as it is, over the full join; Catalyst alone optimises it."""
    df, names = wide_join(engine.tree.graph, query.exclude, query.versions, query.ring)
    for w in query.where:
        df = df.filter(F.expr(w))
    probe = bind(engine.tree, SpjaQuery(query.ring))
    out, names = engine._add_up(probe, df, names, query.group)
    return out.select(*query.group, *query.ring.finalise(set(names)))


def naive_sql(graph: JoinGraph, query: SpjaQuery) -> str:
    """The same as SQL text over the raw tables, for any engine."""
    version, todo = dict(query.versions), [n for n in graph.relations if n not in query.exclude]
    src = lambda n: graph.relations[n].version_sql[version[n]] if version.get(n) else graph.relations[n].sql
    have, first = set(graph.relations[todo[0]].df.columns), todo.pop(0)
    text = f"({src(first)}) AS {first}"
    while todo:
        n = next((n for n in todo if set(graph.relations[n].df.columns) & have), todo[0])
        todo.remove(n)
        on = sorted(set(graph.relations[n].df.columns) & have)
        text += f" JOIN ({src(n)}) AS {n} USING ({', '.join(on)})" if on else f" CROSS JOIN ({src(n)}) AS {n}"
        have |= set(graph.relations[n].df.columns)
    keys = ", ".join(query.group)
    where = " WHERE " + " AND ".join(f"({w})" for w in query.where) if query.where else ""
    return f"SELECT {', '.join([*query.group, *query.ring.sql()])} FROM {text}{where}" + (f" GROUP BY {keys}" if keys else "")


def factorized(engine: Engine, query: SpjaQuery, trace: Trace | None = None) -> DataFrame:
    return engine.factorized(query, trace=trace)


def offline_only(engine: Engine, dashboard_query, query: SpjaQuery, trace: Trace | None = None) -> DataFrame:
    """The dashboard's calibrated query is the only pivot, whatever came in between."""
    return answer(engine, dashboard_query, query, trace)[0]


def wide_cube(engine: Engine, query: SpjaQuery, attrs: list[str]) -> DataFrame:
    """A data cube over the denormalised join: every subset of the attributes, whole-query columns added up."""
    df, names = wide_join(engine.tree.graph, query.exclude, query.versions, query.ring)
    for w in query.where:
        df = df.filter(F.expr(w))
    if not names:
        one = query.ring.one()
        df, names = df.withColumns(one), list(one)
    cube = df.cube(*attrs).agg(F.grouping_id().alias("level"), *query.ring.plus(names))
    return cube.select("level", *attrs, *query.ring.finalise(set(names)))


def offline_batch(engine: Engine, query: SpjaQuery, attrs: list[str]) -> DataFrame:
    """Every interaction that groups by one more attribute, computed ahead: (attribute, value, answer)."""
    out = None
    for a in attrs:
        rows = engine.factorized(query.add_group(a))
        shown = [c for c in rows.columns if c not in (*query.group, a)]
        rows = rows.select(F.lit(a).alias("attribute"), F.col(a).cast("string").alias("value"), *query.group, *shown)
        out = rows if out is None else out.unionByName(rows)
    return out


def elimination_groupby(engine: Engine, query: SpjaQuery) -> DataFrame:
    """A fresh tree by variable elimination for each query, group attributes eliminated last, so that one
    bag must hold them all: the plan that carrying group attributes avoids."""
    from joindash.plans.graph import elimination_order

    graph = engine.tree.graph.only(set(engine.tree.graph.relations) - query.exclude)
    used = frozenset().union(frozenset(query.group), *[attributes_in(w, frozenset().union(*[r.attrs for r in graph.relations.values()])) for w in query.where])
    hyper = {n: r.attrs for n, r in graph.relations.items()}
    tree = JoinTree.from_order(graph, elimination_order(hyper, keep=used & frozenset(query.group)))
    fresh = Engine(engine.spark, tree, engine.store, elide=False)
    fresh._rows = engine._rows
    return fresh.factorized(SpjaQuery(query.ring, query.group, query.where, frozenset(), query.versions))


def early_marginalise(engine: Engine, query: SpjaQuery, order: list[str]) -> DataFrame:
    """A fixed join order in which everything not needed later is added up after each join."""
    graph, version = engine.tree.graph, dict(query.versions)
    known = frozenset().union(*[r.attrs for r in graph.relations.values()])
    probe, names, df = bind(engine.tree, SpjaQuery(query.ring)), [], None
    waiting = list(query.where)
    for i, n in enumerate(order):
        rel = graph.relations[n]
        lift = query.ring.lift(n) or {}
        right = rel.at(version.get(n, 0))
        right = right.select(*right.columns, *[v.alias(k) for k, v in lift.items()])
        df, names = (right, list(lift)) if df is None else engine._join(probe, (df, names), (right, list(lift)), False)
        for w in [w for w in waiting if attributes_in(w, known) <= set(df.columns)]:
            df = df.filter(F.expr(w))
            waiting.remove(w)
        later = frozenset().union(frozenset(query.group), *[graph.relations[m].attrs for m in order[i + 1 :]], *[attributes_in(w, known) for w in waiting])
        df, names = engine._add_up(probe, df, names, [c for c in df.columns if c in later])
    return df.select(*query.group, *query.ring.finalise(set(names)))


def timed(make, repeat: int = 1) -> float:
    """Least seconds of collecting what ``make`` returns."""
    best = float("inf")
    for _ in range(repeat):
        began = time.perf_counter()
        make().collect()
        best = min(best, time.perf_counter() - began)
    return best
