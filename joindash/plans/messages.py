"""Message passing as DataFrame plans: messages, absorption, and the trace of what was done."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from joindash.operators.joins import UnboundedJoin
from joindash.plans.graph import Condition, JoinTree
from joindash.plans.query import Bound, SpjaQuery, attributes_in, bind
from joindash.plans.store import MessageStore

#: a side is broadcast only when it is a stored message whose rows take at most so many bytes in memory
BROADCAST_BYTES = 32 << 20
#: rows of a side that is joined without any equality
LOOP_ROWS = 10_000


@dataclass
class Trace:
    """What an answer reused, computed, left out and absorbed."""

    events: list[tuple] = field(default_factory=list)
    seconds: dict[str, float] = field(default_factory=dict)

    def add(self, kind: str, u: str, v: str = "") -> None:
        if (kind, u, v) not in self.events:
            self.events.append((kind, u, v))

    def edges(self, kind: str) -> list[tuple[str, str]]:
        return [(u, v) for k, u, v in self.events if k == kind]

    def count(self, kind: str) -> int:
        return len(self.edges(kind))


class Engine:
    """Answers bound queries over one join tree.  ``elide`` leaves out messages that are all ones."""

    def __init__(self, spark: SparkSession, tree: JoinTree, store: MessageStore | None = None, elide: bool = True):
        self.spark, self.tree, self.elide = spark, tree, elide
        self.store = store or MessageStore(spark)
        self._rows: dict[tuple[str, int], int] = {}
        self._ndv: dict[tuple[str, str], int] = {}

    # ---- statistics -------------------------------------------------------------------------

    def rows(self, relation: str, version: int = 0) -> int:
        key = (relation, version)
        if key not in self._rows:
            self._rows[key] = self.tree.graph.relations[relation].at(version).count()
        return self._rows[key]

    def bag_rows(self, bag: str) -> int:
        rels = self.tree.mapped(bag)
        return max((self.rows(r) for r in rels), default=1)

    def distinct(self, attr: str) -> int:
        """Approximate domain size, from the least relation that holds the attribute."""
        rels = [r for r, x in self.tree.graph.relations.items() if attr in x.attrs]
        rel = min(rels, key=self.rows)
        if (rel, attr) not in self._ndv:
            self._ndv[rel, attr] = max(1, self.tree.graph.relations[rel].df.agg(F.approx_count_distinct(attr)).first()[0])
        return self._ndv[rel, attr]

    # ---- plans ------------------------------------------------------------------------------

    def _operand(self, bound: Bound, relation: str, needed: frozenset[str], preds: list[tuple[str, str]]) -> tuple[DataFrame, list[str], list]:
        rel = self.tree.graph.relations[relation] if relation in self.tree.graph.relations else bound.tree.graph.relations[relation]
        df, left = rel.at(bound.version(relation)), []
        for p in preds:  # filters go below the joins wherever one relation can evaluate them
            if attributes_in(p[1], needed | rel.attrs) <= rel.attrs:
                df = df.filter(F.expr(p[1]))
            else:
                left.append(p)
        lift = bound.ring.lift(relation) or {}
        keep = [F.col(a) for a in sorted(rel.attrs & needed)]
        return df.select(*keep, *[v.alias(k) for k, v in lift.items()]), list(lift), left

    def _product(self, left: DataFrame, right: DataFrame, condition: str | None = None) -> DataFrame:
        """Two sides without an equality: only where one of them has few rows."""
        few = lambda df: all(c.startswith("__") for c in df.columns) or df.limit(LOOP_ROWS + 1).count() <= LOOP_ROWS
        if not few(right):
            if not few(left):
                raise UnboundedJoin("a join without an equality between two large sides; give the condition a bin width")
            left, right = right, left
        return left.join(F.broadcast(right), F.expr(condition)) if condition else left.crossJoin(F.broadcast(right))

    def _compared(self, left: DataFrame, right: DataFrame, on: list[str], c: Condition) -> DataFrame:
        """Two sides under a condition: by bins where it has a width, else by a nested loop."""
        if not c.width:
            if on:
                return left.join(right, on).filter(F.expr(c.expr))
            return self._product(left, right, c.expr)
        point, span = (left, right) if c.value in left.columns else (right, left)
        point = point.withColumn("__bin", F.floor(F.col(c.value) / c.width))
        first, last = F.floor(F.col(c.low) / c.width), F.floor(F.col(c.high) / c.width)
        span = span.withColumn("__bin", F.explode(F.sequence(first, F.greatest(first, last))))
        return point.join(span, [*on, "__bin"]).filter(F.expr(c.expr)).drop("__bin")

    def _join(self, bound: Bound, a, b, small: bool, edge: tuple[Condition | None, bool] = (None, False)):
        """Natural join of two annotated operands, annotations multiplied.  ``edge``: a condition beside
        equal names, and whether rows of the left stay without the right."""
        (left, mine), (right, theirs) = a, b
        condition, outer = edge
        clash = [n for n in theirs if n in mine]
        for n in clash:
            right = right.withColumnRenamed(n, f"{n}__r")
        on = sorted({c for c in left.columns if not c.startswith("__")} & {c for c in right.columns if not c.startswith("__")})
        side = F.broadcast(right) if small else right
        ring = bound.ring
        if condition:
            if outer:
                raise UnboundedJoin("an outer edge joins by equal names")
            joined = self._compared(left, side, on, condition)
        elif outer:
            joined = left.join(side, on, "left")
            own, absent = {f"{n}__r" if n in clash else n: n for n in theirs}, ring.absent(theirs)
            joined = joined.select(*[F.coalesce(c, absent[own[c]]).alias(c) if own.get(c) in absent else F.col(c) for c in joined.columns])
        else:
            joined = left.join(side, on) if on else self._product(left, right)
        if not mine or not theirs:
            names = mine or theirs
            return joined, list(names)
        x = {n: F.col(n) for n in mine}
        y = {n: F.col(f"{n}__r" if n in clash else n) for n in theirs}
        product = ring.times(x, y)
        attrs = [c for c in joined.columns if not c.startswith("__")]
        return joined.select(*attrs, *[v.alias(k) for k, v in product.items()]), list(product)

    def _bag(self, bound: Bound, bag: str, incoming: list, wanted) -> tuple[DataFrame, list[str]]:
        """The bag's relations and incoming messages joined, filters applied; columns ``wanted`` remain."""
        preds = bound.predicates(bag)
        around = bound.tree.neighbours(bag)
        used = frozenset().union(frozenset(wanted), *[attributes_in(e, bound.tree.bags[bag]) for _, e in preds], *[bound.tree.separator(bag, w) | bound.compared(bag, w) for w in around])
        rels = bound.active(bag)
        shared = frozenset(a for a in bound.tree.bags[bag] if sum(a in bound.tree.graph.relations[r].attrs for r in rels) > 1)
        operands = []
        for r in sorted(rels, key=lambda r: (-self.rows(r) if len(rels) > 1 else 0, r)):
            df, names, preds = self._operand(bound, r, used | shared, preds)
            operands.append((df, names, False, (None, False)))
        graph = bound.tree.graph
        for w, (ref_df, names, small) in sorted(incoming, key=lambda m: ((bag, m[0]) in graph.optional, not m[1][2] if rels else m[1][2])):
            operands.append((ref_df, names, small, (graph.conditions.get(frozenset((w, bag))), (bag, w) in graph.optional)))
        if not operands:
            raise ValueError(f"nothing to join in {bag}")
        df, names = operands[0][:2]
        rest = operands[1:]
        while rest:  # connected operands first, so that no product arises where a join will do
            have = {c for c in df.columns if not c.startswith("__")}
            near = lambda d, edge: have & {c for c in d.columns if not c.startswith("__")} or edge[0] and attributes_in(edge[0].expr, have)  # noqa: E731, B023
            at = next((i for i, (d, _, _, edge) in enumerate(rest) if near(d, edge)), 0)
            d, n, small, edge = rest.pop(at)
            df, names = self._join(bound, (df, names), (d, n), small, edge)
        for _, e in preds:
            df = df.filter(F.expr(e))
        return df, names

    def _add_up(self, bound: Bound, df: DataFrame, names: list[str], keys) -> tuple[DataFrame, list[str]]:
        if not names:
            one = bound.ring.one()
            df, names = df.select(*keys, *[v.alias(k) for k, v in one.items()]), list(one)
        aggs = bound.ring.plus(names)
        if not aggs:
            return (df.select(*keys).distinct() if keys else df.select(F.lit(1).alias("__any")).limit(1)), []
        out = df.groupBy(*keys).agg(*aggs) if keys else df.agg(*aggs)
        return out, [c for c in out.columns if c.startswith("__")]

    def message(self, bound: Bound, u: str, v: str, trace: Trace, use_store: bool = True, keep: bool = False):
        """The operand u → v as (DataFrame, annotation names, small), or None where it is all ones."""
        if bound.is_one(u, v, self.elide):
            trace.add("elided", u, v)
            return None
        if (u, v) in bound.tree.graph.optional:
            raise UnboundedJoin(f"{v} is on the outer side of an outer join: no message goes there")
        fp = bound.fingerprint(u, v, self.elide)
        ref = self.store.get(fp) if use_store else None
        if ref is None:
            kids = [(w, self.message(bound, w, u, trace, use_store, keep)) for w in bound.tree.neighbours(u) if w != v]
            keys = bound.keys(u, v)
            df, names = self._bag(bound, u, [k for k in kids if k[1]], keys)
            df, names = self._add_up(bound, df, names, keys)
            trace.add("computed", u, v)
            if not keep:
                return df, names, False
            began = time.perf_counter()
            ref = self.store.put(fp, df, tuple(sorted(bound.tree.separator(u, v) & set(keys))))
            trace.seconds[f"{u}→{v}"] = time.perf_counter() - began
            if ref is None:
                return df, names, False
        else:
            trace.add("reused", u, v)
        return ref.df, [c for c in ref.df.columns if c.startswith("__")], ref.memory <= BROADCAST_BYTES

    def absorb(self, bound: Bound, root: str, trace: Trace | None = None, use_store: bool = True, keys=None, raw: bool = False) -> DataFrame:
        """Join everything that reaches ``root`` and add up to the query's groups."""
        trace = trace if trace is not None else Trace()
        incoming = [(w, m) for w in bound.tree.neighbours(root) if (m := self.message(bound, w, root, trace, use_store))]
        keys = tuple(bound.group if keys is None else keys)
        df, names = self._bag(bound, root, incoming, keys)
        trace.add("absorbed", root)
        df, names = self._add_up(bound, df, names, keys)
        if raw:
            return df
        return df.select(*keys, *bound.ring.finalise(set(names)))

    def fanout(self, bound: Bound, u: str, targets: list[str], trace: Trace) -> None:
        """Store the messages from one bag to several neighbours after a single scan of it.

        Possible where those neighbours send nothing but ones: the bag's join is then the same for all of
        them, and one pass over grouping sets adds it up along each one's keys."""
        if not all(bound.is_one(t, u, self.elide) for t in targets):
            raise ValueError("a shared scan needs neighbours whose own messages are all ones")
        incoming = [(w, m) for w in bound.tree.neighbours(u) if w not in targets and (m := self.message(bound, w, u, trace))]
        keys = {t: bound.keys(u, t) for t in targets}
        every = sorted({k for ks in keys.values() for k in ks})
        df, names = self._bag(bound, u, incoming, every)
        if not names:
            one = bound.ring.one()
            df, names = df.select(*every, *[v.alias(k) for k, v in one.items()]), list(one)
        sets = df.groupingSets([[F.col(k) for k in ks] for ks in keys.values()], *[F.col(k) for k in every])
        both = sets.agg(F.grouping_id().alias("gid"), *bound.ring.plus(names)).persist()
        for t, ks in keys.items():
            gid = sum(1 << (len(every) - 1 - i) for i, k in enumerate(every) if k not in ks)
            part = both.filter(F.col("gid") == gid).select(*ks, *[c for c in both.columns if c.startswith("__")])
            self.store.put(bound.fingerprint(u, t, self.elide), part)
            trace.add("computed", u, t)
        both.unpersist()

    # ---- whole queries ----------------------------------------------------------------------

    def factorized(self, query: SpjaQuery, root: str | None = None, trace: Trace | None = None) -> DataFrame:
        """Message passing from the base tables, nothing shared."""
        from joindash.plans.planner import plan_single

        root = root or plan_single(self, query)
        return self.absorb(bind(self.tree, query, root), root, trace, use_store=False)

    def to_sql(self, bound: Bound, u: str, v: str) -> str:
        """The message u → v as one SPJA statement over its operands, for reading and audits."""
        parts = [f"{r}{'@' + str(bound.version(r)) if bound.version(r) else ''}" for r in bound.active(u)]
        parts += [f"message_{w}_{u}" for w in bound.tree.neighbours(u) if w != v and not bound.is_one(w, u, self.elide)]
        keys = ", ".join(bound.keys(u, v))
        where = " AND ".join(f"({e})" for _, e in bound.predicates(u))
        return f"SELECT {keys or '1'}, <{bound.ring.ident}> FROM {' NATURAL JOIN '.join(parts)}{' WHERE ' + where if where else ''}{' GROUP BY ' + keys if keys else ''}"
