"""Relations, join graphs, join trees and ear removal: driver-side metadata."""

from __future__ import annotations

import hashlib
import re
import uuid
from dataclasses import dataclass, field
from itertools import combinations

from pyspark.sql import DataFrame


class InvalidTree(ValueError):
    pass


class DisconnectsJoinGraph(ValueError):
    pass


@dataclass
class Relation:
    """A table under canonical attribute names; shared names are join conditions.

    ``unique``: attribute sets that are keys.  ``versions`` keep the schema; version 0 is ``df``.
    ``sql``: a SELECT that gives the same rows on the raw tables, for the naive SQL text.
    ``ident``: names the contents.  Equal idents mean equal rows, in this process and in others, so give
    one only where it is derived from the data's place and state; otherwise every relation has its own.
    """

    name: str
    df: DataFrame
    unique: tuple[frozenset[str], ...] = ()
    sql: str = ""
    versions: dict[int, DataFrame] = field(default_factory=dict)
    version_sql: dict[int, str] = field(default_factory=dict)
    ident: str = field(default_factory=lambda: uuid.uuid4().hex)
    version_ident: dict[int, str] = field(default_factory=dict)
    appended: list[str] = field(default_factory=list)  # files whose rows the last version has beside ``df``

    @property
    def attrs(self) -> frozenset[str]:
        return frozenset(self.df.columns)

    def at(self, version: int) -> DataFrame:
        return self.versions[version] if version else self.df

    def identity(self, version: int) -> str:
        return self.version_ident[version] if version else self.ident

    def add_version(self, df: DataFrame, sql: str = "", ident: str | None = None) -> int:
        if df.schema.names != self.df.schema.names:
            raise InvalidTree(f"a version of {self.name} keeps its columns")
        n = max(self.versions, default=0) + 1
        self.versions[n], self.version_sql[n] = df, sql
        self.version_ident[n] = ident or uuid.uuid4().hex
        return n


def content_ident(*parts: str) -> str:
    return hashlib.sha256("\x00".join(parts).encode()).hexdigest()[:32]


@dataclass(frozen=True)
class Condition:
    """A join condition other than equal names.  With ``width``, it is low <= value < high, and both sides
    are dealt to bins of that width first; without, one side must be small enough for a nested loop."""

    expr: str
    value: str = ""
    low: str = ""
    high: str = ""
    width: float = 0.0

    @staticmethod
    def between(value: str, low: str, high: str, width: float) -> Condition:
        return Condition(f"{value} >= {low} AND {value} < {high}", value, low, high, width)


@dataclass
class JoinGraph:
    """``complete``: (many, one) pairs of relations whose foreign keys all resolve; with a key on the one
    side, such a side does not change a count.  ``conditions``: by pair of bags, conditions beyond equal
    names.  ``optional``: (bag, bag) pairs of outer joins, rows of the first stay without the second."""

    relations: dict[str, Relation]
    complete: frozenset[tuple[str, str]] = frozenset()
    conditions: dict[frozenset[str], Condition] = field(default_factory=dict)
    optional: frozenset[tuple[str, str]] = frozenset()

    @staticmethod
    def of(*relations: Relation, complete=()) -> JoinGraph:
        return JoinGraph({r.name: r for r in relations}, frozenset(complete))

    def only(self, names) -> JoinGraph:
        names = set(names)
        pairs = lambda ps: frozenset(p for p in ps if names >= set(p))
        conditions = {p: c for p, c in self.conditions.items() if names >= p}
        return JoinGraph({k: v for k, v in self.relations.items() if k in names}, pairs(self.complete), conditions, pairs(self.optional))

    def shared(self, a: str, b: str) -> frozenset[str]:
        return self.relations[a].attrs & self.relations[b].attrs

    def hyperedges(self) -> dict[str, frozenset[str]]:
        """Each relation's join attributes: those that another relation has too."""
        out = {}
        for n, r in self.relations.items():
            others = frozenset().union(*[x.attrs for m, x in self.relations.items() if m != n]) if len(self.relations) > 1 else frozenset()
            out[n] = r.attrs & others
        return out


def ear_removal(hyperedges: dict[str, frozenset[str]], attrs: dict[str, frozenset[str]] | None = None, keyed: frozenset[str] = frozenset()) -> tuple[list[str], list[tuple[str, str]], dict[str, frozenset[str]]]:
    """(attribute elimination order, tree edges, residual core).

    Repeats two steps until nothing changes: drop attributes seen in one relation, and fold a relation
    that is contained in another into it.  The core is empty exactly for acyclic graphs.  ``keyed``
    relations (dimensions) are folded later and preferred as hosts, so that facts end up as leaves.
    """
    live = {n: set((attrs or hyperedges)[n]) for n in hyperedges}
    order: list[str] = []
    edges: list[tuple[str, str]] = []
    moved = True
    while moved and live:
        moved = False
        for n in sorted(live):
            lonely = sorted(a for a in live[n] if not any(a in live[m] for m in live if m != n))
            if lonely:
                order += lonely
                live[n] -= set(lonely)
                moved = True
        for n in sorted(live, key=lambda n: (len(live[n]), n in keyed, n)):
            hosts = [m for m in live if m != n and live[n] <= live[m]]
            if hosts and (live[n] or len(live) > 1):
                host = min(hosts, key=lambda m: (m not in keyed, len(live[m]), m))
                edges.append((n, host))
                del live[n]
                moved = True
                break
        if len(live) == 1 and not next(iter(live.values())):
            live.clear()
    return order, edges, {n: frozenset(v) for n, v in live.items()}


def elimination_order(hyperedges: dict[str, frozenset[str]], keep: frozenset[str] = frozenset(), sizes: dict[str, int] | None = None) -> list[str]:
    """Greedy order for any graph: next the attribute whose cluster of relations covers fewest attributes
    (least product of domain sizes where they are known).  Kept attributes come last."""
    live = [set(v) for v in hyperedges.values()]
    out, left = [], set().union(*live) if live else set()
    while left:
        pool = left - keep or left

        def cost(a: str):
            cluster = set().union(*[e for e in live if a in e])
            weight = 1
            for x in cluster:
                weight *= (sizes or {}).get(x, 2)
            return weight, len(cluster), a

        a = min(pool, key=cost)
        cluster = set().union(*[e for e in live if a in e]) - {a}
        live = [e for e in live if a not in e] + ([cluster] if cluster else [])
        out.append(a)
        left.discard(a)
    return out


@dataclass
class JoinTree:
    """Bags (attribute sets), undirected links, and the bag that each relation is mapped to."""

    bags: dict[str, frozenset[str]]
    links: set[frozenset[str]]
    mapping: dict[str, str]
    graph: JoinGraph

    # ---- building ----

    @staticmethod
    def from_graph(graph: JoinGraph) -> JoinTree:
        """One bag per relation of an acyclic graph."""
        hyper = graph.hyperedges()
        keyed = frozenset(n for n, r in graph.relations.items() if any(k <= hyper[n] for k in r.unique))
        _, edges, core = ear_removal(hyper, {n: r.attrs for n, r in graph.relations.items()}, keyed)
        if core:
            raise InvalidTree(f"the join graph is cyclic in {sorted(core)}; pre-join the cycle")
        bags = {n: r.attrs for n, r in graph.relations.items()}
        tree = JoinTree(bags, {frozenset(e) for e in edges}, {n: n for n in bags}, graph)
        tree.validate()
        return tree

    @staticmethod
    def from_order(graph: JoinGraph, order: list[str]) -> JoinTree:
        """A bag per eliminated attribute: the cluster of relations and earlier bags that hold it."""
        live = {n: set(r.attrs) for n, r in graph.relations.items()}
        mapping, bags, links, made = {}, {}, set(), {}
        for a in order:
            cluster = [n for n in live if a in live[n]]
            if not cluster:
                continue
            name, attrs = f"bag_{a}", frozenset().union(*[live[n] for n in cluster])
            bags[name] = attrs
            for n in cluster:
                if n in graph.relations:
                    mapping[n] = name
                else:
                    links.add(frozenset((made[n], name)))
                del live[n]
            rest = attrs - {a}
            if rest:
                live[f"after_{a}"] = set(rest)
                made[f"after_{a}"] = name
        tree = JoinTree(bags, links, mapping, graph)
        tree._contract()
        tree.validate()
        return tree

    def _contract(self) -> None:
        """Fold a bag into a neighbour that contains it."""
        while True:
            fold = next(((a, b) for e in sorted(map(sorted, self.links)) for a, b in (e, e[::-1]) if self.bags[a] <= self.bags[b]), None)
            if not fold:
                return
            a, b = fold
            for c in self.neighbours(a):
                self.links.discard(frozenset((a, c)))
                if c != b:
                    self.links.add(frozenset((b, c)))
            for r, bag in self.mapping.items():
                if bag == a:
                    self.mapping[r] = b
            del self.bags[a]

    @staticmethod
    def decompose_cycles(graph: JoinGraph, groups: list[list[str]] | None = None, name: str = "core") -> JoinTree:
        """Cyclic graphs: each group (by default the residual core) shares one bag whose relations are
        joined together there."""
        if groups is None:
            _, _, core = ear_removal(graph.hyperedges(), {n: r.attrs for n, r in graph.relations.items()})
            groups = [sorted(core)] if core else []
        merged, used = {}, set()
        for i, g in enumerate(groups):
            merged[f"{name}{i or ''}"] = (frozenset().union(*[graph.relations[n].attrs for n in g]), g)
            used |= set(g)
        bags = {b: a for b, (a, _) in merged.items()} | {n: r.attrs for n, r in graph.relations.items() if n not in used}
        _, edges, core = ear_removal({b: a for b, a in bags.items()})
        if core:
            raise InvalidTree("the groups leave a cycle")
        mapping = {n: b for b, (_, g) in merged.items() for n in g} | {n: n for n in graph.relations if n not in used}
        tree = JoinTree(bags, {frozenset(e) for e in edges}, mapping, graph)
        tree.validate()
        return tree

    # ---- shape ----

    def neighbours(self, bag: str) -> list[str]:
        return sorted(next(iter(e - {bag})) for e in self.links if bag in e)

    def separator(self, u: str, v: str) -> frozenset[str]:
        return self.bags[u] & self.bags[v]

    def directed(self) -> list[tuple[str, str]]:
        return [p for e in sorted(map(sorted, self.links)) for p in (tuple(e), tuple(e[::-1]))]

    def upstream(self, u: str, v: str) -> frozenset[str]:
        """The bags on the side of ``u`` of the edge u → v."""
        out, stack = {u}, [u]
        while stack:
            for w in self.neighbours(stack.pop()):
                if w != v and w not in out:
                    out.add(w)
                    stack.append(w)
        return frozenset(out)

    def path(self, a: str, b: str) -> list[str]:
        back, stack = {a: None}, [a]
        while stack:
            x = stack.pop()
            for y in self.neighbours(x):
                if y not in back:
                    back[y] = x
                    stack.append(y)
        out = [b]
        while out[-1] != a:
            out.append(back[out[-1]])
        return out[::-1]

    def optional_bags(self) -> frozenset[str]:
        """Bags on the outer side of an outer join: no query can be read there."""
        return frozenset().union(*[self.upstream(b, a) for a, b in self.graph.optional if a in self.bags and b in self.bags])

    def steiner(self, terminals) -> frozenset[str]:
        """The least subtree that holds all terminals: the union of paths between them."""
        terminals = sorted(terminals)
        out = set(terminals[:1])
        for t in terminals[1:]:
            out |= set(self.path(terminals[0], t))
        return frozenset(out)

    def toward(self, root: str) -> list[tuple[str, str]]:
        """Edges directed at the root, leaves first."""
        out, stack, seen = [], [root], {root}
        while stack:
            x = stack.pop()
            for y in self.neighbours(x):
                if y not in seen:
                    seen.add(y)
                    out.append((y, x))
                    stack.append(y)
        return out[::-1]

    def mapped(self, bag: str) -> list[str]:
        return sorted(r for r, b in self.mapping.items() if b == bag)

    def holders(self, attrs) -> list[str]:
        need = frozenset(attrs)
        return sorted(b for b, a in self.bags.items() if need <= a)

    # ---- rules ----

    def validate(self) -> None:
        if len(self.links) != len(self.bags) - 1 or (self.bags and len(self.upstream(next(iter(self.bags)), "")) != len(self.bags)):
            raise InvalidTree("bags and links do not form a tree")
        covered = frozenset().union(*self.bags.values()) if self.bags else frozenset()
        for n, r in self.graph.relations.items():
            if not r.attrs <= covered:
                raise InvalidTree(f"attributes of {n} are in no bag")
            if n not in self.mapping or not r.attrs <= self.bags[self.mapping[n]]:
                raise InvalidTree(f"{n} is not inside its bag")
        for a in covered:
            hold = [b for b, x in self.bags.items() if a in x]
            if self.steiner(hold) != frozenset(hold):
                raise InvalidTree(f"the bags of {a} are not connected")

    def map(self, relation: str, bag: str) -> JoinTree:
        """Another bag for a relation; any bag that covers it gives the same answers."""
        tree = self.copy()
        tree.mapping[relation] = bag
        tree.validate()
        return tree

    def copy(self) -> JoinTree:
        return JoinTree(dict(self.bags), set(self.links), dict(self.mapping), self.graph)

    def add_empty_bag(self, name: str, attrs, at: str) -> JoinTree:
        """A bag without relation next to ``at``, taking over its links whose separators it covers."""
        tree, attrs = self.copy(), frozenset(attrs)
        if not attrs <= self.bags[at]:
            raise InvalidTree("an empty bag's attributes come from the bag beside it")
        for w in self.neighbours(at):
            if self.separator(at, w) <= attrs:
                tree.links.discard(frozenset((at, w)))
                tree.links.add(frozenset((name, w)))
        tree.bags[name] = attrs
        tree.links.add(frozenset((at, name)))
        tree.validate()
        return tree

    def attach(self, relation: Relation, condition: Condition | None = None, optional: bool = False) -> JoinTree:
        """A new relation as a bag of its own, beside one bag that holds all it shares or is compared with.

        ``optional``: rows of the bag beside it stay where the relation has none for them (an outer join);
        a filter on the relation then holds before the join."""
        covered = frozenset().union(*self.bags.values())
        shared = relation.attrs & covered
        if condition:
            words = frozenset(re.findall(r"[A-Za-z_]\w*", re.sub(r"'(?:[^']|'')*'", "", condition.expr)))
            shared |= words & covered - relation.attrs
        hosts = self.holders(shared)
        if not shared or not hosts:
            raise InvalidTree(f"{relation.name} shares attributes with no single bag")
        host = min(hosts, key=lambda b: (len(self.bags[b]), b))
        pair = {frozenset((relation.name, host)): condition} if condition else {}
        outer = {(host, relation.name)} if optional else set()
        old = self.graph
        graph = JoinGraph(old.relations | {relation.name: relation}, old.complete, old.conditions | pair, old.optional | outer)
        tree = JoinTree(self.bags | {relation.name: relation.attrs}, self.links | {frozenset((relation.name, host))}, self.mapping | {relation.name: relation.name}, graph)
        tree.validate()
        return tree


def fractional_edge_cover(hyperedges: dict[str, frozenset[str]]) -> float:
    """Least total weight on relations such that every attribute is covered by weight 1.

    The optimum of this small linear program is half-integral on graphs with two attributes per relation
    and lies on a vertex in general; vertices are enumerated by solving the tight constraints.
    """
    import numpy as np

    names = sorted(hyperedges)
    attrs = sorted(set().union(*hyperedges.values())) if hyperedges else []
    if not attrs:
        return 0.0
    n = len(names)
    a = np.array([[1.0 if x in hyperedges[r] else 0.0 for r in names] for x in attrs])
    rows = [*[(v, 1.0) for v in a], *[(np.eye(n)[i], 0.0) for i in range(n)]]
    best = float(n)
    for pick in combinations(range(len(rows)), n):
        m = np.array([rows[i][0] for i in pick])
        if abs(np.linalg.det(m)) < 1e-9:
            continue
        w = np.linalg.solve(m, np.array([rows[i][1] for i in pick]))
        if (w >= -1e-9).all() and (a @ w >= 1 - 1e-9).all():
            best = min(best, float(w.sum()))
    return best
