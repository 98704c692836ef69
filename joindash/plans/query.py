"""SPJA queries, and queries bound to a join tree as annotations on bags."""

from __future__ import annotations

import hashlib
import json
import re
from dataclasses import dataclass, field, replace

from joindash.functions.semiring import Semiring
from joindash.plans.graph import DisconnectsJoinGraph, JoinTree


class UnsupportedPredicate(ValueError):
    """A predicate whose attributes share no bag."""


def _digest(text: str) -> str:
    return hashlib.sha256(text.encode()).hexdigest()[:16]


def attributes_in(expr: str, known) -> frozenset[str]:
    bare = re.sub(r"'(?:[^']|'')*'", "", expr)
    return frozenset(re.findall(r"[A-Za-z_]\w*", bare)) & frozenset(known)


@dataclass(frozen=True)
class SpjaQuery:
    """A semi-ring aggregate over the join of all relations, by group attributes, under conjunctive
    predicates, without the excluded relations and with the given relation versions."""

    ring: Semiring
    group: tuple[str, ...] = ()
    where: tuple[str, ...] = ()
    exclude: frozenset[str] = frozenset()
    versions: tuple[tuple[str, int], ...] = ()

    def with_filter(self, expr: str) -> SpjaQuery:
        return replace(self, where=(*self.where, expr))

    def without_filter(self, expr: str) -> SpjaQuery:
        return replace(self, where=tuple(w for w in self.where if w != expr))

    def add_group(self, attr: str) -> SpjaQuery:
        return self if attr in self.group else replace(self, group=(*self.group, attr))

    def drop_group(self, attr: str) -> SpjaQuery:
        return replace(self, group=tuple(g for g in self.group if g != attr))

    def set_group(self, *attrs: str) -> SpjaQuery:
        return replace(self, group=tuple(attrs))

    def remove_table(self, name: str) -> SpjaQuery:
        return replace(self, exclude=self.exclude | {name})

    def update_table(self, name: str, version: int) -> SpjaQuery:
        return replace(self, versions=(*[v for v in self.versions if v[0] != name], (name, version)))

    def predicates(self) -> dict[str, str]:
        """Predicate id -> expression; the id does not depend on spacing or order."""
        return {_digest(re.sub(r"\s+", " ", w.strip())): w for w in self.where}


@dataclass(frozen=True)
class Bound:
    """Where each annotation sits.  ``drops`` are marginalisations: (attribute, bag) where a carried
    attribute is summed out again."""

    tree: JoinTree
    ring: Semiring
    group: tuple[str, ...]
    groups: tuple[tuple[str, str], ...] = ()
    selects: tuple[tuple[str, str, str], ...] = ()  # id, expression, bag
    drops: frozenset[tuple[str, str]] = frozenset()
    exclude: frozenset[str] = frozenset()
    versions: tuple[tuple[str, int], ...] = ()
    memo: dict = field(default_factory=dict, compare=False, repr=False)

    def __post_init__(self):
        for attr, bag in self.groups:
            if attr not in self.tree.bags[bag]:
                raise ValueError(f"{attr} is not in {bag}")
        for _, expr, bag in self.selects:
            used = attributes_in(expr, frozenset().union(*self.tree.bags.values()))
            if not used <= self.tree.bags[bag]:
                raise UnsupportedPredicate(f"{expr!r} does not fit {bag}")
        for rel in self.exclude:
            check_exclusion(self.tree, rel, self.exclude, {b for _, b in self.groups} | {b for *_, b in self.selects})

    def active(self, bag: str) -> list[str]:
        return [r for r in self.tree.mapped(bag) if r not in self.exclude]

    def version(self, relation: str) -> int:
        return dict(self.versions).get(relation, 0)

    def predicates(self, bag: str) -> list[tuple[str, str]]:
        return sorted((i, e) for i, e, b in self.selects if b == bag)

    def annotated(self, bag: str) -> bool:
        return bool(self.predicates(bag)) or any(b == bag for _, b in self.groups) or any(self.version(r) for r in self.active(bag))

    def carried(self, u: str, v: str) -> frozenset[str]:
        """Group attributes from upstream that stay in the message u → v."""
        up, out = self.tree.upstream(u, v), set()
        for attr, bag in self.groups:
            if bag in up and not any((attr, b) in self.drops for b in self.tree.path(bag, u)):
                out.add(attr)
        return frozenset(out)

    def keys(self, u: str, v: str) -> tuple[str, ...]:
        """Separator attributes that a relation upstream supplies, and carried group attributes."""
        rels = [r for b in self.tree.upstream(u, v) for r in self.active(b)]
        supplied = frozenset().union(*[self.tree.graph.relations[r].attrs for r in rels]) if rels else frozenset()
        return tuple(sorted((self.tree.separator(u, v) & supplied) | self.carried(u, v) | self.compared(u, v)))

    def compared(self, u: str, v: str) -> frozenset[str]:
        """Attributes of ``u`` that a condition on the edge reads."""
        condition = self.tree.graph.conditions.get(frozenset((u, v)))
        return attributes_in(condition.expr, self.tree.bags[u]) if condition else frozenset()

    def is_one(self, u: str, v: str, elide: bool = True) -> bool:
        """Whether the message u → v multiplies every matching row by one, so that it can be left out.

        True for sides without relation, and, with ``elide``, for sides of key-unique dimensions whose
        foreign keys all resolve, as long as no annotation or measure lies there."""
        key = ("one", u, v, elide)
        if key not in self.memo:
            self.memo[key] = self._is_one(u, v, elide)
        return self.memo[key]

    def _is_one(self, u: str, v: str, elide: bool) -> bool:
        if self.annotated(u):
            return False
        rels = self.active(u)
        kids = [w for w in self.tree.neighbours(u) if w != v]
        if not all(self.is_one(w, u, elide) for w in kids):
            return False
        if not rels:
            return True
        if not elide or len(rels) > 1 or self.ring.lift(rels[0]) is not None:
            return False
        rel, others = self.tree.graph.relations[rels[0]], self.active(v) if v in self.tree.bags else []
        sep = self.tree.separator(u, v)
        unique = any(k <= sep for k in rel.unique)
        if unique and (v, u) in self.tree.graph.optional:
            return True
        return unique and any((o, rel.name) in self.tree.graph.complete for o in others)

    def fingerprint(self, u: str, v: str, elide: bool = True) -> str:
        """Digest of everything upstream of u → v: equal digests mean equal messages."""
        key = ("fp", u, v, elide)
        if key not in self.memo:
            up = self.tree.upstream(u, v)
            spec = {
                "relations": [(r, self.tree.graph.relations[r].identity(self.version(r))) for r in self.active(u)],
                "predicates": self.predicates(u),
                "keys": self.keys(u, v),
                "ring": self.ring.part({r for b in up for r in self.active(b)}),
                "children": sorted(self._edge(w, u) + ("1" if self.is_one(w, u, elide) else self.fingerprint(w, u, elide)) for w in self.tree.neighbours(u) if w != v),
            }
            self.memo[key] = hashlib.sha256(json.dumps(spec, sort_keys=True).encode()).hexdigest()
        return self.memo[key]

    def _edge(self, w: str, u: str) -> str:
        """How the message w → u is joined, where it is not by equal names."""
        condition = self.tree.graph.conditions.get(frozenset((w, u)))
        return (f"if {condition.expr} " if condition else "") + ("outer " if (u, w) in self.tree.graph.optional else "")


def check_exclusion(tree: JoinTree, relation: str, excluded: frozenset[str], annotated: set[str]) -> None:
    """A relation may go if its bag keeps another relation that covers the bag's links, or if its bag is
    a leaf without annotations."""
    bag = tree.mapping[relation]
    rest = [r for r in tree.mapped(bag) if r not in excluded]
    need = frozenset().union(*[tree.separator(bag, w) for w in tree.neighbours(bag)]) if tree.neighbours(bag) else frozenset()
    if any(need <= tree.graph.relations[r].attrs for r in rest):
        return
    kept = [w for w in tree.neighbours(bag) if any(r not in excluded for b in tree.upstream(w, bag) for r in tree.mapped(b))]
    if len(kept) > 1:
        raise DisconnectsJoinGraph(f"without {relation} the join graph falls apart")
    if bag in annotated:
        raise DisconnectsJoinGraph(f"{relation} holds an attribute that the query still uses")


def bind(tree: JoinTree, query: SpjaQuery, near: str | None = None) -> Bound:
    """Single-query placement: predicates as deep as possible (the bag of the least relation that covers
    them, farthest from ``near``), groups as near to ``near`` as possible."""
    hops = (lambda b: len(tree.path(b, near))) if near else (lambda b: 0)
    known = frozenset().union(*tree.bags.values())
    selects = []
    for i, e in sorted(query.predicates().items()):
        bags = tree.holders(attributes_in(e, known))
        if not bags:
            raise UnsupportedPredicate(f"{e!r} spans several bags; split it, or pre-join them")
        bags = [b for b in bags if any(r not in query.exclude for r in tree.mapped(b))] or bags
        selects.append((i, e, min(bags, key=lambda b: (-hops(b), len(tree.bags[b]), b))))
    groups = []
    for g in query.group:
        bags = tree.holders([g])
        if not bags:
            raise ValueError(f"no bag holds {g}")
        groups.append((g, min(bags, key=lambda b: (hops(b), len(tree.bags[b]), b))))
    return Bound(tree, query.ring, tuple(query.group), tuple(groups), tuple(selects), frozenset(), query.exclude, tuple(sorted(query.versions)))
