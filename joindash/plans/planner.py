"""Root choice, pivot differences, reuse subtrees and placement."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from joindash.plans.messages import Engine, Trace
from joindash.plans.query import Bound, SpjaQuery, UnsupportedPredicate, attributes_in, bind


# ---- cost -----------------------------------------------------------------------------------


def message_cost(engine: Engine, bound: Bound, u: str, v: str | None, selectivity: float = 0.1) -> float:
    """Sort-based cost of a message (or, without target, of absorption): operands × width × S log S,
    where S is the bag's relation under its filters, times the domain of every carried attribute."""
    if v is not None and bound.is_one(u, v, engine.elide):
        return 0.0
    kids = [w for w in bound.tree.neighbours(u) if w != v]
    carried = bound.carried(u, v) if v else frozenset().union(*[bound.carried(w, u) for w in kids]) if kids else frozenset()
    size = max((engine.rows(r, bound.version(r)) for r in bound.active(u)), default=1)
    if not bound.active(u):
        size = min(math.prod(engine.distinct(a) for a in sorted(bound.tree.bags[u])), max((engine.bag_rows(w) for w in kids), default=1))
    s = size * selectivity ** len(bound.predicates(u))
    for a in carried - bound.tree.bags[u]:
        s *= min(engine.distinct(a), max(size, 2))
    s = max(s, 2.0)
    return (len(kids) + 1) * (len(bound.tree.bags[u]) + len(carried)) * s * math.log2(s)


def plan_cost(engine: Engine, bound: Bound, root: str, within: frozenset[str] | None = None) -> float:
    """Cost of all messages toward the root, inside a subtree where one is given, and of absorption."""
    total = message_cost(engine, bound, root, None)
    for u, v in bound.tree.toward(root):
        if within is None or (u in within and v in within):
            total += message_cost(engine, bound, u, v)
    return total


def plan_single(engine: Engine, query: SpjaQuery) -> str:
    """The root with the least cost, every bag tried."""
    outer = engine.tree.optional_bags()
    roots = [b for b in sorted(engine.tree.bags) if b not in outer and any(r not in query.exclude for r in engine.tree.mapped(b))]
    return min(roots, key=lambda r: (plan_cost(engine, bind(engine.tree, query, r), r), r))


# ---- pivot and new query --------------------------------------------------------------------


@dataclass(frozen=True)
class Difference:
    new_selects: tuple[tuple[str, str], ...]
    old_selects: tuple[tuple[str, str, str], ...]
    new_groups: tuple[str, ...]
    old_groups: tuple[tuple[str, str], ...]
    relations: frozenset[str]  # excluded, included again, or at another version

    @property
    def empty(self) -> bool:
        return not (self.new_selects or self.old_selects or self.new_groups or self.old_groups or self.relations)


def difference(pivot: Bound, query: SpjaQuery) -> Difference:
    have, want = {i for i, _, _ in pivot.selects}, query.predicates()
    live = {a for a, b in pivot.groups if not any((a, x) in pivot.drops for x in pivot.tree.bags)}
    old_v, new_v = dict(pivot.versions), dict(query.versions)
    moved = {r for r in {*old_v, *new_v} if old_v.get(r, 0) != new_v.get(r, 0)}
    return Difference(
        tuple((i, e) for i, e in sorted(want.items()) if i not in have),
        tuple(s for s in pivot.selects if s[0] not in want),
        tuple(g for g in query.group if g not in live),
        tuple((a, b) for a, b in pivot.groups if a in live and a not in query.group),
        frozenset(pivot.exclude ^ query.exclude) | frozenset(moved),
    )


@dataclass
class ReusePlan:
    bound: Bound
    root: str
    subtree: frozenset[str]
    diff_bags: frozenset[str]


def _place(engine: Engine, tree, attrs, near: frozenset[str]) -> str:
    """The bag that holds the attributes nearest to a set of bags; the smaller one of equals."""
    bags = tree.holders(attrs)
    if not bags:
        raise UnsupportedPredicate(f"no bag holds all of {sorted(attrs)}")
    far = lambda b: min((len(tree.path(b, n)) for n in near), default=0)
    return min(bags, key=lambda b: (far(b), engine.bag_rows(b), b))


def init_placement(engine: Engine, pivot: Bound, query: SpjaQuery, compensate: bool = True) -> tuple[Bound, dict[tuple, str]]:
    """The new query on the pivot's tree: shared annotations stay, new ones get a bag each, and a group of
    the pivot alone is summed out in its own bag.  Returns the movable differences and their bags too."""
    tree, diff = pivot.tree, difference(pivot, query)
    if query.ring != pivot.ring:
        raise ValueError("a pivot serves queries over its own ring")
    known = frozenset().union(*tree.bags.values())
    movable: dict[tuple, str] = {}
    fixed = frozenset(tree.mapping[r] for r in diff.relations) | frozenset(b for *_, b in diff.old_selects)
    for i, e in diff.new_selects:
        movable["select", i, e] = _place(engine, tree, attributes_in(e, known), fixed | frozenset(movable.values()))
    for g in diff.new_groups:
        movable["group", g] = _place(engine, tree, {g}, fixed | frozenset(movable.values()))
    if compensate:
        for a, b in diff.old_groups:
            movable["drop", a] = b
    return _bound(pivot, query, movable), movable


def _bound(pivot: Bound, query: SpjaQuery, movable: dict[tuple, str]) -> Bound:
    want = query.predicates()
    selects = [s for s in pivot.selects if s[0] in want] + [(k[1], k[2], b) for k, b in movable.items() if k[0] == "select"]
    fresh = {k[1]: b for k, b in movable.items() if k[0] == "group"}
    groups = [(a, b) for a, b in pivot.groups if a not in fresh] + sorted(fresh.items())
    drops = {d for d in pivot.drops if d[0] not in fresh} | {(k[1], b) for k, b in movable.items() if k[0] == "drop"}
    return Bound(pivot.tree, query.ring, tuple(query.group), tuple(groups), tuple(selects), frozenset(drops), query.exclude, tuple(sorted(query.versions)))


def diff_bags(pivot: Bound, query: SpjaQuery, movable: dict[tuple, str]) -> frozenset[str]:
    diff = difference(pivot, query)
    return frozenset(movable.values()) | frozenset(b for *_, b in diff.old_selects) | frozenset(pivot.tree.mapping[r] for r in diff.relations)


def shrink(engine: Engine, pivot: Bound, query: SpjaQuery, movable: dict[tuple, str]) -> dict[tuple, str]:
    """Move annotations off the leaves of the reuse subtree, largest relation first, to inner bags that hold
    their attributes, until no leaf can be freed.  Exclusions, versions and undone filters stay."""
    tree, movable = pivot.tree, dict(movable)
    known = frozenset().union(*tree.bags.values())
    diff = difference(pivot, query)
    fixed = frozenset(tree.mapping[r] for r in diff.relations) | frozenset(b for *_, b in diff.old_selects)

    def needs(k: tuple) -> frozenset[str]:
        return attributes_in(k[2], known) if k[0] == "select" else frozenset({k[1]})

    while True:
        bags = diff_bags(pivot, query, movable)
        subtree = tree.steiner(bags)
        leaves = [b for b in subtree if len([w for w in tree.neighbours(b) if w in subtree]) <= 1]
        for leaf in sorted(leaves, key=lambda b: (-engine.bag_rows(b), b)):
            mine = [k for k, b in movable.items() if b == leaf]
            if leaf in fixed or not mine or len(subtree) == 1:
                continue
            inner = subtree - {leaf}
            target = {}
            for k in mine:
                hosts = [b for b in tree.holders(needs(k)) if b in inner]
                if not hosts:
                    break
                target[k] = min(hosts, key=lambda b: (len(tree.path(leaf, b)), engine.bag_rows(b), b))
            else:
                movable.update(target)
                break
        else:
            return movable


def plan_reuse(engine: Engine, pivot: Bound, query: SpjaQuery, policy: str = "reuse") -> ReusePlan:
    """Placement, reuse subtree and root for a query on a calibrated pivot.

    ``policy``: 'reuse' shrinks the subtree; 'initial' keeps the first placement (to compare)."""
    _, movable = init_placement(engine, pivot, query)
    if policy == "reuse":
        movable = shrink(engine, pivot, query, movable)
    bound, bags = _bound(pivot, query, movable), diff_bags(pivot, query, movable)
    if not bags:  # nothing differs: any bag answers, the least is read
        live = [b for b in pivot.tree.bags if bound.active(b) and b not in pivot.tree.optional_bags() and frozenset(query.group) <= pivot.tree.bags[b] | _reaching(bound, b)]
        root = min(live, key=lambda b: (engine.bag_rows(b), b))
        return ReusePlan(bound, root, frozenset({root}), bags)
    subtree = pivot.tree.steiner(bags)
    outer = pivot.tree.optional_bags()
    if subtree <= outer:  # only an outer side differs: it is read where its rows are kept
        subtree |= {a for a, b in pivot.tree.graph.optional if b in pivot.tree.bags and subtree <= pivot.tree.upstream(b, a)}
        subtree = pivot.tree.steiner(subtree)
    roots = [b for b in sorted(subtree - outer) if bound.active(b) or not pivot.tree.mapped(b)]
    if not roots:  # only bags whose relations are gone differ: absorb beside them
        roots = sorted({w for b in subtree for w in pivot.tree.neighbours(b)} - subtree)
        subtree |= frozenset(roots[:1])
        roots = roots[:1]
    root = min(roots, key=lambda b: (plan_cost(engine, bound, b, subtree), b))
    return ReusePlan(bound, root, subtree, bags)


def _reaching(bound: Bound, bag: str) -> frozenset[str]:
    kids = bound.tree.neighbours(bag)
    return frozenset().union(*[bound.carried(w, bag) for w in kids]) if kids else frozenset()


def answer(engine: Engine, pivot: Bound, query: SpjaQuery, trace: Trace | None = None, policy: str = "reuse"):
    """The query's rows, from the pivot's messages wherever the sides of the tree are equal."""
    plan = plan_reuse(engine, pivot, query, policy)
    return engine.absorb(plan.bound, plan.root, trace), plan


def place_select(engine: Engine, query: SpjaQuery, expr: str, root: str, policy: str = "weighted", weight: float = 1.0, history: dict[str, float] | None = None) -> str:
    """Where a filter should sit: 'single' far from the root (least messages now), 'reuse' near it (most
    messages reusable next), 'weighted' the least cost now + weight × expected cost of the next change.

    ``history``: how often each attribute's filter changes; a filter that changes often belongs near the root.
    """
    tree, known = engine.tree, frozenset().union(*engine.tree.bags.values())
    used = attributes_in(expr, known)
    bags = tree.holders(used)
    hops = lambda b: len(tree.path(b, root))
    if policy == "single":
        return max(bags, key=lambda b: (hops(b), b))
    if policy == "reuse":
        return min(bags, key=lambda b: (hops(b), b))
    base = bind(tree, replace(query, where=tuple(w for w in query.where if w != expr)), root)
    share = max((history or {}).get(a, 0.5) for a in used) if used else 0.5

    def cost(b: str) -> float:
        bound = replace(base, selects=(*base.selects, ("new", expr, b)), memo={})
        redo = sum(message_cost(engine, bound, *e) for e in tree.toward(root) if b in tree.upstream(*e))
        return plan_cost(engine, bound, root) + weight * share * redo

    return min(bags, key=lambda b: (cost(b), b))
