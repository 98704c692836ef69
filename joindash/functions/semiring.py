"""Aggregates as commutative semi-rings over flat columns.

An annotation is a dict of Catalyst expressions.  A missing key stands for the neutral value of its
ring (zero for a moment, the count for a product term, the other side's value for an extreme), so a
message carries only the columns that its side of the tree contributes, and a relation that contributes
nothing (annotation ``None``) is not multiplied at all.

Exact measures are lifted to scaled integers and accumulated as DECIMAL(38,0), so every strategy gives
the same digits in whatever order it adds; products are cast back, because Catalyst widens decimals.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

WIDE = "decimal(38,0)"
Ann = dict[str, Column]


class UnsupportedAggregate(ValueError):
    """An aggregate that no constant-size semi-ring element can carry."""


@dataclass(frozen=True)
class Measure:
    """A numeric expression over one relation.  ``scale``: decimals kept exactly; None: plain doubles."""

    name: str
    relation: str
    expr: str
    scale: int | None = 2

    def lifted(self) -> Column:
        if self.scale is None:
            return F.expr(f"CAST({self.expr} AS DOUBLE)")
        return F.expr(f"CAST(ROUND(({self.expr}) * {10**self.scale}) AS {WIDE})")

    def sql(self) -> str:
        """The same for the naive SQL text; HUGEINT holds what DECIMAL(38,0) holds."""
        return f"CAST({self.expr} AS DOUBLE)" if self.scale is None else f"CAST(ROUND(({self.expr}) * {10**self.scale}) AS HUGEINT)"

    @property
    def kind(self) -> str:
        return "double" if self.scale is None else WIDE

    @property
    def unit(self) -> float:
        return 1.0 if self.scale is None else float(10**self.scale)


class Semiring:
    """``lift`` a relation's rows, multiply with ``times``, add with ``plus``, read with ``finalise``."""

    #: canonical definition: part of every message's fingerprint
    ident: str = ""

    def part(self, relations: set[str]) -> str:
        """What the ring computes on one side of an edge: sides without a measure are shared by rings."""
        return self.ident

    def lift(self, relation: str) -> Ann | None:
        raise NotImplementedError

    def one(self) -> Ann:
        raise NotImplementedError

    def absent(self, names: list[str]) -> Ann:
        """What the columns of a message hold for a row that an outer join keeps without it; other columns
        stay null, which extremes and sketches pass over."""
        return {}

    def times(self, a: Ann, b: Ann) -> Ann:
        raise NotImplementedError

    def plus(self, names: list[str]) -> list[Column]:
        raise NotImplementedError

    def finalise(self, names: set[str]) -> list[Column]:
        raise NotImplementedError

    def sql(self) -> list[str]:
        """Select-list items of the naive query, with the same names and digits as ``finalise``."""
        raise NotImplementedError


@dataclass(frozen=True)
class MomentRing(Semiring):
    """Count, sums and sums of products of measures, up to ``degree``; the basis of COUNT, SUM, AVG, VAR,
    covariance, correlation and linear regression.  ``shows`` names what ``finalise`` returns:
    (kind, alias, measure names)."""

    measures: tuple[Measure, ...] = ()
    degree: int = 0
    shows: tuple[tuple[str, str, tuple[str, ...]], ...] = (("count", "cnt", ()),)

    @property
    def ident(self) -> str:
        return f"moment{self.degree}{[(m.name, m.relation, m.expr, m.scale) for m in self.measures]}"

    def part(self, relations: set[str]) -> str:
        own = [m for m in self.measures if m.relation in relations] if self.degree else []
        return f"moment{self.degree}{[(m.name, m.relation, m.expr, m.scale) for m in own]}" if own else "count"

    def _pairs(self):
        ms = self.measures
        return [(ms[i], ms[j]) for i in range(len(ms)) for j in range(i, len(ms))] if self.degree > 1 else []

    def lift(self, relation: str) -> Ann | None:
        own = [m for m in self.measures if m.relation == relation]
        if not own or self.degree == 0:
            return None
        x = {m.name: F.coalesce(m.lifted(), F.lit(0).cast(m.kind)) for m in own}
        out = {"__c": F.lit(1).cast("long")} | {f"__s_{k}": v for k, v in x.items()}
        for a, b in self._pairs():
            if a.name in x and b.name in x:
                out[f"__q_{a.name}_{b.name}"] = self._mul(x[a.name], x[b.name], a, b)
        return out

    def one(self) -> Ann:
        return {"__c": F.lit(1).cast("long")}

    def absent(self, names: list[str]) -> Ann:
        return {n: F.lit(int(n == "__c")) for n in names}

    @staticmethod
    def _mul(x: Column, y: Column, *ms: Measure) -> Column:
        return (x * y).cast("double" if any(m.scale is None for m in ms) else WIDE)

    def times(self, a: Ann, b: Ann) -> Ann:
        out = {"__c": a["__c"] * b["__c"]}
        by = {m.name: m for m in self.measures}
        for k in [*a, *b]:
            if k.startswith("__s_") and k not in out:
                m = by[k[4:]]
                parts = [self._mul(x[k], y["__c"], m) for x, y in ((a, b), (b, a)) if k in x]
                out[k] = parts[0] if len(parts) == 1 else (parts[0] + parts[1]).cast(m.kind)
        for m, n in self._pairs():
            k, parts = f"__q_{m.name}_{n.name}", []
            for x, y in ((a, b), (b, a)):
                if k in x:
                    parts.append(self._mul(x[k], y["__c"], m, n))
                if f"__s_{m.name}" in x and f"__s_{n.name}" in y:
                    parts.append(self._mul(x[f"__s_{m.name}"], y[f"__s_{n.name}"], m, n))
            if parts:
                total = parts[0]
                for p in parts[1:]:
                    total = total + p
                out[k] = total.cast("double" if m.scale is None or n.scale is None else WIDE)
        return out

    def plus(self, names: list[str]) -> list[Column]:
        kinds = {m.name: m.kind for m in self.measures}
        out = []
        for n in names:
            if n == "__c":
                out.append(F.sum(n).alias(n))
            else:
                wide = "double" if "double" in {kinds[x] for x in kinds if n in (f"__s_{x}",) or n.startswith(f"__q_{x}_") or n.endswith(f"_{x}")} else WIDE
                out.append(F.sum(n).cast(wide).alias(n))
        return out

    def _value(self, kind: str, names: tuple[str, ...], c: Column, have: set[str], col) -> Column:
        by = {m.name: m for m in self.measures}
        s = lambda n: col(f"__s_{n}").cast("double") / by[n].unit

        def q(a: str, b: str) -> Column:
            key = f"__q_{a}_{b}" if f"__q_{a}_{b}" in have else f"__q_{b}_{a}"
            return col(key).cast("double") / (by[a].unit * by[b].unit)

        some = lambda v: F.when(c > 0, v)
        if kind == "count":
            return F.coalesce(c, F.lit(0)).cast("long")
        if kind == "sum":
            return some(s(names[0]))
        if kind == "avg":
            return some(F.round(s(names[0]) / c, 6))
        if kind == "var":
            return some(F.round(q(names[0], names[0]) / c - (s(names[0]) / c) * (s(names[0]) / c), 6))
        if kind == "stddev":
            return some(F.round(F.sqrt(F.greatest(q(names[0], names[0]) / c - (s(names[0]) / c) * (s(names[0]) / c), F.lit(0.0))), 6))
        cov = q(*names) / c - (s(names[0]) / c) * (s(names[1]) / c)
        if kind == "covar":
            return some(F.round(cov, 6))
        v = [q(n, n) / c - (s(n) / c) * (s(n) / c) for n in names]
        if kind == "corr":
            return some(F.round(F.try_divide(cov, F.sqrt(v[0] * v[1])), 6))
        if kind == "slope":  # of the first on the second
            return some(F.round(F.try_divide(cov, v[1]), 6))
        if kind == "cross":
            return some(q(*names))
        raise ValueError(kind)

    def finalise(self, names: set[str]) -> list[Column]:
        return [self._value(k, ms, F.col("__c"), names, F.col).alias(a) for k, a, ms in self.shows]

    def sql(self) -> list[str]:
        by, out = {m.name: m for m in self.measures}, []
        tot = lambda e: f"CAST(SUM({e}) AS DOUBLE)"
        s = lambda n: f"({tot(by[n].sql())} / {by[n].unit})"
        q = lambda a, b: f"({tot(f'({by[a].sql()}) * ({by[b].sql()})')} / ({by[a].unit} * {by[b].unit}))"
        c = "COUNT(*)"
        var = lambda n: f"({q(n, n)} / {c} - ({s(n)} / {c}) * ({s(n)} / {c}))"
        for kind, alias, ms in self.shows:
            cov = f"({q(*ms)} / {c} - ({s(ms[0])} / {c}) * ({s(ms[1])} / {c}))" if len(ms) == 2 else ""
            out.append({
                "count": lambda: c, "sum": lambda: s(ms[0]), "avg": lambda: f"ROUND({s(ms[0])} / {c}, 6)", "var": lambda: f"ROUND({var(ms[0])}, 6)",
                "stddev": lambda: f"ROUND(SQRT(GREATEST({var(ms[0])}, 0.0)), 6)", "covar": lambda: f"ROUND({cov}, 6)",
                "corr": lambda: f"ROUND({cov} / NULLIF(SQRT({var(ms[0])} * {var(ms[1])}), 0), 6)", "slope": lambda: f"ROUND({cov} / NULLIF({var(ms[1])}, 0), 6)",
                "cross": lambda: q(*ms),
            }[kind]() + f" AS {alias}")
        return out


def count_ring() -> MomentRing:
    return MomentRing()


def sum_ring(m: Measure, alias: str | None = None) -> MomentRing:
    return MomentRing((m,), 1, (("sum", alias or m.name, (m.name,)),))


def avg_ring(m: Measure, alias: str | None = None) -> MomentRing:
    return MomentRing((m,), 1, (("avg", alias or m.name, (m.name,)),))


def var_ring(m: Measure) -> MomentRing:
    return MomentRing((m,), 2, (("var", f"var_{m.name}", (m.name,)), ("stddev", f"sd_{m.name}", (m.name,))))


def gram_ring(measures: list[Measure]) -> MomentRing:
    """Count, sums and all sums of products: what linear regression needs."""
    names = [m.name for m in measures]
    pairs = [(a, b) for i, a in enumerate(names) for b in names[i:]]
    shows = (("count", "cnt", ()), *[("sum", f"s_{n}", (n,)) for n in names], *[("cross", f"q_{a}_{b}", (a, b)) for a, b in pairs])
    return MomentRing(tuple(measures), 2, shows)


def multi_ring(shows: list[tuple[str, str, Measure]]) -> MomentRing:
    """All sums, averages and counts of a dashboard in one pass."""
    ms = tuple({m.name: m for _, _, m in shows if m}.values())
    degree = 2 if any(k in ("var", "stddev") for k, _, _ in shows) else 1
    return MomentRing(ms, degree, tuple((k, a, (m.name,) if m else ()) for k, a, m in shows))


@dataclass(frozen=True)
class TermsRing(Semiring):
    """Sums of products whose factors may lie in different relations; several terms side by side.

    ``terms``: (name, ((relation, expr, scale), …)).  ``result``: an expression over the term names."""

    terms: tuple[tuple[str, tuple[tuple[str, str, int], ...]], ...]
    result: str
    alias: str = "value"
    digits: int = 2

    @property
    def ident(self) -> str:
        return f"terms{self.terms}"

    def part(self, relations: set[str]) -> str:
        own = [(n, [f for f in fs if f[0] in relations]) for n, fs in self.terms]
        return f"terms{own}" if any(fs for _, fs in own) else "count"

    @staticmethod
    def _factor(expr: str, scale: int) -> str:
        return f"CAST(ROUND(({expr}) * {10**scale}) AS {WIDE})"

    def lift(self, relation: str) -> Ann | None:
        out = {}
        for name, factors in self.terms:
            own = [self._factor(e, s) for r, e, s in factors if r == relation]
            if own:
                v = F.expr(own[0])
                for e in own[1:]:
                    v = (v * F.expr(e)).cast(WIDE)
                out[f"__t_{name}"] = v
        return {"__c": F.lit(1).cast("long")} | out if out else None

    def one(self) -> Ann:
        return {"__c": F.lit(1).cast("long")}

    def absent(self, names: list[str]) -> Ann:
        return {n: F.lit(int(n == "__c")) for n in names}

    def times(self, a: Ann, b: Ann) -> Ann:
        out = {"__c": a["__c"] * b["__c"]}
        for k in {*a, *b} - {"__c"}:
            out[k] = (a.get(k, a["__c"]) * b.get(k, b["__c"])).cast(WIDE)
        return out

    def plus(self, names: list[str]) -> list[Column]:
        return [F.sum(n).cast("bigint" if n == "__c" else WIDE).alias(n) for n in names]

    def _unit(self, name: str) -> float:
        return float(10 ** sum(s for _, _, s in dict(self.terms)[name]))

    def finalise(self, names: set[str]) -> list[Column]:
        expr = self.result
        for name, _ in self.terms:
            expr = expr.replace(f"{{{name}}}", f"(CAST(__t_{name} AS DOUBLE) / {self._unit(name)}D)")
        return [F.expr(f"ROUND({expr}, {self.digits})").alias(self.alias)]

    def sql(self) -> list[str]:
        expr = self.result
        for name, factors in self.terms:
            prod = " * ".join(f"CAST(ROUND(({e}) * {10**s}) AS HUGEINT)" for _, e, s in factors)
            expr = expr.replace(f"{{{name}}}", f"(CAST(SUM({prod}) AS DOUBLE) / {self._unit(name)})")
        return [f"ROUND({expr}, {self.digits}) AS {self.alias}"]


@dataclass(frozen=True)
class ExtremeRing(Semiring):
    """MIN and MAX of values of one relation: the least (greatest) is the sum, and a product keeps the
    one value there is; for numbers this equals adding zero."""

    relation: str
    expr: str
    least: bool = True
    alias: str = "value"

    @property
    def ident(self) -> str:
        return f"{'min' if self.least else 'max'}:{self.relation}:{self.expr}"

    def lift(self, relation: str) -> Ann | None:
        return {"__v": F.expr(self.expr)} if relation == self.relation else None

    def one(self) -> Ann:
        return {}

    def times(self, a: Ann, b: Ann) -> Ann:
        return a | b

    def plus(self, names: list[str]) -> list[Column]:
        return [(F.min if self.least else F.max)(n).alias(n) for n in names]

    def finalise(self, names: set[str]) -> list[Column]:
        return [F.col("__v").alias(self.alias)]

    def sql(self) -> list[str]:
        return [f"{'MIN' if self.least else 'MAX'}({self.expr}) AS {self.alias}"]


@dataclass(frozen=True)
class ExistsRing(Semiring):
    """Whether any joined row exists: presence of a row is *true*, absence is *false*."""

    alias: str = "present"
    ident: str = "exists"

    def lift(self, relation: str) -> Ann | None:
        return None

    def one(self) -> Ann:
        return {}

    def times(self, a: Ann, b: Ann) -> Ann:
        return {}

    def plus(self, names: list[str]) -> list[Column]:
        return []

    def finalise(self, names: set[str]) -> list[Column]:
        return [F.lit(True).alias(self.alias)]

    def sql(self) -> list[str]:
        return [f"TRUE AS {self.alias}"]


@dataclass(frozen=True)
class SketchRing(Semiring):
    """Approximate distinct count: sketches unite, and any matching row keeps its sketch."""

    relation: str
    expr: str
    alias: str = "approx_distinct"
    bits: int = 14

    @property
    def ident(self) -> str:
        return f"hll{self.bits}:{self.relation}:{self.expr}"

    def lift(self, relation: str) -> Ann | None:
        return {"__raw": F.expr(self.expr)} if relation == self.relation else None

    def one(self) -> Ann:
        return {}

    def times(self, a: Ann, b: Ann) -> Ann:
        return a | b

    def plus(self, names: list[str]) -> list[Column]:
        return [
            F.hll_sketch_agg(F.col(n), self.bits).alias("__sketch") if n == "__raw" else F.hll_union_agg(F.col(n)).alias("__sketch") for n in names
        ]

    def finalise(self, names: set[str]) -> list[Column]:
        return [F.hll_sketch_estimate("__sketch").alias(self.alias)]


def rejected(kind: str) -> Semiring:
    """Median, percentile and exact distinct count need state that grows with the data."""
    raise UnsupportedAggregate(f"{kind} has no constant-size semi-ring element; use SketchRing, or group by the value and rank it at the root")


RINGS: dict[str, type] = {"moment": MomentRing, "terms": TermsRing, "extreme": ExtremeRing, "exists": ExistsRing, "sketch": SketchRing}
