"""A small SQL front end for SPJA queries over a standing join graph."""

from __future__ import annotations

import re

from joindash.functions.semiring import ExtremeRing, Measure, MomentRing, rejected
from joindash.plans.graph import JoinGraph
from joindash.plans.query import SpjaQuery, attributes_in


class SqlError(ValueError):
    pass


CLAUSES = re.compile(
    r"^\s*SELECT\s+(?P<items>.+?)\s+FROM\s+(?P<tables>.+?)(?:\s+WHERE\s+(?P<where>.+?))?(?:\s+GROUP\s+BY\s+(?P<group>.+?))?\s*;?\s*$",
    re.I | re.S,
)
AGGREGATE = re.compile(r"^(?P<fn>\w+)\s*\(\s*(?P<distinct>DISTINCT\s+)?(?P<arg>.*)\)\s*(?:AS\s+(?P<alias>\w+))?$", re.I | re.S)


def split_top(text: str, word: str) -> list[str]:
    """Parts between a separator that stands outside brackets, quotes and BETWEEN … AND."""
    out, depth, at, quote, between, i = [], 0, 0, False, False, 0
    pattern = re.compile(re.escape(word) if not word.isalpha() else rf"\b{word}\b", re.I)
    while i < len(text):
        ch = text[i]
        if ch == "'":
            quote = not quote
        elif not quote:
            depth += (ch == "(") - (ch == ")")
            if depth == 0 and re.match(r"\bBETWEEN\b", text[i:], re.I) and (i == 0 or not text[i - 1].isalnum()):
                between = True
            m = pattern.match(text, i) if depth == 0 else None
            if m and (not word.isalpha() or i == 0 or not (text[i - 1].isalnum() or text[i - 1] == "_")):
                if between and word.upper() == "AND":
                    between = False
                else:
                    out.append(text[at:i].strip())
                    at = m.end()
                i = m.end()
                continue
        i += 1
    return [*out, text[at:].strip()]


def parse_spja(sql: str, graph: JoinGraph, scale: int | None = 2) -> tuple[SpjaQuery, frozenset[str]]:
    """(query, relations named) of ``SELECT groups, aggregates FROM a NATURAL JOIN b … WHERE … GROUP BY …``."""
    m = CLAUSES.match(sql)
    if not m:
        raise SqlError("expected SELECT … FROM … [WHERE …] [GROUP BY …]")
    names = [t.strip() for t in re.split(r"\s+NATURAL\s+JOIN\s+|\s*,\s*", m["tables"].strip(), flags=re.I)]
    unknown = [n for n in names if n not in graph.relations]
    if unknown:
        raise SqlError(f"unknown relations: {unknown}")
    known = {n: graph.relations[n].attrs for n in names}
    group = tuple(g.strip() for g in split_top(m["group"], ",")) if m["group"] else ()
    shows, measures, extreme = [], {}, None
    for item in split_top(m["items"], ","):
        if item in group:
            continue
        a = AGGREGATE.match(item)
        if not a:
            raise SqlError(f"{item!r} is neither a group attribute nor an aggregate")
        fn, arg = a["fn"].lower(), a["arg"].strip()
        alias = a["alias"] or f"{fn}_{len(shows)}"
        if a["distinct"] or fn in ("median", "percentile", "percentile_approx"):
            rejected(f"{fn.upper()}{' DISTINCT' if a['distinct'] else ''}")
        if fn == "count" and arg == "*":
            shows.append(("count", alias, ()))
            continue
        used = attributes_in(arg, frozenset().union(*known.values()))
        homes = [n for n, attrs in known.items() if used and used <= attrs]
        if not homes:
            raise SqlError(f"the attributes of {arg!r} lie in no single relation")
        if fn in ("min", "max"):
            extreme = ExtremeRing(homes[0], arg, fn == "min", alias)
            continue
        kind = {"sum": "sum", "avg": "avg", "var_pop": "var", "stddev_pop": "stddev"}.get(fn)
        if not kind:
            raise SqlError(f"{fn} is not supported")
        key = f"m{list(measures.values()).index((homes[0], arg))}" if (homes[0], arg) in measures.values() else f"m{len(measures)}"
        measures[key] = (homes[0], arg)
        shows.append((kind, alias, (key,)))
    if extreme and shows:
        raise SqlError("MIN and MAX stand alone")
    degree = 2 if any(k in ("var", "stddev") for k, _, _ in shows) else 1 if measures else 0
    ring = extreme or MomentRing(tuple(Measure(k, r, e, scale) for k, (r, e) in measures.items()), degree, tuple(shows))
    where = tuple(w for w in split_top(m["where"], "AND")) if m["where"] else ()
    return SpjaQuery(ring, group, where), frozenset(names)
