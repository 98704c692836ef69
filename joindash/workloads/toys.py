"""Small relations with known answers; counts ride in a column ``n`` that a sum-product ring multiplies."""

from __future__ import annotations

from pyspark.sql import SparkSession

from joindash.functions.semiring import TermsRing
from joindash.plans.graph import JoinGraph, JoinTree, Relation
from joindash.plans.messages import Engine
from joindash.plans.store import MessageStore

STAR_ROWS = {
    "R": (("A", "B"), [(1, 1, 2), (1, 2, 3)]),
    "S": (("A", "C"), [(1, 1, 3), (1, 2, 5)]),
    "T": (("A", "D"), [(1, 1, 1), (1, 2, 2), (2, 1, 4)]),
}
PATH_ROWS = {"R": (("A", "B"), [(1, 1, 1)]), "S": (("B", "C"), [(1, 1, 1)]), "T": (("C", "D"), [(1, 1, 1)])}
TRIANGLE_ROWS = {"R": (("A", "B"), [(1, 1, 1), (1, 2, 1)]), "S": (("B", "C"), [(1, 1, 1), (2, 1, 1)]), "T": (("C", "A"), [(1, 1, 1)])}
#: five bags on two attributes each: the pair (x, y) of bag i has count (2x + 3y + i) mod 4
CHAIN = ["BF", "BC", "AC", "CD", "DE"]
CHAIN_ROWS = {b: ((b[0], b[1]), [(x, y, (2 * x + 3 * y + i) % 4) for x in (1, 2, 3) for y in (1, 2, 3) if (2 * x + 3 * y + i) % 4]) for i, b in enumerate(CHAIN)}


def graph(spark: SparkSession, rows: dict) -> JoinGraph:
    """Each relation's count column is named after it, so that only attributes join."""
    rels = []
    for name, ((x, y), data) in rows.items():
        df = spark.createDataFrame(data, f"{x} int, {y} int, n_{name} int")
        values = ", ".join(map(str, data))
        rels.append(Relation(name, df, (), f"SELECT * FROM (VALUES {values}) AS t({x}, {y}, n_{name})"))
    return JoinGraph.of(*rels)


def ring(rows: dict) -> TermsRing:
    return TermsRing((("c", tuple((n, f"n_{n}", 0) for n in rows)),), "{c}", "cnt", 0)


def engine(spark: SparkSession, rows: dict) -> Engine:
    g = graph(spark, rows)
    if rows is CHAIN_ROWS:
        links = {frozenset(p) for p in zip(CHAIN, CHAIN[1:], strict=False)}
        tree = JoinTree({n: r.attrs for n, r in g.relations.items()}, links, {n: n for n in rows}, g)
        tree.validate()
    else:
        tree = JoinTree.from_graph(g)
    return Engine(spark, tree, MessageStore(spark, "memory"))
