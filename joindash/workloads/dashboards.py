"""The experiment workloads over the given tables: engines, charts, interactions and their SQL."""

from __future__ import annotations

import random
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from joindash.functions.semiring import (
    Measure,
    TermsRing,
    avg_ring,
    count_ring,
    sum_ring,
    var_ring,
)
from joindash.plans.baselines import naive_sql
from joindash.plans.graph import JoinGraph, JoinTree, Relation
from joindash.plans.messages import Engine
from joindash.plans.query import SpjaQuery
from joindash.plans.session import Answer, Dashboard, Session
from joindash.plans.store import MessageStore
from joindash.sources import tables
from joindash.sources.tables import STAR

PRICE = Measure("amount", "lineitem", "l_extendedprice", 2)
REVENUE = Measure("revenue", "lineitem", "l_extendedprice * (1 - l_discount)", 4)
DISCOUNT = Measure("avg_discount", "lineitem", "l_discount", 2)
QUANTITY = Measure("avg_quantity", "lineitem", "l_quantity", 2)

CRM = ["lineitem", "part", "supplier", "nation_s", "region_s", "orders"]
FLIGHT = STAR
#: fixed constants of the interactions
PART_V2_SQL = (
    "SELECT p_partkey AS partkey, p_name, p_brand, CASE WHEN p_partkey % 10 = 3 THEN concat(p_type, ' V2') ELSE p_type END AS p_type, p_size, p_retailprice FROM part"
)


@dataclass
class Workload:
    """Charts by name, and for each the edits that follow one another.  ``each``: every interaction starts
    from the dashboard's query instead."""

    name: str
    relations: list[str]
    charts: dict[str, SpjaQuery]
    steps: dict[str, list[Callable[[SpjaQuery], SpjaQuery]]]
    each: bool = False
    prepare: Callable[[JoinGraph], None] | None = None
    tree: Callable[[JoinGraph], JoinTree] = JoinTree.from_graph
    graph: Callable[[SparkSession, str], JoinGraph] | None = None

    def join_graph(self, spark: SparkSession, sf_dir: str) -> JoinGraph:
        g = self.graph(spark, sf_dir) if self.graph else tables.graph(spark, sf_dir, self.relations)
        if self.prepare:
            self.prepare(g)
        return g

    def query(self, chart: str, step: int) -> SpjaQuery:
        """The chart's query after ``step`` interactions (0: as the dashboard shows it)."""
        q = self.charts[chart]
        for e in self.steps[chart][step - 1 : step] if self.each else self.steps[chart][:step]:
            q = e(q)
        return q


def _crm_prepare(g: JoinGraph) -> None:
    from pyspark.sql import functions as F

    part = g.relations["part"]
    if not part.versions:
        kind = F.when(F.col("partkey") % 10 == 3, F.concat("p_type", F.lit(" V2"))).otherwise(F.col("p_type"))
        part.add_version(part.df.withColumn("p_type", kind), PART_V2_SQL)


_CRM_STEPS = [
    lambda q: q.with_filter("s_name = 'Supplier#000000003'"),
    lambda q: q.with_filter("r_name_s = 'ASIA'"),
    lambda q: q.with_filter("p_size BETWEEN 10 AND 20"),
    lambda q: q.with_filter("n_name_s = 'NATION_7'"),
    lambda q: q.add_group("r_name_s"),
    lambda q: q.add_group("o_orderstatus"),
    lambda q: q.update_table("part", 1),
    lambda q: q.remove_table("orders"),
]
crm = Workload("crm", CRM, {"v1": SpjaQuery(sum_ring(PRICE)), "v2": SpjaQuery(sum_ring(PRICE), ("p_type",))}, {"v1": _CRM_STEPS, "v2": _CRM_STEPS}, each=True, prepare=_crm_prepare)

flight = Workload(
    "flight",
    FLIGHT,
    {
        "v1": SpjaQuery(count_ring(), ("o_orderpriority",)),
        "v2": SpjaQuery(sum_ring(PRICE), ("n_name_s",)),
        "v3": SpjaQuery(avg_ring(DISCOUNT), ("p_brand",)),
        "v4": SpjaQuery(count_ring(), ("ship_year",)),
        "v5": SpjaQuery(avg_ring(QUANTITY), ("c_mktsegment", "p_type")),
    },
    {
        "v1": [lambda q: q.with_filter("r_name_c = 'ASIA'"), lambda q: q.with_filter("c_mktsegment = 'BUILDING'")],
        "v2": [lambda q: q.with_filter("ship_year = 1997"), lambda q: q.with_filter("p_type = 'PROMO'")],
        "v3": [lambda q: q.with_filter("l_returnflag = 'R'"), lambda q: q.with_filter("n_name_s = 'NATION_7'")],
        "v4": [lambda q: q.with_filter("o_orderstatus = 'F'")],
        "v5": [lambda q: q.with_filter("r_name_s = 'EUROPE'")],
    },
)

PROFIT = TermsRing(
    (
        ("rev", (("lineitem", "l_extendedprice * (1 - l_discount)", 4),)),
        ("cost", (("part", "p_retailprice", 2), ("lineitem", "l_quantity", 2))),
    ),
    "{rev} - {cost}",
    "profit",
)


def _nation_cycle(spark: SparkSession, sf_dir: str) -> JoinGraph:
    """Customers and suppliers of one nation: both meet the same nation, which closes a cycle."""
    g = tables.graph(spark, sf_dir, ["lineitem", "orders"])
    raw = lambda t, *cols: tables.read_table(spark, sf_dir, t).selectExpr(*cols)
    for name, table, cols, key in (
        ("customer_n", "customer", ["c_custkey AS custkey", "c_nationkey AS nk"], "custkey"),
        ("supplier_n", "supplier", ["s_suppkey AS suppkey", "s_nationkey AS nk"], "suppkey"),
        ("nation", "nation", ["n_nationkey AS nk", "n_name", "n_regionkey AS rk"], "nk"),
        ("region", "region", ["r_regionkey AS rk", "r_name"], "rk"),
        ("order_calendar", "orders", ["o_orderdate AS orderdate", "year(o_orderdate) AS order_year"], "orderdate"),
    ):
        df = raw(table, *cols)
        distinct = name == "order_calendar"
        g.relations[name] = Relation(name, df.distinct() if distinct else df, (frozenset({key}),), f"SELECT {'DISTINCT ' if distinct else ''}{', '.join(cols)} FROM {table}")
    return g


def _nation_tree(g: JoinGraph) -> JoinTree:
    return JoinTree.decompose_cycles(g, [["orders", "customer_n"], ["lineitem", "supplier_n"]], "pair")


tpch = {
    "q3": Workload(
        "q3", ["lineitem", "orders", "customer"],
        {"q3": SpjaQuery(sum_ring(REVENUE), ("orderkey", "orderdate"), ("c_mktsegment = 'BUILDING'", "orderdate < TIMESTAMP '1998-03-15'", "shipdate > TIMESTAMP '1998-03-15'"))},
        {"q3": [
            lambda q: q.without_filter("c_mktsegment = 'BUILDING'").with_filter("c_mktsegment = 'MACHINERY'"),
            lambda q: SpjaQuery(q.ring, q.group, ("c_mktsegment = 'BUILDING'", "orderdate < TIMESTAMP '1997-06-01'", "shipdate > TIMESTAMP '1997-06-01'")),
        ]}, each=True),
    "q5": Workload(
        "q5", [], {"q5": SpjaQuery(sum_ring(REVENUE), ("n_name",), ("r_name = 'ASIA'", "order_year = 1997"))},
        {"q5": [
            lambda q: q.without_filter("r_name = 'ASIA'").with_filter("r_name = 'EUROPE'"),
            lambda q: q.without_filter("order_year = 1997").with_filter("order_year = 1998"),
        ]}, each=True, tree=_nation_tree, graph=_nation_cycle),
    "q8": Workload(
        "q8", STAR, {"q8": SpjaQuery(sum_ring(REVENUE), ("order_year", "n_name_s"), ("r_name_c = 'ASIA'", "p_type = 'PROMO'", "order_year BETWEEN 1995 AND 1996"))},
        {"q8": [
            lambda q: q.without_filter("r_name_c = 'ASIA'").with_filter("r_name_c = 'AMERICA'"),
            lambda q: q.without_filter("p_type = 'PROMO'").with_filter("p_type = 'ECONOMY'"),
        ]}, each=True),
    "q9": Workload(
        "q9", ["lineitem", "part", "supplier", "nation_s", "orders", "order_calendar"],
        {"q9": SpjaQuery(PROFIT, ("n_name_s", "order_year"), ("p_name LIKE '%red%'",))},
        {"q9": [lambda q: q.without_filter("p_name LIKE '%red%'").with_filter("p_name LIKE '%blue%'")]}, each=True),
    "q10": Workload(
        "q10", ["lineitem", "orders", "customer", "nation_c", "order_calendar"],
        {"q10": SpjaQuery(sum_ring(REVENUE), ("custkey", "c_name", "c_acctbal", "n_name_c"), ("l_returnflag = 'R'", "order_month BETWEEN 199701 AND 199703"))},
        {"q10": [lambda q: q.without_filter("order_month BETWEEN 199701 AND 199703").with_filter("order_month BETWEEN 199704 AND 199706")]}, each=True),
}

many_to_many = Workload(
    "m2n", ["events", "customer", "orders", "lineitem"], {"total": SpjaQuery(count_ring()), "by_segment": SpjaQuery(count_ring(), ("c_mktsegment",))},
    {"total": [lambda q: q.remove_table("events")], "by_segment": [lambda q: q.with_filter("event_type = 'click'")]}, each=True)

documents = Workload(
    "docs", ["documents", "labels"],
    {
        "by_lang": SpjaQuery(count_ring(), ("lang",)),
        "quality_by_source": SpjaQuery(avg_ring(Measure("avg_quality", "labels", "quality", 0)), ("source",)),
        "size_by_lang": SpjaQuery(var_ring(Measure("n_chars", "documents", "n_chars", 0)), ("lang",)),
    },
    {"by_lang": [lambda q: q.with_filter("toxic = 1")], "quality_by_source": [lambda q: q.with_filter("lang = 'en'")], "size_by_lang": [lambda q: q.with_filter("source = 'src3'")]}, each=True)

WORKLOADS = {w.name: w for w in (crm, flight, many_to_many, documents, *tpch.values())}


#: what a random session may add, one after another
CHOICES = [
    "r_name_c = 'ASIA'", "r_name_c = 'EUROPE'", "c_mktsegment = 'BUILDING'", "c_mktsegment = 'MACHINERY'", "p_type = 'PROMO'", "p_size BETWEEN 5 AND 25", "o_orderstatus = 'F'",
    "ship_year = 1997", "n_name_s LIKE 'NATION_1%'", "l_returnflag = 'R'", "l_quantity > 20", "+r_name_s", "+o_orderpriority", "+ship_year", "+p_brand",
]


def random_session(chart: str, steps: int, seed: int) -> list[SpjaQuery]:
    """A chart of the flight dashboard and ``steps`` drawn interactions, each on top of the last."""
    q, r = flight.charts[chart], random.Random(seed)
    out = [q]
    for c in r.sample(CHOICES, steps):
        q = q.add_group(c[1:]) if c[0] == "+" else q.with_filter(c)
        out.append(q)
    return out


# ---- engines kept over queries of one session -------------------------------------------------

_boards: dict[tuple[str, str, str], Dashboard] = {}


def board(spark: SparkSession, sf_dir: str, name: str, mode: str = "memory", fresh: bool = False) -> Dashboard:
    """The workload's dashboard over one engine; calibrated charts stay for the session's other queries."""
    key = (spark.sparkContext.applicationId, sf_dir, f"{name}/{mode}")
    if fresh or key not in _boards:
        w = WORKLOADS[name]
        g = w.join_graph(spark, sf_dir)
        d = Dashboard(Engine(spark, w.tree(g), MessageStore(spark, mode)))
        for c, q in w.charts.items():
            d.chart(c, q)
        if fresh:
            return d
        _boards[key] = d
    return _boards[key]


def shown(spark: SparkSession, sf_dir: str, name: str, chart: str) -> DataFrame:
    """The dashboard's own answer, from its calibrated messages."""
    d = board(spark, sf_dir, name)
    d.calibrate_offline([chart])
    return d.show(chart)


def interaction(spark: SparkSession, sf_dir: str, name: str, chart: str, step: int, online: bool = True, calibrated: int | None = None) -> DataFrame:
    """The answer after ``step`` interactions, each from its pivot.  ``calibrated`` bounds the messages
    stored in think-time (None: all)."""
    return _interact(board(spark, sf_dir, name), name, chart, step, online, calibrated).rows


def fresh_interaction(spark: SparkSession, sf_dir: str, name: str, chart: str, step: int, online: bool = True, calibrated: int | None = None) -> Answer:
    """The same on a dashboard and a store of its own, so that nothing but this session's calibration is
    reused; the answer's trace says what was."""
    return _interact(board(spark, sf_dir, name, fresh=True), name, chart, step, online, calibrated)


def _interact(d: Dashboard, name: str, chart: str, step: int, online: bool, calibrated: int | None) -> Answer:
    w = WORKLOADS[name]
    d.calibrate_offline([chart])
    s = Session(d, online=online)
    todo = [w.query(chart, step)] if w.each else [w.query(chart, k) for k in range(1, step + 1)]
    for k, q in enumerate(todo):
        a = s.interact(chart, query=q)
        if online and k + 1 < len(todo):
            s.calibrate_online(chart, limit=calibrated)
    return a


def sql(name: str, chart: str, step: int) -> str:
    """The naive SQL text of a chart after ``step`` interactions, without touching a session."""
    w = WORKLOADS[name]
    return naive_sql(_shape(w), w.query(chart, step))


class _Columns:
    """Stands for a DataFrame where only column names are asked for."""

    def __init__(self, columns):
        self.columns = list(columns)


def _shape(w: Workload) -> JoinGraph:
    if w.graph:
        layout = {
            "lineitem": None, "orders": None,
            "customer_n": ("customer", [("c_custkey", "custkey"), ("c_nationkey", "nk")], False), "supplier_n": ("supplier", [("s_suppkey", "suppkey"), ("s_nationkey", "nk")], False),
            "nation": ("nation", [("n_nationkey", "nk"), ("n_name", "n_name"), ("n_regionkey", "rk")], False), "region": ("region", [("r_regionkey", "rk"), ("r_name", "r_name")], False),
            "order_calendar": ("orders", [("o_orderdate", "orderdate"), ("year(o_orderdate)", "order_year")], True),
        }
    else:
        layout = dict.fromkeys(w.relations)
    out = {}
    for n, own in layout.items():
        table, cols, distinct = own or (tables.LAYOUT[n][0], tables.LAYOUT[n][1], tables.LAYOUT[n][3])
        text = f"SELECT {'DISTINCT ' if distinct else ''}{', '.join(f'{e} AS {a}' for e, a in cols)} FROM {table}"
        out[n] = Relation(n, _Columns(a for _, a in cols), (), text, version_sql={1: PART_V2_SQL} if n == "part" else {})
    return JoinGraph(out)


