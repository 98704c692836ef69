"""Every query of the engine by name, with its SQL for the comparison with DuckDB."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from joindash.functions.semiring import ExistsRing, ExtremeRing, Measure, MomentRing, SketchRing, TermsRing, avg_ring, count_ring, gram_ring, multi_ring, sum_ring, var_ring
from joindash.operators import aggs, joins
from joindash.plans import baselines as base
from joindash.plans import calibrate as cal
from joindash.plans import measure
from joindash.plans.graph import Condition, JoinGraph, JoinTree, Relation, ear_removal
from joindash.plans.messages import Engine, Trace
from joindash.plans.planner import answer
from joindash.plans.query import SpjaQuery, bind
from joindash.plans.sqlfront import parse_spja
from joindash.plans.store import MessageStore
from joindash.sources import tables
from joindash.workloads import dashboards, regression, toys
from joindash.workloads.dashboards import PRICE, QUANTITY, REVENUE, WORKLOADS, board, interaction, naive_sql, shown

#: messages that an interaction computes anew after so many messages of think-time; and by strategy, with
#: whether the fact is read: fixed by the shape of the join tree
SENSITIVITY = {0: 2, 1: 2, 2: 2, 3: 2, 5: 0, 8: 0}
CASE_STUDY = {"factorized": (4, True), "offline": (2, True), "online": (0, False)}

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def add(name: str, fn: Query, sql: str | None = None) -> None:
    QUERIES[name] = fn
    if sql:
        SQL[name] = sql


def spja(name: str, workload: str, query: SpjaQuery, how: Callable[[Engine, SpjaQuery], DataFrame]) -> None:
    """A query answered by ``how`` over the workload's engine, against the naive SQL."""
    add(name, lambda s, d: how(board(s, d, workload).engine, query), naive_sql(dashboards._shape(WORKLOADS[workload]), query))


def single(e: Engine, q: SpjaQuery) -> DataFrame:
    return e.factorized(q)


def from_pivot(pivot: SpjaQuery):
    """Calibrate the pivot, then answer from it."""

    def run(e: Engine, q: SpjaQuery) -> DataFrame:
        b = bind(e.tree, pivot)
        cal.calibrate(e, b)
        return answer(e, b, q)[0]

    return run


def constant(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


# ---- rings ----------------------------------------------------------------------------------

_BY = ("n_name_s",)
BALANCE = Measure("balance", "customer", "c_acctbal", 2)
for _name, _ring, _group in (
    ("ring_count", count_ring(), _BY),
    ("ring_sum", sum_ring(PRICE), _BY),
    ("ring_avg", avg_ring(QUANTITY), _BY),
    ("ring_var", var_ring(BALANCE), ("r_name_c",)),
    ("ring_min", ExtremeRing("part", "p_retailprice", True), ("n_name_c",)),
    ("ring_max", ExtremeRing("part", "p_retailprice", False), ("n_name_c",)),
    ("ring_max_text", ExtremeRing("part", "p_name", False), ("r_name_c",)),
    ("ring_sumproduct", TermsRing((("v", (("part", "p_retailprice", 2), ("lineitem", "l_quantity", 2))),), "{v}", "stock_value"), _BY),
    ("ring_gram", gram_ring([Measure("q", "lineitem", "l_quantity", 0), Measure("size", "part", "p_size", 0), Measure("bal", "customer", "c_acctbal", 2)]), ("r_name_s",)),
    ("ring_covar_corr", MomentRing((QUANTITY, Measure("size", "part", "p_size", 0)), 2, (("covar", "covar_qs", ("avg_quantity", "size")), ("corr", "corr_qs", ("avg_quantity", "size")), ("slope", "slope_qs", ("avg_quantity", "size")))), ("r_name_s",)),
    ("ring_multi", multi_ring([("count", "n", None), ("sum", "amount", PRICE), ("avg", "avg_quantity", QUANTITY), ("sum", "balance", BALANCE)]), ("o_orderpriority",)),
):
    spja(_name, "flight", SpjaQuery(_ring, _group), single)


def _exists(spark: SparkSession, d: str) -> DataFrame:
    return single(board(spark, d, "flight").engine, SpjaQuery(ExistsRing(), ("p_type", "r_name_c"), ("l_returnflag = 'R'", "l_quantity > 49")))


add("ring_exists", _exists, naive_sql(dashboards._shape(WORKLOADS["flight"]), SpjaQuery(ExistsRing(), ("p_type", "r_name_c"), ("l_returnflag = 'R'", "l_quantity > 49"))))


def _sketched(spark: SparkSession, d: str) -> DataFrame:
    """Whether the sketches stay within five of their standard errors (0.8 %) of the exact counts."""
    e = board(spark, d, "flight").engine
    exact = single(e, SpjaQuery(ExistsRing(), ("r_name_s", "partkey"))).groupBy("r_name_s").agg(F.count(F.lit(1)).alias("exact"))
    both = single(e, SpjaQuery(SketchRing("lineitem", "partkey"), ("r_name_s",))).join(exact, "r_name_s")
    return both.select("r_name_s", (F.abs(F.col("approx_distinct") - F.col("exact")) <= 0.04 * F.col("exact")).alias("within"))


add("ring_approx_distinct", _sketched, "SELECT DISTINCT r_name AS r_name_s, TRUE AS within FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")


def _quantile(spark: SparkSession, d: str) -> DataFrame:
    hist = single(board(spark, d, "flight").engine, SpjaQuery(count_ring(), ("r_name_s", "l_quantity")))
    return aggs.weighted_quantile(hist, ["r_name_s"], "l_quantity", "cnt", 0.5)


_WIDE = naive_sql(dashboards._shape(WORKLOADS["flight"]), SpjaQuery(count_ring())).replace("SELECT COUNT(*) AS cnt", "SELECT r_name_s, l_quantity")
add("ring_quantile", _quantile, f"SELECT r_name_s, quantile_disc(l_quantity, 0.5) AS quantile FROM ({_WIDE}) AS w GROUP BY r_name_s")


def _clusters(spark: SparkSession, d: str, dims: int = 64) -> DataFrame:
    """What k-means needs of each cluster, its size and vector sum, as one ring element per label."""
    rows = tables.read_table(spark, d, "embeddings", ["label", "embedding"])
    points = Relation("points", rows.select("label", *[F.get("embedding", F.lit(i)).alias(f"x{i}") for i in range(dims)]))
    ms = tuple(Measure(f"x{i}", "points", f"CAST(x{i} AS DOUBLE)", 6) for i in range(dims))
    e = Engine(spark, JoinTree.from_graph(JoinGraph.of(points)), MessageStore(spark, "memory"))
    sums = e.factorized(SpjaQuery(MomentRing(ms, 1, (("count", "n", ()), *[("sum", f"x{i}", (f"x{i}",)) for i in range(dims)])), ("label",)))
    each = F.explode(F.array(*[F.struct(F.lit(i).alias("pos"), F.col(f"x{i}").alias("total")) for i in range(dims)])).alias("e")
    return sums.select("label", "n", each).select("label", "e.pos", "n", F.round("e.total", 6).alias("total"))


add(
    "ring_cluster_moments", _clusters,
    "SELECT label, CAST(pos - 1 AS INTEGER) AS pos, COUNT(*) AS n, ROUND(CAST(SUM(CAST(ROUND(CAST(x AS DOUBLE) * 1e6) AS BIGINT)) AS DOUBLE) / 1e6, 6) AS total "
    "FROM (SELECT label, unnest(embedding) AS x, generate_subscripts(embedding, 1) AS pos FROM embeddings) AS e GROUP BY label, pos",
)

# ---- algebra and trees ------------------------------------------------------------------------

_CRM = WORKLOADS["crm"]
_ORDER = ["region_s", "nation_s", "supplier", "lineitem", "part", "orders"]
spja("early_marginalise", "crm", SpjaQuery(sum_ring(PRICE), ("r_name_s",)), lambda e, q: base.early_marginalise(e, q, _ORDER))
spja("base_elimination_groupby", "crm", SpjaQuery(sum_ring(PRICE), ("n_name_s", "p_type")), base.elimination_groupby)
spja("variable_elimination", "crm", SpjaQuery(sum_ring(PRICE), (), ("r_name_s = 'ASIA'",)), base.elimination_groupby)


def _gyo(spark: SparkSession, d: str) -> DataFrame:
    """The attributes of a path of customers, orders and lines, summed out in the order of ear removal: each
    with the rows that are left of its relations."""
    path = {"customer": {"nk_c", "custkey"}, "orders": {"custkey", "orderkey"}, "lineitem": {"orderkey", "partkey"}}
    order, _, _ = ear_removal({n: frozenset(a) for n, a in path.items()})
    live, out = [tables.relation(spark, d, n).df.select(*sorted(a)) for n, a in path.items()], []
    for i, a in enumerate(order):
        holders, live = [x for x in live if a in x.columns], [x for x in live if a not in x.columns]
        joined = joins.multiway(holders, [[a]] * (len(holders) - 1))
        rest = [c for c in joined.columns if c != a]
        left = joined.select(*rest).distinct() if rest else joined.limit(1)
        out.append((i, a, left.count()))
        live += [left] * bool(rest)
    return constant(spark, out, "step int, attribute string, n_rows bigint")


add("gyo_order", _gyo, "SELECT CAST(0 AS INTEGER) AS step, 'nk_c' AS attribute, COUNT(DISTINCT c_custkey) AS n_rows FROM customer UNION ALL "
    "SELECT 1, 'partkey', COUNT(DISTINCT l_orderkey) FROM lineitem UNION ALL "
    "SELECT 2, 'custkey', COUNT(DISTINCT o_orderkey) FROM orders JOIN customer ON o_custkey = c_custkey UNION ALL "
    "SELECT 3, 'orderkey', CAST(COUNT(*) > 0 AS BIGINT) FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey")


def _multi(spark: SparkSession, d: str) -> DataFrame:
    """Nation and region of suppliers share one bag, joined together there."""
    e = board(spark, d, "crm").engine
    t = JoinTree.decompose_cycles(e.tree.graph, [["nation_s", "region_s"]], "place")
    return Engine(spark, t, e.store).factorized(SpjaQuery(sum_ring(PRICE), ("r_name_s",)))


add("multi_relation_bag", _multi, naive_sql(dashboards._shape(_CRM), SpjaQuery(sum_ring(PRICE), ("r_name_s",))))
spja("cyclic_prejoin", "q5", SpjaQuery(sum_ring(REVENUE), ("n_name",)), single)


def _theta(spark: SparkSession, d: str, root: str = "bands") -> DataFrame:
    """A range condition as an edge: events fall into value bands, counted by band."""
    bands = Relation("bands", constant(spark, [(i, i * 10.0, i * 10.0 + 10.0) for i in range(10)], "band int, low double, high double"))
    tree = JoinTree.from_graph(tables.graph(spark, d, ["events"])).attach(bands, Condition.between("event_value", "low", "high", 10.0))
    e, q = Engine(spark, tree, MessageStore(spark, "memory")), SpjaQuery(count_ring(), ("band", "event_type"))
    return e.absorb(bind(tree, q, root), root)


add("theta_join_edge", _theta, "SELECT CAST(b AS INTEGER) AS band, event_type, COUNT(*) AS cnt FROM events JOIN range(10) AS r(b) ON value >= b * 10 AND value < b * 10 + 10 GROUP BY ALL")


def _outer(spark: SparkSession, d: str) -> DataFrame:
    """Customers without events keep multiplicity one; only the measure's part is missing."""
    tree = JoinTree.from_graph(tables.graph(spark, d, ["customer"])).attach(tables.relation(spark, d, "events"), optional=True)
    ring = multi_ring([("count", "cnt", None), ("sum", "total", Measure("event_value", "events", "event_value", 2))])
    e = Engine(spark, tree, MessageStore(spark, "memory"))
    return e.factorized(SpjaQuery(ring, ("c_mktsegment",)))


add("outer_join_edge", _outer, "SELECT c_mktsegment, COUNT(*) AS cnt, CAST(COALESCE(SUM(CAST(ROUND(value * 100) AS HUGEINT)), 0) AS DOUBLE) / 100 AS total FROM customer LEFT JOIN events ON c_custkey = user_id GROUP BY c_mktsegment")


def _training_engine(spark: SparkSession, d: str) -> Engine:
    return regression.augmenter(spark, d).engine


def _empty_bag(spark: SparkSession, d: str, attrs: tuple[str, ...]) -> tuple[Engine, str]:
    g = regression.training_graph(spark, d).only(["sales", "supplier", "months"])
    tree = JoinTree.from_graph(g).add_empty_bag("view", attrs, "sales")
    return Engine(spark, tree, MessageStore(spark, "memory")), "view"


def _view(spark: SparkSession, d: str) -> DataFrame:
    e, bag = _empty_bag(spark, d, ("suppkey", "ship_month"))
    return e.absorb(bind(e.tree, SpjaQuery(count_ring(), ("suppkey", "ship_month")), bag), bag)


_VIEW_SQL = f"SELECT suppkey, ship_month, COUNT(*) AS cnt FROM ({regression.SALES_SQL}) AS s GROUP BY suppkey, ship_month"
add("emptybag_view", _view, _VIEW_SQL)
add("emptybag_max_count", lambda s, d: _view(s, d).agg(F.max("cnt").alias("max_cnt")), f"SELECT MAX(cnt) AS max_cnt FROM ({_VIEW_SQL}) AS v")


def _no_bag(spark: SparkSession, d: str) -> DataFrame:
    g = regression.training_graph(spark, d).only(["sales", "supplier", "months"])
    e = Engine(spark, JoinTree.from_graph(g))
    return e.absorb(bind(e.tree, SpjaQuery(count_ring(), ("suppkey", "ship_month")), "sales"), "sales", use_store=False).agg(F.max("cnt").alias("max_cnt"))


add("no_emptybag_max_count", _no_bag, f"SELECT MAX(cnt) AS max_cnt FROM ({_VIEW_SQL}) AS v")


def _bag_inside(spark: SparkSession, d: str) -> DataFrame:
    """The empty bag lies between the fact and its dimensions: a filter on a month reads the view only."""
    e, bag = _empty_bag(spark, d, ("suppkey", "ship_month"))
    b = bind(e.tree, SpjaQuery(count_ring()), bag)
    cal.calibrate(e, b, bag)
    return answer(e, b, SpjaQuery(count_ring(), ("ship_year",), ("s_name = 'Supplier#000000003'",)))[0]


add("empty_bag_internal", _bag_inside, "SELECT year(l_shipdate) AS ship_year, COUNT(*) AS cnt FROM lineitem JOIN supplier ON l_suppkey = s_suppkey WHERE s_name = 'Supplier#000000003' GROUP BY year(l_shipdate)")


def _empty_leaf(spark: SparkSession, d: str) -> DataFrame:
    """A star of events and orders around their customers; a leaf without a relation holds the counts by event type."""
    tree = JoinTree.from_graph(tables.graph(spark, d, ["events", "customer", "orders"])).add_empty_bag("view", {"event_type"}, "events")
    e = Engine(spark, tree, MessageStore(spark, "memory"))
    return e.absorb(bind(tree, SpjaQuery(count_ring(), ("event_type",)), "view"), "view")


add("empty_bag_leaf", _empty_leaf, "SELECT event_type, COUNT(*) AS cnt FROM events JOIN customer ON user_id = c_custkey JOIN orders ON o_custkey = c_custkey GROUP BY event_type")
add(
    "advise_empty_bags",
    lambda s, d: constant(s, [(",".join(c), bool(ok)) for c, _, ok in measure.advise_empty_bags(_training_engine(s, d), "sales", [("suppkey", "ship_month"), ("suppkey", "partkey")])], "attributes string, worth_it boolean"),
    "SELECT attributes, rows >= 2.0 * n AS worth_it FROM (SELECT 'suppkey,ship_month' AS attributes, (SELECT COUNT(*) FROM lineitem) AS rows, "
    "(SELECT COUNT(*) FROM (SELECT DISTINCT l_suppkey, year(l_shipdate), month(l_shipdate) FROM lineitem)) AS n UNION ALL "
    "SELECT 'suppkey,partkey', (SELECT COUNT(*) FROM lineitem), (SELECT COUNT(*) FROM (SELECT DISTINCT l_suppkey, l_partkey FROM lineitem))) AS t",
)

# ---- annotations, from one calibrated pivot -----------------------------------------------------

_PIVOT = SpjaQuery(sum_ring(PRICE), ("p_type",))
for _name, _q in {
    "ann_groupby": _PIVOT.set_group("n_name_s"),
    "ann_two_groups": _PIVOT.set_group("n_name_s", "o_orderstatus"),
    "ann_select": _PIVOT.with_filter("r_name_s = 'ASIA'"),
    "ann_marginalise": _PIVOT.drop_group("p_type"),
    "ann_exclude_leaf": _PIVOT.remove_table("orders"),
    "ann_version": _PIVOT.update_table("part", 1),
    "steiner_reuse": _PIVOT.set_group("r_name_s").with_filter("o_orderstatus = 'F'"),
    "pivot_no_difference": _PIVOT,
}.items():
    spja(_name, "crm", _q, from_pivot(_PIVOT))

# ---- message passing and calibration ------------------------------------------------------------

spja("msg_upward", "crm", SpjaQuery(count_ring(), ("o_orderstatus",)), lambda e, q: e.factorized(q, "part"))
spja("absorb_root", "crm", SpjaQuery(count_ring(), ("p_type",)), lambda e, q: e.factorized(q, "part"))


def _every_root(spark: SparkSession, d: str) -> DataFrame:
    e, out = board(spark, d, "crm").engine, None
    for root in sorted(e.tree.bags):
        df = e.factorized(SpjaQuery(sum_ring(PRICE), ("r_name_s",), ("p_size < 20",)), root).withColumn("root", F.lit(root))
        out = df if out is None else out.unionByName(df)
    return out.groupBy("r_name_s", "amount").agg(F.count(F.lit(1)).alias("roots"))


add("msg_every_root", _every_root, f"SELECT r_name_s, amount, CAST(6 AS BIGINT) AS roots FROM ({naive_sql(dashboards._shape(_CRM), SpjaQuery(sum_ring(PRICE), ('r_name_s',), ('p_size < 20',)))}) AS q")


def _calibrated(spark: SparkSession, d: str) -> tuple[Engine, object]:
    e = board(spark, d, "crm").engine
    b = bind(e.tree, _PIVOT)
    cal.calibrate(e, b)
    return e, b


_EDGES = "lineitem-orders lineitem-part lineitem-supplier nation_s-region_s nation_s-supplier".split()
add("calibrate_check", lambda s, d: cal.check_calibrated(*_calibrated(s, d)), "SELECT edge, CAST(0 AS BIGINT) AS differing_rows FROM (VALUES " + ", ".join(f"('{e}')" for e in _EDGES) + ") AS t(edge)")


def _any_bag(spark: SparkSession, d: str) -> DataFrame:
    e, b = _calibrated(spark, d)
    out = None
    for bag in sorted(e.tree.bags):
        df = e.absorb(b, bag, keys=()).withColumn("bag", F.lit(bag))
        out = df if out is None else out.unionByName(df)
    return out


_TOTAL = naive_sql(dashboards._shape(_CRM), SpjaQuery(sum_ring(PRICE)))
add("calibrated_any_bag", _any_bag, f"SELECT amount, bag FROM ({_TOTAL}) AS t CROSS JOIN (VALUES " + ", ".join(f"('{b}')" for b in _CRM.relations) + ") AS b(bag)")


def _partial(spark: SparkSession, d: str) -> DataFrame:
    board_ = board(spark, d, "flight", fresh=True)
    b = board_.charts["v2"].bound
    cal.calibrate(board_.engine, b, limit=3, policy="cheap")
    return answer(board_.engine, b, WORKLOADS["flight"].query("v2", 2))[0]


add("partial_calibration", _partial, dashboards.sql("flight", "v2", 2))


def _chain_plan(spark: SparkSession, d: str) -> DataFrame:
    """The worked reuse example: how many bags each placement touches, and that the answers agree."""
    e, r = toys.engine(spark, toys.CHAIN_ROWS), toys.ring(toys.CHAIN_ROWS)
    pivot = bind(e.tree, SpjaQuery(r, ("D",), ("B = 1",)), "DE")
    pivot = replace(pivot, groups=(("D", "DE"),), selects=tuple((i, x, "BC") for i, x, _ in pivot.selects), memo={})
    cal.calibrate(e, pivot, "AC")
    out = []
    for policy in ("initial", "reuse"):
        t = Trace()
        q = SpjaQuery(r, ("A",), ("C = 1",))
        rows, plan = answer(e, pivot, q, t, policy)
        total = sum(int(x["cnt"]) for x in rows.collect())
        out.append((policy, len(plan.subtree), t.count("computed") < len(plan.subtree), total))
    return constant(spark, out, "policy string, bags int, within boolean, total int")


add("shrink_example", _chain_plan, "SELECT p AS policy, CAST(b AS INTEGER) AS bags, TRUE AS within, CAST(t AS INTEGER) AS total FROM (VALUES ('initial', 4, 2912), ('reuse', 3, 2912)) AS x(p, b, t)")


def _cache(spark: SparkSession, d: str) -> DataFrame:
    """A second user's chart finds every message of the first in the shared store."""
    e, b = _calibrated(spark, d)
    t = Trace()
    e.absorb(bind(e.tree, _PIVOT), "part", t).collect()
    return constant(spark, [(t.count("computed"),)], "computed int")


add("fingerprint_cache", _cache, "SELECT CAST(0 AS INTEGER) AS computed")


def _append(spark: SparkSession, d: str) -> DataFrame:
    """Orders' lines of odd keys arrive later; messages are brought up to date from them alone."""
    g = dashboards.WORKLOADS["crm"].join_graph(spark, d)
    rel = g.relations["lineitem"]
    old, new = rel.df.filter("orderkey % 2 = 0"), rel.df.filter("orderkey % 2 = 1")
    rel.df = old
    e = Engine(spark, JoinTree.from_graph(g), MessageStore(spark, "memory"))
    b = bind(e.tree, _PIVOT)
    cal.calibrate(e, b)
    v = cal.append_rows(e, "lineitem", new, [b])
    t = Trace()
    b2 = replace(b, versions=(("lineitem", v),), memo={})
    return e.absorb(b2, "part", t)


add("append_delta", _append, naive_sql(dashboards._shape(_CRM), _PIVOT))


def _shared_scan(spark: SparkSession, d: str) -> DataFrame:
    """The fact's messages to its plain dimensions from one scan; any bag then gives the answer."""
    e = Engine(spark, board(spark, d, "crm").engine.tree, MessageStore(spark, "memory"))
    b = bind(e.tree, _PIVOT)
    cal.calibrate_shared_scan(e, b)
    return answer(e, b, _PIVOT.set_group("n_name_s"))[0]


add("calibrate_shared_scan", _shared_scan, naive_sql(dashboards._shape(_CRM), _PIVOT.set_group("n_name_s")))


def _random(spark: SparkSession, d: str, chart: str, seed: int) -> DataFrame:
    e, rows = board(spark, d, "flight").engine, None
    todo = dashboards.random_session(chart, 3, seed)
    pivot = bind(e.tree, todo[0])
    cal.calibrate(e, pivot)
    for q in todo[1:]:
        rows, plan = answer(e, pivot, q)
        pivot = plan.bound
    return rows


for _c, _seed in (("v1", 1), ("v3", 2), ("v5", 3)):
    add(f"random_session_{_seed}", lambda s, d, c=_c, seed=_seed: _random(s, d, c, seed), naive_sql(dashboards._shape(WORKLOADS["flight"]), dashboards.random_session(_c, 3, _seed)[-1]))
add("sql_front_end", lambda s, d: (lambda e: e.factorized(parse_spja("SELECT n_name_s, SUM(l_extendedprice) AS amount, COUNT(*) AS cnt FROM lineitem NATURAL JOIN part NATURAL JOIN supplier NATURAL JOIN nation_s NATURAL JOIN region_s NATURAL JOIN orders WHERE p_size BETWEEN 10 AND 20 AND r_name_s = 'ASIA' GROUP BY n_name_s", e.tree.graph)[0]))(board(s, d, "crm").engine),
    "SELECT n_name AS n_name_s, CAST(SUM(CAST(ROUND(l_extendedprice * 100) AS HUGEINT)) AS DOUBLE) / 100 AS amount, COUNT(*) AS cnt FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE p_size BETWEEN 10 AND 20 AND r_name = 'ASIA' GROUP BY n_name")

# ---- baselines --------------------------------------------------------------------------------

_B = SpjaQuery(sum_ring(PRICE), ("r_name_s",), ("p_type = 'PROMO'",))
spja("base_naive", "crm", _B, base.naive)
spja("base_factorized", "crm", _B, lambda e, q: Engine(e.spark, e.tree, None, elide=False).factorized(q))
spja("base_factorized_elided", "crm", _B, single)


def _counted(a: dashboards.Answer) -> DataFrame:
    """An answer's rows beside the number of messages that it computed anew."""
    return a.rows.withColumn("computed", F.lit(a.trace.count("computed")))


def counted_sql(name: str, chart: str, step: int, computed: int) -> str:
    return f"SELECT *, CAST({computed} AS INTEGER) AS computed FROM ({dashboards.sql(name, chart, step)}) AS q"


for _name, _online, _n in (("base_offline_only", False, 2), ("base_online", True, 0)):
    add(_name, lambda s, d, on=_online: _counted(dashboards.fresh_interaction(s, d, "flight", "v2", 2, online=on)), counted_sql("flight", "v2", 2, _n))


def _all_roots(spark: SparkSession, d: str) -> DataFrame:
    e = Engine(spark, board(spark, d, "crm").engine.tree, MessageStore(spark, "memory"), elide=False)
    b = bind(e.tree, SpjaQuery(count_ring()))
    t_all, t_cal = Trace(), Trace()
    n = sum(len(e.tree.toward(r)) for r in e.tree.bags)
    cal.calibrate(e, b, trace=t_cal)
    cal.calibrate_all_roots(e, b, t_all)
    return constant(spark, [("all_roots", n), ("calibrated", t_cal.count("computed"))], "strategy string, messages int")


add("base_all_roots", _all_roots, "SELECT s AS strategy, CAST(n AS INTEGER) AS messages FROM (VALUES ('all_roots', 30), ('calibrated', 10)) AS t(s, n)")
_CUBE = SpjaQuery(sum_ring(PRICE))
add("base_wide_cube", lambda s, d: base.wide_cube(board(s, d, "crm").engine, _CUBE, ["r_name_s", "p_type"]),
    f"SELECT CAST(GROUPING_ID(r_name_s, p_type) AS BIGINT) AS level, r_name_s, p_type, {_CUBE.ring.sql()[0]} " + _TOTAL[_TOTAL.index("FROM"):] + " GROUP BY CUBE (r_name_s, p_type)")
add("base_batch", lambda s, d: base.offline_batch(board(s, d, "crm").engine, _CUBE, ["r_name_s", "p_type", "o_orderstatus"]),
    " UNION ALL ".join(f"SELECT '{a}' AS attribute, CAST({a} AS VARCHAR) AS value, amount FROM ({naive_sql(dashboards._shape(_CRM), _CUBE.add_group(a))}) AS q" for a in ("r_name_s", "p_type", "o_orderstatus")))

# ---- workloads --------------------------------------------------------------------------------


def _steps(name: str, prefix: str) -> None:
    w = WORKLOADS[name]
    for chart in w.charts:
        add(f"{prefix}_{chart}_dash", lambda s, d, c=chart: shown(s, d, name, c), dashboards.sql(name, chart, 0))
        for k in range(1, len(w.steps[chart]) + 1):
            add(f"{prefix}_{chart}_i{k}", lambda s, d, c=chart, k=k: interaction(s, d, name, c, k), dashboards.sql(name, chart, k))


_steps("crm", "crm")
_steps("flight", "flight")
for _k, _n in SENSITIVITY.items():
    add(f"sensitivity_k{_k}", lambda s, d, k=_k: _counted(dashboards.fresh_interaction(s, d, "flight", "v3", 2, calibrated=k)), counted_sql("flight", "v3", 2, _n))


def _case_study(spark: SparkSession, d: str) -> DataFrame:
    """The second interaction of the second chart under three strategies, each on a store of its own: the
    messages computed for it, whether the fact table is read, and the answer's total."""
    w, out = WORKLOADS["flight"], []
    for strategy in ("factorized", "offline", "online"):
        if strategy == "factorized":
            e, trace = board(spark, d, "flight", fresh=True).engine, Trace()
            rows = e.factorized(w.query("v2", 2), trace=trace)
        else:
            a = dashboards.fresh_interaction(spark, d, "flight", "v2", 2, online=strategy == "online")
            rows, trace = a.rows, a.trace
        touched = {u for u, _ in trace.edges("computed")} | {u for u, _ in trace.edges("absorbed")}
        out.append((strategy, trace.count("computed"), "lineitem" in touched, rows.agg(F.round(F.sum("amount"), 2)).first()[0]))
    return constant(spark, out, "strategy string, computed int, reads_fact boolean, total double")


add("case_study_answer", _case_study, "SELECT s AS strategy, CAST(n AS INTEGER) AS computed, f AS reads_fact, (SELECT ROUND(SUM(amount), 2) FROM "
    f"({dashboards.sql('flight', 'v2', 2)}) AS q) AS total FROM (VALUES " + ", ".join(f"('{k}', {n}, {f})" for k, (n, f) in CASE_STUDY.items()) + ") AS t(s, n, f)")


def _tpch(name: str, finish: Callable[[DataFrame], DataFrame], sql_finish: str) -> None:
    w = WORKLOADS[name]
    for k in range(len(w.steps[name]) + 1):
        fn = (lambda s, d: finish(shown(s, d, name, name))) if k == 0 else (lambda s, d, k=k: finish(interaction(s, d, name, name, k)))
        add(f"tpch_{name}" + (f"_i{k}" if k else ""), fn, sql_finish.format(q=dashboards.sql(name, name, k)))


_tpch("q3", lambda df: df.orderBy(F.desc("revenue"), "orderkey").limit(10).withColumn("orderdate", F.col("orderdate").cast("date").cast("string")), "SELECT orderkey, CAST(CAST(orderdate AS DATE) AS VARCHAR) AS orderdate, revenue FROM ({q}) AS q ORDER BY revenue DESC, orderkey LIMIT 10")
_tpch("q5", lambda df: df, "SELECT * FROM ({q}) AS q")
_SHARE = "ROUND(SUM(CASE WHEN n_name_s = 'NATION_7' THEN revenue ELSE 0 END) / SUM(revenue), 4)"
_tpch("q8", lambda df: df.groupBy("order_year").agg(F.round(F.sum(F.when(F.col("n_name_s") == "NATION_7", F.col("revenue")).otherwise(0.0)) / F.sum("revenue"), 4).alias("share")), f"SELECT order_year, {_SHARE} AS share FROM ({{q}}) AS q GROUP BY order_year")
_tpch("q9", lambda df: df, "SELECT * FROM ({q}) AS q")
_tpch("q10", lambda df: df.orderBy(F.desc("revenue"), "custkey").limit(20), "SELECT * FROM ({q}) AS q ORDER BY revenue DESC, custkey LIMIT 20")


def _q4(spark: SparkSession, d: str, low: int, high: int) -> DataFrame:
    """Existence of a returned line passes from the lines to their orders; orders are counted there."""
    g = tables.graph(spark, d, ["lineitem", "orders", "order_calendar"])
    e = Engine(spark, JoinTree.from_graph(g), MessageStore(spark, "memory"))
    b = bind(e.tree, SpjaQuery(ExistsRing(), ("orderkey",), ("l_returnflag = 'R'",)), "lineitem")
    returned, _, _ = e.message(b, "lineitem", "orders", Trace())
    orders = g.relations["orders"].df.join(g.relations["order_calendar"].df, "orderdate").filter(F.col("order_month").between(low, high))
    return joins.semi(orders, returned, ["orderkey"]).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("cnt"))


for _n, _lo, _hi in (("tpch_q4", 199701, 199703), ("tpch_q4_i1", 199704, 199706)):
    add(_n, lambda s, d, lo=_lo, hi=_hi: _q4(s, d, lo, hi), f"SELECT o_orderpriority, COUNT(*) AS cnt FROM orders WHERE year(o_orderdate) * 100 + month(o_orderdate) BETWEEN {_lo} AND {_hi} AND EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_returnflag = 'R') GROUP BY o_orderpriority")

_steps("m2n", "m2n")
_steps("docs", "docs")

# regression by messages
_TRAIN = dashboards.JoinGraph({n: dashboards.Relation(n, dashboards._Columns([a for _, a in tables.LAYOUT[n][1]]), (), f"SELECT {', '.join(f'{e} AS {a}' for e, a in tables.LAYOUT[n][1])} FROM {tables.LAYOUT[n][0]}") for n in ("supplier", "nation_s", "region_s", "part")})
_TRAIN.relations["sales"] = dashboards.Relation("sales", dashboards._Columns(["suppkey", "partkey", "ship_month", "l_quantity"]), (), regression.SALES_SQL)
_TRAIN.relations["supplier_month"] = dashboards.Relation("supplier_month", dashboards._Columns(["suppkey", "ship_month", "transactions"]), (), regression.TARGET_SQL)


def _gram_sql(dim: str | None) -> str:
    g = dashboards.JoinGraph(dict(_TRAIN.relations))
    ms = [*regression.FEATURES, regression.TARGET]
    if dim:
        g.relations[f"aug_{dim}_1"] = dashboards.Relation(f"aug_{dim}_1", dashboards._Columns([regression.KEYS[dim], "v"]), (), regression.candidate_sql(dim, 1, True))
        ms.append(Measure("v", f"aug_{dim}_1", "v", 3))
    return naive_sql(g, SpjaQuery(gram_ring(ms)))


add("aug_base_gram", lambda s, d: regression.augmenter(s, d).base_gram(), _gram_sql(None))
for _dim in regression.KEYS:
    add(f"aug_{_dim}_gram", lambda s, d, dim=_dim: regression.gram(s, d, dim), _gram_sql(_dim))


def _one_feature(spark: SparkSession, d: str) -> DataFrame:
    """R² of the quantity alone, from the calibrated Gram matrix."""
    n, x, y = F.col("cnt"), F.col("s_quantity"), F.col("s_transactions")
    xy = n * F.col("q_quantity_transactions") - x * y
    r2 = xy * xy / ((n * F.col("q_quantity_quantity") - x * x) * (n * F.col("q_transactions_transactions") - y * y))
    return regression.augmenter(spark, d).base_gram().select(F.round(r2, 6).alias("r2"))


add("regr_r2", _one_feature, f"SELECT ROUND(regr_r2(t.transactions, s.l_quantity), 6) AS r2 FROM ({regression.SALES_SQL}) AS s JOIN ({regression.TARGET_SQL}) AS t ON s.suppkey = t.suppkey AND s.ship_month = t.ship_month")
add("aug_r2_ranking", lambda s, d: regression.ranking(s, d))

# annotated-bag sizes and message sizes
_SIZES = ["region_s", "nation_s", "supplier", "part", "customer", "orders", "lineitem"]
add("bag_size_counts", lambda s, d: constant(s, [(b, board(s, d, "flight").engine.bag_rows(b)) for b in _SIZES], "bag string, n_rows bigint"),
    " UNION ALL ".join(f"SELECT '{b}' AS bag, COUNT(*) AS n_rows FROM {tables.LAYOUT[b][0]}" for b in _SIZES))


def _message_sizes(spark: SparkSession, d: str) -> DataFrame:
    dash = board(spark, d, "flight")
    dash.calibrate_offline(["v1"])
    b, e = dash.charts["v1"].bound, dash.engine
    out = [(f"{u}->{v}", e.store.get(b.fingerprint(u, v)).rows) for u, v in b.tree.directed() if not b.is_one(u, v)]
    return constant(spark, [x for x in out if x[0] in ("lineitem->part", "lineitem->supplier", "orders->customer")], "message string, n_rows bigint")


add("message_sizes", _message_sizes,
    "SELECT 'lineitem->part' AS message, COUNT(*) AS n_rows FROM (SELECT DISTINCT l_partkey, o_orderpriority FROM lineitem JOIN orders ON l_orderkey = o_orderkey) AS a UNION ALL "
    "SELECT 'lineitem->supplier', COUNT(*) FROM (SELECT DISTINCT l_suppkey, o_orderpriority FROM lineitem JOIN orders ON l_orderkey = o_orderkey) AS b UNION ALL "
    "SELECT 'orders->customer', COUNT(*) FROM (SELECT DISTINCT o_custkey, o_orderpriority FROM lineitem JOIN orders ON l_orderkey = o_orderkey) AS c")
add("intermediate_sizes", lambda s, d: constant(s, [(measure.intermediate_report(board(s, d, "m2n").engine, SpjaQuery(count_ring()))["full_join"],)], "full_join bigint"),
    "SELECT COUNT(*) AS full_join FROM events JOIN customer ON user_id = c_custkey JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey")


def _bound_holds(spark: SparkSession, d: str) -> DataFrame:
    e = board(spark, d, "crm").engine
    rows = measure.bound_vs_actual(e, bind(e.tree, _PIVOT))
    return constant(spark, [(sum(n > limit for _, _, n, limit in rows),)], "messages_over_bound int")


add("message_bound", _bound_holds, "SELECT CAST(0 AS INTEGER) AS messages_over_bound")


def queries() -> dict[str, Query]:
    from joindash.workloads import support

    return QUERIES | support.QUERIES


def oracle_sql() -> dict[str, str]:
    from joindash.workloads import support

    return SQL | support.SQL

