"""Queries of the ordinary operators, sources, functions and streams around the engine."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from joindash.functions import frames, scalars
from joindash.operators import aggs, joins, relational, udx, windows
from joindash.runtime import importable, new_path
from joindash.sources import tables
from joindash.streaming import streams

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def add(name: str, sql: str | None = None):
    def keep(fn: Query) -> Query:
        QUERIES[name] = fn
        if sql:
            SQL[name] = sql
        return fn

    return keep


def t(spark: SparkSession, d: str, name: str, *cols: str) -> DataFrame:
    return tables.read_table(spark, d, name, list(cols) or None)


N = lambda: F.count(F.lit(1))
cents = lambda c: F.sum(F.round(F.col(c) * 100).cast("decimal(38,0)")).cast("double") / 100
CENTS = "CAST(SUM(CAST(ROUND({0} * 100) AS HUGEINT)) AS DOUBLE) / 100"

# ---- sources and sinks ------------------------------------------------------------------------


@add("op_scan_pushdown", "SELECT l_returnflag, COUNT(*) AS n FROM lineitem WHERE l_quantity > 45 AND l_shipdate >= TIMESTAMP '1997-01-01' GROUP BY l_returnflag")
def _(s, d):
    df = tables.read_table(s, d, "lineitem", ["l_returnflag"], "l_quantity > 45 AND l_shipdate >= TIMESTAMP_NTZ '1997-01-01'")
    return df.groupBy("l_returnflag").agg(N().alias("n"))


def _formats(fmt: str) -> None:
    @add(f"op_{fmt}_round_trip", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
    def _(s, d):
        df, path = t(s, d, "nation"), new_path(s, fmt)
        tables.write_as(df, path, fmt)
        return tables.read_as(s, path, fmt, df.schema).select("n_nationkey", "n_name", "n_regionkey")


for _fmt in ("csv", "json", "orc"):
    _formats(_fmt)


@add("op_text_round_trip", "SELECT r_name AS value FROM region")
def _(s, d):
    path = new_path(s, "text")
    tables.write_as(t(s, d, "region", "r_name"), path, "text")
    return tables.read_as(s, path, "text", "value string")


@add("op_bucketed_join", "SELECT o_orderstatus, COUNT(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderstatus")
def _(s, d):
    names = []
    for table, key in (("orders", "o_orderkey"), ("lineitem", "l_orderkey")):
        name = f"bucketed_{table}_{abs(hash(new_path(s, 'b'))) % 10**9}"
        tables.write_as(t(s, d, table), new_path(s, "bucketed"), "parquet", (8, [key]), name)
        names.append(name)
    return s.table(names[0]).join(s.table(names[1]), F.expr("o_orderkey = l_orderkey")).groupBy("o_orderstatus").agg(N().alias("n"))


@add("op_memory_relation", "SELECT c_custkey AS k, c_mktsegment AS v FROM customer")
def _(s, d):
    return t(s, d, "customer", "c_custkey", "c_mktsegment").toDF("k", "v").persist()


# ---- projection and filters -------------------------------------------------------------------


# in whole ten-thousandths: doubles on the edge of rounding differ between engines
_REVENUE = "CAST(ROUND(l_extendedprice * 100) AS BIGINT) * (100 - CAST(ROUND(l_discount * 100) AS BIGINT))"


@add("op_project", f"SELECT l_orderkey AS orderkey, l_linenumber, {_REVENUE} AS revenue_e4 FROM lineitem")
def _(s, d):
    return relational.project(t(s, d, "lineitem"), {"orderkey": "l_orderkey", "l_linenumber": "l_linenumber", "revenue_e4": _REVENUE})


_PRED = "(p_size BETWEEN 5 AND 15 AND p_type IN ('PROMO', 'SMALL') OR p_name LIKE '%red%') AND NOT p_brand = 'Brand#11' AND p_name IS NOT NULL"


@add("op_predicates", f"SELECT p_partkey, p_size FROM part WHERE {_PRED}")
def _(s, d):
    return relational.where(t(s, d, "part"), _PRED).select("p_partkey", "p_size")


@add("op_case", "SELECT CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'middle' ELSE 'large' END AS size_class, COUNT(*) AS n FROM part GROUP BY 1")
def _(s, d):
    kind = F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "middle").otherwise("large")
    return t(s, d, "part").groupBy(kind.alias("size_class")).agg(N().alias("n"))


@add("op_perturb", "SELECT p_partkey, CASE WHEN p_partkey % 10 = 3 THEN p_size + 1 ELSE p_size END AS p_size FROM part")
def _(s, d):
    return relational.perturb(t(s, d, "part"), "p_partkey", "p_size", 10, 3, F.col("p_size") + 1).select("p_partkey", "p_size")


@add("op_scale_out", "SELECT c_custkey + k * 1000000 AS c_custkey, c_mktsegment FROM customer CROSS JOIN range(3) AS r(k)")
def _(s, d):
    return relational.scale_out(t(s, d, "customer", "c_custkey", "c_mktsegment"), {"c_custkey": 1_000_000}, 3)


@add("op_data_scaler", """SELECT p_type, TRUE AS share_kept, CAST(0 AS BIGINT) AS orphans, TRUE AS size_kept
    FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_type""")
def _(s, d):
    """Wide rows resampled to twice their number and cut into a fact and two dimensions again: each type
    keeps its share, every key resolves, and the size is the one asked for."""
    wide = t(s, d, "lineitem", "l_quantity", "l_partkey", "l_suppkey").join(t(s, d, "part", "p_partkey", "p_type"), F.expr("l_partkey = p_partkey")).join(t(s, d, "supplier", "s_suppkey", "s_nationkey"), F.expr("l_suppkey = s_suppkey"))
    wanted = 2 * wide.count()
    parts = relational.resample_normalised(wide.select("l_quantity", "p_type", "s_nationkey"), wanted, {"kind": ["p_type"], "place": ["s_nationkey"]})
    fact = parts["fact"].join(parts["kind"], "kind_key", "left").join(parts["place"], "place_key", "left")
    lost = (F.col("p_type").isNull() | F.col("s_nationkey").isNull()).cast("long")
    sums = fact.agg(F.sum(lost).alias("orphans"), (F.abs(N() - wanted) <= 0.05 * wanted).alias("size_kept"), N().alias("all_rows"))
    grown = fact.groupBy("p_type").agg(N().alias("n")).crossJoin(F.broadcast(sums))  # one row
    before = wide.groupBy("p_type").agg((N() / (wanted / 2)).alias("share"))
    return grown.join(before, "p_type").select("p_type", (F.abs(F.col("n") / F.col("all_rows") - F.col("share")) < 0.02).alias("share_kept"), "orphans", "size_kept")


# ---- joins --------------------------------------------------------------------------------------

_JOIN = "SELECT o_orderpriority, COUNT(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority"


def _equi(strategy: str) -> None:
    @add(f"op_join_{strategy}", _JOIN)
    def _(s, d):
        left = t(s, d, "lineitem", "l_orderkey").withColumnRenamed("l_orderkey", "k")
        right = t(s, d, "orders", "o_orderkey", "o_orderpriority").withColumnRenamed("o_orderkey", "k")
        joined = joins.salted(left, right, ["k"]) if strategy == "salted" else joins.equi(left, right, ["k"], "inner", strategy)
        return joined.groupBy("o_orderpriority").agg(N().alias("n"))


for _strategy in ("broadcast", "hash", "merge", "salted"):
    _equi(_strategy)


def _outer(how: str, sql: str) -> None:
    @add(f"op_join_{how}", f"SELECT c_mktsegment, event_type, COUNT(*) AS n FROM customer {sql} JOIN events ON c_custkey = user_id GROUP BY c_mktsegment, event_type")
    def _(s, d):
        left, right = t(s, d, "customer", "c_custkey", "c_mktsegment").withColumnRenamed("c_custkey", "k"), t(s, d, "events", "user_id", "event_type").withColumnRenamed("user_id", "k")
        return joins.equi(left, right, ["k"], how).groupBy("c_mktsegment", "event_type").agg(N().alias("n"))


for _how, _sql in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
    _outer(_how, _sql)


@add("op_join_semi", "SELECT COUNT(*) AS n FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_returnflag = 'R')")
def _(s, d):
    r = t(s, d, "lineitem").filter("l_returnflag = 'R'").select(F.col("l_orderkey").alias("o_orderkey"))
    return joins.semi(t(s, d, "orders"), r, ["o_orderkey"]).agg(N().alias("n"))


@add("op_join_anti", "SELECT COUNT(*) AS n FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def _(s, d):
    return joins.anti(t(s, d, "orders"), t(s, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey")), ["o_orderkey"]).agg(N().alias("n"))


@add("op_join_theta", "SELECT a.r_name AS a, b.r_name AS b FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey")
def _(s, d):
    a, b = t(s, d, "region").toDF("ak", "a"), t(s, d, "region").toDF("bk", "b")
    return joins.theta(a, b, F.col("ak") < F.col("bk")).select("a", "b")


@add("op_join_range", "SELECT p.p_partkey, CAST(b AS INTEGER) AS band FROM part p JOIN range(50) AS r(b) ON p.p_retailprice >= b * 100 AND p.p_retailprice < b * 100 + 250")
def _(s, d):
    spans = s.range(50).select(F.col("id").cast("int").alias("band"), (F.col("id") * 100.0).alias("low"), (F.col("id") * 100.0 + 250.0).alias("high"))
    return joins.range_join(t(s, d, "part", "p_partkey", "p_retailprice"), spans, "p_retailprice", "low", "high", 250.0).select("p_partkey", "band")


@add("op_join_asof", "SELECT e.event_id, p.value AS last_purchase FROM (SELECT * FROM events WHERE event_type = 'view') e ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'purchase' GROUP BY user_id, ts) p ON e.user_id = p.user_id AND e.ts >= p.ts")
def _(s, d):
    ev = t(s, d, "events", "event_id", "user_id", "ts", "event_type", "value")
    right = ev.filter("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("value").alias("last_purchase"))
    return joins.asof(ev.filter("event_type = 'view'").select("event_id", "user_id", "ts"), right, "ts", ["user_id"], ["last_purchase"]).select("event_id", "last_purchase")


@add("op_join_cross", "SELECT a.r_name AS a, b.r_name AS b FROM region a CROSS JOIN region b")
def _(s, d):
    return joins.cross(t(s, d, "region", "r_name").toDF("a"), t(s, d, "region", "r_name").toDF("b"))


@add("op_join_multiway", "SELECT r_name, COUNT(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def _(s, d):
    c = t(s, d, "customer").select(F.col("c_nationkey").alias("nk"))
    n = t(s, d, "nation").select(F.col("n_nationkey").alias("nk"), F.col("n_regionkey").alias("rk"))
    r = t(s, d, "region").select(F.col("r_regionkey").alias("rk"), "r_name")
    return joins.multiway([c, n, r], [["nk"], ["rk"]]).groupBy("r_name").agg(N().alias("n"))


# ---- aggregation --------------------------------------------------------------------------------


@add("op_agg_basic", f"SELECT l_returnflag, l_linestatus, COUNT(*) AS n, {CENTS.format('l_extendedprice')} AS total, MIN(l_quantity) AS low, MAX(l_quantity) AS high, ROUND(AVG(l_quantity), 6) AS mean FROM lineitem GROUP BY l_returnflag, l_linestatus")
def _(s, d):
    return aggs.agg(t(s, d, "lineitem"), ["l_returnflag", "l_linestatus"], [N().alias("n"), cents("l_extendedprice").alias("total"), F.min("l_quantity").alias("low"), F.max("l_quantity").alias("high"), F.round(F.avg("l_quantity"), 6).alias("mean")])


@add("op_agg_statistics", "SELECT l_returnflag, ROUND(var_pop(l_quantity), 4) AS v, ROUND(stddev_samp(l_quantity), 4) AS sd, ROUND(covar_pop(l_quantity, l_discount), 4) AS cv, ROUND(corr(l_quantity, l_extendedprice), 4) AS r, ROUND(regr_slope(l_extendedprice, l_quantity), 4) AS slope, ROUND(regr_r2(l_extendedprice, l_quantity), 4) AS r2 FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    r4 = lambda c, a: F.round(c, 4).alias(a)
    return t(s, d, "lineitem").groupBy("l_returnflag").agg(
        r4(F.var_pop("l_quantity"), "v"), r4(F.stddev_samp("l_quantity"), "sd"), r4(F.covar_pop("l_quantity", "l_discount"), "cv"),
        r4(F.corr("l_quantity", "l_extendedprice"), "r"), r4(F.regr_slope("l_extendedprice", "l_quantity"), "slope"), r4(F.regr_r2("l_extendedprice", "l_quantity"), "r2"))


@add("op_agg_salted", f"SELECT l_returnflag, {CENTS.format('l_extendedprice')} AS total FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    df = t(s, d, "lineitem").select("l_returnflag", F.round(F.col("l_extendedprice") * 100).cast("decimal(38,0)").alias("c"))
    return aggs.salted_sum(df, ["l_returnflag"], {"total": "c"}).withColumn("total", F.col("total").cast("double") / 100)


@add("op_grouping_sets", "SELECT CAST(GROUPING_ID(o_orderstatus, o_orderpriority) AS BIGINT) AS level, o_orderstatus, o_orderpriority, COUNT(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def _(s, d):
    return aggs.grouping_sets(t(s, d, "orders"), [["o_orderstatus"], ["o_orderpriority"], []], [N().alias("n")])


@add("op_cube", "SELECT CAST(GROUPING_ID(o_orderstatus, o_orderpriority) AS BIGINT) AS level, o_orderstatus, o_orderpriority, COUNT(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def _(s, d):
    return aggs.cube(t(s, d, "orders"), ["o_orderstatus", "o_orderpriority"], [N().alias("n")])


@add("op_rollup", "SELECT CAST(GROUPING_ID(p_brand, p_type) AS BIGINT) AS level, p_brand, p_type, COUNT(*) AS n FROM part GROUP BY ROLLUP (p_brand, p_type)")
def _(s, d):
    return aggs.rollup(t(s, d, "part"), ["p_brand", "p_type"], [N().alias("n")])


@add("op_count_distinct", "SELECT o_orderstatus, COUNT(DISTINCT o_custkey) AS n FROM orders GROUP BY o_orderstatus")
def _(s, d):
    return t(s, d, "orders").groupBy("o_orderstatus").agg(F.countDistinct("o_custkey").alias("n"))


@add("op_approx_distinct", "SELECT o_orderstatus, TRUE AS within FROM orders GROUP BY o_orderstatus")
def _(s, d):
    """Whether the sketch stays within four of its standard errors (2 %) of the exact count."""
    both = t(s, d, "orders").groupBy("o_orderstatus").agg(F.approx_count_distinct("o_custkey", 0.02).alias("n"), F.countDistinct("o_custkey").alias("exact"))
    return both.select("o_orderstatus", (F.abs(F.col("n") - F.col("exact")) <= 0.08 * F.col("exact")).alias("within"))


@add("op_percentile", "SELECT l_returnflag, quantile_cont(l_quantity, 0.9) AS p90, median(l_quantity) AS med FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    return t(s, d, "lineitem").groupBy("l_returnflag").agg(F.percentile("l_quantity", 0.9).alias("p90"), F.median("l_quantity").alias("med"))


@add("op_agg_of_agg", "SELECT MAX(n) AS top, MIN(n) AS low FROM (SELECT l_suppkey, COUNT(*) AS n FROM lineitem GROUP BY l_suppkey) AS q")
def _(s, d):
    return aggs.agg_of_agg(t(s, d, "lineitem"), ["l_suppkey"], N().alias("n"), [F.max("n").alias("top"), F.min("n").alias("low")])


@add("op_filtered_agg", "SELECT o_orderstatus, COUNT(*) FILTER (WHERE o_totalprice > 100000) AS big, SUM(CASE WHEN o_orderpriority = '1-URGENT' THEN 1 ELSE 0 END)::BIGINT AS urgent FROM orders GROUP BY o_orderstatus")
def _(s, d):
    return t(s, d, "orders").groupBy("o_orderstatus").agg(F.count_if(F.col("o_totalprice") > 100000).alias("big"), F.sum(F.when(F.col("o_orderpriority") == "1-URGENT", 1).otherwise(0)).alias("urgent"))


@add("op_argmax", "SELECT p_brand, arg_max(p_partkey, p_retailprice * 1000000 - p_partkey) AS top FROM part GROUP BY p_brand")
def _(s, d):
    return t(s, d, "part").groupBy("p_brand").agg(F.max_by("p_partkey", F.col("p_retailprice") * 1000000 - F.col("p_partkey")).alias("top"))


@add("op_pivot", "SELECT l_returnflag, SUM(CASE WHEN l_linestatus = 'F' THEN 1 END)::BIGINT AS F, SUM(CASE WHEN l_linestatus = 'O' THEN 1 END)::BIGINT AS O FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    return aggs.pivot(t(s, d, "lineitem"), ["l_returnflag"], "l_linestatus", ["F", "O"], N())


# ---- windows, sorting, sets -----------------------------------------------------------------------


@add("op_ranks", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS tile, ROUND(percent_rank() OVER v, 6) AS pr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")
def _(s, d):
    df = t(s, d, "orders")
    full, part = [F.desc("o_totalprice"), F.col("o_orderkey")], [F.col("o_orderpriority")]
    df = windows.rank_within(df, ["o_custkey"], full)
    for fn, a in (("rank", "rk"), ("dense_rank", "dr"), ("percent_rank", "pr")):
        df = windows.rank_within(df, ["o_custkey"], part, fn, a)
    return windows.tiles(df, ["o_custkey"], full, 4).select("o_orderkey", "rn", "rk", "dr", "tile", F.round("pr", 6).alias("pr"))


@add("op_frames", "SELECT event_id, lag(value) OVER w AS prev, lead(value) OVER w AS next, first_value(value) OVER w AS head, ROUND(SUM(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS run3 FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def _(s, d):
    order = [F.col("ts"), F.col("event_id")]
    df = windows.framed(t(s, d, "events"), ["user_id"], order, None, {"prev": F.lag("value"), "next": F.lead("value"), "head": F.first("value")})
    df = windows.framed(df, ["user_id"], order, (-2, 0), {"run3": F.sum("value")})
    return df.select("event_id", "prev", "next", "head", F.round("run3", 4).alias("run3"))


@add("op_share", "SELECT n_regionkey, n_nationkey, ROUND(n / SUM(n) OVER (PARTITION BY n_regionkey), 6) AS share FROM (SELECT n_regionkey, n_nationkey, COUNT(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1, 2) AS q")
def _(s, d):
    df = t(s, d, "customer").join(t(s, d, "nation"), F.expr("c_nationkey = n_nationkey")).groupBy("n_regionkey", "n_nationkey").agg(N().alias("n"))
    return windows.share(df, ["n_regionkey"], "n").select("n_regionkey", "n_nationkey", F.round("share", 6).alias("share"))


@add("op_last_turn", "SELECT conv_id, turn, role FROM (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn DESC) AS rn FROM conversations) AS q WHERE rn = 1")
def _(s, d):
    return windows.top_per_group(t(s, d, "conversations", "conv_id", "turn", "role"), ["conv_id"], [F.desc("turn")], 1)


@add("op_top_k", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 15")
def _(s, d):
    return relational.top_k(t(s, d, "orders", "o_orderkey", "o_totalprice"), [F.desc("o_totalprice"), F.col("o_orderkey")], 15)


@add("op_top_per_group", "SELECT p_brand, p_partkey FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS rn FROM part) AS q WHERE rn <= 3")
def _(s, d):
    return windows.top_per_group(t(s, d, "part"), ["p_brand"], [F.desc("p_retailprice"), F.col("p_partkey")], 3).select("p_brand", "p_partkey")


def _sets(kind: str, sql: str, keep_all: bool) -> None:
    @add(f"op_{kind}{'_all' if keep_all else ''}", f"SELECT c_nationkey AS k FROM customer {sql} SELECT s_nationkey AS k FROM supplier")
    def _(s, d):
        return relational.set_op(t(s, d, "customer").select(F.col("c_nationkey").alias("k")), t(s, d, "supplier").select(F.col("s_nationkey").alias("k")), kind, keep_all)


for _kind, _word in (("union", "UNION"), ("intersect", "INTERSECT"), ("except", "EXCEPT")):
    _sets(_kind, _word, False)
    _sets(_kind, f"{_word} ALL", True)

# ---- scalar functions -------------------------------------------------------------------------------


@add("op_strings", "SELECT p_partkey, substring(p_name, 1, 3) AS head, upper(p_brand) AS u, length(p_name) AS n, regexp_extract(p_brand, '([0-9]+)', 1) AS num, concat_ws('-', p_brand, p_type) AS both, string_split(p_name, ' ')[1] AS w FROM part")
def _(s, d):
    return t(s, d, "part").select("p_partkey", F.substring("p_name", 1, 3).alias("head"), F.upper("p_brand").alias("u"), F.length("p_name").cast("long").alias("n"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("num"), F.concat_ws("-", "p_brand", "p_type").alias("both"), F.split("p_name", " ")[0].alias("w"))


@add("op_dates", "SELECT o_orderkey, CAST(year(o_orderdate) * 100 + month(o_orderdate) AS INTEGER) AS ym, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR) AS m, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, CAST(CAST(CAST(o_orderdate AS DATE) + INTERVAL 2 MONTH AS DATE) AS VARCHAR) AS later FROM orders")
def _(s, d):
    day = F.col("o_orderdate").cast("date")
    return t(s, d, "orders").select("o_orderkey", scalars.year_month(F.col("o_orderdate")).alias("ym"), F.trunc(day, "month").cast("string").alias("m"), F.datediff(day, F.lit("1995-01-01").cast("date")).alias("days"), F.add_months(day, 2).cast("string").alias("later"))


@add("op_math", "SELECT p_partkey, floor(p_retailprice)::BIGINT AS f, ROUND(sqrt(p_retailprice), 6) AS r, ROUND(ln(p_retailprice), 6) AS l, greatest(p_size, 20) AS g, p_partkey % 7 AS m, ROUND(power(p_size, 2), 2) AS p FROM part")
def _(s, d):
    price = F.col("p_retailprice")
    return t(s, d, "part").select("p_partkey", F.floor(price).alias("f"), F.round(F.sqrt(price), 6).alias("r"), F.round(F.log(price), 6).alias("l"), F.greatest("p_size", F.lit(20)).alias("g"), F.pmod("p_partkey", F.lit(7)).alias("m"), F.round(F.pow("p_size", F.lit(2)), 2).alias("p"))


@add("op_arrays", "SELECT vec_id, ROUND(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 4) AS norm, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")
def _(s, d):
    return t(s, d, "embeddings").select("vec_id", F.round(scalars.squared_norm(F.col("embedding")), 4).alias("norm"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"))


@add("op_maps", "SELECT user_id, COUNT(*) FILTER (WHERE event_type = 'click') AS clicks FROM events GROUP BY user_id")
def _(s, d):
    by = t(s, d, "events").groupBy("user_id", "event_type").agg(N().alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return by.select("user_id", F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0)).alias("clicks"))


@add("op_json", "SELECT event_id, json_extract_string(props, '$.page') AS page FROM events")
def _(s, d):
    return t(s, d, "events").select("event_id", scalars.json_field(F.col("props"), "page").alias("page"))


@add("op_structs", "SELECT c_custkey, c_mktsegment AS seg, c_nationkey AS nk FROM customer")
def _(s, d):
    return t(s, d, "customer").select("c_custkey", F.struct(F.col("c_mktsegment").alias("seg"), F.col("c_nationkey").alias("nk")).alias("x")).select("c_custkey", "x.*")


@add("op_hashes", "SELECT c_custkey, md5(c_name) AS m, sha256(concat_ws('|', c_name, c_mktsegment)) AS s, ROUND(CAST(CAST(('0x' || substr(md5(concat(CAST(c_custkey AS VARCHAR), ':1')), 1, 8)) AS BIGINT) AS DOUBLE) / 4294967296.0, 9) AS u FROM customer")
def _(s, d):
    return t(s, d, "customer").select("c_custkey", F.md5(F.col("c_name").cast("binary")).alias("m"), scalars.digest(F.col("c_name"), F.col("c_mktsegment")).alias("s"), F.round(scalars.noise(F.col("c_custkey"), 1), 9).alias("u"))


# ---- SQL and Python surfaces ------------------------------------------------------------------------

_CTE = "WITH big AS (SELECT o_custkey, COUNT(*) AS n FROM orders GROUP BY o_custkey HAVING COUNT(*) > 10) SELECT c_mktsegment, COUNT(*) AS n FROM customer WHERE EXISTS (SELECT 1 FROM big WHERE o_custkey = c_custkey) AND c_acctbal > (SELECT AVG(c_acctbal) FROM customer) GROUP BY c_mktsegment"


@add("op_sql", _CTE)
def _(s, d):
    for n in ("orders", "customer"):
        t(s, d, n).createOrReplaceTempView(n)
    return s.sql(_CTE)


@add("op_vector_udf", "SELECT p_partkey, reverse(p_name) AS back FROM part")
def _(s, d):
    importable(s)
    return t(s, d, "part").select("p_partkey", udx.vector_udf(frames.reversed_text, "string")("p_name").alias("back"))


@add("op_grouped_map", "SELECT s_suppkey, ROUND(s_acctbal - MAX(s_acctbal) OVER (PARTITION BY s_nationkey), 2) AS gap FROM supplier")
def _(s, d):
    return udx.grouped_map(t(s, d, "supplier", "s_suppkey", "s_nationkey", "s_acctbal"), ["s_nationkey"], frames.gap_to_best, "s_suppkey long, gap double")


@add("op_table_function", "SELECT CAST(i AS INTEGER) AS step, a AS action, u AS source, v AS target FROM (VALUES (0, 'reused', 'orders', 'lineitem'), (1, 'absorbed', 'lineitem', '')) AS t(i, a, u, v)")
def _(s, d):
    return udx.plan_rows([("reused", "orders", "lineitem"), ("absorbed", "lineitem", "")])()


# ---- streams ------------------------------------------------------------------------------------------


def _events(s: SparkSession, d: str) -> DataFrame:
    return streams.stream_table(s, f"{d}/events.parquet")


_fresh = iter(range(1_000_000))


def _run(df: DataFrame, mode: str, *more) -> DataFrame:
    return streams.drained(df, f"joindash_stream_{next(_fresh)}", mode, *more)


_EPOCH = "CAST(epoch(time_bucket(INTERVAL {w}, ts)) AS BIGINT)"


@add("st_tumbling", f"SELECT {_EPOCH.format(w='6 HOUR')} AS start, event_type, COUNT(*) AS n FROM events GROUP BY 1, 2")
def _(s, d):
    df = streams.windowed(_events(s, d), "ts", "tumbling", "6 hours", by=["event_type"], watermark="30 days")
    return _run(df, "complete").select(F.unix_timestamp("start").alias("start"), "event_type", "n")


@add("st_sliding", "SELECT CAST(epoch(time_bucket(INTERVAL 6 HOUR, ts)) AS BIGINT) - k * 21600 AS start, COUNT(*) AS n FROM events CROSS JOIN range(2) AS r(k) GROUP BY 1")
def _(s, d):
    df = streams.windowed(_events(s, d), "ts", "sliding", "12 hours", "6 hours", watermark="30 days")
    return _run(df, "complete").select(F.unix_timestamp("start").alias("start"), "n")


@add("st_session", "SELECT user_id, COUNT(*) AS n, CAST(floor(MIN(epoch(ts))) AS BIGINT) AS start FROM (SELECT *, SUM(gap) OVER (PARTITION BY user_id ORDER BY ts) AS g FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS gap FROM events) AS a) AS b GROUP BY user_id, g")
def _(s, d):
    df = streams.windowed(_events(s, d), "ts", "session", "2 hours", by=["user_id"], watermark="30 days")
    return _run(df, "complete").select("user_id", "n", F.unix_timestamp("start").alias("start"))


@add("st_dedupe", "SELECT COUNT(*) AS n, COUNT(DISTINCT event_id) AS k FROM events")
def _(s, d):
    ev = _events(s, d)
    twice = ev.unionByName(ev)
    return _run(streams.deduplicated(twice, ["event_id"], "ts", "60 days").select("event_id"), "append", True).agg(N().alias("n"), F.countDistinct("event_id").alias("k"))


@add("st_stream_static", "SELECT c_mktsegment, COUNT(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY c_mktsegment")
def _(s, d):
    message = t(s, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return _run(streams.with_message(_events(s, d), message, ["user_id"]).groupBy("c_mktsegment").agg(N().alias("n")), "complete")


@add("st_stream_stream", "SELECT COUNT(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def _(s, d):
    a = _events(s, d).filter("event_type = 'click'").select("user_id", "ts")
    b = _events(s, d).filter("event_type = 'purchase'").select(F.col("user_id").alias("right_user_id"), F.col("ts").alias("right_ts"))
    return _run(streams.paired(a, b, "user_id", "ts", "right_ts", "1 hour"), "append").agg(N().alias("n"))


@add("st_latest_state", """SELECT user_id, arg_max(event_type, n) AS latest, CAST(SUM(CASE WHEN event_type IS DISTINCT FROM prev THEN 1 ELSE 0 END) AS INTEGER) AS changes
    FROM (SELECT user_id, event_type, row_number() OVER w AS n, lag(event_type) OVER w AS prev FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) AS q GROUP BY user_id""")
def _(s, d):
    return _run(streams.latest_per_key(_events(s, d).select("user_id", "event_type", "ts", "event_id"), "user_id", "event_type", ["ts", "event_id"]), "update")


@add("st_append_delta", "SELECT c_mktsegment, COUNT(*) AS cnt FROM events JOIN customer ON user_id = c_custkey GROUP BY c_mktsegment")
def _(s, d):
    """Events arrive as a stream; the chart is answered from messages that each batch has brought up to date."""
    from dataclasses import replace

    from joindash.functions.semiring import count_ring
    from joindash.plans import calibrate as cal
    from joindash.plans.graph import JoinTree
    from joindash.plans.messages import Engine
    from joindash.plans.query import SpjaQuery, bind
    from joindash.plans.store import MessageStore

    g = tables.graph(s, d, ["events", "customer"])
    g.relations["events"].df = g.relations["events"].df.limit(0)
    e = Engine(s, JoinTree.from_graph(g), MessageStore(s, "memory"))
    b = bind(e.tree, SpjaQuery(count_ring(), ("c_mktsegment",)), "customer")
    cal.calibrate(e, b, "customer")
    stream = _events(s, d).select("event_id", F.col("user_id").alias("custkey"), "event_type", F.col("value").alias("event_value"))
    versions: list[int] = []
    streams.maintain(e, stream, "events", [b], versions).awaitTermination()
    return e.absorb(replace(b, versions=(("events", versions[-1]),), memo={}), "customer")


