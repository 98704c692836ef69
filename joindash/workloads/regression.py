"""The feature-augmentation experiment: 30 synthetic tables, ten on each of three keys."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from joindash.functions.semiring import Measure
from joindash.plans.augment import Augmenter, mixing_weights
from joindash.plans.graph import JoinGraph, JoinTree, Relation
from joindash.plans.messages import Engine
from joindash.plans.store import MessageStore
from joindash.runtime import new_path
from joindash.sources import tables

SALES_SQL = "SELECT l_suppkey AS suppkey, l_partkey AS partkey, year(l_shipdate) * 100 + month(l_shipdate) AS ship_month, l_quantity FROM lineitem"
TARGET_SQL = f"SELECT suppkey, ship_month, COUNT(*) AS transactions FROM ({SALES_SQL}) AS s GROUP BY suppkey, ship_month"
KEYS = {"supplier": "suppkey", "month": "ship_month", "part": "partkey"}
WEIGHTS = mixing_weights()
FEATURES = [
    Measure("quantity", "sales", "l_quantity", 0),
    *[Measure(f"in_{r.lower()}", "region_s", f"CASE WHEN r_name_s = '{r}' THEN 1 ELSE 0 END", 0) for r in ("ASIA", "EUROPE", "AMERICA", "AFRICA")],
    Measure("promo", "part", "CASE WHEN p_type = 'PROMO' THEN 1 ELSE 0 END", 0),
]
TARGET = Measure("transactions", "supplier_month", "transactions", 0)


def candidate_sql(dim: str, i: int, duck: bool) -> str:
    """A table (key, v): the key's mean target mixed with reproducible noise, in either dialect."""
    k, phi = KEYS[dim], WEIGHTS[i % len(WEIGHTS)]
    head = f"substr(md5(concat(CAST({k} AS VARCHAR(20)), ':{i}')), 1, 8)"
    noise = f"CAST(('0x' || {head}) AS BIGINT)" if duck else f"CAST(conv({head}, 16, 10) AS BIGINT)"
    mean = (
        f"SELECT s.{k} AS {k}, CAST(SUM(t.transactions) AS DOUBLE) / COUNT(*) AS yhat FROM ({SALES_SQL}) AS s "
        f"JOIN ({TARGET_SQL}) AS t ON s.suppkey = t.suppkey AND s.ship_month = t.ship_month GROUP BY s.{k}"
    )
    spread = f"SELECT ROUND(stddev_pop(yhat) * SQRT(12.0), 1) AS spread FROM ({mean}) AS m"
    value = f"{phi} * yhat + {round(1 - phi, 6)} * (CAST({noise} AS DOUBLE) / 4294967296.0) * spread"
    return f"SELECT {k}, ROUND(CAST({value} AS DOUBLE), 3) AS v FROM ({mean}) AS y CROSS JOIN ({spread}) AS z"


_kept: dict[tuple[str, str], Augmenter] = {}


def training_graph(spark: SparkSession, sf_dir: str) -> JoinGraph:
    tables.read_table(spark, sf_dir, "lineitem").createOrReplaceTempView("lineitem")
    g = tables.graph(spark, sf_dir, ["supplier", "nation_s", "region_s", "part"])
    ident = lambda sql: tables.table_ident(spark, sf_dir, sql, "lineitem")
    g.relations["sales"] = Relation("sales", spark.sql(SALES_SQL), (), SALES_SQL, ident=ident(SALES_SQL))
    g.relations["supplier_month"] = Relation("supplier_month", spark.sql(TARGET_SQL), (frozenset({"suppkey", "ship_month"}),), TARGET_SQL, ident=ident(TARGET_SQL))
    months = "SELECT DISTINCT year(l_shipdate) * 100 + month(l_shipdate) AS ship_month, year(l_shipdate) AS ship_year FROM lineitem"
    g.relations["months"] = Relation("months", spark.sql(months), (frozenset({"ship_month"}),), months, ident=ident(months))
    return JoinGraph(g.relations, g.complete | {("sales", r) for r in ("supplier", "part", "supplier_month", "months")})


def augmenter(spark: SparkSession, sf_dir: str) -> Augmenter:
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _kept:
        g = training_graph(spark, sf_dir)
        _kept[key] = Augmenter(Engine(spark, JoinTree.from_graph(g), MessageStore(spark, "memory")), FEATURES, TARGET)
        _kept[key].calibrate()
    return _kept[key]


def candidate(spark: SparkSession, sf_dir: str, dim: str, i: int) -> Relation:
    tables.read_table(spark, sf_dir, "lineitem").createOrReplaceTempView("lineitem")
    sql = candidate_sql(dim, i, False)
    return Relation(f"aug_{dim}_{i}", spark.sql(sql), (frozenset({KEYS[dim]}),), candidate_sql(dim, i, True), ident=tables.table_ident(spark, sf_dir, sql, "lineitem"))


def stored_candidates(spark: SparkSession, sf_dir: str, per_key: int = 10) -> list[Relation]:
    """The experiment's tables as files, as a user brings them; each key's mean target is computed once."""
    out = []
    for dim, k in KEYS.items():
        tables.read_table(spark, sf_dir, "lineitem").createOrReplaceTempView("lineitem")
        every = None
        for i in range(1, per_key + 1):
            part = candidate(spark, sf_dir, dim, i).df.select(k, F.lit(i).alias("i"), "v")
            every = part if every is None else every.unionByName(part)
        path = new_path(spark, "candidates")
        every.write.partitionBy("i").parquet(path)
        out += [Relation(f"aug_{dim}_{i}", spark.read.parquet(f"{path}/i={i}"), (frozenset({k}),), candidate_sql(dim, i, True)) for i in range(1, per_key + 1)]
    return out


def gram(spark: SparkSession, sf_dir: str, dim: str, i: int = 1) -> DataFrame:
    return augmenter(spark, sf_dir).gram(candidate(spark, sf_dir, dim, i))


def ranking(spark: SparkSession, sf_dir: str, per_key: int = 10) -> DataFrame:
    """All tables by R², rounded; the gain is over the model without them."""
    a = augmenter(spark, sf_dir)
    rows = a.rank(stored_candidates(spark, sf_dir, per_key))
    return spark.createDataFrame([(n, round(r, 6), round(g, 6)) for n, r, g, _ in rows], "augmentation string, r2 double, gain double")
