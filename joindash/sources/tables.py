"""The given tables as relations of the standing join graph."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from joindash.plans.graph import JoinGraph, Relation, content_ident
from joindash.runtime import snapshot

#: relation -> (table, [(expression, canonical name)], key, distinct)
LAYOUT: dict[str, tuple[str, list[tuple[str, str]], tuple[str, ...], bool]] = {
    "lineitem": ("lineitem", [("l_orderkey", "orderkey"), ("l_partkey", "partkey"), ("l_suppkey", "suppkey"), ("l_shipdate", "shipdate"), *[(c, c) for c in ("l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus")]], (), False),
    "orders": ("orders", [("o_orderkey", "orderkey"), ("o_custkey", "custkey"), ("o_orderdate", "orderdate"), *[(c, c) for c in ("o_orderstatus", "o_totalprice", "o_orderpriority")]], ("orderkey",), False),
    "customer": ("customer", [("c_custkey", "custkey"), ("c_nationkey", "nk_c"), *[(c, c) for c in ("c_name", "c_acctbal", "c_mktsegment")]], ("custkey",), False),
    "supplier": ("supplier", [("s_suppkey", "suppkey"), ("s_nationkey", "nk_s"), ("s_name", "s_name"), ("s_acctbal", "s_acctbal")], ("suppkey",), False),
    "part": ("part", [("p_partkey", "partkey"), *[(c, c) for c in ("p_name", "p_brand", "p_type", "p_size", "p_retailprice")]], ("partkey",), False),
    "nation_c": ("nation", [("n_nationkey", "nk_c"), ("n_name", "n_name_c"), ("n_regionkey", "rk_c")], ("nk_c",), False),
    "nation_s": ("nation", [("n_nationkey", "nk_s"), ("n_name", "n_name_s"), ("n_regionkey", "rk_s")], ("nk_s",), False),
    "region_c": ("region", [("r_regionkey", "rk_c"), ("r_name", "r_name_c")], ("rk_c",), False),
    "region_s": ("region", [("r_regionkey", "rk_s"), ("r_name", "r_name_s")], ("rk_s",), False),
    "ship_calendar": ("lineitem", [("l_shipdate", "shipdate"), ("year(l_shipdate) * 100 + month(l_shipdate)", "ship_month"), ("year(l_shipdate)", "ship_year")], ("shipdate",), True),
    "order_calendar": ("orders", [("o_orderdate", "orderdate"), ("year(o_orderdate) * 100 + month(o_orderdate)", "order_month"), ("year(o_orderdate)", "order_year")], ("orderdate",), True),
    "events": ("events", [("event_id", "event_id"), ("user_id", "custkey"), ("event_type", "event_type"), ("value", "event_value")], ("event_id",), False),
    "documents": ("documents", [("doc_id", "doc_id"), ("lang", "lang"), ("source", "source"), ("n_chars", "n_chars")], ("doc_id",), False),
    "labels": ("labels", [("doc_id", "doc_id"), ("quality", "quality"), ("toxic", "toxic")], ("doc_id",), False),
}
#: (many, one): every foreign key of the first resolves in the second
COMPLETE = [
    ("lineitem", "orders"), ("lineitem", "part"), ("lineitem", "supplier"), ("lineitem", "ship_calendar"), ("orders", "customer"), ("orders", "order_calendar"),
    ("customer", "nation_c"), ("supplier", "nation_s"), ("nation_c", "region_c"), ("nation_s", "region_s"), ("events", "customer"), ("labels", "documents"),
]


def read_table(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None, where: str | None = None) -> DataFrame:
    """A Parquet table with column pruning and filter pushdown."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if where:
        df = df.filter(F.expr(where))
    return df.select(*cols) if cols else df


def relation(spark: SparkSession, sf_dir: str, name: str) -> Relation:
    table, cols, key, distinct = LAYOUT[name]
    items = [e if e == a else f"{e} AS {a}" for e, a in cols]
    df = read_table(spark, sf_dir, table).selectExpr(*items)
    df = df.distinct() if distinct else df
    sql = f"SELECT {'DISTINCT ' if distinct else ''}{', '.join(items)} FROM {table}"
    return Relation(name, df, (frozenset(key),) if key else (), sql, ident=table_ident(spark, sf_dir, sql, table))


def table_ident(spark: SparkSession, sf_dir: str, sql: str, *names: str) -> str:
    """The contents of a SELECT over tables, by the tables' place and state."""
    return content_ident(sql, *[snapshot(spark, f"{sf_dir}/{n}.parquet") for n in names])


def graph(spark: SparkSession, sf_dir: str, names: list[str]) -> JoinGraph:
    return JoinGraph.of(*[relation(spark, sf_dir, n) for n in names], complete=[p for p in COMPLETE if p[0] in names and p[1] in names])


STAR = ["lineitem", "orders", "customer", "supplier", "part", "nation_c", "nation_s", "region_c", "region_s", "ship_calendar", "order_calendar"]


def verify_complete(g: JoinGraph) -> list[tuple[str, str]]:
    """The declared pairs whose keys do not all resolve (should be none)."""
    bad = []
    for many, one in sorted(g.complete):
        on = sorted(g.shared(many, one))
        if not g.relations[many].df.select(on).distinct().join(g.relations[one].df, on, "left_anti").isEmpty():
            bad.append((many, one))
    return bad


def read_as(spark: SparkSession, path: str, fmt: str, schema: T.StructType | str | None = None, **options) -> DataFrame:
    """Any file format with an explicit schema; JDBC by ``fmt='jdbc'`` and its options."""
    reader = spark.read.format(fmt).options(**options)
    if schema is not None and fmt != "jdbc":
        reader = reader.schema(schema)
    return reader.load(path) if path else reader.load()


def write_as(df: DataFrame, path: str, fmt: str, bucket_by: tuple[int, list[str]] | None = None, table: str | None = None, **options) -> None:
    """A file or a bucketed table; bucketed sides of one bucket count join without a shuffle."""
    writer = df.write.format(fmt).mode("overwrite").options(**options)
    if bucket_by:
        writer.bucketBy(bucket_by[0], *bucket_by[1]).sortBy(*bucket_by[1]).option("path", path).saveAsTable(table)
    else:
        writer.save(path)
