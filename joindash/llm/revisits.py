"""Operator 8 – archive records: resolving not-modified revisits.

A revisit says that a page had not changed when it was asked for again.  Each revisit takes the latest
earlier full response of its canonical URL (an as-of join), the validators of both are compared, and
the headers that a 304 answer may renew are laid over the stored ones.

The as-of join is a range sort by URL and time, a running "last full response" inside each sorted
partition, and one carried record per partition for URLs that cross its border, so a URL with a third
of all records is spread like any other.  Only the columns named in ``RECORD`` are read and sorted.

Defined results: a null URL or time, or no earlier full response, gives ``missing``; records at the same
time are not earlier than each other, and the greatest id wins among full ones of one time; repeated rows
each get the same result; empty and very long texts are values like others; an empty table gives an
empty result; other input columns, whatever their names, stay out.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from joindash.llm.common import table, without, written

#: Headers that a not-modified answer may renew.
PERMITTED = ["cache-control", "content-location", "date", "etag", "expires", "last-modified", "vary"]
SPLIT = r"^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//([^/?#]*)([^?#]*)(?:\?([^#]*))?"


def canonical_url(url: Column) -> Column:
    """Host without case, ``www.`` and default port; path without its last slash; sorted query without
    tracking parameters; no scheme and no fragment.  What is no absolute URL stays as it is."""
    host = F.regexp_replace(F.regexp_replace(F.lower(F.regexp_extract(url, SPLIT, 1)), "^www\\.", ""), ":(80|443)$", "")
    path = F.regexp_replace(F.regexp_extract(url, SPLIT, 2), "/+$", "")
    args = F.array_sort(F.filter(F.split(F.regexp_extract(url, SPLIT, 3), "&"), lambda x: (x != "") & ~x.startswith("utm_")))
    query = F.when(F.size(args) > 0, F.concat(F.lit("?"), F.array_join(args, "&"))).otherwise("")
    return F.when(url.rlike(SPLIT), F.concat(host, path, query)).otherwise(url)


def header(headers: Column, name: str) -> Column:
    """A header's value, by its lower-case name; the last entry wins."""
    return F.try_element_at(F.filter(F.map_entries(headers), lambda e: F.lower(e["key"]) == name), F.lit(-1))["value"]


def merged_headers(stored: Column, fresh: Column) -> Column:
    """Stored headers with the permitted fresh ones laid over them; names in lower case."""
    low = lambda m: F.transform(F.coalesce(F.map_entries(m), F.expr("cast(array() as array<struct<key:string,value:string>>)")), lambda e: F.struct(F.lower(e["key"]).alias("key"), e["value"].alias("value")))
    new = F.filter(low(fresh), lambda e: e["key"].isin(PERMITTED))
    old = F.filter(low(stored), lambda e: ~F.exists(new, lambda n: n["key"] == e["key"]))
    both = F.array_sort(F.concat(old, new))
    # one entry per name: the last of equal names in sorted order
    last = F.filter(both, lambda e, i: ~F.coalesce(F.get(both, i + 1)["key"] == e["key"], F.lit(False)))
    return F.map_from_entries(last)


def weak(tag: Column) -> Column:
    return F.regexp_replace(F.trim(tag), "^W/", "")


RECORD = ["record_id", "url", "captured_at", "kind", "status", "headers", "digest"]
OUT = ["canonical_url", "full_id", "outcome", "resolved_headers", "resolved_status", "full_digest"]


def resolve_revisits(records: DataFrame) -> DataFrame:
    """Revisit records with the full response they stand for.

    ``records``: record_id, url, captured_at, kind ('response' or 'revisit'), status, headers
    map<string,string>, digest (of the payload, null where unknown).  Adds canonical_url, full_id,
    outcome ('resolved', 'unverified', 'mismatch', 'missing'), resolved_headers, resolved_status and
    full_digest.  A mismatch keeps full_id but resolves nothing.  Other columns, payloads among them, are
    neither read nor returned: join what is wanted by record_id.
    """
    spark = records.sparkSession
    rest = records.select(*RECORD)
    full = (F.col("kind") == "response") & (F.col("status") == 200) & F.col("captured_at").isNotNull()
    facts = F.struct(F.col("record_id").alias("id"), "status", "headers", "digest")
    rows = rest.withColumn("canonical_url", canonical_url(F.col("url"))).filter(F.col("kind").isin("response", "revisit"))
    rows = rows.withColumn("__jd_full", F.when(full, facts)).filter((F.col("kind") == "revisit") | F.col("__jd_full").isNotNull())
    keys = ["canonical_url", "captured_at", F.col("__jd_full").isNotNull(), "record_id", "__jd_tie"]
    placed = written(
        rows.withColumn("__jd_tie", F.monotonically_increasing_id())
        .repartitionByRange(*keys)
        .sortWithinPartitions(*keys)
        .drop("__jd_tie")
        .withColumn("__jd_part", F.spark_partition_id())
        .withColumn("__jd_row", F.monotonically_increasing_id())
    )
    # A (partition, URL) group is never larger than a sorted partition.
    before = Window.partitionBy("__jd_part", "canonical_url").orderBy("__jd_row").rowsBetween(Window.unboundedPreceding, -1)
    run = placed.withColumn("__jd_near", F.last("__jd_full", ignorenulls=True).over(before))
    ends = placed.groupBy("__jd_part").agg(
        F.min_by("canonical_url", "__jd_row").alias("first"),
        F.max_by("canonical_url", "__jd_row").alias("last"),
        F.max_by(F.struct("canonical_url", "__jd_full"), F.when(F.col("__jd_full").isNotNull(), F.col("__jd_row"))).alias("full"),
    )
    carried, held = [], None  # (URL, facts) that reaches into the next partition
    for e in sorted(ends.collect(), key=lambda e: e["__jd_part"]):  # one row per partition
        carried.append((e["__jd_part"], *(held or (None, None))))
        if e["full"] is not None and e["full"]["canonical_url"] is not None and e["full"]["canonical_url"] == e["last"]:
            held = (e["last"], e["full"]["__jd_full"])
        elif held and held[0] != e["last"]:
            held = None
    schema = f"__jd_part int, __jd_url string, __jd_carry {placed.schema['__jd_full'].dataType.simpleString()}"
    carry = spark.createDataFrame(carried, schema)
    revisits = run.filter("kind = 'revisit'").join(F.broadcast(carry), "__jd_part")
    known = F.col("canonical_url").isNotNull() & F.col("captured_at").isNotNull()
    far = F.when(F.col("canonical_url") == F.col("__jd_url"), F.col("__jd_carry"))
    out = revisits.withColumn("__jd_hit", F.when(known, F.coalesce("__jd_near", far)))
    hit, mine = F.col("__jd_hit"), F.col("headers")
    pairs = [
        (weak(header(mine, "etag")), weak(header(hit["headers"], "etag"))),
        (header(mine, "last-modified"), header(hit["headers"], "last-modified")),
        (F.col("digest"), hit["digest"]),
    ]
    same = F.array(*[a == b for a, b in pairs])  # null where one side is missing
    outcome = (
        F.when(hit.isNull(), "missing")
        .when(F.exists(same, lambda x: F.coalesce(~x, F.lit(False))), "mismatch")
        .when(F.exists(same, lambda x: F.coalesce(x, F.lit(False))), "resolved")
        .otherwise("unverified")
    )
    out = out.withColumn("outcome", outcome).withColumn("full_id", hit["id"])
    good = F.col("outcome").isin("resolved", "unverified")
    return out.select(
        *rest.columns,
        "canonical_url",
        "full_id",
        "outcome",
        F.when(good, merged_headers(hit["headers"], mine)).alias("resolved_headers"),
        F.when(good, hit["status"]).alias("resolved_status"),
        F.when(good, hit["digest"]).alias("full_digest"),
    )


def with_payload(resolved: DataFrame, records: DataFrame, payload: str = "payload") -> DataFrame:
    """Resolved revisits with the payload of their full response; ``record_id`` is unique among these."""
    stored = records.filter("kind = 'response'").select(F.col("record_id").alias("full_id"), F.col(payload).alias("__jd_payload"))
    keep = F.when(F.col("full_digest").isNotNull() | F.col("outcome").isin("resolved", "unverified"), F.col("__jd_payload"))
    return without(resolved, [payload]).join(stored, "full_id", "left").withColumn(payload, keep).drop("__jd_payload")


def page_records(pages: DataFrame) -> DataFrame:
    """A crawl log over the page table: each page is fetched at its id (one in seven had no full answer),
    and asked for again 1,000 later; one answer in ten carries another page's validator."""
    tag = F.concat(F.lit('"'), F.md5(F.coalesce(F.col("html"), F.lit("")).cast("binary")), F.lit('"'))
    other = F.concat(F.lit('"'), F.md5(F.coalesce(F.col("url"), F.lit("")).cast("binary")), F.lit('"'))
    entry = lambda **h: F.create_map(*[x for k, v in h.items() for x in (F.lit(k.replace("_", "-")), v)])
    pid = F.col("page_id")
    first = pages.filter((pid % 7 != 0) | pid.isNull()).select(
        (pid * 2).alias("record_id"), "url", pid.alias("captured_at"), F.lit("response").alias("kind"), F.lit(200).alias("status"),
        entry(ETag=tag, Content_Type=F.lit("text/html"), Cache_Control=F.lit("max-age=60")).alias("headers"), F.md5(F.col("html").cast("binary")).alias("digest"),
    )
    again = pages.select(
        (pid * 2 + 1).alias("record_id"), "url", (pid + 1000).alias("captured_at"), F.lit("revisit").alias("kind"), F.lit(304).alias("status"),
        entry(etag=F.when(pid % 10 == 3, other).otherwise(F.concat(F.lit("W/"), tag)), content_type=F.lit("text/plain"), cache_control=F.concat(F.lit("max-age="), pid.cast("string"))).alias("headers"),
        F.lit(None).cast("string").alias("digest"),
    )
    return first.unionByName(again)


def op8_revisit_resolution(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = resolve_revisits(page_records(table(spark, sf_dir, "pages").select("page_id", "url", "html")))
    got = lambda name: header(F.col("resolved_headers"), name)
    return found.select(
        F.expr("(record_id - 1) div 2").alias("page_id"),
        "canonical_url",
        F.expr("full_id div 2").alias("full_page_id"),
        "outcome",
        got("etag").alias("etag"),
        got("content-type").alias("content_type"),
        got("cache-control").alias("cache_control"),
        "full_digest",
    )


_CANON = r"""
  case when regexp_matches(url, '^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//([^/?#]*)([^?#]*)(?:\?([^#]*))?') then
    regexp_replace(regexp_replace(lower(regexp_extract(url, '^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//([^/?#]*)', 1)), '^www\.', ''), ':(80|443)$', '')
    || regexp_replace(regexp_extract(url, '^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//[^/?#]*([^?#]*)', 1), '/+$', '')
    || case when len(args) > 0 then '?' || array_to_string(list_sort(args), '&') else '' end
  else url end"""
ORACLE_SQL = {
    "op8_revisit_resolution": rf"""
with parsed as (
  select page_id, url, html, list_filter(string_split(regexp_extract(url, '^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//[^/?#]*[^?#]*\?([^#]*)', 1), '&'),
         lambda x: x <> '' and not starts_with(x, 'utm_')) as args from pages),
canon as (select page_id, html, url, {_CANON} as canonical_url from parsed),
full_r as (select canonical_url as c, page_id as at, max(page_id) as f, any_value(md5(html)) as d from canon where page_id % 7 <> 0 group by 1, 2),
asked as (select page_id, canonical_url, page_id + 1000 as at,
          '"' || case when page_id % 10 = 3 then md5(url) else md5(html) end || '"' as tag from canon),
met as (select a.*, r.f, r.d from asked a asof left join full_r r on a.canonical_url = r.c and a.at > r.at)
select page_id, canonical_url, f as full_page_id,
  case when f is null then 'missing' when tag = '"' || d || '"' then 'resolved' else 'mismatch' end as outcome,
  case when tag = '"' || d || '"' then case when page_id % 10 = 3 then '' else 'W/' end || tag end as etag,
  case when tag = '"' || d || '"' then 'text/html' end as content_type,
  case when tag = '"' || d || '"' then 'max-age=' || page_id end as cache_control,
  case when tag = '"' || d || '"' then d end as full_digest
from met"""
}
QUERIES = {"op8_revisit_resolution": op8_revisit_resolution}
