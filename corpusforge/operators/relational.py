"""Relational operators around the methods, thin over the Spark API; each is a query over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from corpusforge.engine import read


def join_broadcast(spark: SparkSession, sf: str) -> DataFrame:
    s, n, r = read(spark, sf, "supplier"), read(spark, sf, "nation"), read(spark, sf, "region")
    named = s.join(F.broadcast(n), s.s_nationkey == n.n_nationkey).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))  # nation and region have a fixed number of rows
    return named.groupBy("r_name", "n_name").agg(F.count(F.lit(1)).alias("suppliers"))


def join_smj(spark: SparkSession, sf: str) -> DataFrame:
    o, li = read(spark, sf, "orders", "o_orderkey", "o_orderpriority"), read(spark, sf, "lineitem", "l_orderkey", "l_quantity")
    return o.join(li.hint("merge"), o.o_orderkey == li.l_orderkey).groupBy("o_orderpriority").agg(F.round(F.sum("l_quantity"), 2).alias("quantity"), F.count(F.lit(1)).alias("n"))


def join_semi(spark: SparkSession, sf: str) -> DataFrame:
    d, la = read(spark, sf, "documents", "doc_id", "lang"), read(spark, sf, "labels", "doc_id")
    return d.join(la, "doc_id", "left_semi").groupBy("lang").agg(F.count(F.lit(1)).alias("n"))


def join_anti(spark: SparkSession, sf: str) -> DataFrame:
    c, o = read(spark, sf, "customer", "c_custkey", "c_nationkey"), read(spark, sf, "orders", "o_custkey", "o_orderpriority").filter("o_orderpriority = '1-URGENT'")
    return c.join(o, c.c_custkey == o.o_custkey, "left_anti").groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("n"))


def join_full(spark: SparkSession, sf: str) -> DataFrame:
    d, p = read(spark, sf, "documents", "doc_id", "lang"), read(spark, sf, "pages", "page_id", "url")
    linked = p.select(F.regexp_extract("url", r"/([0-9]+)$", 1).try_cast("long").alias("doc_id"), "page_id")
    both = d.join(linked, "doc_id", "full")
    return both.groupBy(F.col("lang").isNull().alias("no_doc"), F.col("page_id").isNull().alias("no_page")).agg(F.count(F.lit(1)).alias("n"))


def join_range(spark: SparkSession, sf: str, days: int = 30) -> DataFrame:
    """Orders with the order windows they lie in: an equi-join on binned days, then the exact condition."""
    o = read(spark, sf, "orders", "o_orderkey", "o_orderdate").withColumn("day", F.datediff("o_orderdate", F.lit("1992-01-01").cast("date")))
    windows = o.select((F.floor(F.col("day") / 90) * 90).alias("first")).distinct().withColumn("last", F.col("first") + days)
    bins = windows.withColumn("bin", F.explode(F.sequence(F.floor(F.col("first") / 30), F.floor(F.col("last") / 30))))
    hit = o.withColumn("bin", F.floor(F.col("day") / 30)).join(bins, "bin").filter((F.col("day") >= F.col("first")) & (F.col("day") <= F.col("last")))
    return hit.groupBy(F.col("first").cast("long").alias("first")).agg(F.count(F.lit(1)).alias("n"))


def join_asof(spark: SparkSession, sf: str) -> DataFrame:
    """For each error the user's last purchase before it: one ordered window, no join."""
    e = read(spark, sf, "events", "event_id", "user_id", "ts", "event_type").filter(F.col("event_type").isin("purchase", "error"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("purchase_id", F.coalesce(last, F.lit(-1))).filter("event_type = 'error'").select("event_id", "purchase_id")


def agg_rollup(spark: SparkSession, sf: str) -> DataFrame:
    return read(spark, sf, "documents", "lang", "source").rollup("lang", "source").agg(F.count(F.lit(1)).alias("n"))


def agg_cube(spark: SparkSession, sf: str) -> DataFrame:
    return read(spark, sf, "lineitem", "l_returnflag", "l_linestatus", "l_quantity").cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


def agg_grouping_sets(spark: SparkSession, sf: str) -> DataFrame:
    d = read(spark, sf, "documents", "lang", "source", "n_chars")
    return d.groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.sum("n_chars").alias("chars"))


def agg_distinct(spark: SparkSession, sf: str) -> DataFrame:
    from corpusforge.functions.text import exploded_lines

    return exploded_lines(read(spark, sf, "documents", "lang", "text")).groupBy("lang").agg(F.countDistinct("line").alias("n_lines"))


def agg_pivot(spark: SparkSession, sf: str) -> DataFrame:
    d = read(spark, sf, "documents", "source", "lang")
    return d.groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).agg(F.count(F.lit(1))).na.fill(0)


def win_rank(spark: SparkSession, sf: str) -> DataFrame:
    o = read(spark, sf, "orders", "o_orderkey", "o_custkey", "o_totalprice")
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return o.withColumn("rank", F.row_number().over(w)).filter("rank <= 2").select("o_custkey", "o_orderkey", "rank")


def win_frame(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("lang").orderBy("doc_id").rowsBetween(Window.unboundedPreceding, 0)
    return read(spark, sf, "documents", "doc_id", "lang", "n_chars").select("doc_id", F.sum("n_chars").over(w).alias("running"))


def win_range(spark: SparkSession, sf: str) -> DataFrame:
    e = read(spark, sf, "events", "event_id", "user_id", "ts")
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-86_400_000_000, 0)
    return e.select("event_id", F.count(F.lit(1)).over(w).alias("in_a_day"))


def topk_group(spark: SparkSession, sf: str, k: int = 3) -> DataFrame:
    w = Window.partitionBy("lang").orderBy(F.desc("n_chars"), "doc_id")
    return read(spark, sf, "documents", "doc_id", "lang", "n_chars").withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def set_intersect(spark: SparkSession, sf: str) -> DataFrame:
    d = read(spark, sf, "documents", "doc_id", "text").withColumn("h", F.md5("text"))
    return d.filter("doc_id % 2 = 0").select("h").intersect(d.filter("doc_id % 2 = 1").select("h"))


def set_except(spark: SparkSession, sf: str) -> DataFrame:
    d = read(spark, sf, "documents", "doc_id", "text").withColumn("h", F.md5("text"))
    return d.filter("doc_id % 2 = 0").select("h").exceptAll(d.filter("doc_id % 2 = 1").select("h"))


def json_props(spark: SparkSession, sf: str) -> DataFrame:
    e = read(spark, sf, "events", "event_type", "props")
    return e.groupBy("event_type").agg(F.count(F.get_json_object("props", "$")).alias("n_json"), F.count(F.lit(1)).alias("n"))


def date_ops(spark: SparkSession, sf: str) -> DataFrame:
    o = read(spark, sf, "orders", "o_orderdate")
    month = F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM")
    return o.groupBy(month.alias("month")).agg(F.count(F.lit(1)).alias("n"), F.max(F.dayofmonth("o_orderdate")).alias("last_day"))


QUERIES = {
    f.__name__: f
    for f in (join_broadcast, join_smj, join_semi, join_anti, join_full, join_range, join_asof, agg_rollup, agg_cube, agg_grouping_sets, agg_distinct, agg_pivot, win_rank, win_frame, win_range, topk_group, set_intersect, set_except, json_props, date_ops)
}

SQL = {
    "join_broadcast": "select r_name, n_name, count(*) as suppliers from supplier join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by all",
    "join_smj": "select o_orderpriority, round(sum(l_quantity), 2) as quantity, count(*) as n from orders join lineitem on o_orderkey = l_orderkey group by all",
    "join_semi": "select lang, count(*) as n from documents where doc_id in (select doc_id from labels) group by all",
    "join_anti": "select c_nationkey, count(*) as n from customer where not exists (select 1 from orders where o_custkey = c_custkey and o_orderpriority = '1-URGENT') group by all",
    "join_full": "with p as (select try_cast(regexp_extract(url, '/([0-9]+)$', 1) as bigint) as doc_id, page_id from pages) select lang is null as no_doc, page_id is null as no_page, count(*) as n from documents full join p using (doc_id) group by all",
    "join_range": "with o as (select date_diff('day', date '1992-01-01', cast(o_orderdate as date)) as day from orders), w as (select distinct cast(floor(day / 90) * 90 as bigint) as first from o) select first, count(*) as n from w join o on day >= first and day <= first + 30 group by all",
    "join_asof": "with e as (select event_id, user_id, ts, event_type from events where event_type in ('purchase', 'error')), x as (select *, last_value(case when event_type = 'purchase' then event_id end ignore nulls) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) as purchase_id from e) select event_id, coalesce(purchase_id, -1) as purchase_id from x where event_type = 'error'",
    "agg_rollup": "select lang, source, count(*) as n from documents group by rollup (lang, source)",
    "agg_cube": "select l_returnflag, l_linestatus, count(*) as n, round(sum(l_quantity), 2) as quantity from lineitem group by cube (l_returnflag, l_linestatus)",
    "agg_grouping_sets": "select lang, source, cast(sum(n_chars) as bigint) as chars from documents group by grouping sets ((lang), (source), ())",
    "agg_distinct": "select lang, count(distinct line) as n_lines from (select lang, trim(unnest(string_split(text, chr(10)))) as line from documents) where line <> '' group by all",
    "agg_pivot": "select source, count(*) filter (lang = 'de') as de, count(*) filter (lang = 'en') as en, count(*) filter (lang = 'es') as es, count(*) filter (lang = 'fr') as fr from documents group by all",
    "win_rank": "select o_custkey, o_orderkey, cast(rank as integer) as rank from (select *, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as rank from orders) where rank <= 2",
    "win_frame": "select doc_id, cast(sum(n_chars) over (partition by lang order by doc_id rows unbounded preceding) as bigint) as running from documents",
    "win_range": "select event_id, count(*) over (partition by user_id order by ts range between interval 1 day preceding and current row) as in_a_day from events",
    "topk_group": "select doc_id, lang, n_chars, cast(rank as integer) as rank from (select doc_id, lang, n_chars, row_number() over (partition by lang order by n_chars desc, doc_id) as rank from documents) where rank <= 3",
    "set_intersect": "select md5(text) as h from documents where doc_id % 2 = 0 intersect select md5(text) from documents where doc_id % 2 = 1",
    "set_except": "select md5(text) as h from documents where doc_id % 2 = 0 except all select md5(text) from documents where doc_id % 2 = 1",
    "json_props": "select event_type, count(case when json_valid(props) then 1 end) as n_json, count(*) as n from events group by all",
    "date_ops": "select strftime(date_trunc('month', o_orderdate), '%Y-%m') as month, count(*) as n, cast(max(day(o_orderdate)) as integer) as last_day from orders group by all",
}
