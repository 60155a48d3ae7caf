"""Relational operators around the methods, on the given tables."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.registry import commutative_print
from ..operators import relational as R
from ..plans.store import Store
from . import sql as Q
from .tables import table


def asof(spark, d):
    orders = table(spark, d, "orders", F.col("o_custkey").alias("k"), "o_orderkey", "o_orderdate")
    acts = table(spark, d, "events", F.col("user_id").alias("k"), "event_id", "ts").groupBy("k", "ts").agg(F.max("event_id").alias("event_id"))
    return R.asof_join(orders, acts, "k", "o_orderdate", "ts", "event_id").select("k", "o_orderkey", "event_id")


def range_join(spark, d):
    bands = table(spark, d, "nation", "n_nationkey").select("n_nationkey", (F.col("n_nationkey") * 20000).cast("long").alias("lo"), (F.col("n_nationkey") * 20000 + 30000).cast("long").alias("hi"))
    price = table(spark, d, "orders", "o_orderkey", F.floor("o_totalprice").alias("p"))
    return R.range_join(price, bands, "p", "lo", "hi", 10000).groupBy("n_nationkey").agg(F.count("*").alias("n"), F.min("p").alias("least"), F.max("p").alias("most"))


def rollup(spark, d):
    docs = table(spark, d, "documents", "source", "lang", "n_chars")
    return docs.rollup("source", "lang").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


def cube(spark, d):
    docs = table(spark, d, "documents", "source", "lang", "n_chars")
    return docs.cube("lang", "source").agg(F.count("*").alias("n"), F.max("n_chars").alias("longest"))


def grouping_sets(spark, d):
    docs = table(spark, d, "documents", "source", "lang", "n_chars")
    return docs.groupingSets([[F.col("source")], [F.col("lang")], []], "source", "lang").agg(F.count("*").alias("n"), F.grouping_id().alias("gid"))


def set_ops(spark, d):
    """(customer, brand) pairs of open lines and of finished ones."""
    from . import engine

    a, b = (df.select("subject", "component") for df in engine._trade_sets(spark, d))
    parts = {"union": a.union(b).distinct(), "intersect": a.intersect(b), "except": a.exceptAll(b)}
    out = None
    for name, df in parts.items():
        row = df.agg(F.count("*").alias("n"), F.sum("subject").alias("s")).select(F.lit(name).alias("op"), "n", "s")
        out = row if out is None else out.unionByName(row)
    return out


def topk(spark, d):
    part = table(spark, d, "part", "p_partkey", "p_brand", "p_retailprice")
    return R.top_k(part, "p_brand", [F.desc("p_retailprice"), F.col("p_partkey")], 3)


def window_frames(spark, d):
    w = Window.partitionBy("l_suppkey").orderBy("l_shipdate", "l_orderkey", "l_linenumber")
    item = table(spark, d, "lineitem", "l_suppkey", "l_orderkey", "l_linenumber", "l_shipdate", "l_quantity")
    return item.select("l_orderkey", "l_linenumber", F.row_number().over(w).alias("rn"), F.sum("l_quantity").over(w.rowsBetween(-2, 0)).alias("q3"), F.lag("l_quantity").over(w).alias("prev"), F.ntile(4).over(w).alias("quarter"))


def json_props(spark, d):
    e = table(spark, d, "events", "event_type", "props")
    return e.groupBy("event_type").agg(F.count("*").alias("n"), F.count_if(F.get_json_object("props", "$").isNotNull()).alias("n_json"))


def array_stats(spark, d):
    e = table(spark, d, "embeddings", "vec_id", "embedding", "label")
    return e.select("vec_id", "label", F.size("embedding").alias("dims"), F.round(F.array_max("embedding"), 6).cast("double").alias("top"), F.size(F.filter("embedding", lambda x: x > 0)).alias("n_pos"))


def dates(spark, d):
    o = table(spark, d, "orders", "o_orderdate", "o_totalprice")
    return o.groupBy(F.date_trunc("month", F.col("o_orderdate").cast("timestamp")).cast("date").alias("month")).agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


def label_histogram(spark, d):
    line = table(spark, d, "lineitem", "l_returnflag", "l_linestatus", "l_quantity", "l_discount")
    return line.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.avg("l_discount"), 6).alias("mean_discount"), F.round(F.var_samp("l_quantity"), 4).alias("var_q"), F.count_distinct("l_quantity").alias("n_q"))


def maps(spark, d):
    """Languages of a source as a map, beside the map of all: how many it has, English ones, and its share of the language it has most of."""
    docs = table(spark, d, "documents", "source", "lang").where("lang is not null and source is not null")
    counts = docs.groupBy("source", "lang").agg(F.count("*").alias("n"))
    hist = lambda df, *by: df.groupBy(*by).agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("lang", "n")))).alias("m"))  # noqa: E731  a handful of languages
    every = hist(docs.groupBy("lang").agg(F.count("*").alias("n"))).withColumnRenamed("m", "all")
    both = hist(counts, "source").crossJoin(F.broadcast(every))  # one row
    share = F.map_zip_with("m", "all", lambda k, a, b: F.coalesce(a, F.lit(0)) / b)
    return both.select("source", F.size("m").cast("long").alias("n_langs"), F.coalesce(F.try_element_at("m", F.lit("en")), F.lit(0)).alias("n_en"), F.round(F.array_max(F.map_values(share)), 6).alias("top_share"))


def levenshtein(spark, d):
    part = table(spark, d, "part", "p_partkey", "p_name", "p_type")
    return part.select("p_partkey", F.levenshtein("p_name", F.lower("p_type")).cast("long").alias("distance"), F.substring_index("p_name", " ", 1).alias("first_word"))


def formats(spark, d):
    """Suppliers written and read back as CSV, JSON and ORC, and as Parquet by nation."""
    store = Store(spark, "formats")
    rows = table(spark, d, "supplier", "s_suppkey", "s_name", "s_nationkey", "s_acctbal")
    out = None
    for kind in ("csv", "json", "orc", "parquet"):
        writer = rows.write.partitionBy("s_nationkey") if kind == "parquet" else rows.write
        writer.format(kind).save(store.path(kind))
        back = spark.read.schema(rows.schema).format(kind).load(store.path(kind)).select(rows.columns)
        row = back.agg(F.lit(kind).alias("format"), F.count("*").alias("n"), F.sum("s_nationkey").alias("nations"), F.round(F.sum("s_acctbal"), 2).alias("balance"), F.min("s_name").alias("first"))
        out = row if out is None else out.unionByName(row)
    return out


def grouped_udf(spark, d):
    """Class prints by a grouped-aggregate function in Python, a document's lines at a time; the built-in sum says the same."""
    from ..operators import extract as E
    from ..operators import units as U

    lines = U.lines(table(spark, d, "documents", "doc_id", "text"), F.col("doc_id").alias("class_id"))
    functions = E.functions_of(lines).select("class_id", "own")
    return functions.groupBy("class_id").agg(commutative_print()("own").alias("print"))


def star_join(spark, d):
    c = table(spark, d, "customer", "c_custkey", F.col("c_nationkey").alias("n_nationkey"))
    n = table(spark, d, "nation").join(F.broadcast(table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")  # 25 and 5 rows by definition
    o = table(spark, d, "orders", F.col("o_custkey").alias("c_custkey"), "o_totalprice")
    return o.join(c, "c_custkey").join(F.broadcast(n), "n_nationkey").groupBy("r_name", "n_name").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


QUERIES = {
    "rel_asof": asof, "rel_range_join": range_join, "rel_rollup": rollup, "rel_cube": cube, "rel_grouping_sets": grouping_sets, "rel_set_ops": set_ops, "rel_topk": topk,
    "rel_window_frames": window_frames, "rel_json": json_props, "rel_arrays": array_stats, "rel_dates": dates, "rel_label_histogram": label_histogram, "rel_star_join": star_join,
    "rel_maps": maps, "rel_levenshtein": levenshtein, "rel_formats": formats, "rel_grouped_udf": grouped_udf,
}
ORACLE = {
    "rel_asof": "with a as (select user_id as k, ts, max(event_id) as event_id from events group by all) select o_custkey as k, o_orderkey, event_id from orders asof left join a on o_custkey = k and o_orderdate >= ts",
    "rel_range_join": "select n_nationkey, count(*) as n, cast(min(p) as bigint) as least, cast(max(p) as bigint) as most from (select cast(floor(o_totalprice) as bigint) as p from orders) join nation on p >= n_nationkey * 20000 and p < n_nationkey * 20000 + 30000 group by 1",
    "rel_rollup": "select source, lang, count(*) as n, cast(sum(n_chars) as bigint) as chars from documents group by rollup (source, lang)",
    "rel_cube": "select lang, source, count(*) as n, max(n_chars) as longest from documents group by cube (lang, source)",
    "rel_grouping_sets": "select source, lang, count(*) as n, grouping(source, lang) as gid from documents group by grouping sets ((source), (lang), ())",
    "rel_set_ops": "with tt as (select distinct o_custkey as k, p_brand, l_linestatus as st from lineitem join part on p_partkey = l_partkey join orders on o_orderkey = l_orderkey), a as (select k, p_brand from tt where st = 'O'), b as (select k, p_brand from tt where st = 'F') select op, count(*) as n, cast(sum(k) as bigint) as s from (select 'union' as op, k from (select * from a union select * from b) union all select 'intersect', k from (select * from a intersect select * from b) union all select 'except', k from (select * from a except select * from b)) group by op",
    "rel_topk": "select *, row_number() over (partition by p_brand order by p_retailprice desc, p_partkey) as place from (select p_partkey, p_brand, p_retailprice from part) qualify place <= 3",
    "rel_window_frames": "select l_orderkey, l_linenumber, row_number() over w as rn, sum(l_quantity) over (w rows between 2 preceding and current row) as q3, lag(l_quantity) over w as prev, ntile(4) over w as quarter from lineitem window w as (partition by l_suppkey order by l_shipdate, l_orderkey, l_linenumber)",
    "rel_json": "select event_type, count(*) as n, count(case when json_valid(props) then 1 end) as n_json from events group by 1",
    "rel_arrays": "select vec_id, label, len(embedding) as dims, cast(round(list_max(embedding), 6) as double) as top, len(list_filter(embedding, lambda x: x > 0)) as n_pos from embeddings",
    "rel_dates": "select cast(date_trunc('month', o_orderdate) as date) as month, count(*) as n, round(sum(o_totalprice), 2) as total from orders group by 1",
    "rel_label_histogram": "select l_returnflag, l_linestatus, count(*) as n, round(avg(l_discount), 6) as mean_discount, round(var_samp(l_quantity), 4) as var_q, count(distinct l_quantity) as n_q from lineitem group by all",
    "rel_maps": "with c as (select source, lang, count(*) as n from documents where lang is not null and source is not null group by all), t as (select lang, sum(n) as total from c group by all) select source, count(*) as n_langs, cast(coalesce(sum(case when lang = 'en' then n end), 0) as bigint) as n_en, round(max(n / total), 6) as top_share from c join t using (lang) group by source",
    "rel_levenshtein": "select p_partkey, levenshtein(p_name, lower(p_type)) as distance, string_split(p_name, ' ')[1] as first_word from part",
    "rel_formats": "select f as format, count(*) as n, cast(sum(s_nationkey) as bigint) as nations, round(sum(s_acctbal), 2) as balance, min(s_name) as first from supplier cross join (select unnest(['csv', 'json', 'orc', 'parquet']) as f) group by f",
    "rel_grouped_udf": f"with {Q.LINES} select doc_id as class_id, {Q.mod('sum(own)')} as print from (select doc_id, {Q.bag('lower(line)')} as own from lines) group by doc_id",
    "rel_star_join": "select r_name, n_name, count(*) as n, round(sum(o_totalprice), 2) as total from orders join customer on c_custkey = o_custkey join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey group by all",
}
