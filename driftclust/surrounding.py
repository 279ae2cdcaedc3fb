"""Operators around the methods: joins, aggregates, windows, sets, functions.

Where both engines read the same text, one SQL string serves as query and oracle
alike would prove little, so the Spark side is written with DataFrame operators.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .sources.tables import table as _table

_QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_SQL: dict[str, str] = {}


def query(sql: str):
    def add(f):
        _QUERIES[f.__name__] = f
        _SQL[f.__name__] = sql
        return f

    return add


@query("select c_mktsegment, count(*) as n, round(sum(o_totalprice), 2) as total from customer join orders on c_custkey = o_custkey group by 1")
def join_equi(spark, d):
    o, c = _table(spark, d, "orders"), _table(spark, d, "customer")
    return o.join(c, o.o_custkey == c.c_custkey).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query("select doc_id, quality, toxic, n_chars from documents join labels using (doc_id)")
def join_sort_merge(spark, d):
    docs, labels = _table(spark, d, "documents").select("doc_id", "n_chars"), _table(spark, d, "labels")
    return docs.hint("merge").join(labels, "doc_id").select("doc_id", "quality", "toxic", "n_chars")


@query("select a.n_nationkey as i, b.n_nationkey as j from nation a join nation b on a.n_nationkey < b.n_nationkey")
def join_theta(spark, d):
    n = _table(spark, d, "nation").select("n_nationkey")
    a, b = n.alias("a"), n.alias("b")
    return a.join(b, F.col("a.n_nationkey") < F.col("b.n_nationkey")).select(F.col("a.n_nationkey").alias("i"), F.col("b.n_nationkey").alias("j"))


@query("select a.event_id as a_id, count(*) as near from events a join events b on a.event_type = b.event_type and a.user_id = b.user_id and a.event_id <> b.event_id and b.ts between a.ts - interval 6 hour and a.ts + interval 6 hour group by 1")
def join_interval(spark, d):
    """Range join: time is cut into buckets of the range's width, each row looks
    into its own bucket and the two beside it."""
    e = _table(spark, d, "events").select("event_id", "event_type", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    width = 6 * 3600 * 1_000_000
    a = e.select(F.col("event_id").alias("a_id"), "event_type", "user_id", F.col("t").alias("ta"), F.explode(F.sequence(F.floor(F.col("t") / width) - 1, F.floor(F.col("t") / width) + 1)).alias("b"))
    b = e.select(F.col("event_id").alias("b_id"), "event_type", "user_id", F.col("t").alias("tb"), F.floor(F.col("t") / width).alias("b"))
    return a.join(b, ["event_type", "user_id", "b"]).where((F.col("a_id") != F.col("b_id")) & (F.abs(F.col("ta") - F.col("tb")) <= width)).groupBy("a_id").agg(F.count("*").alias("near"))


@query("select e.event_id as obj_id, (select max(v.event_id) from events v where v.event_id % 100 = 0 and v.event_id <= e.event_id) as version from events e")
def join_as_of(spark, d):
    """Latest version at or before each row, by ranges of keys."""
    e = _table(spark, d, "events").select(F.col("event_id").alias("t"))
    both = e.withColumn("version", F.when(F.col("t") % 100 == 0, F.col("t"))).withColumn("b", F.floor(F.col("t") / 1000))
    seen = F.last("version", ignorenulls=True).over(Window.partitionBy("b").orderBy("t").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    tops = both.groupBy("b").agg(F.max("version").alias("top")).withColumn("before", F.last("top", ignorenulls=True).over(Window.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)))
    return both.withColumn("seen", seen).join(F.broadcast(tops), "b").select(F.col("t").alias("obj_id"), F.coalesce("seen", "before").alias("version"))


@query("select doc_id from documents where doc_id in (select doc_id from labels)")
def join_semi(spark, d):
    return _table(spark, d, "documents").select("doc_id").join(_table(spark, d, "labels"), "doc_id", "left_semi")


@query("select doc_id from documents where doc_id not in (select doc_id from labels)")
def join_anti(spark, d):
    return _table(spark, d, "documents").select("doc_id").join(_table(spark, d, "labels"), "doc_id", "left_anti")


@query("select event_type, cast(date_diff('day', date '2024-01-01', cast(ts as date)) as integer) as day, count(*) as n from events group by cube (event_type, day)")
def agg_cube(spark, d):
    e = _table(spark, d, "events").withColumn("day", F.datediff("ts", F.lit("2024-01-01")))
    return e.cube("event_type", "day").agg(F.count("*").alias("n"))


@query("select l_returnflag, l_linestatus, count(*) as n from lineitem group by rollup (l_returnflag, l_linestatus)")
def agg_rollup(spark, d):
    return _table(spark, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("select event_type, count(distinct user_id) as users from events group by 1")
def agg_distinct(spark, d):
    return _table(spark, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@query("select l_returnflag, round(avg(l_quantity), 6) as m, round(var_pop(l_quantity), 6) as v, round(covar_pop(l_quantity, l_extendedprice), 2) as c, round(corr(l_quantity, l_extendedprice), 6) as r, quantile_cont(l_quantity, 0.5) as med from lineitem group by 1")
def agg_statistics(spark, d):
    q, p = F.col("l_quantity"), F.col("l_extendedprice")
    return _table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.avg(q), 6).alias("m"), F.round(F.var_pop(q), 6).alias("v"), F.round(F.covar_pop(q, p), 2).alias("c"), F.round(F.corr(q, p), 6).alias("r"), F.percentile(q, 0.5).alias("med"))


@query("select c_nationkey, count(*) as n from customer group by 1 having count(*) < 60")
def filter_small_clusters(spark, d):
    return _table(spark, d, "customer").groupBy("c_nationkey").agg(F.count("*").alias("n")).where("n < 60")


@query("select l_returnflag, count(*) filter (where l_linestatus = 'F') as f, count(*) filter (where l_linestatus = 'O') as o from lineitem group by 1")
def pivot_status(spark, d):
    p = _table(spark, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count()
    return p.select("l_returnflag", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))


def _ranked(o):
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
    return o.select("o_orderkey", *[f().over(w).cast("long").alias(n) for f, n in ((F.row_number, "rn"), (F.rank, "rk"), (F.dense_rank, "dr"))], F.ntile(4).over(w).cast("long").alias("nt"))


@query("select o_orderkey, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, ntile(4) over w as nt from (select * from orders where o_orderkey < 2000) window w as (partition by o_custkey order by o_totalprice, o_orderkey)")
def win_ranking(spark, d):
    return _ranked(_table(spark, d, "orders").where("o_orderkey < 2000"))


@query("select o_orderkey, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, ntile(4) over w as nt from orders window w as (partition by o_custkey order by o_totalprice, o_orderkey)")
def win_ranking_all(spark, d):
    return _ranked(_table(spark, d, "orders"))


@query("select event_id, round(avg(value) over (partition by user_id order by event_id rows between 4 preceding and current row), 6) as moving, lag(event_id) over (partition by user_id order by event_id) as before, max(value) over (partition by user_id order by event_id rows unbounded preceding) as top from events")
def win_frames(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id")
    e = _table(spark, d, "events")
    return e.select("event_id", F.round(F.avg("value").over(w.rowsBetween(-4, 0)), 6).alias("moving"), F.lag("event_id").over(w).alias("before"), F.max("value").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("top"))


@query("select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 25")
def topk_orders(spark, d):
    return _table(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25)


@query("(select o_custkey as k from orders intersect select c_custkey from customer where c_acctbal > 0) except select c_custkey from customer where c_nationkey < 5")
def set_operations(spark, d):
    o, c = _table(spark, d, "orders").select(F.col("o_custkey").alias("k")), _table(spark, d, "customer")
    return o.intersect(c.where("c_acctbal > 0").select("c_custkey")).exceptAll(c.where("c_nationkey < 5").select("c_custkey"))


@query("select vec_id, round(list_sum(list_transform(embedding, lambda v: v::double * v::double)), 5) as norm, list_position(embedding, list_max(embedding)) as place from embeddings")
def array_functions(spark, d):
    e = _table(spark, d, "embeddings")
    return e.select("vec_id", F.round(F.aggregate(F.transform("embedding", lambda v: v.cast("double") * v.cast("double")), F.lit(0.0), lambda a, v: a + v), 5).alias("norm"), F.array_position("embedding", F.array_max("embedding")).cast("int").alias("place"))


@query("select c.a as neuron, count(*) as degree from (select n_nationkey as a, n_regionkey from nation) c join nation m on m.n_regionkey = c.n_regionkey and m.n_nationkey <> c.a group by 1")
def map_adjacency(spark, d):
    n = _table(spark, d, "nation")
    members = n.groupBy("n_regionkey").agg(F.collect_list("n_nationkey").alias("all"))
    near = n.join(F.broadcast(members), "n_regionkey").select(F.create_map("n_nationkey", F.array_except("all", F.array("n_nationkey"))).alias("m"))
    return near.select(F.explode("m")).select(F.col("key").alias("neuron"), F.size("value").cast("long").alias("degree"))


@query("select cast(props->>'$.k' as bigint) as k, count(*) as n from events group by 1")
def json_props(spark, d):
    return _table(spark, d, "events").select(F.from_json("props", "k bigint")["k"].alias("k")).groupBy("k").agg(F.count("*").alias("n"))


@query("select page_id, length(html) as size, length(html) - length(replace(html, '<', '')) as tags, lower(left(url, 8)) as scheme from pages")
def string_functions(spark, d):
    return _table(spark, d, "pages").select("page_id", F.length("html").cast("long").alias("size"), F.regexp_count("html", F.lit("<")).cast("long").alias("tags"), F.lower(F.left("url", F.lit(8))).alias("scheme"))


@query("select cast(hour(ts) as integer) as h, cast(date_trunc('day', ts) as date) as day, count(*) as n from events group by 1, 2")
def date_functions(spark, d):
    return _table(spark, d, "events").groupBy(F.hour("ts").alias("h"), F.to_date(F.date_trunc("day", "ts")).alias("day")).agg(F.count("*").alias("n"))


@query("select event_id from events where ((event_id * 1103515245 + 12345) % 2147483648) % 10 = 0")
def sample_hashed(spark, d):
    from .operators.sampler import lcg

    return _table(spark, d, "events").where(lcg(F.col("event_id")) % 10 == 0).select("event_id")


@query("select user_id, count(*) as sessions, sum(n)::bigint as n from (select user_id, s, count(*) n from (select user_id, sum(new) over (partition by user_id order by ts, event_id rows unbounded preceding) s from (select *, case when ts - lag(ts) over (partition by user_id order by ts, event_id) < interval 2 hour then 0 else 1 end as new from events)) group by 1, 2) group by 1")
def session_windows(spark, d):
    e = _table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    s = e.groupBy("user_id", F.session_window("ts", "2 hours")).agg(F.count("*").alias("c"))
    return s.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("c").alias("n"))


def queries():
    return dict(_QUERIES)


def oracle_sql():
    return dict(_SQL)
