"""General operators around the methods, each as a query on the given tables with its SQL.

The SQL of most is the same text for both engines where the dialects agree; the DataFrame side never runs it.
"""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from discourselab.functions.stats import average_rank
from discourselab.functions.text import clean_text, ngrams, plural
from discourselab.session import scratch, table
from discourselab.sources.files import event_stream, replay, replay_stream, roundtrip
from discourselab.streaming import monitor

Query = Callable[[SparkSession, str], DataFrame]
_FOUND: dict[str, tuple[Query, str | None]] = {}


def op(sql: str | None) -> Callable[[Query], Query]:
    def held(f: Query) -> Query:
        _FOUND[f"op_{f.__name__}"] = (f, sql)
        return f

    return held


# scans, filters, projections


@op("select l_orderkey, l_linenumber, l_quantity from lineitem where l_shipdate >= timestamp '1997-01-01' and l_shipdate < timestamp '1997-02-01'")
def scan_prune(spark: SparkSession, d: str) -> DataFrame:
    return (
        table(spark, d, "lineitem")
        .where("l_shipdate >= timestamp_ntz'1997-01-01' and l_shipdate < timestamp_ntz'1997-02-01'")
        .select("l_orderkey", "l_linenumber", "l_quantity")
    )


@op((
    "select o_orderkey from orders where o_orderstatus in ('F', 'O') and o_orderpriority like '1%' and o_totalprice "
    "between 1000 and 300000 and o_custkey is not distinct from o_custkey"
))
def filter_predicates(spark: SparkSession, d: str) -> DataFrame:
    o = table(spark, d, "orders")
    return (
        o.where(o.o_orderstatus.isin("F", "O") & o.o_orderpriority.like("1%") & o.o_totalprice.between(1000, 300000) & o.o_custkey.eqNullSafe(o.o_custkey))
        .select("o_orderkey")
    )


@op("select l_orderkey, l_linenumber, l_quantity, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 6) as charge from lineitem")
def project_expr(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").select(
        "l_orderkey",
        "l_linenumber",
        "l_quantity",
        (F.col("l_extendedprice") * (1 - F.col("l_discount")) * (1 + F.col("l_tax"))).alias("charge"),
    )


@op((
    "select c_custkey, case when c_acctbal < 0 then 'debt' when c_acctbal < 5000 then 'some' else 'rich' end as band, "
    "coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') as segment from customer"
))
def case_coalesce(spark: SparkSession, d: str) -> DataFrame:
    band = F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal") < 5000, "some").otherwise("rich")
    return table(spark, d, "customer").select(
        "c_custkey",
        band.alias("band"),
        F.coalesce(F.nullif("c_mktsegment", F.lit("BUILDING")), F.lit("none")).alias("segment"),
    )


@op("select o_orderkey from orders where o_orderkey % 7 = 3")
def sample_hash(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").where(F.col("o_orderkey") % 7 == 3).select("o_orderkey")


# sources and sinks


@op("select * from nation")
def csv_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    return roundtrip(table(spark, d, "nation"), "csv", header="true")


@op("select * from customer")
def json_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    return roundtrip(table(spark, d, "customer"), "json")


@op("select * from supplier")
def orc_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    return roundtrip(table(spark, d, "supplier"), "orc")


@op("select o_orderstatus, count(*) as n from orders group by 1")
def partitioned_write(spark: SparkSession, d: str) -> DataFrame:
    held = roundtrip(table(spark, d, "orders").select("o_orderkey", "o_orderstatus"), "parquet", partition_by="o_orderstatus")
    return held.groupBy("o_orderstatus").agg(F.count("*").alias("n"))


@op("select event_id, user_id, event_type, round(value, 6) as value from events")
def replay_source(spark: SparkSession, d: str) -> DataFrame:
    """The events through a Python data source."""
    return replay(table(spark, d, "events"))


# joins

_JOIN_SQL = (
    "select n_name, count(*) as n, round(sum(o_totalprice), 2) as total from orders join customer on o_custkey = c_custkey "
    "join nation on c_nationkey = n_nationkey group by 1"
)


def _joined(spark: SparkSession, d: str, hint: str) -> DataFrame:
    o, c, n = (table(spark, d, x) for x in ("orders", "customer", "nation"))
    held = o.join(c.hint(hint), o.o_custkey == c.c_custkey).join(F.broadcast(n), F.col("c_nationkey") == n.n_nationkey)
    return held.groupBy("n_name").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@op(_JOIN_SQL)
def join_broadcast(spark: SparkSession, d: str) -> DataFrame:
    return _joined(spark, d, "broadcast")


@op(_JOIN_SQL)
def join_sortmerge(spark: SparkSession, d: str) -> DataFrame:
    return _joined(spark, d, "merge")


@op(_JOIN_SQL)
def join_shufflehash(spark: SparkSession, d: str) -> DataFrame:
    return _joined(spark, d, "shuffle_hash")


@op("select s_suppkey, n_nationkey from supplier join nation on s_acctbal > n_nationkey * 400 and s_nationkey <> n_nationkey")
def join_theta(spark: SparkSession, d: str) -> DataFrame:
    s, n = table(spark, d, "supplier"), table(spark, d, "nation")
    return s.join(F.broadcast(n), (s.s_acctbal > n.n_nationkey * 400) & (s.s_nationkey != n.n_nationkey)).select("s_suppkey", "n_nationkey")


_NEAR = (
    "select a.event_id as error_id, b.event_id as near_id from events a join events b on a.user_id = b.user_id and "
    "a.event_type = 'error' and b.event_type <> 'error' and b.ts between a.ts and a.ts + interval 1 hour"
)


def near_errors(events: DataFrame, seconds: int = 3600) -> DataFrame:
    """Range join by buckets: rows of a user at most ``seconds`` after an error, by equality on (user, bucket)."""
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    width = seconds * 1_000_000
    base = events.select("event_id", "user_id", "event_type", at.alias("at"))
    errors = (
        base.where("event_type = 'error'")
        .select(
            F.col("event_id").alias("error_id"),
            "user_id",
            F.col("at").alias("t"),
            F.explode(F.array(F.floor(F.col("at") / width), F.floor(F.col("at") / width) + 1)).alias("bucket"),
        )
    )
    others = base.where("event_type <> 'error'").select(F.col("event_id").alias("near_id"), "user_id", "at", F.floor(F.col("at") / width).alias("bucket"))
    return errors.join(others, ["user_id", "bucket"]).where((F.col("at") >= F.col("t")) & (F.col("at") <= F.col("t") + width)).select("error_id", "near_id")


@op(_NEAR)
def join_range(spark: SparkSession, d: str) -> DataFrame:
    return near_errors(table(spark, d, "events"))


@op("select e.event_id, k as slot from events e join range(0, 30) r(k) on e.value >= k * 10 and e.value < k * 10 + 10")
def join_interval(spark: SparkSession, d: str) -> DataFrame:
    e, slots = table(spark, d, "events"), spark.range(30).withColumnRenamed("id", "slot")
    return e.join(F.broadcast(slots), (e.value >= F.col("slot") * 10) & (e.value < F.col("slot") * 10 + 10)).select("event_id", "slot")


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """left with the right row's ``value`` at or before ``at`` for the same key: one sort by key, no range join."""
    rows = (
        left.withColumn("_side", F.lit(1))
        .unionByName(right.select(key, at, F.col(value).alias("_v")).withColumn("_side", F.lit(0)), allowMissingColumns=True)
    )
    before = Window.partitionBy(key).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return rows.withColumn(value, F.last("_v", ignorenulls=True).over(before)).where("_side = 1").drop("_side", "_v")


@op((
    "select event_id, (select max_by(b.event_id, (b.ts, b.event_id)) from events b where b.user_id = a.user_id and "
    "b.event_type = 'error' and b.ts <= a.ts) as last_error from events a where event_type = 'click'"
))
def join_asof(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events")
    right = e.where("event_type = 'error'").withColumnRenamed("event_id", "last_error").groupBy("user_id", "ts").agg(F.max("last_error").alias("last_error"))
    return as_of(e.where("event_type = 'click'").select("event_id", "user_id", "ts"), right, "user_id", "ts", "last_error").select("event_id", "last_error")


@op("select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 400000)")
def join_semi(spark: SparkSession, d: str) -> DataFrame:
    return (
        table(spark, d, "customer")
        .join(table(spark, d, "orders").where("o_totalprice > 400000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi")
        .select("c_custkey")
    )


@op("select o_orderkey from orders where not exists (select 1 from lineitem where l_orderkey = o_orderkey)")
def join_anti(spark: SparkSession, d: str) -> DataFrame:
    return (
        table(spark, d, "orders")
        .join(table(spark, d, "lineitem").select("l_orderkey"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti")
        .select("o_orderkey")
    )


@op("select c_custkey, count(o_orderkey) as n from customer left join orders on o_custkey = c_custkey group by 1")
def join_left(spark: SparkSession, d: str) -> DataFrame:
    return (
        table(spark, d, "customer")
        .join(table(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left")
        .groupBy("c_custkey")
        .agg(F.count("o_orderkey").alias("n"))
    )


@op((
    "select coalesce(a.k, b.k) as k, a.n as customers, b.n as suppliers from (select c_nationkey as k, count(*) as n from "
    "customer group by 1) a full join (select s_nationkey as k, count(*) as n from supplier group by 1) b on a.k = b.k"
))
def join_full(spark: SparkSession, d: str) -> DataFrame:
    a = table(spark, d, "customer").groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("customers"))
    return a.join(table(spark, d, "supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("suppliers")), "k", "full")


@op("select a.s_suppkey as a, b.s_suppkey as b from supplier a join supplier b on a.s_nationkey = b.s_nationkey and a.s_suppkey < b.s_suppkey")
def join_self(spark: SparkSession, d: str) -> DataFrame:
    s = table(spark, d, "supplier").select("s_suppkey", "s_nationkey")
    return s.withColumnRenamed("s_suppkey", "a").join(s.withColumnRenamed("s_suppkey", "b"), "s_nationkey").where("a < b").select("a", "b")


@op("select conv_id, turn, w from conversations, lateral (select unnest(string_split(role, 's')) as w)")
def join_lateral(spark: SparkSession, d: str) -> DataFrame:
    c = table(spark, d, "conversations")
    return c.lateralJoin(spark.tvf.explode(F.split(F.col("role").outer(), "s")).toDF("w")).select("conv_id", "turn", "w")


# aggregation


@op((
    "select l_returnflag, l_linestatus, count(*) as n, round(sum(l_quantity), 2) as q, round(avg(l_discount), 6) as disc, "
    "min(l_tax) as low, max(l_tax) as high from lineitem group by 1, 2"
))
def agg_basic(spark: SparkSession, d: str) -> DataFrame:
    return (
        table(spark, d, "lineitem")
        .groupBy("l_returnflag", "l_linestatus")
        .agg(
            F.count("*").alias("n"),
            F.round(F.sum("l_quantity"), 2).alias("q"),
            F.avg("l_discount").alias("disc"),
            F.min("l_tax").alias("low"),
            F.max("l_tax").alias("high"),
        )
    )


@op("select o_orderstatus, count(distinct o_custkey) as customers, count(distinct o_orderpriority) as priorities from orders group by 1")
def agg_distinct(spark: SparkSession, d: str) -> DataFrame:
    return (
        table(spark, d, "orders")
        .groupBy("o_orderstatus")
        .agg(F.count_distinct("o_custkey").alias("customers"), F.count_distinct("o_orderpriority").alias("priorities"))
    )


@op("select event_type, count(*) filter (value > 50) as high, count(*) filter (value <= 50) as low from events group by 1")
def agg_filter(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events").groupBy("event_type").agg(F.count_if(F.col("value") > 50).alias("high"), F.count_if(F.col("value") <= 50).alias("low"))


@op((
    "select event_type, round(stddev_samp(value), 6) as sd, round(corr(value, user_id), 6) as r, round(covar_samp(value, "
    "user_id), 5) as cov, round(var_pop(value), 5) as var from events group by 1"
))
def agg_stats(spark: SparkSession, d: str) -> DataFrame:
    return (
        table(spark, d, "events")
        .groupBy("event_type")
        .agg(
            F.stddev_samp("value").alias("sd"),
            F.corr("value", "user_id").alias("r"),
            F.round(F.covar_samp("value", "user_id"), 5).alias("cov"),
            F.round(F.var_pop("value"), 5).alias("var"),
        )
    )


@op("select event_type, quantile_cont(value, 0.5) as p50, quantile_cont(value, 0.9) as p90 from events group by 1")
def agg_percentile(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events").groupBy("event_type").agg(F.percentile("value", 0.5).alias("p50"), F.percentile("value", 0.9).alias("p90"))


@op((
    "select o_custkey, max_by(o_orderkey, (o_totalprice, o_orderkey)) as dearest, min_by(o_orderkey, (o_totalprice, "
    "o_orderkey)) as cheapest from orders group by 1"
))
def agg_maxby(spark: SparkSession, d: str) -> DataFrame:
    at = F.struct("o_totalprice", "o_orderkey")
    return table(spark, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", at).alias("dearest"), F.min_by("o_orderkey", at).alias("cheapest"))


@op("select n_regionkey, string_agg(n_name, ',' order by n_name) as names from nation group by 1")
def agg_collect(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_set("n_name")), ",").alias("names"))


@op((
    "select c_nationkey, c_mktsegment as top_segment from (select c_nationkey, c_mktsegment, row_number() over (partition "
    "by c_nationkey order by count(*) desc, c_mktsegment) as r from customer group by 1, 2) where r = 1"
))
def agg_mode(spark: SparkSession, d: str) -> DataFrame:
    counted = table(spark, d, "customer").groupBy("c_nationkey", "c_mktsegment").agg(F.count("*").alias("n"))
    return counted.groupBy("c_nationkey").agg(F.min_by("c_mktsegment", F.struct(-F.col("n"), "c_mktsegment")).alias("top_segment"))


@op(
    (
        "select event_type, count(distinct user_id) as users, quantile_cont(value, 0.5) as median, 0 as hll_class, 0 as "
        "theta_class, 0 as kll_class from events group by 1"
    )
)
def agg_approx(spark: SparkSession, d: str) -> DataFrame:
    """Exact values, and by how many steps of 10 % a sketch misses each (0: by less than one)."""
    kll = F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double("value"), F.lit(0.5))
    held = (
        table(spark, d, "events")
        .groupBy("event_type")
        .agg(
            F.count_distinct("user_id").alias("users"),
            F.percentile("value", 0.5).alias("median"),
            F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("hll"),
            F.theta_sketch_estimate(F.theta_sketch_agg("user_id")).alias("theta"),
            kll.alias("kll"),
        )
    )
    steps = lambda found, exact: F.floor(F.abs(found - exact) / (0.1 * exact)).cast("int")
    classes = [steps(F.col(x), F.col("median" if x == "kll" else "users")).alias(f"{x}_class") for x in ("hll", "theta", "kll")]
    return held.select("event_type", "users", "median", *classes)


_SETS = "select o_orderstatus, o_orderpriority, count(*) as n from orders group by {}"


@op(_SETS.format("grouping sets ((o_orderstatus), (o_orderpriority), ())"))
def grouping_sets(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").groupingSets([["o_orderstatus"], ["o_orderpriority"], []], "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@op(_SETS.format("rollup (o_orderstatus, o_orderpriority)"))
def rollup(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@op(_SETS.format("cube (o_orderstatus, o_orderpriority)"))
def cube(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@op("select event_type, count(*) filter (user_id % 2 = 0) as even, count(*) filter (user_id % 2 = 1) as odd from events group by 1")
def pivot(spark: SparkSession, d: str) -> DataFrame:
    parity = F.when(F.col("user_id") % 2 == 0, "even").otherwise("odd")
    return table(spark, d, "events").withColumn("parity", parity).groupBy("event_type").pivot("parity", ["even", "odd"]).agg(F.count(F.lit(1)))


@op("select r_regionkey, 'low' as part, r_regionkey * 2 as value from region union all select r_regionkey, 'high', r_regionkey * 3 from region")
def unpivot(spark: SparkSession, d: str) -> DataFrame:
    held = table(spark, d, "region").select("r_regionkey", (F.col("r_regionkey") * 2).alias("low"), (F.col("r_regionkey") * 3).alias("high"))
    return held.unpivot("r_regionkey", ["low", "high"], "part", "value")


# windows

_BY = "partition by o_custkey order by o_orderdate, o_orderkey"


def _orders(spark: SparkSession, d: str) -> tuple[DataFrame, Window]:
    return table(spark, d, "orders"), Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")


@op((
    "select o_orderkey, row_number() over w as rn, rank() over v as rk, dense_rank() over v as dr, round(percent_rank() "
    "over v, 6) as pr, round(cume_dist() over v, 6) as cd from orders window w as (partition by o_custkey order by "
    "o_orderdate, o_orderkey), v as (partition by o_custkey order by o_orderpriority)"
))
def win_rank(spark: SparkSession, d: str) -> DataFrame:
    o, w = _orders(spark, d)
    v = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return o.select(
        "o_orderkey",
        F.row_number().over(w).alias("rn"),
        F.rank().over(v).alias("rk"),
        F.dense_rank().over(v).alias("dr"),
        F.percent_rank().over(v).alias("pr"),
        F.cume_dist().over(v).alias("cd"),
    )


@op((
    f"select o_orderkey, lag(o_orderkey) over w as before, lead(o_orderkey, 2) over w as later, first_value(o_orderkey) "
    f"over w as first, nth_value(o_orderkey, 2) over w as second from orders window w as ({_BY})"
))
def win_offset(spark: SparkSession, d: str) -> DataFrame:
    o, w = _orders(spark, d)
    return o.select(
        "o_orderkey",
        F.lag("o_orderkey").over(w).alias("before"),
        F.lead("o_orderkey", 2).over(w).alias("later"),
        F.first("o_orderkey").over(w).alias("first"),
        F.nth_value("o_orderkey", 2).over(w).alias("second"),
    )


@op(f"select o_orderkey, round(avg(o_totalprice) over ({_BY} rows between 2 preceding and 1 following), 4) as m from orders")
def win_frame_rows(spark: SparkSession, d: str) -> DataFrame:
    o, w = _orders(spark, d)
    return o.select("o_orderkey", F.round(F.avg("o_totalprice").over(w.rowsBetween(-2, 1)), 4).alias("m"))


@op((
    "select o_orderkey, count(*) over (partition by o_custkey order by cast(o_orderdate as date) - date '1970-01-01' range "
    "between 30 preceding and current row) as n from orders"
))
def win_frame_range(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy(F.unix_date(F.to_date("o_orderdate"))).rangeBetween(-30, 0)
    return table(spark, d, "orders").select("o_orderkey", F.count("*").over(w).alias("n"))


@op(f"select o_orderkey, ntile(4) over ({_BY}) as q from orders")
def win_ntile(spark: SparkSession, d: str) -> DataFrame:
    o, w = _orders(spark, d)
    return o.select("o_orderkey", F.ntile(4).over(w).alias("q"))


@op(f"select o_orderkey, round(sum(o_totalprice) over ({_BY} rows unbounded preceding), 2) as total from orders")
def win_cumulative(spark: SparkSession, d: str) -> DataFrame:
    o, w = _orders(spark, d)
    return o.select("o_orderkey", F.round(F.sum("o_totalprice").over(w.rowsBetween(Window.unboundedPreceding, 0)), 2).alias("total"))


# sorts, limits, sets


@op("select o_orderkey from orders order by o_totalprice desc nulls last, o_orderkey")
def sort_global(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").orderBy(F.desc_nulls_last("o_totalprice"), "o_orderkey").select("o_orderkey")


@op("select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 20")
def topk(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")


@op("select o_custkey, o_orderkey from orders qualify row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) <= 2")
def topk_group(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(spark, d, "orders").withColumn("r", F.row_number().over(w)).where("r <= 2").select("o_custkey", "o_orderkey")


@op("select o_orderkey from orders order by o_orderkey limit 10 offset 15")
def limit_offset(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").orderBy("o_orderkey").offset(15).limit(10).select("o_orderkey")


def _keys(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    return table(spark, d, "customer").select(F.col("c_nationkey").alias("k")), table(spark, d, "supplier").select(F.col("s_nationkey").alias("k"))


@op("select c_nationkey as k from customer union all select s_nationkey from supplier")
def union(spark: SparkSession, d: str) -> DataFrame:
    a, b = _keys(spark, d)
    return a.union(b)


@op("select c_nationkey as k from customer intersect select s_nationkey from supplier")
def intersect(spark: SparkSession, d: str) -> DataFrame:
    a, b = _keys(spark, d)
    return a.intersect(b)


@op("select c_nationkey as k from customer except all select s_nationkey from supplier")
def except_all(spark: SparkSession, d: str) -> DataFrame:
    a, b = _keys(spark, d)
    return a.exceptAll(b)


@op("select n_name as name, n_regionkey as region, null::int as extra from nation union all select r_name, r_regionkey, 1 from region")
def union_by_name(spark: SparkSession, d: str) -> DataFrame:
    n = table(spark, d, "nation").select(F.col("n_name").alias("name"), F.col("n_regionkey").alias("region"))
    return n.unionByName(
        table(spark, d, "region").select(F.col("r_regionkey").alias("region"), F.lit(1).alias("extra"), F.col("r_name").alias("name")),
        allowMissingColumns=True,
    )


# functions


@op((
    "select p_partkey, upper(p_brand) as up, trim(substring(p_name, 3, 5)) as part, length(p_name) as n, replace(p_type, ' "
    "', '_') as kind, levenshtein(p_brand, 'Brand#11') as dist, translate(p_brand, 'Bd', 'bD') as tr, concat_ws('-', "
    "p_brand, p_type) as joined from part"
))
def str_funcs(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "part").select(
        "p_partkey",
        F.upper("p_brand").alias("up"),
        F.trim(F.substring("p_name", 3, 5)).alias("part"),
        F.length("p_name").alias("n"),
        F.replace("p_type", F.lit(" "), F.lit("_")).alias("kind"),
        F.levenshtein("p_brand", F.lit("Brand#11")).alias("dist"),
        F.translate("p_brand", "Bd", "bD").alias("tr"),
        F.concat_ws("-", "p_brand", "p_type").alias("joined"),
    )


@op((
    "select doc_id, regexp_extract(text, '[0-9]+', 0) as digits, len(regexp_extract_all(text, '[aeiou]')) as vowels, "
    "md5(regexp_replace(text, '[0-9]', '#', 'g')) as masked from documents"
))
def regex_funcs(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").select(
        "doc_id",
        F.regexp_extract("text", "[0-9]+", 0).alias("digits"),
        F.regexp_count("text", F.lit("[aeiou]")).alias("vowels"),
        F.md5(F.regexp_replace("text", "[0-9]", "#")).alias("masked"),
    )


@op((
    "select item_id, array_to_string(w[i:i + 1], ' ') as gram from (select item_id, "
    "string_split(trim(regexp_replace(regexp_replace(lower(text), '[^\\p{L}\\p{N}\\s]', '', 'g'), '\\s+', ' ', 'g')), ' ') "
    "as w from benchmark), unnest(range(1, len(w))) u(i)"
))
def word_ngrams(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "benchmark").select("item_id", F.explode(ngrams(F.split(clean_text(F.col("text")), " "), 2, 2)).alias("gram"))


@op((
    "select o_orderkey, cast(date_trunc('month', o_orderdate) as date) as month, cast(o_orderdate as date) + 10 as later, "
    "date_diff('day', date '1995-01-01', cast(o_orderdate as date)) as days, year(o_orderdate) as y, "
    "weekofyear(o_orderdate) as w from orders"
))
def date_funcs(spark: SparkSession, d: str) -> DataFrame:
    day = F.to_date("o_orderdate")
    return table(spark, d, "orders").select(
        "o_orderkey",
        F.trunc(day, "month").alias("month"),
        F.date_add(day, 10).alias("later"),
        F.datediff(day, F.lit("1995-01-01").cast("date")).alias("days"),
        F.year(day).alias("y"),
        F.weekofyear(day).alias("w"),
    )


@op((
    "select c_custkey, round(ln(1 + abs(c_acctbal)), 6) as lg, cast(floor(c_acctbal) as bigint) as fl, "
    "cast(sign(c_acctbal) as int) as sg, round(sqrt(abs(c_acctbal)), 6) as sq, greatest(c_acctbal, 0.0) as pos, "
    "round(c_acctbal / nullif(c_custkey, 0), 6) as ratio from customer"
))
def math_funcs(spark: SparkSession, d: str) -> DataFrame:
    a = F.col("c_acctbal")
    return table(spark, d, "customer").select(
        "c_custkey",
        F.log1p(F.abs(a)).alias("lg"),
        F.floor(a).alias("fl"),
        F.signum(a).cast("int").alias("sg"),
        F.sqrt(F.abs(a)).alias("sq"),
        F.greatest(a, F.lit(0.0)).alias("pos"),
        F.try_divide(a, "c_custkey").alias("ratio"),
    )


@op((
    "select vec_id, round(list_sum(list_transform(embedding[1:4], lambda x: x::double * x::double)), 6) as s, "
    "len(list_filter(embedding, lambda x: x > 0)) as positive, round(list_max(embedding)::double, 6) as high from "
    "embeddings"
))
def array_funcs(spark: SparkSession, d: str) -> DataFrame:
    e = F.col("embedding")
    return table(spark, d, "embeddings").select(
        "vec_id",
        F.aggregate(F.slice(e, 1, 4), F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")).alias("s"),
        F.size(F.filter(e, lambda x: x > 0)).alias("positive"),
        F.array_max(e).cast("double").alias("high"),
    )


@op("select n_nationkey, n_name || '/' || n_regionkey as pair, 2 as size from nation")
def map_funcs(spark: SparkSession, d: str) -> DataFrame:
    m = F.create_map(F.lit("name"), F.col("n_name"), F.lit("region"), F.col("n_regionkey").cast("string"))
    return table(spark, d, "nation").select(
        "n_nationkey",
        F.concat_ws("/", F.element_at(m, "name"), F.element_at(m, "region")).alias("pair"),
        F.size(F.map_keys(m)).alias("size"),
    )


@op("select event_id, cast(json_extract_string(props, '$.k') as int) as k, cast(json_extract_string(props, '$.k') as int) + 1 as next from events")
def json_funcs(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events")
    return e.select("event_id", F.from_json("props", "k int").getField("k").alias("k"), (F.variant_get(F.parse_json("props"), "$.k", "int") + 1).alias("next"))


@op("select page_id, len(regexp_extract_all(html, 'href=\"[^\"]*\"')) as n from pages")
def html_links(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "pages").select("page_id", F.regexp_count("html", F.lit('href="[^"]*"')).alias("n"))


# SQL front


def _views(spark: SparkSession, d: str, *names: str) -> None:
    for name in names:
        table(spark, d, name).createOrReplaceTempView(name)


_CTE = (
    "with big as (select * from orders where o_totalprice > 300000), per as (select o_custkey, count(*) as n from big "
    "group by o_custkey) select n, count(*) as customers from per group by n"
)
_RECURSIVE = (
    "with recursive r(k, f, n) as (select 1, 1, count(*) from orders union all select k + 1, f * 2, n from r where k < 12), "
    "per as (select floor(o_totalprice / 50000) as k, count(*) as held from orders group by 1) "
    "select r.k, r.f, r.n, coalesce(per.held, 0) as held from r left join per on per.k = r.k"
)
_SCALAR = "select o_orderkey from orders where o_totalprice > (select avg(o_totalprice) * 1.8 from orders)"
_EXISTS = "select s_suppkey from supplier where exists (select 1 from lineitem where l_suppkey = s_suppkey and l_quantity > 49)"
_CORRELATED = "select o_orderkey from orders a where o_totalprice = (select max(o_totalprice) from orders b where b.o_custkey = a.o_custkey)"


@op(_CTE)
def cte(spark: SparkSession, d: str) -> DataFrame:
    _views(spark, d, "orders")
    return spark.sql(_CTE)


@op(_RECURSIVE)
def recursive_cte(spark: SparkSession, d: str) -> DataFrame:
    _views(spark, d, "orders")
    return spark.sql(_RECURSIVE)


@op(_SCALAR)
def subquery_scalar(spark: SparkSession, d: str) -> DataFrame:
    _views(spark, d, "orders")
    return spark.sql(_SCALAR)


@op(_EXISTS)
def subquery_exists(spark: SparkSession, d: str) -> DataFrame:
    _views(spark, d, "supplier", "lineitem")
    return spark.sql(_EXISTS)


@op(_CORRELATED)
def subquery_correlated(spark: SparkSession, d: str) -> DataFrame:
    _views(spark, d, "orders")
    return spark.sql(_CORRELATED)


@op("select n_regionkey, count(*) as n from nation group by 1")
def sql_pipe(spark: SparkSession, d: str) -> DataFrame:
    _views(spark, d, "nation")
    return spark.sql("from nation |> aggregate count(*) as n group by n_regionkey")


# Python functions, Arrow batches


@op("select c_custkey, round(greatest(0.0, c_acctbal) / 100, 6) as scaled from customer")
def udf_scalar(spark: SparkSession, d: str) -> DataFrame:
    scale = F.pandas_udf(lambda s: s.clip(lower=0) / 100, "double")
    return table(spark, d, "customer").select("c_custkey", scale("c_acctbal").alias("scaled"))


@op("select event_type, round(max(value) - min(value), 6) as span from events group by 1")
def udf_grouped(spark: SparkSession, d: str) -> DataFrame:
    def span(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"event_type": [key[0]], "span": [rows["value"].max() - rows["value"].min()]})

    return table(spark, d, "events").select("event_type", "value").groupBy("event_type").applyInPandas(span, "event_type string, span double")


@op((
    "select n_nationkey, unnest([lower(n_name), lower(n_name) || 's']) as form from nation where not "
    "regexp_matches(lower(n_name), '(s|x|z|ch|sh|[^aeiou]y)$')"
))
def udtf_expand(spark: SparkSession, d: str) -> DataFrame:
    @F.udtf(returnType="form string")
    class Forms:
        def eval(self, term: str):  # noqa: ANN202
            yield (term,)
            yield (term + "s",)

    n = table(spark, d, "nation").select("n_nationkey", F.lower("n_name").alias("name")).where(~F.col("name").rlike("(s|x|z|ch|sh|[^aeiou]y)$"))
    return n.lateralJoin(Forms(F.col("name").outer())).select("n_nationkey", "form")


@op("select n_nationkey, lower(n_name) || 's' as form from nation where not regexp_matches(lower(n_name), '(s|x|z|ch|sh|[^aeiou]y)$')")
def plural_forms(spark: SparkSession, d: str) -> DataFrame:
    n = table(spark, d, "nation").select("n_nationkey", F.lower("n_name").alias("name")).where(~F.col("name").rlike("(s|x|z|ch|sh|[^aeiou]y)$"))
    return n.select("n_nationkey", plural(F.col("name")).alias("form"))


@op((
    "select event_type, round(corr(rx, ry), 6) as r_s from (select event_type, rank() over (partition by event_type order "
    "by value) + (count(*) over (partition by event_type, value) - 1) / 2.0 as rx, rank() over (partition by event_type "
    "order by user_id) + (count(*) over (partition by event_type, user_id) - 1) / 2.0 as ry from events) group by 1"
))
def udaf_spearman(spark: SparkSession, d: str) -> DataFrame:
    def rho(x: pd.Series, y: pd.Series) -> float:
        return x.rank().corr(y.rank())

    grouped = F.pandas_udf(rho, "double", F.PandasUDFType.GROUPED_AGG)
    return table(spark, d, "events").groupBy("event_type").agg(grouped("value", "user_id").alias("r_s"))


@op((
    "select o_orderkey, round(rank() over (partition by o_custkey order by o_orderpriority) + (count(*) over (partition by "
    "o_custkey, o_orderpriority) - 1) / 2.0, 6) as r from orders"
))
def tie_rank(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").select("o_orderkey", average_rank("o_orderpriority", ["o_custkey"]).alias("r"))


@op((
    "select coalesce(c.k, s.k) as k, coalesce(c.n, 0) as a, coalesce(s.n, 0) as b from (select c_nationkey as k, count(*) "
    "as n from customer group by 1) c full join (select s_nationkey as k, count(*) as n from supplier group by 1) s on c.k "
    "= s.k"
))
def cogroup(spark: SparkSession, d: str) -> DataFrame:
    a, b = _keys(spark, d)

    def both(key: tuple, x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"k": [key[0]], "a": [len(x)], "b": [len(y)]})

    return a.groupBy("k").cogroup(b.groupBy("k")).applyInPandas(both, "k int, a long, b long")


# streams: replayed in several batches and compared with SQL that states the watermark's rule


def _replayed(spark: SparkSession, d: str) -> DataFrame:
    return event_stream(spark, d, monitor.BATCHES)


#: The last watermark: what ends after it is not yet written.
_MARK = "(select max(ts) - interval 1 day from events)"


@op((
    f"select cast(ts as date) as day, event_type, count(*) as n, round(sum(value), 6) as total from events group by 1, 2 "
    f"having day + interval 1 day <= {_MARK}"
))
def stream_tumbling(spark: SparkSession, d: str) -> DataFrame:
    held = monitor.drain(monitor.tumbling(_replayed(spark, d)))
    return held.select(F.to_date("window.start").alias("day"), "event_type", "n", "total")


@op((
    f"select day, sum(n) as n from (select cast(ts as date) + k as day, count(*) as n from events, (values (0), (-1)) v(k) "
    f"group by 1) group by 1 having day + interval 2 day <= {_MARK}"
))
def stream_sliding(spark: SparkSession, d: str) -> DataFrame:
    held = monitor.drain(monitor.sliding(_replayed(spark, d)))
    return held.select(F.to_date("window.start").alias("day"), "n")


@op(
    "select user_id, count(*) as sessions from (select user_id, s, max(ts) as last from (select user_id, ts, sum(case when before is null or ts - before >= interval 1 hour then 1 else 0 end) over (partition by user_id order by ts) as s "
    "from (select user_id, ts, lag(ts) over (partition by user_id order by ts) as before from events)) group by 1, 2) "
    f"where last + interval 1 hour <= {_MARK} group by 1"
)
def stream_session(spark: SparkSession, d: str) -> DataFrame:
    held = monitor.drain(monitor.sessions(_replayed(spark, d)))
    return held.groupBy("user_id").agg(F.count("*").alias("sessions"))


@op("select user_id, event_type, cast(ts as date) as day from events group by 1, 2, 3")
def stream_dedup(spark: SparkSession, d: str) -> DataFrame:
    return monitor.drain(monitor.deduplicated(_replayed(spark, d)))


@op("select event_id, event_type, round(value * case event_type when 'error' then -1.0 else 0.5 end, 6) as score from events")
def stream_static_join(spark: SparkSession, d: str) -> DataFrame:
    kinds = table(spark, d, "events").select("event_type").distinct()
    valence = kinds.withColumn("valence", F.when(F.col("event_type") == "error", -1.0).otherwise(0.5))
    return monitor.drain(monitor.scored(_replayed(spark, d), valence))


@op(
    "select a.event_id as incident, b.event_id as post from events a join events b on a.user_id = b.user_id and a.event_type = 'error' and b.event_type <> 'error' and b.ts between a.ts and a.ts + interval 1 hour"
)
def stream_stream_join(spark: SparkSession, d: str) -> DataFrame:
    return monitor.drain(monitor.posts_near_incidents(_replayed(spark, d)))


@op("select user_id, count(*) as n, cast(sum(round(value * 100)) as bigint) as cents from events group by 1")
def stream_stateful(spark: SparkSession, d: str) -> DataFrame:
    return monitor.drain(monitor.folded_profiles(_replayed(spark, d)), "update", ("user_id",))


@op(f"select cast(ts as date) as day, count(*) as n from events where event_id % 50 <> 0 group by 1 having day + interval 1 day <= {_MARK}")
def stream_late(spark: SparkSession, d: str) -> DataFrame:
    """Every fiftieth event comes after all others: of days that the watermark has passed it is dropped."""
    late = event_stream(spark, d, monitor.BATCHES, F.col("event_id") % 50 == 0)
    held = monitor.drain(monitor.tumbling(late))
    return held.groupBy(F.to_date("window.start").alias("day")).agg(F.sum("n").alias("n"))


@op("select event_id, user_id, event_type, round(value, 6) as value from events")
def stream_replay(spark: SparkSession, d: str) -> DataFrame:
    """A Python data source read as a stream of the events, in five batches at least."""
    return monitor.drain(replay_stream(table(spark, d, "events"), monitor.BATCHES), bounded=False)


@op("select event_id as value, event_type from events")
def stream_rate(spark: SparkSession, d: str) -> DataFrame:
    """A rate source that numbers the events: its one batch covers all numbers up to the last event's."""
    events = table(spark, d, "events").select(F.col("event_id").alias("value"), "event_type")
    last = events.agg(F.max("value")).first()[0]
    rate = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", (last or 0) + 1).option("numPartitions", 2).load()
    return monitor.drain(rate.select("value").join(events, "value"))


# more sinks


@op("select n_name as value from nation")
def text_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    return roundtrip(table(spark, d, "nation").select(F.col("n_name").alias("value")), "text")


@op("select n_nationkey, case when n_regionkey = 1 then lower(n_name) else n_name end as n_name, n_regionkey from nation")
def write_dynamic(spark: SparkSession, d: str) -> DataFrame:
    """Only the partitions that are written are replaced."""
    path = scratch(spark, "dynamic")
    nation = table(spark, d, "nation").select("n_nationkey", "n_name", "n_regionkey")
    nation.write.partitionBy("n_regionkey").parquet(path)
    again = nation.where("n_regionkey = 1").withColumn("n_name", F.lower("n_name"))
    again.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("n_regionkey").parquet(path)
    return spark.read.schema(nation.schema).parquet(path)


def queries() -> dict[str, Query]:
    return {name: f for name, (f, _) in _FOUND.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in _FOUND.items() if sql}
