"""Relational operators around rule programs, each as a DataFrame plan with its SQL: projections, set operators, joins, windows, scalars."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


COMPARISONS = {"eq": "=", "ne": "!=", "lt": "<", "le": "<=", "gt": ">", "ge": ">="}


def integer_division(a: Column, b: int) -> Column:
    """Floor division that Spark and other engines agree on."""
    return F.floor(a / b).cast("bigint")


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """Each left row with the last right value at or before it, by one sorted pass over both (no range join)."""
    both = left.select(key, at, F.lit(1).alias("rw_side"), F.lit(None).cast(right.schema[value].dataType).alias(value)).unionByName(right.select(key, at, F.lit(0).alias("rw_side"), value))
    w = Window.partitionBy(key).orderBy(at, "rw_side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value, F.last(value, ignorenulls=True).over(w)).filter("rw_side = 1").drop("rw_side")


def range_join(points: DataFrame, spans: DataFrame, point: str, low: str, high: str, width: int) -> DataFrame:
    """Points inside [low, high]: spans are spread over the buckets of `width` they touch, then an equi join and a filter."""
    spread = spans.withColumn("rw_bucket", F.explode(F.sequence(integer_division(F.col(low), width), integer_division(F.col(high), width))))
    return points.withColumn("rw_bucket", integer_division(F.col(point), width)).join(spread, "rw_bucket").filter(F.col(point).between(F.col(low), F.col(high))).drop("rw_bucket")


def _t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _cases() -> dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]]:
    by_user = lambda: Window.partitionBy("user_id").orderBy("ts", "event_id")  # noqa: E731  windows need a session
    return {
        "project_filter": (
            lambda s, d: _t(s, d, "orders").filter("o_totalprice > 200000 and o_orderstatus = 'F'").select("o_orderkey", (F.col("o_orderkey") % 8).alias("bucket")),
            "select o_orderkey, o_orderkey % 8 bucket from orders where o_totalprice > 200000 and o_orderstatus = 'F'",
        ),
        "union_distinct": (
            lambda s, d: _t(s, d, "customer").select(F.col("c_nationkey").alias("n")).union(_t(s, d, "supplier").select("s_nationkey")).distinct(),
            "select c_nationkey n from customer union select s_nationkey from supplier",
        ),
        "difference": (
            lambda s, d: _t(s, d, "customer").select(F.col("c_custkey").alias("k")).join(_t(s, d, "orders").select(F.col("o_custkey").alias("k")), "k", "left_anti"),
            "select c_custkey k from customer where c_custkey not in (select o_custkey from orders)",
        ),
        "intersection": (
            lambda s, d: _t(s, d, "customer").select(F.col("c_nationkey").alias("n")).intersect(_t(s, d, "supplier").select("s_nationkey")),
            "select c_nationkey n from customer intersect select s_nationkey from supplier",
        ),
        "top_k": (
            lambda s, d: _t(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey"),
            "select o_orderkey from orders order by o_totalprice desc, o_orderkey limit 20",
        ),
        "equi_join_sum": (
            lambda s, d: _t(s, d, "lineitem").join(_t(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("bigint")).alias("quantity")),
            "select o_orderstatus, count(*) n, cast(sum(cast(l_quantity as bigint)) as bigint) quantity from lineitem join orders on o_orderkey = l_orderkey group by o_orderstatus",
        ),
        "semi_join": (
            lambda s, d: _t(s, d, "part").select("p_partkey").join(_t(s, d, "lineitem").filter("l_quantity <= 1").select(F.col("l_partkey").alias("p_partkey")), "p_partkey", "left_semi"),
            "select p_partkey from part where p_partkey in (select l_partkey from lineitem where l_quantity <= 1)",
        ),
        "anti_join": (
            lambda s, d: _t(s, d, "part").select("p_partkey").join(_t(s, d, "lineitem").filter("l_quantity <= 1").select(F.col("l_partkey").alias("p_partkey")), "p_partkey", "left_anti"),
            "select p_partkey from part where p_partkey not in (select l_partkey from lineitem where l_quantity <= 1)",
        ),
        "self_join": (
            lambda s, d: _t(s, d, "supplier").select(F.col("s_suppkey").alias("a"), "s_nationkey").join(_t(s, d, "supplier").select(F.col("s_suppkey").alias("b"), "s_nationkey"), "s_nationkey").filter("a < b").select("a", "b"),
            "select x.s_suppkey a, y.s_suppkey b from supplier x join supplier y using (s_nationkey) where x.s_suppkey < y.s_suppkey",
        ),
        "range_join": (
            lambda s, d: range_join(_t(s, d, "events").select("event_id"), _t(s, d, "supplier").select("s_suppkey", (F.col("s_suppkey") * 37).alias("lo"), (F.col("s_suppkey") * 37 + 10).alias("hi")), "event_id", "lo", "hi", 64).select("event_id", "s_suppkey"),
            "select event_id, s_suppkey from events join supplier on event_id between s_suppkey * 37 and s_suppkey * 37 + 10",
        ),
        "as_of_join": (
            lambda s, d: as_of(_t(s, d, "events").filter("event_type = 'error'").select("user_id", "event_id"), _t(s, d, "events").filter("event_type = 'signup'").select("user_id", "event_id", F.col("event_id").alias("signup")), "user_id", "event_id", "signup").fillna(-1, ["signup"]),
            "select e.user_id, e.event_id, coalesce((select max(s.event_id) from events s where s.event_type = 'signup' and s.user_id = e.user_id and s.event_id <= e.event_id), -1) signup from events e where e.event_type = 'error'",
        ),
        "distinct_count": (
            lambda s, d: _t(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_orderkey", "l_partkey").alias("n")),
            "select l_returnflag, count(distinct (l_orderkey, l_partkey)) n from lineitem group by l_returnflag",
        ),
        "group_min_max": (
            lambda s, d: _t(s, d, "orders").groupBy("o_custkey").agg(F.min("o_orderkey").alias("first"), F.max("o_orderkey").alias("last"), F.count("*").alias("n")),
            "select o_custkey, min(o_orderkey) \"first\", max(o_orderkey) \"last\", count(*) n from orders group by o_custkey",
        ),
        "having": (
            lambda s, d: _t(s, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")).filter("n >= 15"),
            "select o_custkey, count(*) n from orders group by o_custkey having count(*) >= 15",
        ),
        "median": (
            lambda s, d: _t(s, d, "part").groupBy("p_type").agg(F.percentile("p_size", 0.5).alias("middle")),
            "select p_type, quantile_cont(p_size, 0.5) middle from part group by p_type",
        ),
        "rollup": (
            lambda s, d: _t(s, d, "part").rollup("p_brand", "p_type").agg(F.count("*").alias("n")),
            "select p_brand, p_type, count(*) n from part group by rollup (p_brand, p_type)",
        ),
        "cube": (
            lambda s, d: _t(s, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")),
            "select o_orderstatus, o_orderpriority, count(*) n from orders group by cube (o_orderstatus, o_orderpriority)",
        ),
        "window_lead": (
            lambda s, d: _t(s, d, "events").select("event_id", F.lead("event_id", 1, -1).over(by_user()).alias("later"), F.lag("event_id", 1, -1).over(by_user()).alias("earlier")),
            "select event_id, lead(event_id, 1, -1) over w later, lag(event_id, 1, -1) over w earlier from events window w as (partition by user_id order by ts, event_id)",
        ),
        "window_ranks": (
            lambda s, d: _t(s, d, "events").select("event_id", F.row_number().over(by_user()).alias("place"), F.dense_rank().over(Window.partitionBy("user_id").orderBy("event_type")).alias("kind"), F.ntile(4).over(by_user()).alias("part4")),
            "select event_id, row_number() over (partition by user_id order by ts, event_id) place, dense_rank() over (partition by user_id order by event_type) kind, ntile(4) over (partition by user_id order by ts, event_id) part4 from events",
        ),
        "window_running": (
            lambda s, d: _t(s, d, "events").select("event_id", F.sum(F.when(F.col("event_type") == "purchase", 1).otherwise(0)).over(by_user().rowsBetween(Window.unboundedPreceding, 0)).alias("bought")),
            "select event_id, cast(sum(case when event_type = 'purchase' then 1 else 0 end) over (partition by user_id order by ts, event_id rows between unbounded preceding and current row) as bigint) bought from events",
        ),
        "top_k_per_group": (
            lambda s, d: _t(s, d, "part").withColumn("place", F.row_number().over(Window.partitionBy("p_brand").orderBy(F.desc("p_size"), "p_partkey"))).filter("place <= 3").select("p_brand", "p_partkey", "place"),
            "select p_brand, p_partkey, place from (select *, row_number() over (partition by p_brand order by p_size desc, p_partkey) place from part) where place <= 3",
        ),
        "scalar_functions": (
            lambda s, d: _t(s, d, "part").select("p_partkey", F.substring("p_brand", 7, 10).cast("bigint").alias("brand"), F.length("p_name").cast("bigint").alias("n"), F.upper("p_type").alias("kind"), F.greatest("p_size", F.lit(10)).alias("size"), integer_division(F.col("p_partkey"), 7).alias("part")),
            "select p_partkey, cast(substr(p_brand, 7) as bigint) brand, cast(length(p_name) as bigint) n, upper(p_type) kind, greatest(p_size, 10) size, cast(floor(p_partkey / 7) as bigint) part from part",
        ),
        "json_and_dates": (
            lambda s, d: _t(s, d, "events").select("event_id", F.regexp_extract("props", "([0-9]+)", 1).cast("bigint").alias("leaf"), F.year("ts").alias("y"), F.date_format(F.date_trunc("month", "ts"), "yyyy-MM-dd").alias("m")),
            "select event_id, cast(regexp_extract(props, '([0-9]+)', 1) as bigint) leaf, year(ts) y, strftime(date_trunc('month', ts), '%Y-%m-%d') m from events",
        ),
        "null_safe": (
            lambda s, d: _t(s, d, "events").select("event_id", F.lag("event_id").over(by_user()).alias("prev")).filter(F.coalesce("prev", F.lit(-1)) <= 100).select("event_id", F.col("prev").eqNullSafe(F.lit(None)).alias("first")),
            "select event_id, prev is not distinct from null \"first\" from (select event_id, lag(event_id) over (partition by user_id order by ts, event_id) prev from events) where coalesce(prev, -1) <= 100",
        ),
    }


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {n: f for n, (f, _) in _cases().items()}


def oracle_sql() -> dict[str, str]:
    return {n: s for n, (_, s) in _cases().items()}


