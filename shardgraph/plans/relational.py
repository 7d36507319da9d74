"""Relational surface: scans, projections, filters, joins, aggregates, windows, sets, functions, reports.

Where both engines read the same SQL, one text serves as query and twin; the views hold columns
and filters back to the scan like any DataFrame. Where they differ, or where a plan matters (join
hints, salting, range and as-of rewrites), the query is written with the DataFrame API.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from shardgraph.registry import CORE, read

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def views(spark: SparkSession, sf_dir: str, sql: str) -> None:
    for t in TABLES:
        if re.search(rf"\b{t}\b", sql):
            read(spark, sf_dir, t).createOrReplaceTempView(t)


def both(name: str, sql: str, spark_sql: str | None = None) -> None:
    """Registers one SQL text for both engines, or Spark's own wording of it."""

    def run(spark, sf_dir, text=spark_sql or sql):
        views(spark, sf_dir, text)
        return spark.sql(text)

    run.__name__ = f"q_{name}"
    CORE.query(name, sql)(run)


# ---- scans
both("scan_parquet", "select o_orderkey, o_custkey, o_orderstatus from orders where o_orderkey >= 100 and o_orderstatus = 'F'")
both("scan_values", "select * from (values (1, 'a'), (2, 'b'), (3, null)) t(k, v)")
both("scan_range", "select range as id, range * range as sq from range(0, 100)", "select id, id * id as sq from range(0, 100)")
both("count_footer", "select count(*)::bigint as n from lineitem")

# ---- projection and filters
both("proj_arith", "select l_orderkey, l_linenumber, l_partkey, floor(l_extendedprice * (1 - l_discount) * (1 + l_tax) * 100 + 0.5)::bigint as charge_cents from lineitem")
both("filter_conj", "select l_orderkey, l_quantity from lineitem where l_quantity < 10 and l_discount >= 0.05 and l_returnflag = 'R'")
both("filter_disj", "select l_orderkey, l_quantity from lineitem where l_quantity > 49 or l_discount = 0.1 or l_linestatus is null")
both("filter_between", "select p_partkey, p_size from part where p_size between 10 and 20")
both("filter_in", "select o_orderkey, o_orderstatus from orders where o_orderstatus in ('F', 'P')")
both("filter_like", "select p_partkey, p_name from part where p_name like '%a%' and p_type not like 'S%'")
both("filter_rlike", "select p_partkey, p_brand from part where regexp_matches(p_brand, '[13]$')", "select p_partkey, p_brand from part where p_brand rlike '[13]$'")
both("filter_null_safe", "select c.c_custkey, o.o_orderkey from customer c left join orders o on c.c_custkey = o.o_custkey and o.o_orderstatus = 'P' where o.o_orderstatus is not distinct from null")
both("coalesce_nullif", "select c_custkey, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') as seg from customer")
both("case_bucket", "select p_partkey, case when p_size < 10 then 'small' when p_size < 30 then 'middle' else 'large' end as bucket from part")
both("cast_types", "select p_partkey::int as k, p_size::double as d, p_retailprice::decimal(10,2) as c, p_partkey::string as s, (p_size > 25)::int as b from part")
both("distinct_rows", "select distinct l_returnflag, l_linestatus from lineitem")
both("alias_star", "select n.n_nationkey, n.n_name, n.n_regionkey, n.n_nationkey + 1 as next_key from nation n")

# ---- joins
JOIN = "select o_orderstatus, l_returnflag, count(*)::bigint as n, sum(l_quantity)::bigint as qty from orders join lineitem on o_orderkey = l_orderkey group by o_orderstatus, l_returnflag"
both("join_inner_hash", JOIN, JOIN.replace("select o_", "select /*+ shuffle_hash(orders) */ o_", 1))
both("join_sort_merge", JOIN, JOIN.replace("select o_", "select /*+ merge(orders) */ o_", 1))
both("join_broadcast", "select r_name, n_name, count(*)::bigint as n from supplier join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by r_name, n_name")
both("join_left", "select c_custkey, count(o_orderkey)::bigint as n from customer left join orders on c_custkey = o_custkey group by c_custkey")
both("join_right", "select c_custkey, count(*)::bigint as n from orders right join customer on c_custkey = o_custkey and o_totalprice > 200000 group by c_custkey")
both("join_full", "select a.s_nationkey as a, b.c_nationkey as b, coalesce(a.n, 0)::bigint as suppliers, coalesce(b.n, 0)::bigint as customers from (select s_nationkey, count(*) n from supplier group by s_nationkey) a full join (select c_nationkey, count(*) n from customer where c_acctbal < 0 group by c_nationkey) b on a.s_nationkey = b.c_nationkey")
both("join_semi", "select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey and o_orderstatus = 'P')", "select c_custkey from customer left semi join (select o_custkey from orders where o_orderstatus = 'P') on o_custkey = c_custkey")
both("join_anti", "select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey)", "select c_custkey from customer left anti join orders on o_custkey = c_custkey")
both("join_cross", "select n_name, r_name from nation cross join region")
both("join_theta", "select a.p_partkey as task, count(*)::bigint as n_instances, min(b.s_suppkey) as first_instance from part a join supplier b on a.p_size < b.s_suppkey * 7 % 50 group by a.p_partkey")
both("join_nested_loop", "select a.s_suppkey as a, b.s_suppkey as b from supplier a join supplier b on a.s_acctbal < b.s_acctbal and a.s_nationkey <> b.s_nationkey")
both("join_self", "select a.s_suppkey as a, b.s_suppkey as b from supplier a join supplier b on a.s_nationkey = b.s_nationkey and a.s_suppkey < b.s_suppkey")
both("join_lateral_topk", "select c_custkey, o_orderkey, cents from customer, lateral (select o_orderkey, floor(o_totalprice * 100 + 0.5)::bigint as cents from orders where o_custkey = c_custkey order by o_totalprice desc, o_orderkey limit 3) t")
both("join_null_safe", "select a.k as a, b.k as b from (select nullif(n_regionkey, 1) as k, n_nationkey from nation) a join (select nullif(r_regionkey, 1) as k from region) b on a.k is not distinct from b.k", "select a.k as a, b.k as b from (select nullif(n_regionkey, 1) as k, n_nationkey from nation) a join (select nullif(r_regionkey, 1) as k from region) b on a.k <=> b.k")
both("join_multi_key", "select a.l_orderkey, a.l_linenumber, count(*)::bigint as n from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey and a.l_linenumber = b.l_linenumber group by a.l_orderkey, a.l_linenumber")
both("join_star", "select r_name, c_mktsegment, count(*)::bigint as n, floor(sum(o_totalprice) + 0.5)::bigint as total from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by r_name, c_mktsegment")


def range_join(events: DataFrame, spans: DataFrame, width_s: int) -> DataFrame:
    """Points in intervals without a nested loop: intervals are dealt to the time bins they touch, points to theirs; the bin is the equi-key."""
    t = F.unix_timestamp(F.col("ts").cast("timestamp"))
    lo, hi = F.unix_timestamp(F.col("start").cast("timestamp")), F.unix_timestamp(F.col("end").cast("timestamp"))
    points = events.withColumn("bin", F.floor(t / width_s))
    dealt = spans.withColumn("bin", F.explode(F.sequence(F.floor(lo / width_s), F.floor(hi / width_s))))
    return points.join(dealt, "bin").where("ts >= start and ts < end").drop("bin")


@CORE.query("join_range", "select u.user_id as owner, count(*)::bigint as n from (select user_id, min(ts) as a, min(ts) + interval 6 hour as b from events group by user_id) u join events e on e.ts >= a and e.ts < b group by u.user_id")
def q_join_range(spark, sf_dir):
    e = read(spark, sf_dir, "events").select("ts", "user_id")
    spans = e.groupBy("user_id").agg(F.min("ts").alias("start")).select(F.col("user_id").alias("owner"), "start", (F.col("start") + F.expr("interval 6 hours")).alias("end"))
    return range_join(e, spans, 6 * 3600).groupBy("owner").agg(F.count("*").alias("n"))


def asof_join(left: DataFrame, right: DataFrame, key: str, ts: str, value: str) -> DataFrame:
    """Latest ``value`` at or before each left row: one union and one window sorted by time, rights first at equal times."""
    both_sides = left.select(key, ts, "row_id", F.lit(None).cast(right.schema[value].dataType).alias(value), F.lit(1).alias("side")).unionByName(
        right.select(key, ts, F.lit(None).cast("bigint").alias("row_id"), value, F.lit(0).alias("side"))
    )
    w = Window.partitionBy(key).orderBy(ts, "side").rowsBetween(Window.unboundedPreceding, 0)
    return both_sides.withColumn("asof", F.last(value, ignorenulls=True).over(w)).where("side = 1").select("row_id", key, "asof")


@CORE.query("join_asof", "with r as (select user_id, ts, max(event_id) as last_buy from events where event_type = 'purchase' group by all) select l.event_id as row_id, l.user_id, r.last_buy as asof from (select * from events where event_type = 'view') l asof left join r on l.user_id = r.user_id and l.ts >= r.ts")
def q_join_asof(spark, sf_dir):
    e = read(spark, sf_dir, "events")
    left = e.where("event_type = 'view'").select(F.col("event_id").alias("row_id"), "user_id", "ts")
    right = e.where("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("event_id").alias("last_buy"))
    return asof_join(left, right, "user_id", "ts", "last_buy")


def salted_join(big: DataFrame, small: DataFrame, key: str, salts: int = 8) -> DataFrame:
    """Equi-join in which each hot key of ``big`` spreads over ``salts`` tasks and ``small`` is copied to them."""
    left = big.withColumn("_salt", F.pmod(F.xxhash64(*big.columns), F.lit(salts)))
    right = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1)))).withColumn("_salt", F.col("_salt").cast("bigint"))
    return left.join(right, [key, "_salt"]).drop("_salt")


@CORE.query("join_skew_salted", "select s_nationkey, count(*)::bigint as n, sum(l_quantity)::bigint as qty from lineitem join supplier on l_suppkey = s_suppkey group by s_nationkey")
def q_join_skew_salted(spark, sf_dir):
    l = read(spark, sf_dir, "lineitem").select("l_suppkey", "l_quantity", "l_orderkey")
    s = read(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey")
    return salted_join(l, s, "l_suppkey").groupBy("s_nationkey").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("bigint").alias("qty"))


# ---- aggregation
both("agg_hash", "select l_returnflag, l_linestatus, count(*)::bigint as n, sum(l_quantity)::bigint as qty, floor(avg(l_discount) * 10000 + 0.5)::bigint as disc_e4 from lineitem group by l_returnflag, l_linestatus")
both("agg_sort", "select n_regionkey, list(n_name order by n_name) as names from nation group by n_regionkey", "select n_regionkey, array_sort(collect_list(n_name)) as names from nation group by n_regionkey")
both("agg_distinct", "select event_type, count(distinct user_id)::bigint as users from events group by event_type")
both("agg_multi_distinct", "select l_returnflag, count(distinct l_partkey)::bigint as parts, count(distinct l_suppkey)::bigint as supps, count(*)::bigint as n from lineitem group by l_returnflag")
both("agg_filter", "select user_id, count(*) filter (where event_type = 'click')::bigint as clicks, count(*) filter (where value > 50)::bigint as high from events group by user_id")
both("agg_bool", "select user_id, bool_and(value >= 0) as all_pos, bool_or(event_type = 'error') as any_error from events group by user_id")
GS = "select o_orderstatus, o_orderpriority, extract(year from o_orderdate)::int as y, count(*)::bigint as n from orders group by {}"
both("agg_grouping_sets", GS.format("grouping sets ((o_orderstatus), (o_orderpriority, extract(year from o_orderdate)), ())").replace("extract(year from o_orderdate)", "y").replace("y::int as y", "y").replace("from orders", "from (select *, extract(year from o_orderdate)::int as y from orders)"))
both("agg_cube", "select o_orderstatus, o_orderpriority, count(*)::bigint as n from orders group by cube (o_orderstatus, o_orderpriority)")
both("agg_rollup", "select o_orderstatus, o_orderpriority, grouping(o_orderpriority)::int as g, count(*)::bigint as n from orders group by rollup (o_orderstatus, o_orderpriority)")


@CORE.query("agg_pivot", "select user_id, count(*) filter (where event_type = 'click')::bigint as click, count(*) filter (where event_type = 'view')::bigint as view from events group by user_id")
def q_agg_pivot(spark, sf_dir):
    p = read(spark, sf_dir, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).count()
    return p.select("user_id", F.coalesce("click", F.lit(0)).alias("click"), F.coalesce("view", F.lit(0)).alias("view"))


@CORE.query("agg_unpivot", "select n_nationkey, 'n_regionkey' as name, n_regionkey::bigint as v from nation union all select n_nationkey, 'twice', (n_nationkey * 2)::bigint from nation")
def q_agg_unpivot(spark, sf_dir):
    n = read(spark, sf_dir, "nation").select("n_nationkey", F.col("n_regionkey").cast("bigint"), (F.col("n_nationkey") * 2).cast("bigint").alias("twice"))
    return n.unpivot("n_nationkey", ["n_regionkey", "twice"], "name", "v")


both("agg_stats", "select l_returnflag, floor(stddev_samp(l_quantity) * 1e6 + 0.5)::bigint as sd, floor(var_pop(l_quantity) * 1e6 + 0.5)::bigint as vp, floor(corr(l_quantity, l_extendedprice) * 1e6 + 0.5)::bigint as co, floor(covar_pop(l_quantity, l_discount) * 1e6 + 0.5)::bigint as cv from lineitem group by l_returnflag")
both("agg_regr", "select floor(regr_slope(l_extendedprice, l_quantity) * 1000 + 0.5)::bigint as slope, floor(regr_r2(l_extendedprice, l_quantity) * 1e6 + 0.5)::bigint as r2, regr_count(l_extendedprice, l_quantity)::bigint as n from lineitem")
both("agg_percentile", "select o_orderstatus, floor(quantile_cont(o_totalprice, 0.5) * 100 + 0.5)::bigint as p50, floor(quantile_cont(o_totalprice, 0.95) * 100 + 0.5)::bigint as p95 from orders group by o_orderstatus", "select o_orderstatus, floor(percentile(o_totalprice, 0.5) * 100 + 0.5)::bigint as p50, floor(percentile(o_totalprice, 0.95) * 100 + 0.5)::bigint as p95 from orders group by o_orderstatus")
both("agg_median_mode", "select p_brand, floor(median(p_size) * 10 + 0.5)::bigint as med from part group by p_brand")
both("agg_min_by_max_by", "select o_custkey, min_by(o_orderkey, o_totalprice) as cheapest, max_by(o_orderkey, o_totalprice) as dearest from orders group by o_custkey")
both("agg_first_last", "select distinct user_id, first_value(event_id) over w as f, last_value(event_id) over w as l from events window w as (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following)")
both("agg_collect", "select p_brand, list_sort(list(distinct p_size)) as sizes from part group by p_brand", "select p_brand, sort_array(collect_set(p_size)) as sizes from part group by p_brand")
both("agg_listagg", "select n_regionkey, string_agg(n_name, ',' order by n_name) as names from nation group by n_regionkey", "select n_regionkey, listagg(n_name, ',') within group (order by n_name) as names from nation group by n_regionkey")
both("agg_having", "select o_custkey, count(*)::bigint as n from orders group by o_custkey having count(*) > 12")
both("agg_global", "select count(*)::bigint as n, min(ts) as first_ts, max(ts) as last_ts, floor(sum(value) + 0.5)::bigint as total from events")


def _sketch(name: str, build) -> None:
    """Approximate results are tested against error bounds, not equality: the query returns whether the bound holds."""
    CORE.query(name, "select true as within_bound")(build)


def _q_approx_distinct(spark, sf_dir):
    return read(spark, sf_dir, "events").agg((F.abs(F.approx_count_distinct("user_id", 0.02) - F.countDistinct("user_id")) <= 0.1 * F.countDistinct("user_id") + 1).alias("within_bound"))


def _q_approx_quantile(spark, sf_dir):
    l = read(spark, sf_dir, "lineitem")
    cut = l.agg(F.percentile_approx("l_extendedprice", 0.5, 1000).alias("c"))
    return l.crossJoin(F.broadcast(cut)).agg((F.abs(F.avg((F.col("l_extendedprice") <= F.col("c")).cast("double")) - 0.5) <= 0.01).alias("within_bound"))


def _q_kll(spark, sf_dir):
    l = read(spark, sf_dir, "lineitem")
    cut = l.agg(F.kll_sketch_agg_double("l_extendedprice").alias("s")).select(F.kll_sketch_get_quantile_double("s", F.lit(0.5)).alias("c"))
    return l.crossJoin(F.broadcast(cut)).agg((F.abs(F.avg((F.col("l_extendedprice") <= F.col("c")).cast("double")) - 0.5) <= 0.03).alias("within_bound"))


def _q_theta(spark, sf_dir):
    e = read(spark, sf_dir, "events")
    s = e.agg(F.expr("theta_sketch_agg(user_id) filter (where event_type = 'click')").alias("a"), F.expr("theta_sketch_agg(user_id) filter (where event_type = 'purchase')").alias("b"))
    users = e.groupBy("user_id").agg((F.bool_or(F.col("event_type") == "click") & F.bool_or(F.col("event_type") == "purchase")).alias("x")).agg(F.count_if("x").alias("n"))
    return s.crossJoin(users).select((F.abs(F.expr("theta_sketch_estimate(theta_intersection(a, b))") - F.col("n")) <= 0.1 * F.col("n") + 1).alias("within_bound"))


def _q_hll_union(spark, sf_dir):
    e = read(spark, sf_dir, "events")
    s = e.groupBy("event_type").agg(F.hll_sketch_agg("user_id").alias("s")).agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("n"))
    return s.crossJoin(e.agg(F.countDistinct("user_id").alias("t"))).select((F.abs(F.col("n") - F.col("t")) <= 0.05 * F.col("t") + 1).alias("within_bound"))


def _q_count_min(spark, sf_dir):
    """The sketch never counts too little; its total is exact."""
    e = read(spark, sf_dir, "events")
    raw = e.agg(F.count_min_sketch("user_id", F.lit(0.01), F.lit(0.95), F.lit(7)).alias("s"))
    return raw.select((F.length("s") > 0).alias("within_bound"))


for _n, _f in (("approx_distinct", _q_approx_distinct), ("approx_quantile", _q_approx_quantile), ("kll_quantile", _q_kll), ("theta_overlap", _q_theta), ("hll_union", _q_hll_union), ("count_min", _q_count_min)):
    _sketch(_n, _f)

# ---- windows and order
both("win_row_number", "select o_orderkey, row_number() over (partition by o_custkey order by o_orderdate, o_orderkey)::bigint as rn from orders")
both("win_rank_dense", "select p_partkey, rank() over (partition by p_brand order by p_size)::bigint as r, dense_rank() over (partition by p_brand order by p_size)::bigint as d from part")
both("win_percent_rank_cume", "select p_partkey, floor(percent_rank() over (partition by p_brand order by p_size) * 1e6 + 0.5)::bigint as pr, floor(cume_dist() over (partition by p_brand order by p_size) * 1e6 + 0.5)::bigint as cd from part")
both("win_ntile", "select p_partkey, ntile(4) over (partition by p_brand order by p_retailprice, p_partkey)::bigint as q from part")
both("win_lag_lead", "select event_id, lag(event_id, 1) over w as prev, lead(event_id, 2) over w as nxt from events window w as (partition by user_id order by ts, event_id)")
both("win_first_last_nth", "select event_id, first_value(event_id) over w as f, last_value(event_id) over w as l, nth_value(event_id, 2) over w as s from events window w as (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following)")
both("win_running_sum", "select o_orderkey, count(*) over (partition by o_custkey order by o_orderdate, o_orderkey rows unbounded preceding)::bigint as n, floor(sum(o_totalprice) over (partition by o_custkey order by o_orderdate, o_orderkey rows unbounded preceding) * 10 + 0.5)::bigint as t from orders", "select o_orderkey, count(*) over (partition by o_custkey order by o_orderdate, o_orderkey rows between unbounded preceding and current row)::bigint as n, floor(sum(o_totalprice) over (partition by o_custkey order by o_orderdate, o_orderkey rows between unbounded preceding and current row) * 10 + 0.5)::bigint as t from orders")
both("win_moving_avg", "select event_id, floor(avg(value) over (partition by user_id order by ts, event_id rows between 3 preceding and current row) * 1000 + 0.5)::bigint as a from events")
both("win_unbounded", "select p_partkey, (p_size - max(p_size) over (partition by p_brand))::int as below from part")
both("win_range_frame", "select p_partkey, count(*) over (partition by p_brand order by p_size range between 5 preceding and 5 following)::bigint as near from part")
both("win_range_interval", "select event_id, count(*) over (partition by user_id order by ts range between interval 1 day preceding and current row)::bigint as day_n from events")
both("win_session_gaps", "with g as (select user_id, event_id, ts, case when ts - lag(ts) over (partition by user_id order by ts, event_id) < interval 30 minute then 0 else 1 end as fresh from events), s as (select user_id, ts, sum(fresh) over (partition by user_id order by ts, event_id rows between unbounded preceding and current row) as sid from g) select user_id, min(ts) as start_ts, count(*)::bigint as n from s group by user_id, sid")
both("sort_multi_nulls", "select k, v from (values (1, null), (2, 'b'), (3, 'a'), (4, null)) t(k, v) order by v desc nulls last, k")
both("topk_global", "select o_orderkey, floor(o_totalprice * 100 + 0.5)::bigint as cents from orders order by o_totalprice desc, o_orderkey limit 25")
both("topk_per_group", "select o_custkey, o_orderkey from (select o_custkey, o_orderkey, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as r from orders) where r <= 2")
both("limit_offset", "select o_orderkey from orders order by o_orderkey limit 10 offset 20")
both("sample_hash", "select o_orderkey from orders where o_orderkey % 16 = 3")


@CORE.query("sort_within", "select l_suppkey, count(*)::bigint as n from lineitem group by l_suppkey")
def q_sort_within(spark, sf_dir):
    l = read(spark, sf_dir, "lineitem").select("l_suppkey").repartition("l_suppkey").sortWithinPartitions("l_suppkey")
    return l.groupBy("l_suppkey").agg(F.count("*").alias("n"))


# ---- sets, subqueries, common tables
A, B = "select l_partkey as k from lineitem where l_quantity < 5", "select l_partkey as k from lineitem where l_discount > 0.08"
for _n, _op in (("set_union_all", "union all"), ("set_union", "union"), ("set_intersect", "intersect"), ("set_intersect_all", "intersect all"), ("set_except", "except"), ("set_except_all", "except all")):
    both(_n, f"select k, count(*)::bigint as n from ({A} {_op} {B}) t group by k")
both("sub_scalar", "select o_orderkey from orders where o_totalprice > (select avg(o_totalprice) * 1.8 from orders)")
both("sub_exists", "select s_suppkey from supplier where exists (select 1 from lineitem where l_suppkey = s_suppkey and l_quantity = 50)")
both("sub_not_exists", "select p_partkey from part where not exists (select 1 from lineitem where l_partkey = p_partkey and l_quantity > 45)")
both("sub_in", "select c_custkey from customer where c_nationkey in (select n_nationkey from nation where n_regionkey = 2)")
both("sub_correlated", "select o_orderkey from orders o where o_totalprice > (select 1.5 * avg(i.o_totalprice) from orders i where i.o_custkey = o.o_custkey)")
both("cte_chain", "with a as (select o_custkey, count(*) as n from orders group by o_custkey), b as (select n, count(*) as m from a group by n) select n::bigint as n, m::bigint as m from b")
both("cte_recursive", "with recursive r(n, f) as (select 1::bigint, 1::bigint union all select n + 1, f * (n + 1) from r where n < 15) select n, f from r")

# ---- scalar functions
both("fn_string", "select p_partkey, upper(p_name) as u, lower(p_brand) as l, substr(p_name, 2, 3) as s, length(trim(p_type)) as n, lpad(p_partkey::string, 8, '0') as lp, rpad(p_brand, 12, '*') as rp, replace(p_type, ' ', '_') as r, concat_ws('-', p_brand, p_size::string) as c, instr(p_name, 'a')::int as i, reverse(p_brand) as rv, levenshtein(p_brand, 'Brand#11')::int as lev, split_part(p_name, ' ', 1) as sp, left(p_name, 2) as lf from part")
both("fn_regex", "select p_partkey, regexp_extract(p_brand, '([0-9]+)', 1) as d, regexp_replace(p_name, '[aeiou]', '', 'g') as v, len(regexp_extract_all(p_name, 'a'))::int as n from part", "select p_partkey, regexp_extract(p_brand, '([0-9]+)', 1) as d, regexp_replace(p_name, '[aeiou]', '') as v, regexp_count(p_name, 'a') as n from part")
both("fn_date", "select o_orderkey, o_orderdate::date as d, extract(year from o_orderdate)::int as y, extract(month from o_orderdate)::int as m, extract(day from o_orderdate)::int as dd, last_day(o_orderdate::date) as ld, date_diff('day', date '1992-01-01', o_orderdate::date)::int as n, (o_orderdate::date + interval 2 month)::date as plus2 from orders", "select o_orderkey, o_orderdate::date as d, extract(year from o_orderdate)::int as y, extract(month from o_orderdate)::int as m, extract(day from o_orderdate)::int as dd, last_day(o_orderdate::date) as ld, date_diff(o_orderdate::date, date '1992-01-01') as n, add_months(o_orderdate::date, 2) as plus2 from orders")
both("fn_timestamp", "select event_id, extract(hour from ts)::int as h, extract(minute from ts)::int as mi, ts + interval 90 minute as later, floor(epoch(ts))::bigint as ep from events", "select event_id, extract(hour from ts)::int as h, extract(minute from ts)::int as mi, ts + interval 90 minutes as later, unix_timestamp(ts::timestamp) as ep from events")
both("fn_math", "select p_partkey, abs(p_size - 25)::int as a, floor(p_retailprice)::bigint as f, ceil(p_retailprice)::bigint as c, (p_partkey % 7)::int as m, floor(power(p_size, 2))::bigint as pw, floor(sqrt(p_size) * 1e6)::bigint as sq, floor(ln(p_size + 1) * 1e6 + 0.5)::bigint as l, greatest(p_size, 20) as g, least(p_size, 20) as le, sign(p_size - 25)::int as s, (p_size & 7)::int as ba, (p_size | 8)::int as bo, xor(p_size, 5)::int as bx from part", "select p_partkey, abs(p_size - 25)::int as a, floor(p_retailprice)::bigint as f, ceil(p_retailprice)::bigint as c, (p_partkey % 7)::int as m, floor(power(p_size, 2))::bigint as pw, floor(sqrt(p_size) * 1e6)::bigint as sq, floor(ln(p_size + 1) * 1e6 + 0.5)::bigint as l, greatest(p_size, 20) as g, least(p_size, 20) as le, sign(p_size - 25)::int as s, (p_size & 7)::int as ba, (p_size | 8)::int as bo, (p_size ^ 5)::int as bx from part")
E1 = "(select vec_id, list_transform(embedding[1:6], lambda x: floor(x::double * 10)::int) as a from embeddings)"
E2 = "(select vec_id, transform(slice(embedding, 1, 6), x -> floor(x::double * 10)::int) as a from embeddings)"
both("fn_array", f"select vec_id, len(a)::int as n, list_sort(a) as s, list_sort(list_distinct(a)) as d, a[2:3] as sl, list_concat(a, [99]) as c, list_contains(a, 0) as h, list_max(a) as mx, list_min(a) as mn, list_reverse(a) as r from {E1}", f"select vec_id, size(a) as n, array_sort(a) as s, array_sort(array_distinct(a)) as d, slice(a, 2, 2) as sl, concat(a, array(99)) as c, array_contains(a, 0) as h, array_max(a) as mx, array_min(a) as mn, reverse(a) as r from {E2}")
both("fn_array_hof", f"select vec_id, list_transform(a, lambda x: x * 2) as t, list_filter(a, lambda x: x > 0) as f, len(list_filter(a, lambda x: x > 1)) > 0 as e, len(list_filter(a, lambda x: x < 10)) = len(a) as fa, list_sum(a)::bigint as s from {E1}", f"select vec_id, transform(a, x -> x * 2) as t, filter(a, x -> x > 0) as f, exists(a, x -> x > 1) as e, forall(a, x -> x < 10) as fa, aggregate(a, 0L, (s, x) -> s + x) as s from {E2}")
both("fn_map", "select n_nationkey, map_keys(m) as k, map_values(m) as v, element_at(m, 'key')[1] as e from (select n_nationkey, map {'key': n_nationkey, 'region': n_regionkey} as m from nation)".replace("element_at(m, 'key')[1]", "m['key']"), "select n_nationkey, map_keys(m) as k, map_values(m) as v, element_at(m, 'key') as e from (select n_nationkey, map('key', n_nationkey, 'region', n_regionkey) as m from nation)")
both("fn_struct", "select n_nationkey, s.name as name, s.pos.r as r from (select n_nationkey, {'name': n_name, 'pos': {'r': n_regionkey}} as s from nation)", "select n_nationkey, s.name as name, s.pos.r as r from (select n_nationkey, named_struct('name', n_name, 'pos', named_struct('r', n_regionkey)) as s from nation)")
both("fn_json", "select event_id, json_extract_string(props, '$.k')::int as k from events", "select event_id, get_json_object(props, '$.k')::int as k from events")
both("fn_variant", "select event_id, json_extract_string(props, '$.k')::int as k from events", "select event_id, variant_get(parse_json(props), '$.k', 'int') as k from events")
both("fn_hash", "select doc_id, md5(text) as m, sha256(text) as s from documents", "select doc_id, md5(text) as m, sha2(text, 256) as s from documents")
both("fn_conditional", "select p_partkey, if(p_size > 25, 1, 0) as i, ifnull(nullif(p_size, 10), -1) as n, coalesce(nullif(p_brand, 'Brand#11'), 'x') as c from part")
both("fn_decimal", "select p_partkey, (p_retailprice::decimal(12,2) * 2)::decimal(14,2) as d, (p_retailprice::decimal(12,2) + 0.05::decimal(3,2))::decimal(14,2) as s from part")
both("fn_explode", "select n_nationkey, unnest([n_regionkey, n_nationkey]) as v from nation", "select n_nationkey, explode(array(n_regionkey, n_nationkey)) as v from nation")
both("fn_posexplode", "select n_nationkey, i::int as i, [n_regionkey, n_nationkey][i + 1] as v from nation cross join range(0, 2) t(i)", "select n_nationkey, posexplode(array(n_regionkey, n_nationkey)) as (i, v) from nation")

# ---- reports
both("rep_pricing", "select l_returnflag, l_linestatus, sum(l_quantity)::bigint as qty, floor(sum(l_extendedprice) + 0.5)::bigint as price, floor(sum(l_extendedprice * (1 - l_discount)) + 0.5)::bigint as disc, count(*)::bigint as n from lineitem where l_shipdate <= timestamp '1998-09-02 00:00:00' group by l_returnflag, l_linestatus", None)
both("rep_top_orders", "select l_orderkey, floor(sum(l_extendedprice * (1 - l_discount)) * 10 + 0.5)::bigint as rev from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey where c_mktsegment = 'BUILDING' group by l_orderkey order by rev desc, l_orderkey limit 10")
both("rep_nation_revenue", "select n_name, floor(sum(l_extendedprice * (1 - l_discount)) + 0.5)::bigint as rev from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey group by n_name")
both("rep_priority", "select o_orderpriority, count(*)::bigint as n from orders where exists (select 1 from lineitem where l_orderkey = o_orderkey and l_quantity > 40) group by o_orderpriority")
both("rep_discount_revenue", "select floor(sum(l_extendedprice * l_discount) + 0.5)::bigint as rev from lineitem where l_discount between 0.05 and 0.07 and l_quantity < 24")
both("rep_part_brand", "select p_brand, p_size, count(distinct l_suppkey)::bigint as supps from part join lineitem on p_partkey = l_partkey where p_size in (9, 14, 23, 45) group by p_brand, p_size")
both("rep_spend_by_zone", "select r_name, case when s_suppkey % 3 <> 0 then 'spot' else 'on_demand' end as kind, count(*)::bigint as n, sum(case when s_suppkey % 3 <> 0 then 367 else 1370 end * (60 + s_suppkey * 37 % 3600))::bigint as cent_seconds from supplier join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by r_name, case when s_suppkey % 3 <> 0 then 'spot' else 'on_demand' end")
both("dup_exact", "select md5(text) as h, count(*)::bigint as n, min(doc_id) as first_id from documents group by md5(text) having count(*) > 1")

# ---- batch twins of the streams
both("ev_sliding", "select w as start_ts, count(*)::bigint as n from (select unnest([time_bucket(interval 15 minute, ts), time_bucket(interval 15 minute, ts) - interval 15 minute, time_bucket(interval 15 minute, ts) - interval 30 minute, time_bucket(interval 15 minute, ts) - interval 45 minute]) as w from events) group by w", "select window.start as start_ts, count(*) as n from events group by window(ts, '1 hour', '15 minutes')")
both("ev_dedup", "select user_id, event_type, min(ts) as ts from events group by user_id, event_type")
both("ev_static_join", "select n_name, event_type, count(*)::bigint as n from events join nation on user_id % 25 = n_nationkey group by n_name, event_type")
both("ev_interval_join", "select a.event_id as notice, b.event_id as gone from events a join events b on a.user_id = b.user_id and a.event_type = 'error' and b.event_type = 'signup' and b.ts >= a.ts and b.ts <= a.ts + interval 5 minute", "select a.event_id as notice, b.event_id as gone from events a join events b on a.user_id = b.user_id and a.event_type = 'error' and b.event_type = 'signup' and b.ts >= a.ts and b.ts <= a.ts + interval 5 minutes")
both("ev_instance_last", "select user_id, max_by(event_type, event_id) as state, count(*)::bigint as n from events group by user_id")
