"""Queries for the relational surface around the methods: scans, joins, aggregates, windows, sets, functions, UDFs, files."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from approxboot import ship_package
from approxboot.catalog.methods import cents, t
from approxboot.functions import rng
from approxboot.operators import joins, resample, sampling
from approxboot.sources.shared import fresh_path

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def same_sql(name: str, text: str, spark_text: str | None = None) -> None:
    """A query whose SQL Spark runs as it stands (or as spark_text) over {table} references."""
    import re

    tables = sorted(set(re.findall(r"\{(\w+)\}", spark_text or text)))

    def run(spark, sf_dir):
        return spark.sql(spark_text or text, **{k: t(spark, sf_dir, k) for k in tables})

    QUERIES[name] = run
    ORACLES[name] = re.sub(r"\{(\w+)\}", r"\1", text)


MONEY = "cast(round({} * 100) as bigint)"
P = MONEY.format("l_extendedprice")
O = MONEY.format("o_totalprice")

# --- scans

same_sql("op_scan_projection", "select o_orderkey, o_custkey as customer from {orders}")
same_sql("op_scan_equal", "select o_orderkey from {orders} where o_orderpriority = '1-URGENT'")
same_sql("op_scan_range", "select l_orderkey, l_linenumber from {lineitem} where l_quantity < 3 and l_discount between 0.02 and 0.04")
same_sql("op_scan_in", "select c_custkey from {customer} where c_mktsegment in ('BUILDING', 'MACHINERY')")
same_sql("op_scan_like", "select p_partkey from {part} where p_name like '%a%' and p_type not like 'S%'")
same_sql("op_scan_regex", "select page_id from {pages} where regexp_like(url, '/(en|de)/[0-9]+')")
ORACLES["op_scan_regex"] = "select page_id from pages where regexp_matches(url, '/(en|de)/[0-9]+')"
same_sql("op_scan_null_logic", "select count(*) as n from {orders} where o_orderstatus is not null and not (o_orderstatus = 'F' or o_orderstatus = 'P')")
same_sql("op_scan_case", f"select o_orderkey, case when {O} > 30000000 then 'high' when {O} > 10000000 then 'mid' else 'low' end as band from {{orders}}")
same_sql("op_scan_cast", "select o_orderkey, cast(cast(o_totalprice as decimal(18,2)) as double) as price, cast(o_orderdate as date) as day from {orders}")
same_sql("op_scan_sampled", f"select o_orderkey from {{orders}} where {rng.sql_uniform('sample', 'o_orderkey')} < 0.1")


def _sampled(spark, sf_dir):
    return sampling.bernoulli(t(spark, sf_dir, "orders", "o_orderkey"), ["o_orderkey"], 0.1, kind="md5")


QUERIES["op_scan_sampled"] = _sampled

# --- joins


@query("op_join_inner", f"select n_name, count(*) as n, cast(sum({O}) as bigint) as cents from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey group by n_name")
def op_join_inner(spark, sf_dir):
    o, c, n = t(spark, sf_dir, "orders", "o_custkey", "o_totalprice"), t(spark, sf_dir, "customer", "c_custkey", "c_nationkey"), t(spark, sf_dir, "nation", "n_nationkey", "n_name")
    return o.join(c, o.o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"), F.sum(cents("o_totalprice")).alias("cents"))


same_sql("op_join_left", "select c_custkey, count(o_orderkey) as n from {customer} left join {orders} on c_custkey = o_custkey group by c_custkey")
same_sql("op_join_right", "select n_name, count(s_suppkey) as n from {supplier} right join {nation} on s_nationkey = n_nationkey group by n_name")
same_sql("op_join_full", "select coalesce(ck, sk) as nation, coalesce(c, 0) as c, coalesce(s, 0) as s from (select c_nationkey as ck, count(*) as c from {customer} where c_acctbal > 9000 group by 1) full join (select s_nationkey as sk, count(*) as s from {supplier} group by 1) on ck = sk")
same_sql("op_join_semi", "select c_custkey from {customer} where exists (select 1 from {orders} where o_custkey = c_custkey and o_orderpriority = '1-URGENT')")
same_sql("op_join_anti", "select o_orderkey from {orders} where not exists (select 1 from {lineitem} where l_orderkey = o_orderkey and l_quantity > 40)")
same_sql("op_join_cross", "select r_name, n_name from {region} cross join {nation}")
same_sql("op_join_theta", "select n_name, count(*) as n from {supplier} join {nation} on s_nationkey < n_nationkey group by 1")
same_sql("op_join_null_safe", "select count(*) as n from (select nullif(o_orderstatus, 'F') as k from {orders}) a join (select distinct nullif(o_orderstatus, 'F') as k from {orders}) b on a.k is not distinct from b.k")


@query("op_join_broadcast", "select r_name, count(*) as n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by r_name")
def op_join_broadcast(spark, sf_dir):
    # nation and region have 25 and 5 rows at any scale
    n, r = t(spark, sf_dir, "nation"), t(spark, sf_dir, "region")
    return t(spark, sf_dir, "customer", "c_nationkey").join(F.broadcast(n), F.col("c_nationkey") == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey).groupBy("r_name").agg(F.count(F.lit(1)).alias("n"))


@query("op_join_merge", f"select o_orderpriority, cast(sum({P}) as bigint) as cents from lineitem join orders on l_orderkey = o_orderkey group by 1")
def op_join_merge(spark, sf_dir):
    l, o = t(spark, sf_dir, "lineitem", "l_orderkey", "l_extendedprice"), t(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority").hint("merge")
    return l.join(o, l.l_orderkey == o.o_orderkey).groupBy("o_orderpriority").agg(F.sum(cents("l_extendedprice")).alias("cents"))


@query("op_join_shuffle_hash", "select c_mktsegment, count(*) as n from orders join customer on o_custkey = c_custkey group by 1")
def op_join_shuffle_hash(spark, sf_dir):
    o, c = t(spark, sf_dir, "orders", "o_custkey"), t(spark, sf_dir, "customer", "c_custkey", "c_mktsegment").hint("shuffle_hash")
    return o.join(c, o.o_custkey == c.c_custkey).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@query("op_join_sampled_chain", f"select n_name, count(*) as n, round(count(*) / 0.2, 4) as est from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey where {rng.sql_uniform('sample', 'o_orderkey')} < 0.2 group by n_name")
def op_join_sampled_chain(spark, sf_dir):
    o = sampling.bernoulli(t(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), ["o_orderkey"], 0.2, kind="md5")
    c, n = t(spark, sf_dir, "customer", "c_custkey", "c_nationkey"), t(spark, sf_dir, "nation", "n_nationkey", "n_name")
    out = o.join(c, o.o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))
    return out.withColumn("est", F.round(F.col("n") / 0.2, 4))


@query("op_join_sampled_keys", f"with k as (select o_orderkey, b, {rng.sql_poisson(rng.sql_uniform('boot', 'o_orderkey', 'b'))} as w from orders, (select unnest(range(10)) as b) where {rng.sql_uniform('sample', 'o_orderkey')} < 0.1) select b, round(sum(w * cast(l_quantity as bigint)) / 0.1, 3) as est from k join lineitem on l_orderkey = o_orderkey group by b")
def op_join_sampled_keys(spark, sf_dir):
    o = sampling.sample_keys(t(spark, sf_dir, "orders", "o_orderkey"), "o_orderkey", 0.1, kind="md5")
    l = t(spark, sf_dir, "lineitem", "l_orderkey", "l_quantity")
    w = resample.replicated(o, ["o_orderkey"], 10, kind="md5")
    return l.join(w, l.l_orderkey == w.o_orderkey).groupBy(F.col("b").cast("long").alias("b")).agg(F.round(F.sum(F.col("w") * F.col("l_quantity").cast("long")) / 0.1, 3).alias("est"))


@query("op_join_asof", """with p as (select * from events where event_type = 'purchase'), c as (select user_id, ts, event_id from events where event_type = 'click')
select p.event_id, coalesce(c.event_id, -1) as click from p asof left join c on p.user_id = c.user_id and p.ts >= c.ts""")
def op_join_asof(spark, sf_dir):
    e = t(spark, sf_dir, "events", "event_id", "user_id", "ts", "event_type")
    out = joins.asof_join(e.where("event_type = 'purchase'").drop("event_type"), e.where("event_type = 'click'").drop("event_type"), "ts", ["user_id"], ["event_id"])
    return out.select("event_id", F.coalesce("asof_event_id", F.lit(-1)).alias("click"))


@query("op_join_interval", "select a.event_id as purchase, b.event_id as view from events a join events b on a.user_id = b.user_id and b.ts >= a.ts - interval 1 hour and b.ts <= a.ts where a.event_type = 'purchase' and b.event_type = 'view'")
def op_join_interval(spark, sf_dir):
    e = t(spark, sf_dir, "events", "event_id", "user_id", "ts", "event_type").withColumn("at", F.unix_micros(F.col("ts").cast("timestamp")))
    views = e.where("event_type = 'view'").select("user_id", "at", F.col("event_id").alias("view"))
    buys = e.where("event_type = 'purchase'").select("user_id", F.col("at").alias("end"), F.col("event_id").alias("purchase"))
    hour = 3_600_000_000
    return joins.interval_join(views, buys, ["user_id"], F.col("at"), F.col("end") - hour, F.col("end"), hour).select("purchase", "view")


# --- aggregates

same_sql("op_agg_hash", f"select l_returnflag, l_linestatus, count(*) as n, cast(sum({P}) as bigint) as cents, min(l_quantity) as lo, max(l_quantity) as hi, round(avg(l_quantity), 6) as mean from {{lineitem}} group by l_returnflag, l_linestatus")
same_sql("op_agg_global", f"select count(*) as n, cast(sum({P}) as bigint) as cents, count(distinct l_suppkey) as suppliers from {{lineitem}}")
same_sql("op_agg_distinct", "select l_returnflag, count(distinct l_partkey) as parts, count(distinct l_suppkey) as suppliers from {lineitem} group by l_returnflag")
same_sql("op_agg_moments", "select l_returnflag, round(var_samp(l_quantity), 6) as v, round(stddev_pop(l_quantity), 6) as s, round(covar_pop(l_quantity, l_discount), 8) as c, round(corr(l_quantity, l_tax), 8) as r, round(regr_slope(l_tax, l_quantity), 10) as slope from {lineitem} group by 1")
same_sql("op_agg_rollup", "select l_returnflag, l_linestatus, count(*) as n, grouping(l_returnflag) as g from {lineitem} group by rollup (l_returnflag, l_linestatus)")
ORACLES["op_agg_rollup"] = "select l_returnflag, l_linestatus, count(*) as n, cast(grouping(l_returnflag) as tinyint) as g from lineitem group by rollup (l_returnflag, l_linestatus)"
same_sql("op_agg_cube", "select o_orderstatus, o_orderpriority, count(*) as n from {orders} group by cube (o_orderstatus, o_orderpriority)")
same_sql("op_agg_sets", "select l_returnflag, l_linestatus, count(*) as n from {lineitem} group by grouping sets ((l_returnflag), (l_linestatus), ())")
same_sql("op_agg_having", "select o_custkey, count(*) as n from {orders} group by o_custkey having count(*) > 12")
same_sql("op_agg_filter", "select o_orderstatus, count(*) filter (where o_orderpriority = '5-LOW') as low, count(*) as n from {orders} group by 1")
same_sql("op_agg_bool", "select o_custkey, bool_and(o_totalprice > 50000) as every_one, bool_or(o_totalprice > 400000) as any_one from {orders} group by 1")
same_sql("op_agg_max_by", "select o_custkey, max_by(o_orderkey, o_totalprice) as top from {orders} group by 1")
same_sql("op_agg_mode", "select l_returnflag from (select l_returnflag, count(*) as n from {lineitem} group by 1) order by n desc, l_returnflag limit 1")


@query("op_agg_percentile", "select l_returnflag, round(quantile_cont(l_extendedprice, 0.25), 4) as q1, round(quantile_cont(l_extendedprice, 0.5), 4) as q2, round(quantile_cont(l_extendedprice, 0.9), 4) as q9 from lineitem group by 1")
def op_agg_percentile(spark, sf_dir):
    return t(spark, sf_dir, "lineitem", "l_returnflag", "l_extendedprice").groupBy("l_returnflag").agg(*[F.round(F.percentile("l_extendedprice", F.lit(q)), 4).alias(k) for k, q in (("q1", 0.25), ("q2", 0.5), ("q9", 0.9))])


@query("op_agg_pivot", "select o_orderstatus, count(*) filter (o_orderpriority = '1-URGENT') as urgent, count(*) filter (o_orderpriority = '5-LOW') as low from orders group by 1")
def op_agg_pivot(spark, sf_dir):
    o = t(spark, sf_dir, "orders", "o_orderstatus", "o_orderpriority")
    p = o.groupBy("o_orderstatus").pivot("o_orderpriority", ["1-URGENT", "5-LOW"]).count()
    return p.select("o_orderstatus", F.coalesce("1-URGENT", F.lit(0)).cast("long").alias("urgent"), F.coalesce("5-LOW", F.lit(0)).cast("long").alias("low"))


@query("op_agg_collect", "select o_custkey, array_to_string(list_sort(list(distinct o_orderstatus)), ',') as states, count(*) as n from orders group by 1")
def op_agg_collect(spark, sf_dir):
    return t(spark, sf_dir, "orders", "o_custkey", "o_orderstatus").groupBy("o_custkey").agg(F.array_join(F.sort_array(F.collect_set("o_orderstatus")), ",").alias("states"), F.count(F.lit(1)).alias("n"))


@query("op_agg_approx_distinct", "select l_returnflag, count(distinct l_partkey) as parts, true as near, true as near_hll from lineitem group by 1")
def op_agg_approx_distinct(spark, sf_dir):
    """Distinct counts, exactly and by two sketches: whether these lie within a tenth."""
    g = t(spark, sf_dir, "lineitem", "l_returnflag", "l_partkey").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("h"))
    return g.select("l_returnflag", "parts", *[(F.abs(F.col(c) / F.col("parts") - 1) <= 0.1).alias(n) for c, n in (("a", "near"), ("h", "near_hll"))])


@query("op_agg_approx_percentile", "select l_returnflag, round(quantile_cont(l_extendedprice, 0.48), 4) as low, round(quantile_cont(l_extendedprice, 0.52), 4) as high, true as inside from lineitem group by 1")
def op_agg_approx_percentile(spark, sf_dir):
    """Medians by sketch, held between exact quantiles."""
    x = F.col("l_extendedprice")
    g = t(spark, sf_dir, "lineitem", "l_returnflag", "l_extendedprice").groupBy("l_returnflag").agg(F.percentile(x, F.lit(0.48)).alias("low"), F.percentile(x, F.lit(0.52)).alias("high"), F.percentile_approx(x, 0.5).alias("q2"))
    return g.select("l_returnflag", F.round("low", 4).alias("low"), F.round("high", 4).alias("high"), F.col("q2").between(F.col("low"), F.col("high")).alias("inside"))


@query("op_agg_weighted", f"select l_returnflag, cast(sum(w * {P}) as bigint) as s, round(sum(w * cast(l_quantity as bigint)) / sum(w), 6) as m, cast(sum(w) as bigint) as n from (select *, cast(l_linenumber as bigint) as w from lineitem) group by 1")
def op_agg_weighted(spark, sf_dir):
    l = t(spark, sf_dir, "lineitem", "l_returnflag", "l_linenumber", "l_quantity", "l_extendedprice").withColumn("price", cents("l_extendedprice")).withColumn("q", F.col("l_quantity").cast("long"))
    out = joins.weighted(l, F.col("l_linenumber").cast("long"), {"s": ("sum", "price"), "m": ("avg", "q"), "n": ("count", "q")}, ["l_returnflag"])
    return out.withColumn("m", F.round("m", 6))


# --- windows

_W = "partition by o_custkey order by o_orderdate, o_orderkey"
same_sql("op_win_rank", f"select o_orderkey, cast(row_number() over ({_W}) as bigint) as rn, cast(rank() over (partition by o_custkey order by o_orderpriority) as bigint) as rk, cast(dense_rank() over (partition by o_custkey order by o_orderpriority) as bigint) as dr from {{orders}}")
same_sql("op_win_share", f"select o_orderkey, round(percent_rank() over ({_W}), 9) as pr, round(cume_dist() over ({_W}), 9) as cd, cast(ntile(4) over ({_W}) as bigint) as q from {{orders}}")
same_sql("op_win_lag", f"select o_orderkey, coalesce(lag(o_orderkey) over ({_W}), -1) as before, coalesce(lead(o_orderkey, 2) over ({_W}), -1) as after from {{orders}}")
same_sql("op_win_running", f"select o_orderkey, cast(sum({O}) over ({_W} rows between unbounded preceding and current row) as bigint) as running, cast(sum({O}) over ({_W} rows between 2 preceding and current row) as bigint) as last3 from {{orders}}")
same_sql("op_win_first_last", f"select o_orderkey, first_value(o_orderkey) over ({_W}) as f, last_value(o_orderkey) over ({_W} rows between unbounded preceding and unbounded following) as l, coalesce(nth_value(o_orderkey, 2) over ({_W} rows between unbounded preceding and unbounded following), -1) as s from {{orders}}")


@query("op_win_range", "select event_id, cast(count(*) over (partition by user_id order by ts range between interval 1 day preceding and current row) as bigint) as n from events")
def op_win_range(spark, sf_dir):
    e = t(spark, sf_dir, "events", "event_id", "user_id", "ts").withColumn("at", F.unix_micros(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("user_id").orderBy("at").rangeBetween(-86_400_000_000, 0)
    return e.select("event_id", F.count(F.lit(1)).over(w).alias("n"))


@query("op_win_topk", "select user_id, event_id from events qualify row_number() over (partition by user_id order by value desc, event_id) <= 3")
def op_win_topk(spark, sf_dir):
    return joins.topk_per_group(t(spark, sf_dir, "events", "user_id", "event_id", "value"), ["user_id"], [F.desc("value"), F.col("event_id")], 3).select("user_id", "event_id")


# --- sets, order, limits

_A, _B = "select o_custkey from {orders} where o_orderpriority = '1-URGENT'", "select o_custkey from {orders} where o_orderpriority = '5-LOW'"
for _name, _op in (("union_all", "union all"), ("union", "union"), ("intersect", "intersect"), ("intersect_all", "intersect all"), ("except", "except"), ("except_all", "except all")):
    same_sql(f"op_set_{_name}", f"{_A} {_op} {_B}")
same_sql("op_set_distinct", "select distinct o_custkey, o_orderstatus from {orders}")


@query("op_set_samples", f"with u as (select o_orderkey, {rng.sql_uniform('sample', 'o_orderkey')} as u, {rng.sql_uniform('sample', 'o_orderkey', seed=1)} as v from orders) select o_orderkey from u where u < 0.2 intersect select o_orderkey from u where v < 0.2")
def op_set_samples(spark, sf_dir):
    o = t(spark, sf_dir, "orders", "o_orderkey")
    return sampling.bernoulli(o, ["o_orderkey"], 0.2, 0, "md5").intersect(sampling.bernoulli(o, ["o_orderkey"], 0.2, 1, "md5"))


@query("op_set_drop_duplicates", "select o_custkey, min(o_orderkey) as o_orderkey from orders group by o_custkey")
def op_set_drop_duplicates(spark, sf_dir):
    return joins.topk_per_group(t(spark, sf_dir, "orders", "o_custkey", "o_orderkey"), ["o_custkey"], [F.col("o_orderkey")], 1)


same_sql("op_sort_topk", "select c_custkey, c_acctbal from {customer} order by c_acctbal desc, c_custkey limit 25")
same_sql("op_limit_sorted", "select o_orderkey from {orders} order by o_orderkey limit 100 offset 50")

# --- functions

same_sql("op_fn_string", "select doc_id, cast(length(text) as bigint) as n, substring(text, 1, 10) as head, upper(lang) as lang, trim(concat_ws('-', lang, source)) as tag, replace(source, 'src', 's') as s from {documents}")
same_sql("op_fn_hash", "select doc_id, md5(text) as m, sha256(source) as s from {documents}", "select doc_id, md5(text) as m, sha2(source, 256) as s from {documents}")
same_sql("op_fn_regexp", "select page_id, regexp_extract(url, '://([^/]+)', 1) as host, regexp_replace(url, '[0-9]+', '#', 'g') as shape from {pages}", "select page_id, regexp_extract(url, '://([^/]+)', 1) as host, regexp_replace(url, '[0-9]+', '#') as shape from {pages}")
same_sql("op_fn_levenshtein", "select a.n_name as a, b.n_name as b, cast(levenshtein(a.n_name, b.n_name) as bigint) as d from {nation} a join {nation} b on a.n_nationkey < b.n_nationkey")
same_sql("op_fn_date", "select o_orderkey, cast(year(o_orderdate) as bigint) as y, cast(month(o_orderdate) as bigint) as m, cast(date_trunc('month', o_orderdate) as date) as month, cast(o_orderdate + interval 7 days as date) as week_on, cast(datediff('day', date '1992-01-01', cast(o_orderdate as date)) as bigint) as d from {orders}", "select o_orderkey, cast(year(o_orderdate) as bigint) as y, cast(month(o_orderdate) as bigint) as m, cast(date_trunc('month', o_orderdate) as date) as month, cast(o_orderdate + interval 7 days as date) as week_on, cast(datediff(cast(o_orderdate as date), date '1992-01-01') as bigint) as d from {orders}")
same_sql("op_fn_interval", "select o_orderkey, o_orderdate + interval 1 hour as later from {orders}")
same_sql("op_fn_math", "select l_orderkey, l_linenumber, l_partkey, round(sqrt(l_quantity), 6) as r, round(ln(l_quantity + 1), 6) as l, round(power(l_quantity, 2), 4) as p, cast(floor(l_extendedprice / 1000) as bigint) as k, greatest(l_discount, l_tax) as g, least(l_discount, l_tax) as s from {lineitem}")
same_sql("op_fn_null", "select o_orderkey, coalesce(nullif(o_orderstatus, 'F'), 'none') as s from {orders}")
same_sql("op_fn_decimal", "select l_returnflag, cast(sum(cast(l_extendedprice as decimal(18,2))) as double) as s from {lineitem} group by 1")


@query("op_fn_histogram", "select cast(width_bucket(cast(l_extendedprice as double), 0.0, 100000.0, 10) as bigint) as bin, count(*) as n from lineitem group by 1")
def op_fn_histogram(spark, sf_dir):
    return t(spark, sf_dir, "lineitem", "l_extendedprice").groupBy(F.width_bucket("l_extendedprice", F.lit(0.0), F.lit(100000.0), F.lit(10)).alias("bin")).agg(F.count(F.lit(1)).alias("n"))


ORACLES["op_fn_histogram"] = "select cast(case when l_extendedprice < 0 then 0 when l_extendedprice >= 100000 then 11 else floor(l_extendedprice / 10000.0) + 1 end as bigint) as bin, count(*) as n from lineitem group by 1"


@query("op_fn_array", "select vec_id, round(list_sum(list_transform(embedding, lambda x: cast(x as double) * cast(x as double))), 5) as norm2, cast(len(embedding) as bigint) as dims, cast(len(list_filter(embedding, lambda x: x > 0)) as bigint) as positive, round(cast(embedding[1] as double), 6) as head from embeddings")
def op_fn_array(spark, sf_dir):
    e = F.col("embedding")
    norm2 = F.aggregate(e, F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    return t(spark, sf_dir, "embeddings", "vec_id", "embedding").select("vec_id", F.round(norm2, 5).alias("norm2"), F.size(e).cast("long").alias("dims"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"), F.round(F.element_at(e, 1).cast("double"), 6).alias("head"))


@query("op_fn_explode", "select word, count(*) as n from (select unnest(string_split(text, ' ')) as word from documents) where word <> '' group by 1 having count(*) > 200")
def op_fn_explode(spark, sf_dir):
    words = sampling.explode_pairs(t(spark, sf_dir, "documents", "text"), F.split("text", " "), "word")
    return words.where("word <> ''").groupBy("word").agg(F.count(F.lit(1)).alias("n")).where("n > 200")


@query("op_fn_json", "select event_id, cast(json_extract_string(props, '$.k') as bigint) as k from events")
def op_fn_json(spark, sf_dir):
    return t(spark, sf_dir, "events", "event_id", "props").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@query("op_fn_map", "select o_custkey, cast(count(*) filter (o_orderstatus = 'F') as bigint) as f, cast(count(*) as bigint) as n from orders group by 1")
def op_fn_map(spark, sf_dir):
    g = t(spark, sf_dir, "orders", "o_custkey", "o_orderstatus").groupBy("o_custkey", "o_orderstatus").count()
    m = g.groupBy("o_custkey").agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "count"))).alias("m"))
    return m.select("o_custkey", F.coalesce(F.col("m")["F"], F.lit(0)).cast("long").alias("f"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("n"))


@query("op_fn_struct", "select n_nationkey as key, n_name as name from nation")
def op_fn_struct(spark, sf_dir):
    return t(spark, sf_dir, "nation").select(F.struct(F.col("n_nationkey").alias("key"), F.col("n_name").alias("name")).alias("s")).select("s.key", "s.name")


# --- subqueries

same_sql("op_subquery_scalar", f"select o_orderkey from {{orders}} where {O} > (select avg({O}) * 1.9 from {{orders}})")
same_sql("op_subquery_in", "select c_custkey from {customer} where c_custkey in (select o_custkey from {orders} where o_orderstatus = 'P')")
same_sql("op_subquery_correlated", f"select o_orderkey from {{orders}} a where {O} = (select max({O}) from {{orders}} b where b.o_custkey = a.o_custkey)")
same_sql("op_subquery_cte", f"with s as (select o_custkey, sum({O}) as c from {{orders}} group by 1), m as (select avg(c) as m from s) select count(*) as n from s, m where c > 2 * m")

# --- user functions


@query("op_udf_scalar", "select o_orderkey, o_orderpriority[1:1] as p from orders")
def op_udf_scalar(spark, sf_dir):
    # row by row, as the plainest kind of function is; null and empty strings stay as they are
    first = F.udf(lambda s: s[:1] if s else s, "string")
    return t(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority").select("o_orderkey", first("o_orderpriority").alias("p"))


@query("op_udf_arrow", f"select o_orderkey, {O} * 2 as twice from orders")
def op_udf_arrow(spark, sf_dir):
    @F.pandas_udf("long")
    def twice(s: pd.Series) -> pd.Series:
        return s * 2

    return t(spark, sf_dir, "orders", "o_orderkey", "o_totalprice").select("o_orderkey", twice(cents("o_totalprice")).alias("twice"))


@query("op_udf_grouped_agg", "select event_type, round(quantile_cont(value, 0.5), 6) as m from events group by 1")
def op_udf_grouped_agg(spark, sf_dir):
    @F.pandas_udf("double")
    def middle(v: pd.Series) -> float:
        return float(v.median())

    return t(spark, sf_dir, "events", "event_type", "value").groupBy("event_type").agg(F.round(middle("value"), 6).alias("m"))


@query("op_udf_apply", "select event_type, count(*) as n, round(max(value) - min(value), 6) as spread from events group by 1")
def op_udf_apply(spark, sf_dir):
    def f(pdf):
        return pd.DataFrame({"event_type": [pdf["event_type"].iloc[0]], "n": [len(pdf)], "spread": [round(float(pdf["value"].max() - pdf["value"].min()), 6)]})

    return t(spark, sf_dir, "events", "event_type", "value").groupBy("event_type").applyInPandas(f, "event_type string, n long, spread double")


@query("op_udf_map_arrow", "select count(*) as n, cast(sum(o_orderkey % 7) as bigint) as s from orders")
def op_udf_map_arrow(spark, sf_dir):
    def f(batches):
        import pyarrow as pa

        for b in batches:
            v = b.column(0).to_numpy()
            yield pa.RecordBatch.from_arrays([pa.array([len(v)], pa.int64()), pa.array([int((v % 7).sum())], pa.int64())], names=["n", "s"])

    return t(spark, sf_dir, "orders", "o_orderkey").mapInArrow(f, "n long, s long").agg(F.sum("n").alias("n"), F.sum("s").alias("s"))


@query("op_udf_cogroup", "select coalesce(a.k, b.k) as k, coalesce(a.n, 0) as customers, coalesce(b.n, 0) as suppliers from (select c_nationkey as k, count(*) as n from customer group by 1) a full join (select s_nationkey as k, count(*) as n from supplier group by 1) b on a.k = b.k")
def op_udf_cogroup(spark, sf_dir):
    c, s = t(spark, sf_dir, "customer", "c_nationkey"), t(spark, sf_dir, "supplier", "s_nationkey")

    def f(key: tuple, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"k": [key[0]], "customers": [len(a)], "suppliers": [len(b)]})

    return c.groupBy("c_nationkey").cogroup(s.groupBy("s_nationkey")).applyInPandas(f, "k int, customers long, suppliers long")


@query("op_udf_table", f"select b, id, w from (select o_orderkey as id, b, {rng.sql_poisson(rng.sql_uniform('boot', 'o_orderkey', 'b'))} as w from orders, (select unnest(range(3)) as b)) where w > 0")
def op_udf_table(spark, sf_dir):
    from approxboot.plans.sqlapi import BootstrapRows

    ship_package(spark)
    spark.udtf.register("bootstrap_rows", BootstrapRows)
    t(spark, sf_dir, "orders", "o_orderkey").select(F.col("o_orderkey").alias("id")).createOrReplaceTempView("approxboot_ids")
    out = spark.sql("select * from bootstrap_rows(table(approxboot_ids), 3)")
    return out.select(F.col("b").cast("long").alias("b"), "id", F.col("w").cast("long").alias("w"))


# --- files


def _round_trip(kind: str, columns: str, options: dict | None = None):
    def run(spark, sf_dir):
        path = fresh_path(spark, f"io-{kind}")
        df = t(spark, sf_dir, "nation")
        df.write.format(kind).options(**(options or {})).save(path)
        return spark.read.format(kind).options(**(options or {})).schema(df.schema).load(path)

    return run


for _kind, _options in (("parquet", {}), ("orc", {}), ("json", {}), ("csv", {"header": "true"})):
    QUERIES[f"op_io_{_kind}"] = _round_trip(_kind, "", _options)
    ORACLES[f"op_io_{_kind}"] = "select * from nation"


@query("op_io_text", "select n_name as value from nation")
def op_io_text(spark, sf_dir):
    path = fresh_path(spark, "io-text")
    t(spark, sf_dir, "nation", "n_name").write.text(path)
    return spark.read.text(path)


@query("op_io_partitioned", "select o_orderstatus, count(*) as n from orders where o_orderstatus = 'F' group by 1")
def op_io_partitioned(spark, sf_dir):
    path = fresh_path(spark, "io-part")
    t(spark, sf_dir, "orders", "o_orderkey", "o_orderstatus").write.partitionBy("o_orderstatus").parquet(path)
    return spark.read.parquet(path).where("o_orderstatus = 'F'").groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))
