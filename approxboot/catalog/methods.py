"""Queries for the methods, variants, baselines and measures. Randomised ones use the portable generator, so SQL gives the same rows."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from approxboot import ship_package
from approxboot.functions import accuracy, rng
from approxboot.functions import statistics as st
from approxboot.operators import maintain, resample, sampling
from approxboot.plans import baselines, cost, driver, planner
from approxboot.sources import layout, lines
from approxboot.sources.sampled import LayoutSource, choose_source
from approxboot.sources.shared import fresh_path

QUERIES: dict = {}
ORACLES: dict[str, str] = {}

B = 30
Z95 = accuracy.z_value(0.95)
LINE_IDS = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "price"]


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def t(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def cents(column: str) -> Column:
    return F.round(F.col(column) * 100).cast("long")


def lines_of(spark, sf_dir: str) -> DataFrame:
    """lineitem with whole-number columns and price in cents."""
    df = t(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_returnflag")
    return df.select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", F.col("l_quantity").cast("long").alias("qty"), cents("l_extendedprice").alias("price"), "l_returnflag")


def orders_of(spark, sf_dir: str) -> DataFrame:
    return t(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_totalprice", "o_orderpriority").select("o_orderkey", "o_custkey", cents("o_totalprice").alias("c"), "o_orderpriority")


def orders_sizes(spark, sf_dir: str) -> DataFrame:
    """(n): the different numbers of orders that customers have."""
    return t(spark, sf_dir, "orders", "o_custkey").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n")).select("n").distinct()


# --- pieces of SQL

U_O = rng.sql_uniform("sample", "o_orderkey")
U_L = rng.sql_uniform("sample", *LINE_IDS)
SQL_O = "o as (select o_orderkey, o_custkey, cast(round(o_totalprice * 100) as bigint) as c, o_orderpriority from orders)"
SQL_L = "l as (select l_orderkey, l_partkey, l_suppkey, l_linenumber, cast(l_quantity as bigint) as qty, cast(round(l_extendedprice * 100) as bigint) as price, l_returnflag from lineitem)"


def reps(n: int = B) -> str:
    return f"(select unnest(range({n})) as b)"


def weight(*ids: str) -> str:
    return rng.sql_poisson(rng.sql_uniform("boot", *ids, "b"))


def boot_sql(source: str, ids: list[str], n: int = B) -> str:
    """All columns of source, b and w, rows of weight 0 left out."""
    return f"(select * from (select *, {weight(*ids)} as w from {source}, {reps(n)}) where w > 0)"


BOOT_ORDERS = f"t as (select b, cast(sum(w) as bigint) as n_b, sum(w * c) / sum(w) / 100.0 as theta from {boot_sql('o', ['o_orderkey'])} group by b)"


def boot_orders(spark, sf_dir: str) -> DataFrame:
    """(b, sw, theta): mean of o_totalprice in each replicate."""
    stat = st.mean("c")
    states = resample.bootstrap_states(orders_of(spark, sf_dir), stat, ["o_orderkey"], B, kind="md5")
    return states.select(F.col("b").cast("long").alias("b"), F.col("sw").alias("n_b"), (stat.result() / 100.0).alias("theta"))


# --- samplers

@query("samp_bernoulli", f"with {SQL_O} select count(*) as n, cast(sum(c) as bigint) as cents from o where {U_O} < 0.1")
def samp_bernoulli(spark, sf_dir):
    return sampling.bernoulli(orders_of(spark, sf_dir), ["o_orderkey"], 0.1, kind="md5").agg(F.count(F.lit(1)).alias("n"), F.sum("c").alias("cents"))


@query("samp_grow_disjoint", f"""with {SQL_O}, s as (select c, {U_O} as u from o)
select 's' as part, count(*) as n, cast(sum(c) as bigint) as cents from s where u < 0.05
union all select 'delta', count(*), cast(sum(c) as bigint) from s where u >= 0.05 and u < 0.1
union all select 'grown', count(*), cast(sum(c) as bigint) from s where u < 0.1""")
def samp_grow_disjoint(spark, sf_dir):
    cursor = sampling.SampleCursor(orders_of(spark, sf_dir), ["o_orderkey"], kind="md5")
    parts = [("s", cursor.grow(0.05)), ("delta", cursor.grow(0.1)), ("grown", cursor.sample())]
    out = None
    for name, df in parts:
        one = df.agg(F.lit(name).alias("part"), F.count(F.lit(1)).alias("n"), F.sum("c").alias("cents"))
        out = one if out is None else out.unionByName(one)
    return out


@query("samp_exact_n", f"with {SQL_O} select o_orderkey, c from o order by {U_O}, o_orderkey limit 500")
def samp_exact_n(spark, sf_dir):
    return sampling.exact_n(orders_of(spark, sf_dir), ["o_orderkey"], 500, kind="md5").select("o_orderkey", "c")


@query("samp_pairs_per_key", f"select event_type, event_id from (select event_type, event_id, row_number() over (partition by event_type order by {rng.sql_uniform('sample', 'event_id')}, event_id) as k from events) where k <= 20")
def samp_pairs_per_key(spark, sf_dir):
    return sampling.sample_pairs(t(spark, sf_dir, "events", "event_type", "event_id"), ["event_id"], n=20, by=["event_type"], kind="md5")


@query("samp_pairs_fraction", f"select event_type, count(*) as n from events where {rng.sql_uniform('sample', 'event_id')} < 0.2 group by event_type")
def samp_pairs_fraction(spark, sf_dir):
    return sampling.sample_pairs(t(spark, sf_dir, "events", "event_type", "event_id"), ["event_id"], p=0.2, kind="md5").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@query("samp_key_subset", f"with {SQL_L} select count(*) as n, count(distinct l_orderkey) as keys, cast(sum(price) as bigint) as cents from l where {rng.sql_uniform('sample', 'l_orderkey')} < 0.05")
def samp_key_subset(spark, sf_dir):
    kept = sampling.sample_keys(lines_of(spark, sf_dir), "l_orderkey", 0.05, kind="md5")
    return kept.agg(F.count(F.lit(1)).alias("n"), F.countDistinct("l_orderkey").alias("keys"), F.sum("price").alias("cents"))


def _parts(spark, sf_dir):
    return t(spark, sf_dir, "part", "p_partkey", "p_retailprice").select("p_partkey", cents("p_retailprice").alias("c"))


@query("samp_blocks_biased", f"""with p as (select cast(floor((p_partkey - 1) / 100.0) as bigint) as blk, cast(round(p_retailprice * 100) as bigint) as c from part),
s as (select * from p where {rng.sql_uniform('block', 'blk')} < 0.3)
select (select count(*) from s) as n, round((select sum(c) / count(*) from s), 6) as mean_blocks, round(sum(c) / count(*), 6) as mean_true from p""")
def samp_blocks_biased(spark, sf_dir):
    p = _parts(spark, sf_dir)
    s = sampling.sample_blocks(p, F.col("p_partkey") - 1, 100, 0.3, kind="md5").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("c") / F.count(F.lit(1)), 6).alias("mean_blocks"))
    return s.join(F.broadcast(p.agg(F.round(F.sum("c") / F.count(F.lit(1)), 6).alias("mean_true"))))


@query("samp_bucketed", f"with {SQL_O} select count(*) as n, cast(sum(c) as bigint) as cents from o where {U_O} < 0.15")
def samp_bucketed(spark, sf_dir):
    path = fresh_path(spark, "bucketed")
    layout.write_shuffled(orders_of(spark, sf_dir), path, ["o_orderkey"], 20, kind="md5")
    return layout.read_fraction(spark, path, 0.15, 20).agg(F.count(F.lit(1)).alias("n"), F.sum("c").alias("cents"))


def line_copy(spark, sf_dir) -> str:
    """A newline copy of lineitem in the shared folder."""
    path = fresh_path(spark, "lines")
    lines_of(spark, sf_dir).select(_line().alias("value")).write.text(path)
    return path


def _line() -> Column:
    return F.concat_ws("|", *[F.col(c).cast("string") for c in ("l_orderkey", "l_linenumber", "qty", "price", "l_returnflag")])


@query("samp_lines", f"with {SQL_L} select align, debias, least(400, (select count(*) from l)) as n, least(400, (select count(*) from l)) as distinct_offsets, least(400, (select count(*) from l)) as found, round((select avg(qty) from l), 6) as mean_true, true as near from (values ('back', 'none'), ('next', 'none'), ('back', 'reject'), ('back', 'weight')) as v(align, debias)")
def samp_lines(spark, sf_dir):
    """Samples of lines: their numbers, how many of their lines the table has, and whether the mean of 1 to 50 lies within five standard errors (of length-biased draws, within a tenth more)."""
    ship_package(spark)
    path, table = line_copy(spark, sf_dir), lines_of(spark, sf_dir)
    own = table.select(_line().alias("value")).distinct().withColumn("own", F.lit(1))
    truth = table.agg(F.round(F.avg("qty"), 6).alias("mean_true"))
    out = None
    for align, debias in (("back", "none"), ("next", "none"), ("back", "reject"), ("back", "weight")):
        s = lines.sample_lines(spark, path, 400, 3, align, debias, 1 << 20, "allow").join(own, "value", "left")
        qty = F.split("value", "[|]")[2].cast("double")
        one = s.agg(F.lit(align).alias("align"), F.lit(debias).alias("debias"), F.count(F.lit(1)).alias("n"), F.countDistinct("split", "offset").alias("distinct_offsets"), F.sum("own").alias("found"), (F.sum(qty * F.col("ht_weight")) / F.sum("ht_weight")).alias("mean_qty"))
        out = one if out is None else out.unionByName(one)
    near = F.abs(F.col("mean_qty") - F.col("mean_true")) <= 5 * 14.5 / F.sqrt("n") + F.when(F.col("debias") == "none", 0.1 * F.col("mean_true")).otherwise(0.0)
    return out.join(F.broadcast(truth)).select("align", "debias", "n", "distinct_offsets", "found", "mean_true", near.alias("near"))

@query("samp_row_groups", f"with {SQL_L} select 500 as n, 500 as found, round(avg(qty), 6) as mean_true, true as near from l")
def samp_row_groups(spark, sf_dir):
    ship_package(spark)
    path, table = fresh_path(spark, "groups"), lines_of(spark, sf_dir)
    table.repartition(4).write.option("parquet.block.size", 64 << 10).parquet(path)
    s = lines.sample_row_groups(spark, path, 500, 5, ["qty", "price"])
    own = table.select("qty", "price").distinct().withColumn("own", F.lit(1))
    got = s.join(own, ["qty", "price"], "left").agg(F.count(F.lit(1)).alias("n"), F.sum("own").alias("found"), F.avg("qty").alias("_m"))
    truth = table.agg(F.round(F.avg("qty"), 6).alias("mean_true"))
    return got.join(F.broadcast(truth)).select("n", "found", "mean_true", (F.abs(F.col("_m") - F.col("mean_true")) <= 5 * 14.5 / F.sqrt("n")).alias("near"))

@query("samp_reservoir", f"with {SQL_O} select 300 as n, 300 as keys, 300 as found, round(avg(c), 4) as mean_true, true as near from o")
def samp_reservoir(spark, sf_dir):
    ship_package(spark)
    o = orders_of(spark, sf_dir).select("o_orderkey", "c")
    s = sampling.reservoir(o, 300, 4).join(o.withColumn("own", F.lit(1)), ["o_orderkey", "c"], "left")
    got = s.agg(F.count(F.lit(1)).alias("n"), F.countDistinct("o_orderkey").alias("keys"), F.sum("own").alias("found"), F.avg("c").alias("_m"))
    truth = o.agg(F.round(F.avg("c"), 4).alias("mean_true"), F.stddev_pop("c").alias("_s"))
    return got.join(F.broadcast(truth)).select("n", "keys", "found", "mean_true", (F.abs(F.col("_m") - F.col("mean_true")) <= 5 * F.col("_s") / F.sqrt("n")).alias("near"))

@query("samp_tablesample", f"with {SQL_O} select form, count(*) as n_table, true as n_near, true as mean_near from o, (values ('10 percent'), ('bucket 1 out of 10')) as v(form) group by form")
def samp_tablesample(spark, sf_dir):
    """The built-in forms, a share of rows and one of so many buckets: whether their number and mean lie within five standard errors."""
    o, out = orders_of(spark, sf_dir), None
    for f in ("10 percent", "bucket 1 out of 10"):
        got = spark.sql(f"select '{f}' as form, count(*) as n, avg(c) as m from {{o}} tablesample ({f}) repeatable (7)", o=o)
        out = got if out is None else out.unionByName(got)
    truth = o.agg(F.count(F.lit(1)).alias("n_table"), F.avg("c").alias("_m"), F.stddev_pop("c").alias("_s"))
    near = F.abs(F.col("n") - 0.1 * F.col("n_table")) <= 5 * F.sqrt(0.09 * F.col("n_table"))
    return out.join(F.broadcast(truth)).select("form", "n_table", near.alias("n_near"), (F.abs(F.col("m") - F.col("_m")) <= 5 * F.col("_s") / F.sqrt("n")).alias("mean_near"))

@query("samp_pair_count_error", f"""with d as (select cast(len(list_filter(string_split(text, ' '), lambda w: w <> '')) as bigint) as w, {rng.sql_uniform('sample', 'doc_id')} as u from documents),
a as (select p, cast(sum(case when u < p then w else 0 end) as bigint) as s, cast(sum(w) as bigint) as n_exact from d, (select unnest([0.01, 0.05, 0.2]) as p) group by p)
select cast(p as double) as p, round(s / cast(p as double), 6) as n_est, n_exact, round(abs(s / cast(p as double) - n_exact) / n_exact, 9) as error from a""")
def samp_pair_count_error(spark, sf_dir):
    out = None
    for p in (0.01, 0.05, 0.2):
        one = sampling.word_count_by_lines(t(spark, sf_dir, "documents", "doc_id", "text"), p, kind="md5")
        out = one if out is None else out.unionByName(one)
    return out.select("p", F.round("n_est", 6).alias("n_est"), "n_exact", F.round("error", 9).alias("error"))


@query("samp_stratified", f"with {SQL_O}, s as (select *, {U_O} as u from o) select o_orderpriority, count(*) as n, cast(sum(c) as bigint) as cents from s where u < case when o_orderpriority = '1-URGENT' then 0.2 else 0.1 end group by o_orderpriority")
def samp_stratified(spark, sf_dir):
    kept = sampling.stratified(orders_of(spark, sf_dir), ["o_orderkey"], "o_orderpriority", {"1-URGENT": 0.2}, 0.1, kind="md5")
    return kept.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.sum("c").alias("cents"))

@query("samp_choice", """select case when not load_critical and (needs_exact_count or n < 1000) then 'pairs' else 'lines' end as sampler, needs_exact_count, n, load_critical
from (values (false), (true)) as a(needs_exact_count), (values (false), (true)) as b(load_critical), (select unnest([200, 999, 1000, 100000]) as n)""")
def samp_choice(spark, sf_dir):
    """The rule over a grid of needs: pairs after parsing are worth it only where loading is not critical."""
    cases = [(exact, n, load) for exact in (False, True) for n in (200, 999, 1000, 100000) for load in (False, True)]
    return spark.createDataFrame([(sampling.choose_sampler(*c), *c) for c in cases], "sampler string, needs_exact_count boolean, n int, load_critical boolean")


@query("acc_uniformity", f"""with {SQL_O}, x as (select cast(floor(o_orderkey / 1000.0) as bigint) as blk, case when {U_O} < 0.1 then 1 else 0 end as i from o),
g as (select blk, sum(i) as n, count(*) as total from x group by blk),
e as (select n, total * (select sum(n) from g) / cast((select sum(total) from g) as double) as e from g)
select round(sum((n - e) * (n - e) / e), 6) as chi2, count(*) - 1 as df from e""")
def acc_uniformity(spark, sf_dir):
    o = sampling.blocks_of(orders_of(spark, sf_dir), "o_orderkey", 1000)
    inside = (rng.uniform_md5("sample", "o_orderkey") < 0.1).cast("long")
    g = o.groupBy("blk").agg(F.sum(inside).alias("n"), F.count(F.lit(1)).alias("total"))
    return accuracy.uniformity(g).select(F.round("chi2", 6).alias("chi2"), "df")


# --- resamplers

@query("boot_poisson_mean", f"with {SQL_O}, {BOOT_ORDERS} select b, n_b, round(theta, 6) as mean_b from t")
def boot_poisson_mean(spark, sf_dir):
    return boot_orders(spark, sf_dir).select("b", "n_b", F.round("theta", 6).alias("mean_b"))


@query("boot_poisson_fast", f"with {SQL_O} select b, true as n_near, true as mean_near from o, {reps()} group by b")
def boot_poisson_fast(spark, sf_dir):
    """The same by the fast generator: whether each replicate's weights and mean lie within five standard errors."""
    o = orders_of(spark, sf_dir)
    truth = o.agg(F.count(F.lit(1)).alias("n"), F.avg("c").alias("_m"), F.stddev_pop("c").alias("_s"))
    out = resample.bootstrap_states(o, st.mean("c"), ["o_orderkey"], B).join(F.broadcast(truth))
    return out.select(F.col("b").cast("long").alias("b"), (F.abs(F.col("sw") - F.col("n")) <= 5 * F.sqrt("n")).alias("n_near"), (F.abs(F.col("swx") / F.col("sw") - F.col("_m")) <= 5 * F.col("_s") / F.sqrt("n")).alias("mean_near"))


@query("boot_poisson_grouped", f"with {SQL_O} select o_orderpriority, b, round(sum(w * c) / sum(w) / 100.0, 6) as mean_b from {boot_sql('o', ['o_orderkey'])} group by all")
def boot_poisson_grouped(spark, sf_dir):
    out = resample.bootstrap_poisson(orders_of(spark, sf_dir), st.mean("c"), ["o_orderkey"], B, ["o_orderpriority"], kind="md5")
    return out.select("o_orderpriority", F.col("b").cast("long").alias("b"), F.round(F.col("theta") / 100.0, 6).alias("mean_b"))


SAMPLE_500 = f"s as (select o_orderkey, c, row_number() over (order by {U_O}, o_orderkey) - 1 as pos from o qualify pos < 500)"


def sample_500(spark, sf_dir) -> DataFrame:
    s = sampling.exact_n(orders_of(spark, sf_dir).select("o_orderkey", "c"), ["o_orderkey"], 500, kind="md5")
    return resample.numbered(s, [rng.uniform_md5("sample", "o_orderkey"), "o_orderkey"])


MULTI = f"d as (select b, cast(floor({rng.sql_uniform('draw', 'b', 'j')} * 500) as bigint) as pos from {reps()}, (select unnest(range(500)) as j))"


@query("boot_multinomial_mean", f"with {SQL_O}, {SAMPLE_500}, {MULTI} select b, count(*) as n_b, round(sum(c) / count(*) / 100.0, 6) as mean_b from s join d using (pos) group by b")
def boot_multinomial_mean(spark, sf_dir):
    w = resample.multinomial_weights(sample_500(spark, sf_dir).select("pos"), 500, B, kind="md5")
    return sample_500(spark, sf_dir).join(w, "pos").groupBy("b").agg(F.sum("w").alias("n_b"), F.round(F.sum(F.col("w") * F.col("c")) / F.sum("w") / 100.0, 6).alias("mean_b"))


@query("boot_multinomial_scale", f"with {SQL_O} select b, count(*) as n, round(avg(c) / 100.0, 4) as mean_true, true as near from o, {reps()} group by b")
def boot_multinomial_scale(spark, sf_dir):
    """Draws of each replicate are exactly as many as rows; whether its mean lies within five standard errors of the table's."""
    from approxboot.sources.shared import ensure_checkpoint

    ship_package(spark)
    ensure_checkpoint(spark)
    s = orders_of(spark, sf_dir).select("c").repartition(4).checkpoint()
    truth = s.agg(F.round(F.avg("c") / 100.0, 4).alias("mean_true"), (F.stddev_pop("c") / 100.0).alias("_s"))
    out = resample.bootstrap_multinomial_at_scale(s, "c", B, 3).join(F.broadcast(truth))
    return out.select("b", "n", "mean_true", (F.abs(F.col("sx") / F.col("n") / 100 - F.col("mean_true")) <= 5 * F.col("_s") / F.sqrt("n")).alias("near"))

@query("boot_arrow_moments", f"with {SQL_O} select b, count(*) as n, true as n_near, true as mean_near from o, {reps(100)} group by b")
def boot_arrow_moments(spark, sf_dir):
    """Weights drawn in arrays: whether each replicate's weights and mean lie within five standard errors."""
    ship_package(spark)
    o = orders_of(spark, sf_dir)
    truth = o.agg(F.count(F.lit(1)).alias("n"), F.avg("c").alias("_m"), F.stddev_pop("c").alias("_s"))
    out = resample.bootstrap_arrow(o, "c", F.pmod(F.xxhash64("o_orderkey"), F.lit(64)), 100, 3).join(F.broadcast(truth))
    return out.select("b", "n", (F.abs(F.col("sw") - F.col("n")) <= 5 * F.sqrt("n")).alias("n_near"), (F.abs(F.col("swx") / F.col("sw") - F.col("_m")) <= 5 * F.col("_s") / F.sqrt("n")).alias("mean_near"))

@query("boot_median", f"with e as (select event_id, value from events) select b, round(quantile_cont(value, 0.5), 6) as median_b from (select b, value, unnest(range(w)) as i from {boot_sql('e', ['event_id'])}) group by b")
def boot_median(spark, sf_dir):
    out = resample.bootstrap_poisson(t(spark, sf_dir, "events", "event_id", "value"), st.quantile("value"), ["event_id"], B, kind="md5")
    return out.select(F.col("b").cast("long").alias("b"), F.round("theta", 6).alias("median_b"))


@query("boot_median_sketch", f"with e as (select event_id, value from events) select b, round(quantile_cont(value, 0.45), 6) as low, round(quantile_cont(value, 0.55), 6) as high, true as inside from (select b, value, unnest(range(w)) as i from {boot_sql('e', ['event_id'])}) group by b")
def boot_median_sketch(spark, sf_dir):
    """Medians by sketches, held between exact quantiles of the same replicates."""
    e = resample.replicated(t(spark, sf_dir, "events", "event_id", "value"), ["event_id"], B, kind="md5").withColumn("_i", F.explode(F.expr("array_repeat(0, cast(w as int))")))
    stat = st.quantile_sketch("value")
    states = e.groupBy("b").agg(*stat.aggs(F.lit(1)), F.percentile("value", F.lit(0.45)).alias("low"), F.percentile("value", F.lit(0.55)).alias("high"))
    out = stat.answer(states, ["b", "low", "high"])
    return out.select(F.col("b").cast("long").alias("b"), F.round("low", 6).alias("low"), F.round("high", 6).alias("high"), F.col("theta").between(F.col("low"), F.col("high")).alias("inside"))



S_LINES = f"s as (select * from l where {U_L} < 0.1)"


def lines_sample(spark, sf_dir, p: float = 0.1) -> DataFrame:
    return sampling.bernoulli(lines_of(spark, sf_dir), LINE_IDS, p, kind="md5")


def _boot_lines(spark, sf_dir, stat, digits, out, by=None, p=1.0):
    d = resample.bootstrap_poisson(lines_sample(spark, sf_dir), stat, LINE_IDS, B, by, p, kind="md5")
    return d.select(*(by or []), F.col("b").cast("long").alias("b"), F.round("theta", digits).alias(out))


def _lines_sql(expression: str, by: str = "") -> str:
    return f"with {SQL_L}, {S_LINES} select {by}b, {expression} from {boot_sql('s', LINE_IDS)} group by all"


@query("boot_sum_rescaled", _lines_sql("round(cast(sum(w * price) as bigint) / 0.1, 2) as sum_b"))
def boot_sum_rescaled(spark, sf_dir):
    return _boot_lines(spark, sf_dir, st.total("price"), 2, "sum_b", p=0.1)


@query("boot_sum_known_n", f"with {SQL_L}, {S_LINES}, n as (select count(*) as n from l) select b, round(max(n) * cast(sum(w * price) as bigint) / sum(w), 2) as sum_b from {boot_sql('s', LINE_IDS)}, n group by b")
def boot_sum_known_n(spark, sf_dir):
    return _boot_lines(spark, sf_dir, st.total("price", known_n=lines_of(spark, sf_dir).count()), 2, "sum_b")


@query("boot_count_rescaled", _lines_sql("round(sum(w) / 0.1, 4) as count_b", "l_returnflag, "))
def boot_count_rescaled(spark, sf_dir):
    return _boot_lines(spark, sf_dir, st.count(), 4, "count_b", ["l_returnflag"], 0.1)


@query("boot_proportion", _lines_sql("round(sum(case when l_returnflag = 'R' then w else 0 end) / sum(w), 9) as share_b"))
def boot_proportion(spark, sf_dir):
    return _boot_lines(spark, sf_dir, st.proportion(F.col("l_returnflag") == "R"), 9, "share_b")


@query("boot_variance", _lines_sql("round(sum(w * qty * qty) / sum(w) - (sum(w * qty) / sum(w)) * (sum(w * qty) / sum(w)), 6) as var_b"))
def boot_variance(spark, sf_dir):
    return _boot_lines(spark, sf_dir, st.variance("qty"), 6, "var_b")


@query("boot_ratio", _lines_sql("round(sum(w * price) / sum(w * qty), 6) as ratio_b"))
def boot_ratio(spark, sf_dir):
    return _boot_lines(spark, sf_dir, st.ratio("price", "qty"), 6, "ratio_b")


_D = "cast({} as double)"
_N, _X, _Y = _D.format("sum(w)"), _D.format("sum(w * qty)"), _D.format("sum(w * price)")
_XX, _XY, _YY = _D.format("sum(w * qty * qty)"), _D.format("sum(w * qty * price)"), _D.format("sum(w * price * price)")


def _as_double(df):
    return df.withColumn("qty", F.col("qty").cast("double")).withColumn("price", F.col("price").cast("double"))


def _boot_pair(spark, sf_dir, stat, digits, out):
    weighted = resample.replicated(lines_sample(spark, sf_dir), LINE_IDS, B, kind="md5")
    d = stat.answer(_as_double(weighted).groupBy("b").agg(*stat.aggs(F.col("w"))), ["b"])
    return d.select(F.col("b").cast("long").alias("b"), F.round("theta", digits).alias(out))


@query("boot_corr", _lines_sql(f"round(({_N} * {_XY} - {_X} * {_Y}) / sqrt(({_N} * {_XX} - {_X} * {_X}) * ({_N} * {_YY} - {_Y} * {_Y})), 6) as corr_b"))
def boot_corr(spark, sf_dir):
    return _boot_pair(spark, sf_dir, st.correlation("qty", "price"), 6, "corr_b")


@query("boot_cov", _lines_sql(f"round({_XY} / {_N} - {_X} * {_Y} / {_N} / {_N}, 2) as cov_b"))
def boot_cov(spark, sf_dir):
    return _boot_pair(spark, sf_dir, st.covariance("qty", "price"), 2, "cov_b")


@query("boot_slope", _lines_sql(f"round(({_N} * {_XY} - {_X} * {_Y}) / ({_N} * {_XX} - {_X} * {_X}), 3) as slope_b"))
def boot_slope(spark, sf_dir):
    return _boot_pair(spark, sf_dir, st.slope("qty", "price"), 3, "slope_b")


@query("boot_regression", f"""with {SQL_L}, {S_LINES}, m as (select b, cast(sum(w) as double) as n, sum(w * qty) / cast(sum(w) as double) as mq, sum(w * l_linenumber) / cast(sum(w) as double) as ml, sum(w * price) / cast(sum(w) as double) as mp from {boot_sql('s', LINE_IDS)} group by b),
c as (select b, mq, ml, mp, sum(w * (qty - mq) * (qty - mq)) as qq, sum(w * (l_linenumber - ml) * (l_linenumber - ml)) as ll, sum(w * (qty - mq) * (l_linenumber - ml)) as ql, sum(w * (qty - mq) * (price - mp)) as qp, sum(w * (l_linenumber - ml) * (price - mp)) as lp from {boot_sql('s', LINE_IDS)} join m using (b) group by all),
k as (select *, (qp * ll - lp * ql) / (qq * ll - ql * ql) as kq, (lp * qq - qp * ql) / (qq * ll - ql * ql) as kl from c)
select b, round(mp - kq * mq - kl * ml, 1) as intercept, round(kq, 2) as qty, round(kl, 2) as linenumber from k""")
def boot_regression(spark, sf_dir):
    aggs, solve = st.linear_model(["qty", "l_linenumber"], "price")
    weighted = resample.replicated(lines_sample(spark, sf_dir), LINE_IDS, B, kind="md5")
    # B rows of sums
    rows = weighted.groupBy("b").agg(*aggs(F.col("w"))).collect()
    fits = [(r["b"], *[float(round(x, d)) for x, d in zip(solve(r), (1, 2, 2))]) for r in rows]
    return spark.createDataFrame(fits, "b long, intercept double, qty double, linenumber double")

@query("boot_topk", f"with e as (select event_id, event_type from events), g as (select b, event_type, cast(sum(w) as bigint) as n from {boot_sql('e', ['event_id'])} group by all) select b, event_type, n from g qualify row_number() over (partition by b order by n desc, event_type) <= 3")
def boot_topk(spark, sf_dir):
    from approxboot.operators.joins import topk_per_group

    g = resample.bootstrap_states(t(spark, sf_dir, "events", "event_id", "event_type"), st.count(), ["event_id"], B, ["event_type"], kind="md5")
    top = topk_per_group(g.withColumnRenamed("sw", "n"), ["b"], [F.desc("n"), F.col("event_type")], 3)
    return top.select(F.col("b").cast("long").alias("b"), "event_type", "n")


@query("boot_histogram", f"with {SQL_O}, s as (select * from o where {U_O} < 0.2) select cast(floor(c / 5000000.0) as bigint) as bin, b, round(sum(w) / 0.2, 4) as est from {boot_sql('s', ['o_orderkey'])} group by all")
def boot_histogram(spark, sf_dir):
    s = sampling.bernoulli(orders_of(spark, sf_dir), ["o_orderkey"], 0.2, kind="md5").withColumn("bin", F.floor(F.col("c") / 5000000.0))
    d = resample.bootstrap_poisson(s, st.count(), ["o_orderkey"], B, ["bin"], 0.2, kind="md5")
    return d.select("bin", F.col("b").cast("long").alias("b"), F.round("theta", 4).alias("est"))


SMOOTH = """e as (select cast(round(value * 100) as bigint) as c, row_number() over (order by ts, event_id) - 1 as rn from events),
m as (select rn, sum(c) over (order by rn rows between 19 preceding and current row) / 20.0 / 100.0 as x from e),
m2 as (select rn - 19 as rn, x from m where rn >= 19), n as (select count(*) as n from m2)"""


def smoothed(spark, sf_dir, width: int = 20, span: int = 10_000) -> DataFrame:
    """(rn, x): moving means over width rows of events.value by time, numbered from 0 where the window is full.

    Rows are numbered by ranges; windows are cut into spans, and the rows before a span are repeated in it.
    """
    from pyspark.sql import Window

    e = resample.numbered_table(t(spark, sf_dir, "events", "event_id", "ts", "value").select("ts", "event_id", cents("value").alias("c")), ["ts", "event_id"], "rn").select("c", "rn")
    first, last = F.floor(F.col("rn") / span), F.floor((F.col("rn") + width - 1) / span)
    e = e.withColumn("_s", F.explode(F.sequence(first, last)))
    mean = F.sum("c").over(Window.partitionBy("_s").orderBy("rn").rowsBetween(1 - width, 0)) / float(width) / 100.0
    m = e.withColumn("x", mean).where((F.col("_s") == F.floor(F.col("rn") / span)) & (F.col("rn") >= width - 1))
    return m.select((F.col("rn") - (width - 1)).alias("rn"), "x")


@query("boot_blocks_fixed", f"""with {SMOOTH}, k as (select n // 100 as k from n),
d as (select b, cast(floor({rng.sql_uniform('draw', 'b', 'j')} * k) as bigint) as blk from {reps()}, (select unnest(range((select k from k))) as j), k)
select b, round(avg(x), 6) as mean_b from m2 join d on rn // 100 = blk group by b""")
def boot_blocks_fixed(spark, sf_dir):
    m = smoothed(spark, sf_dir)
    out = resample.bootstrap_blocks(m, "rn", m.count(), 100, st.mean("x"), B, "fixed", kind="md5")
    return out.select("b", F.round("theta", 6).alias("mean_b"))


@query("boot_blocks_moving", f"""with {SMOOTH}, k as (select n // 100 as k, n - 99 as starts from n),
d as (select b, cast(floor({rng.sql_uniform('draw', 'b', 'j')} * starts) as bigint) as st from {reps()}, (select unnest(range((select k from k))) as j), k)
select b, round(avg(x), 6) as mean_b from d join m2 on rn >= st and rn < st + 100 group by b""")
def boot_blocks_moving(spark, sf_dir):
    m = smoothed(spark, sf_dir)
    out = resample.bootstrap_blocks(m, "rn", m.count(), 100, st.mean("x"), B, "moving", kind="md5")
    return out.select("b", F.round("theta", 6).alias("mean_b"))


@query("boot_blocks_circular", f"""with {SMOOTH}, k as (select n // 100 as k, n as starts from n),
d as (select b, cast(floor({rng.sql_uniform('draw', 'b', 'j')} * starts) as bigint) as st from {reps()}, (select unnest(range((select k from k))) as j), k),
c as (select rn, x from m2 union all select rn + n, x from m2, n where rn < 100)
select b, round(avg(x), 6) as mean_b from d join c on rn >= st and rn < st + 100 group by b""")
def boot_blocks_circular(spark, sf_dir):
    m = smoothed(spark, sf_dir)
    out = resample.bootstrap_blocks(m, "rn", m.count(), 100, st.mean("x"), B, "circular", kind="md5")
    return out.select("b", F.round("theta", 6).alias("mean_b"))


@query("boot_keys", f"with {SQL_O} select b, round(sum(w * c) / sum(w) / 100.0, 6) as mean_b from {boot_sql('o', ['o_custkey'])} group by b")
def boot_keys(spark, sf_dir):
    out = resample.bootstrap_keys(orders_of(spark, sf_dir), st.mean("c"), "o_custkey", B, kind="md5")
    return out.select(F.col("b").cast("long").alias("b"), F.round(F.col("theta") / 100.0, 6).alias("mean_b"))


@query("boot_stratified", f"with {SQL_O}, s as (select * from o where {U_O} < 0.1), g as (select o_orderpriority, b, sum(w * c) / sum(w) as m from {boot_sql('s', ['o_orderkey'])} group by all) select o_orderpriority, round(stddev_pop(m) / abs(avg(m)), 9) as cv from g group by o_orderpriority")
def boot_stratified(spark, sf_dir):
    s = sampling.bernoulli(orders_of(spark, sf_dir), ["o_orderkey"], 0.1, kind="md5")
    d = resample.bootstrap_poisson(s, st.mean("c"), ["o_orderkey"], B, ["o_orderpriority"], kind="md5")
    return d.groupBy("o_orderpriority").agg(F.round(accuracy.cv(), 9).alias("cv"))


@query("boot_exact_enum", """with v as (select cast(round(s_acctbal * 100) as bigint) as c from supplier order by s_suppkey limit 5), m as (select (a.c + b.c + c.c + d.c + e.c) / 5.0 / 100.0 as m from v a, v b, v c, v d, v e)
select round(avg(m), 6) as mean, round(var_pop(m), 4) as variance from m""")
def boot_exact_enum(spark, sf_dir):
    rows = t(spark, sf_dir, "supplier", "s_suppkey", "s_acctbal").orderBy("s_suppkey").limit(5).collect()
    mean, var = resample.bootstrap_exact([r["s_acctbal"] for r in rows], np.mean)
    return spark.createDataFrame([(round(float(mean), 6), round(float(var), 4))], "mean double, variance double")


@query("boot_native_sample", f"with {SQL_O}, {SAMPLE_500} select b, round(avg(c) / 100.0, 4) as mean_sample, true as near from s, {reps(5)} group by b")
def boot_native_sample(spark, sf_dir):
    """A job for each replicate: whether its mean lies within five standard errors of the sample's."""
    s = sample_500(spark, sf_dir).select("c")
    m = s.agg((F.avg("c") / 100).alias("m"), (F.stddev_pop("c") / 100).alias("s")).first()
    got = resample.bootstrap_loop(s, 5, lambda df: df.agg(F.avg("c")).first()[0] / 100)
    return spark.createDataFrame([(b, round(m["m"], 4), abs(v - m["m"]) <= 5 * m["s"] / 500**0.5) for b, v in enumerate(got)], "b long, mean_sample double, near boolean")



JACK = f"with {SQL_O}, {SAMPLE_500}, x as (select c / 100.0 as x, pos from s)"


@query("jack_mean", JACK + """, i as (select (sum(x) over () - x) / (count(*) over () - 1) as m, count(*) over () as n from x)
select max(n) as n, round((select avg(x) from x), 6) as theta, round(sqrt((max(n) - 1) / max(n) * sum((m - a) * (m - a))), 6) as se from i, (select avg(m) as a from i)""")
def jack_mean(spark, sf_dir):
    out = resample.jackknife_mean(sample_500(spark, sf_dir).select((F.col("c") / 100.0).alias("x")), "x")
    return out.select("n", F.round("theta", 6).alias("theta"), F.round("se", 6).alias("se"))


@query("jack_median", JACK + """, i as (select a.pos, quantile_cont(b.x, 0.5) as m from x a join x b on a.pos <> b.pos group by a.pos)
select count(*) as n, round((select quantile_cont(x, 0.5) from x), 6) as theta, round(sqrt((count(*) - 1) / count(*) * sum((m - a) * (m - a))), 6) as se from i, (select avg(m) as a from i)""")
def jack_median(spark, sf_dir):
    out = resample.jackknife_median(sample_500(spark, sf_dir).select((F.col("c") / 100.0).alias("x")), "x")
    return out.select(F.col("n").cast("long").alias("n"), F.round("theta", 6).alias("theta"), F.round("se", 6).alias("se"))


@query("jack_groups", f"""with {SQL_O}, g as (select o_orderkey % 50 as g, sum(c) as s, count(*) as n from o group by 1), a as (select sum(s) as s, sum(n) as n from g),
i as (select (a.s - g.s) / (a.n - g.n) as m from g, a)
select count(*) as groups, round(avg(m), 6) as theta, round(sqrt((count(*) - 1) * var_pop(m)), 6) as se from i""")
def jack_groups(spark, sf_dir):
    out = resample.jackknife_groups(orders_of(spark, sf_dir), st.mean("c"), F.pmod("o_orderkey", F.lit(50)), 50)
    return out.select("groups", F.round("theta", 6).alias("theta"), F.round("se", 6).alias("se"))


# --- accuracy

@query("acc_cv", f"with {SQL_O}, {BOOT_ORDERS} select round(stddev_pop(theta) / abs(avg(theta)), 10) as cv from t")
def acc_cv(spark, sf_dir):
    return boot_orders(spark, sf_dir).agg(F.round(accuracy.cv(), 10).alias("cv"))


@query("acc_variance", f"with {SQL_O}, {BOOT_ORDERS} select round(var_pop(theta), 3) as variance from t")
def acc_variance(spark, sf_dir):
    return boot_orders(spark, sf_dir).agg(F.round(accuracy.boot_variance(), 3).alias("variance"))


@query("acc_bias", f"with {SQL_O}, {BOOT_ORDERS} select round(avg(theta) - (select sum(c) / count(*) / 100.0 from o), 5) as bias from t")
def acc_bias(spark, sf_dir):
    at = orders_of(spark, sf_dir).agg((F.sum("c") / F.count("c") / 100.0).alias("at"))
    return boot_orders(spark, sf_dir).join(F.broadcast(at)).groupBy("at").agg(F.round(accuracy.bias("theta", F.first("at")), 5).alias("bias")).select("bias")


@query("acc_ci_percentile", f"with {SQL_O}, {BOOT_ORDERS} select round(quantile_cont(theta, 0.025), 4) as lo, round(quantile_cont(theta, 0.975), 4) as hi from t")
def acc_ci_percentile(spark, sf_dir):
    return accuracy.summarise(boot_orders(spark, sf_dir)).select(F.round("pct_lo", 4).alias("lo"), F.round("pct_hi", 4).alias("hi"))


@query("acc_ci_normal", f"with {SQL_O}, {BOOT_ORDERS} select round(avg(theta) - {Z95!r} * stddev_pop(theta), 4) as lo, round(avg(theta) + {Z95!r} * stddev_pop(theta), 4) as hi from t")
def acc_ci_normal(spark, sf_dir):
    return accuracy.summarise(boot_orders(spark, sf_dir)).select(F.round("lo", 4).alias("lo"), F.round("hi", 4).alias("hi"))


@query("acc_ci_basic", f"with {SQL_O}, {BOOT_ORDERS}, a as (select sum(c) / count(*) / 100.0 as a from o) select round(2 * max(a) - quantile_cont(theta, 0.975), 4) as lo, round(2 * max(a) - quantile_cont(theta, 0.025), 4) as hi from t, a")
def acc_ci_basic(spark, sf_dir):
    at = orders_of(spark, sf_dir).agg((F.sum("c") / F.count("c") / 100.0).alias("at"))
    return accuracy.summarise(boot_orders(spark, sf_dir)).join(F.broadcast(at)).select(F.round(2 * F.col("at") - F.col("pct_hi"), 4).alias("lo"), F.round(2 * F.col("at") - F.col("pct_lo"), 4).alias("hi"))


@query("acc_analytic_se", f"with {SQL_O} select count(*) as n, round(avg(c / 100.0), 6) as mean, round(sqrt(var_samp(c / 100.0) / count(*)), 6) as se, round(sqrt(var_samp(c / 100.0) / count(*)) / avg(c / 100.0), 10) as cv from o")
def acc_analytic_se(spark, sf_dir):
    out = resample.analytic_se(orders_of(spark, sf_dir).select((F.col("c") / 100.0).alias("x")), "x")
    return out.select("n", F.round("mean", 6).alias("mean"), F.round("se", 6).alias("se"), F.round("cv", 10).alias("cv"))


@query("acc_group_average", f"""with {SQL_O}, g as (select o_orderpriority, b, sum(w * c) / sum(w) / 100.0 as theta from {boot_sql('o', ['o_orderkey'])} group by all),
e as (select o_orderpriority, stddev_pop(theta) / abs(avg(theta)) as cv from g group by 1) select round(avg(cv), 10) as avg_cv, round(max(cv), 10) as max_cv, round(quantile_cont(cv, 0.95), 10) as p95_cv from e""")
def acc_group_average(spark, sf_dir):
    d = resample.bootstrap_poisson(orders_of(spark, sf_dir), st.mean("c"), ["o_orderkey"], B, ["o_orderpriority"], kind="md5")
    e = d.groupBy("o_orderpriority").agg(accuracy.cv().alias("cv"))
    return e.agg(F.round(F.avg("cv"), 10).alias("avg_cv"), F.round(F.max("cv"), 10).alias("max_cv"), F.round(F.percentile("cv", F.lit(0.95)), 10).alias("p95_cv"))


@query("acc_stability", f"""with {SQL_O}, {SAMPLE_500}, t as (select b, sum(w * c) / sum(w) / 100.0 as theta from {boot_sql('s', ['o_orderkey'], 50)} group by b),
v as (select b + 1 as n_b, stddev_pop(theta) over w / abs(avg(theta) over w) as cv from t window w as (order by b rows unbounded preceding))
select n_b, round(cv, 8) as cv, round(abs(cv - lag(cv) over (order by n_b)), 8) as tau from v where n_b >= 2""")
def acc_stability(spark, sf_dir):
    from pyspark.sql import Window

    d = resample.bootstrap_poisson(sample_500(spark, sf_dir), st.mean("c"), ["o_orderkey"], 50, kind="md5").withColumn("theta", F.col("theta") / 100.0)
    # fifty rows
    w = Window.orderBy("b").rowsBetween(Window.unboundedPreceding, 0)
    v = d.select((F.col("b") + 1).cast("long").alias("n_b"), (F.stddev_pop("theta").over(w) / F.abs(F.avg("theta").over(w))).alias("cv")).where("n_b >= 2")
    return v.select("n_b", F.round("cv", 8).alias("cv"), F.round(F.abs(F.col("cv") - F.lag("cv").over(Window.orderBy("n_b"))), 8).alias("tau"))


@query("acc_rel_error", f"with {SQL_L}, {S_LINES} select round(abs(e - x) / x, 9) as rel_error, round(e, 6) as early, round(x, 6) as exact from (select sum(price) / count(*) as e from s), (select sum(price) / count(*) as x from l)")
def acc_rel_error(spark, sf_dir):
    e = lines_sample(spark, sf_dir).agg((F.sum("price") / F.count("price")).alias("e"))
    x = lines_of(spark, sf_dir).agg((F.sum("price") / F.count("price")).alias("x"))
    return e.join(F.broadcast(x)).select(F.round(accuracy.rel_error(F.col("e"), F.col("x")), 9).alias("rel_error"), F.round("e", 6).alias("early"), F.round("x", 6).alias("exact"))


_SHARES = {"toxic": ("labels", "toxic = 1"), "quality": ("labels", "quality = 1"), "returned": ("lineitem", "l_returnflag = 'R'"), "purchase": ("events", "event_type = 'purchase'")}


@query("cat_proportion_ci", "with x as (" + " union all ".join(f"select '{k}' as share, count(*) filter ({c}) as x, count(*) as n from {tb}" for k, (tb, c) in _SHARES.items()) + f") select share, x, n, round(x / n - {Z95!r} * sqrt(x / n * (1 - x / n) / n), 9) as lo, round(x / n + {Z95!r} * sqrt(x / n * (1 - x / n) / n), 9) as hi from x")
def cat_proportion_ci(spark, sf_dir):
    out = None
    for k, (tb, c) in _SHARES.items():
        one = t(spark, sf_dir, tb).agg(F.lit(k).alias("share"), F.count(F.when(F.expr(c), 1)).alias("x"), F.count(F.lit(1)).alias("n"))
        out = one if out is None else out.unionByName(one)
    p = F.col("x") / F.col("n")
    half = F.lit(Z95) * F.sqrt(p * (1 - p) / F.col("n"))
    return out.select("share", "x", "n", F.round(p - half, 9).alias("lo"), F.round(p + half, 9).alias("hi"))


# Coefficients of a published rational approximation of the error function.
ERF = [0.254829592, -0.284496736, 1.421413741, -1.453152027, 1.061405429]
ERF_P = 0.3275911


@query("cat_ztest", f"""with x as (select count(*) filter (event_type = 'purchase') as x, count(*) as n from events), z as (select x, n, (x / n - 0.2) / sqrt(0.2 * 0.8 / n) as z from x),
k as (select *, abs(z) / sqrt(2.0) as a, 1 / (1 + {ERF_P} * (abs(z) / sqrt(2.0))) as k from z)
select x, n, round(z, 6) as z, round(k * ({ERF[0]} + k * ({ERF[1]} + k * ({ERF[2]} + k * ({ERF[3]} + k * {ERF[4]})))) * exp(-a * a), 6) as p_value from k""")
def cat_ztest(spark, sf_dir):
    x = t(spark, sf_dir, "events", "event_type").agg(F.count(F.when(F.col("event_type") == "purchase", 1)).alias("x"), F.count(F.lit(1)).alias("n"))
    z = (F.col("x") / F.col("n") - 0.2) / F.sqrt(F.lit(0.2) * 0.8 / F.col("n"))
    a = F.abs(z) / F.sqrt(F.lit(2.0))
    k = 1 / (1 + ERF_P * a)
    tail = F.lit(0.0)
    for c in reversed(ERF):
        tail = k * (F.lit(c) + tail)
    return x.select("x", "n", F.round(z, 6).alias("z"), F.round(tail * F.exp(-a * a), 6).alias("p_value"))


# --- planner

SIGMAS = [0.01, 0.02, 0.05, 0.1, 0.2]


def _pop_cv(spark, sf_dir):
    return lines_of(spark, sf_dir).agg(F.count("qty").alias("n"), (F.stddev_pop("qty") / F.avg("qty")).alias("cv")).first()


@query("plan_theory", f"with {SQL_L}, m as (select stddev_pop(qty) / avg(qty) as cv from l) select cast(s as double) as sigma, cast(ceil(cv / cast(s as double) * (cv / cast(s as double)) - 1e-9) as bigint) as n, cast(ceil(0.5 / (cast(s as double) * cast(s as double)) - 1e-9) as bigint) as resamples from m, (select unnest({SIGMAS}) as s)")
def plan_theory(spark, sf_dir):
    cv = _pop_cv(spark, sf_dir)["cv"]
    return spark.createDataFrame([(s, planner.theory_n(cv, s), planner.theory_B(s)) for s in SIGMAS], "sigma double, n long, resamples long")


@query("plan_feasible", f"with {SQL_L}, m as (select stddev_pop(qty) / avg(qty) as cv, count(*) as total from l), p as (select cast(s as double) as sigma, total, 30 * cast(ceil(cv / cast(s as double) * (cv / cast(s as double)) - 1e-9) as bigint) as rows from m, (select unnest({SIGMAS}) as s)) select sigma, rows, total, case when rows < total then 'early' else 'exact' end as mode from p")
def plan_feasible(spark, sf_dir):
    m = _pop_cv(spark, sf_dir)
    out = []
    for s in SIGMAS:
        n = planner.theory_n(m["cv"], s)
        out.append((s, B * n, m["n"], "early" if planner.feasible(B, n, m["n"])[0] else "exact"))
    return spark.createDataFrame(out, "sigma double, rows long, total long, mode string")


NESTED = [50, 100, 200, 400, 800]
NESTED_SQL = f"""with {SQL_O}, s as (select o_orderkey, c, row_number() over (order by {U_O}, o_orderkey) as k from o qualify k <= 800),
w as (select * from {boot_sql('s', ['o_orderkey'])}), t as (select n_i, b, sum(w * c) / sum(w) / 100.0 as theta from w, (select unnest({NESTED}) as n_i) where k <= n_i group by all),
v as (select n_i, stddev_pop(theta) / abs(avg(theta)) as cv from t group by n_i)"""


def nested_cvs(spark, sf_dir) -> DataFrame:
    """(n_i, cv) of nested samples, whose replicates share weights: one pass over the largest."""
    from pyspark.sql import Window

    s = sampling.exact_n(orders_of(spark, sf_dir).select("o_orderkey", "c"), ["o_orderkey"], 800, kind="md5")
    s = s.withColumn("k", F.row_number().over(Window.orderBy(rng.uniform_md5("sample", "o_orderkey"), "o_orderkey")))
    sized = s.withColumn("n_i", F.explode(F.array(*[F.lit(n) for n in NESTED]))).where("k <= n_i")
    d = resample.bootstrap_poisson(sized, st.mean("c"), ["o_orderkey"], B, ["n_i"], kind="md5")
    return d.groupBy("n_i").agg((F.stddev_pop(F.col("theta") / 100.0) / F.abs(F.avg(F.col("theta") / 100.0))).alias("cv"))


@query("plan_curve", NESTED_SQL + " select cast(n_i as bigint) as n_i, round(cv, 9) as cv, round((select regr_slope(ln(cv), ln(n_i)) from v), 6) as slope from v")
def plan_curve(spark, sf_dir):
    v = nested_cvs(spark, sf_dir)
    fit = v.agg(F.round(F.regr_slope(F.log("cv"), F.log("n_i")), 6).alias("slope"))
    return v.join(F.broadcast(fit)).select(F.col("n_i").cast("long").alias("n_i"), F.round("cv", 9).alias("cv"), "slope")


@query("plan_doubling", NESTED_SQL + ", r as (select n_i, cv, count(*) filter (cv <= 0.03) over (order by n_i rows between unbounded preceding and 1 preceding) as met from v) select cast(n_i as bigint) as n, round(cv, 9) as cv, cv <= 0.03 as stops from r where met = 0")
def plan_doubling(spark, sf_dir):
    from pyspark.sql import Window

    # five rows
    w = Window.orderBy("n_i").rowsBetween(Window.unboundedPreceding, -1)
    v = nested_cvs(spark, sf_dir).withColumn("met", F.count(F.when(F.col("cv") <= 0.03, 1)).over(w))
    return v.where("met = 0").select(F.col("n_i").cast("long").alias("n"), F.round("cv", 9).alias("cv"), (F.col("cv") <= 0.03).alias("stops"))


@query("plan_search", f"with {SQL_O} select rule, cast(sigma as double) as sigma, (select count(*) from o) as total, true as resamples_right, case rule when 'rel' then 'about -1/2' else 'not judged' end as slope, true as mode_right from (values ('abs'), ('rel')) as v(rule), (select unnest([0.02, 0.05, 0.1]) as sigma)")
def plan_search(spark, sf_dir):
    """Plans over tolerances and stop rules: whether resamples are in their bounds, c_v falls about with the root of n, and the mode follows from B * n.

    The absolute rule stops at so few resamples that its curve is noise: nothing is said of its slope.
    """
    o = orders_of(spark, sf_dir)
    pilot, total = driver.pilot_values(o, "c", ["o_orderkey"], 0.3, 0), o.count()
    out = []
    for rule in ("abs", "rel"):
        for sigma in (0.02, 0.05, 0.1):
            p = planner.plan(pilot, np.mean, total, sigma, rule=rule)
            k = float(p.curve.get("k", 0.0))
            out.append((rule, sigma, total, (30 if rule == "rel" else 3) <= p.B <= 100, "not judged" if rule == "abs" else "about -1/2" if -0.8 <= k <= -0.2 else "other", (p.mode == "early") == (p.B * p.n < total)))
    return spark.createDataFrame(out, "rule string, sigma double, total long, resamples_right boolean, slope string, mode_right boolean")



# --- early answers with fixed plans

def _answer(df: DataFrame, scale: float, digits: int, by: list[str] | None = None) -> DataFrame:
    return df.select(*(by or []), *[F.round(F.col(c) / scale, digits).alias(c) for c in ("value", "lo", "hi")], F.round("cv", 9).alias("cv"), "n", "p", F.col("replicates").alias("resamples"))


def _answer_sql(thetas: str, n: str, scale: float, digits: int, p: float, by: str = "") -> str:
    over = f"{by}" if by else ""
    join = f"join ({n}) using ({by.strip(', ')})" if by else f", ({n})"
    return f"""{thetas} select {over}round(avg(theta) / {scale}, {digits}) as value, round((avg(theta) - {Z95!r} * stddev_pop(theta)) / {scale}, {digits}) as lo, round((avg(theta) + {Z95!r} * stddev_pop(theta)) / {scale}, {digits}) as hi,
round(stddev_pop(theta) / abs(avg(theta)), 9) as cv, max(n) as n, cast({p} as double) as p, count(*) as resamples from t {join} {'group by ' + by.strip(', ') if by else ''}"""


@query("early_mean", _answer_sql(f"with {SQL_L}, {S_LINES}, t as (select b, sum(w * price) / sum(w) as theta from {boot_sql('s', LINE_IDS)} group by b)", "select count(*) as n from s", 100.0, 4, 0.1))
def early_mean(spark, sf_dir):
    return _answer(driver.fixed_plan(lines_of(spark, sf_dir), st.mean("price"), LINE_IDS, 0.1, B, kind="md5"), 100.0, 4)


@query("early_median", _answer_sql(f"with e as (select event_id, value from events), s as (select * from e where {rng.sql_uniform('sample', 'event_id')} < 0.2), t as (select b, quantile_cont(value, 0.5) as theta from (select b, value, unnest(range(w)) as i from {boot_sql('s', ['event_id'])}) group by b)", "select count(*) as n from s", 1.0, 5, 0.2))
def early_median(spark, sf_dir):
    return _answer(driver.fixed_plan(t(spark, sf_dir, "events", "event_id", "value"), st.quantile("value"), ["event_id"], 0.2, B, kind="md5"), 1.0, 5)


@query("early_sum", _answer_sql(f"with {SQL_L}, {S_LINES}, t as (select b, cast(sum(w * price) as bigint) / 0.1 as theta from {boot_sql('s', LINE_IDS)} group by b)", "select count(*) as n from s", 100.0, 1, 0.1))
def early_sum(spark, sf_dir):
    return _answer(driver.fixed_plan(lines_of(spark, sf_dir), st.total("price"), LINE_IDS, 0.1, B, kind="md5"), 100.0, 1)


@query("early_grouped", _answer_sql(f"with {SQL_O}, s as (select * from o where {U_O} < 0.2), t as (select o_orderpriority, b, sum(w * c) / sum(w) as theta from {boot_sql('s', ['o_orderkey'])} group by all)", "select o_orderpriority, count(*) as n from s group by 1", 100.0, 4, 0.2, "o_orderpriority, "))
def early_grouped(spark, sf_dir):
    return _answer(driver.fixed_plan(orders_of(spark, sf_dir), st.mean("c"), ["o_orderkey"], 0.2, B, ["o_orderpriority"], kind="md5"), 100.0, 4, ["o_orderpriority"])


@query("early_count", f"with {SQL_L}, {S_LINES}, t as (select l_returnflag, b, sum(w) / 0.1 as theta from {boot_sql('s', LINE_IDS)} group by all) select l_returnflag, round(avg(theta), 4) as value, round(stddev_pop(theta) / abs(avg(theta)), 9) as cv from t group by 1")
def early_count(spark, sf_dir):
    out = driver.fixed_plan(lines_of(spark, sf_dir), st.count(), LINE_IDS, 0.1, B, ["l_returnflag"], kind="md5")
    return out.select("l_returnflag", F.round("value", 4).alias("value"), F.round("cv", 9).alias("cv"))


@query("early_loop", _answer_sql(f"with {SQL_L}, n as (select cast(150 as double) / count(*) as p from l), s as (select l.* from l, n where {U_L} < p), t as (select b, sum(w * price) / sum(w) as theta from {boot_sql('s', LINE_IDS)} group by b)", "select 150 as n", 100.0, 4, 0).replace(", cast(0 as double) as p", ", 'early' as mode, 1 as iterations"))
def early_loop(spark, sf_dir):
    """The loop with 30 resamples of 150 rows from the pre-hashed layout; one round is enough for its tolerance."""
    path = fresh_path(spark, "loop")
    layout.write_shuffled(lines_of(spark, sf_dir), path, LINE_IDS, 20, kind="md5")
    a = driver.early_result(LayoutSource(spark, path, LINE_IDS, 20), st.mean("price"), "price", None, sigma=0.5, fixed=(B, 150), kind="md5")
    out = a.rows.select(*[F.round(F.col(c) / 100.0, 4).alias(c) for c in ("value", "lo", "hi")], F.round("cv", 9).alias("cv"), F.lit(a.n).alias("n"), F.col("replicates").alias("resamples"))
    return out.withColumn("mode", F.lit(a.mode)).withColumn("iterations", F.lit(a.iterations))


@query("early_planned", f"with {SQL_L} select source, count(*) as total, round(avg(price) / 100.0, 4) as mean_true, true as within, true as error_met from l, (values ('scan'), ('layout'), ('lines')) as v(source) group by source")
def early_planned(spark, sf_dir):
    """Planned early answers from each kind of source, for an error of 0.05: whether they hold it, by their own estimate and within four of it of the truth."""
    ship_package(spark)
    df, path, text = lines_of(spark, sf_dir), fresh_path(spark, "planned"), line_copy(spark, sf_dir)
    layout.write_shuffled(df, path, LINE_IDS, 20)
    parse = lambda d: d.select("split", "offset", "ht_weight", F.split("value", "[|]")[3].cast("long").alias("price"))
    made = {"scan": choose_source(spark, LINE_IDS, 0, df), "layout": choose_source(spark, LINE_IDS, 0, df, layout_path=path, buckets=20), "lines": choose_source(spark, LINE_IDS, 100_000, df, line_path=text, parse=parse)}
    truth = df.agg(F.count(F.lit(1)).alias("total"), (F.avg("price") / 100.0).alias("m")).first()
    out = []
    for name, source in made.items():
        a = driver.early_result(source, st.mean("price"), "price", LINE_IDS, 0.05, whole=df)
        r = a.rows.first()
        out.append((name, truth["total"], round(truth["m"], 4), abs(r["value"] / 100.0 - truth["m"]) <= 4 * 0.05 * truth["m"], r["cv"] <= 0.05))
    return spark.createDataFrame(out, "source string, total long, mean_true double, within boolean, error_met boolean")


@query("early_feedback", f"""with {SQL_L}, r as (select cast(unnest([1, 2, 3, 4]) as bigint) as iteration, unnest([0.02, 0.04, 0.08, 0.16]) as p), w as (select * from (select *, {U_L} as u from l) x),
t as (select iteration, b, sum(w * price) / sum(w) as theta from r, {boot_sql('w', LINE_IDS)} where u < p group by all) select iteration, round(stddev_pop(theta) / abs(avg(theta)), 9) as error, true as newer from t group by iteration""")
def early_feedback(spark, sf_dir):
    """Error records of a sample that doubles, with time stamps: each reading takes only what is newer than the last."""
    stat, cursor, log, states = st.mean("price"), sampling.SampleCursor(resample.spread(lines_of(spark, sf_dir), LINE_IDS), LINE_IDS, kind="md5"), driver.ErrorLog(), None
    out = []
    for i, p in enumerate((0.02, 0.04, 0.08, 0.16), 1):
        fresh = resample.bootstrap_states(cursor.grow(p), stat, LINE_IDS, B, kind="md5", dealt=True)
        states = driver._kept(fresh if states is None else maintain.merge_states(states, fresh, stat, ["b"]))
        log.add(i, stat.answer(states, ["b"]).agg(accuracy.cv().alias("cv")).first()["cv"])
        error = log.read()
        out.append((i, round(error, 9), log.read() is None and all(a["at"] <= b["at"] for a, b in zip(log.rows, log.rows[1:]))))
    return spark.createDataFrame(out, "iteration long, error double, newer boolean")

@query("early_sql_block", f"with {SQL_O}, s as (select * from o where c > 0 and {U_O} < 0.2), t as (select o_orderpriority, b, sum(w * c) / sum(w) as theta from {boot_sql('s', ['o_orderkey'])} group by all) select o_orderpriority, 'm' as aggregate, round(avg(theta), 3) as value, round(stddev_pop(theta) / abs(avg(theta)), 9) as cv from t group by 1")
def early_sql_block(spark, sf_dir):
    from approxboot.plans.sqlapi import early_sql

    orders_of(spark, sf_dir).createOrReplaceTempView("approxboot_orders")
    out = early_sql(spark, "select o_orderpriority, avg(c) as m from approxboot_orders where c > 0 group by o_orderpriority", ["o_orderkey"], 0.2, B, kind="md5")
    return out.select("o_orderpriority", "aggregate", F.round("value", 3).alias("value"), F.round("cv", 9).alias("cv"))


# --- maintenance

@query("delta_additive", f"""with {SQL_O}, x as (select *, {U_O} as u from o), w as (select * from {boot_sql('x', ['o_orderkey'])} where u < 0.2),
g as (select 's' as part, b, w, c from w where u < 0.1 union all select 'delta', b, w, c from w where u >= 0.1 union all select 'merged', b, w, c from w)
select part, b, cast(sum(w) as bigint) as sw, cast(sum(w * c) as bigint) as swx from g group by all""")
def delta_additive(spark, sf_dir):
    stat, cursor = st.mean("c"), sampling.SampleCursor(orders_of(spark, sf_dir), ["o_orderkey"], kind="md5")
    old = resample.bootstrap_states(cursor.grow(0.1), stat, ["o_orderkey"], B, kind="md5")
    new = resample.bootstrap_states(cursor.grow(0.2), stat, ["o_orderkey"], B, kind="md5")
    merged = maintain.merge_states(old, new, stat, ["b"])
    out = None
    for name, df in (("s", old), ("delta", new), ("merged", merged)):
        one = df.select(F.lit(name).alias("part"), F.col("b").cast("long").alias("b"), "sw", "swx")
        out = one if out is None else out.unionByName(one)
    return out


def _part_sizes(spark, sf_dir: str, seed: int, modes: tuple[str, ...]) -> DataFrame:
    """(mode, size) of the old part of 1,000 of 2,000 items, one replicate for each order."""
    ship_package(spark)

    def draw(batches):
        import pyarrow as pa

        for batch in batches:
            keys = batch.column(0).to_pylist()
            for mode in modes:
                yield pa.RecordBatch.from_arrays([pa.array([mode] * len(keys)), pa.array([rng.part_size(1000, 2000, seed, k, mode) for k in keys], pa.int64())], names=["mode", "size"])

    return t(spark, sf_dir, "orders", "o_orderkey").mapInArrow(draw, "mode string, size long")


@query("delta_part_size", "select mode, count(*) as replicates, 1000 as mean, 500 as variance, true as mean_near, true as variance_near, true as within_3, true as within_5 from orders, (values ('binomial'), ('gaussian')) as v(mode) group by mode")
def delta_part_size(spark, sf_dir):
    """Sizes of the old part, half of 2,000 draws, one replicate for each order, against the binomial law's mean, variance and spread."""
    sd, off = 500**0.5, F.col("size") - 1000
    shares = [F.avg((F.abs(off) <= k * sd).cast("double")) for k in (3, 5)]
    g = _part_sizes(spark, sf_dir, 1, ("binomial", "gaussian")).groupBy("mode").agg(F.count(F.lit(1)).alias("replicates"), F.avg(off).alias("m"), F.var_pop("size").alias("v"), shares[0].alias("s3"), shares[1].alias("s5"))
    near = [(F.abs("m") < 5 * sd / F.sqrt("replicates")).alias("mean_near"), (F.abs(F.col("v") / 500 - 1) < 0.15).alias("variance_near"), (F.col("s3") >= 0.994).alias("within_3"), (F.col("s5") >= 0.9995).alias("within_5")]
    return g.select("mode", "replicates", F.lit(1000).alias("mean"), F.lit(500).alias("variance"), *near)


@query("delta_three_step", f"select b, 300 as n, 500 as n2, true as touched_right from {reps()}")
def delta_three_step(spark, sf_dir):
    """Resamples of 300 rows grown to 500: sizes, and whether what was touched is the change of the old part and the new part."""
    ship_package(spark)
    out = maintain.maintained_sizes(sample_500(spark, sf_dir), "c", B, 300, 1, "plain")
    return out.select("b", "n", "n2", F.col("touched").between(200 - 60, 200 + 130).alias("touched_right"))

@query("delta_sketch", f"select b, 300 as n, 500 as n2, true as touched_right, 0 as disk_hits from {reps()}")
def delta_sketch(spark, sf_dir):
    """The same with sketches, which are large enough that the layer below is never touched."""
    ship_package(spark)
    out = maintain.maintained_sizes(sample_500(spark, sf_dir), "c", B, 300, 1, "sketch")
    return out.select("b", "n", "n2", F.col("touched").between(200 - 60, 200 + 130).alias("touched_right"), "disk_hits")


@query("delta_sketch_size", "select cast(p as double) as probability, count(*) as changes, true as c_right, true as enough from orders, (select unnest([0.9, 0.99, 0.999]) as p) group by p")
def delta_sketch_size(spark, sf_dir):
    """The sketch factor for a wanted probability: whether the normal law gives it back, and whether such sketches suffice for that share of the changes, one for each order, of a part of 1,000 of 2,000 items."""
    from statistics import NormalDist

    factors = [(p, c, abs(2 * NormalDist().cdf(c) - 1 - p) < 1e-9, float(np.ceil(c * np.sqrt(1000)))) for p in (0.9, 0.99, 0.999) for c in [maintain.pick_c(p)]]
    change = _part_sizes(spark, sf_dir, 7, ("binomial",)).select(F.abs(F.col("size") - 1000).alias("change")).groupBy("change").agg(F.count(F.lit(1)).alias("n"))
    met = change.join(F.broadcast(spark.createDataFrame(factors, "probability double, c double, c_right boolean, room double")))
    g = met.groupBy("probability", "c_right").agg(F.sum("n").alias("changes"), F.sum(F.when(F.col("change") <= F.col("room"), F.col("n")).otherwise(0)).alias("held"))
    return g.select("probability", "changes", "c_right", (F.col("held") / F.col("changes") >= F.col("probability")).alias("enough"))

@query("delta_work_saved", """with g as (select cast(n as bigint) as n, cast(y as double) as y, cast(floor(cast(y as double) * n) as bigint) as k from (select distinct count(*) as n from orders group by o_custkey), (select unnest([0.1, 0.2, 0.3, 0.5]) as y)),
e as (select n, y, k, unnest(range(k)) as i from g), p as (select n, y, k, exp(sum(ln((n - i) / n))) as prob from e group by all)
select n, y, k, round(prob, 9) as prob, round(prob * k / n, 9) as saved from p""")
def delta_work_saved(spark, sf_dir):
    """Work that sharing a part y of a sample saves, for samples as large as each customer's orders."""
    g = orders_sizes(spark, sf_dir).withColumn("y", F.explode(F.array(*map(F.lit, (0.1, 0.2, 0.3, 0.5))))).withColumn("k", F.floor(F.col("y") * F.col("n")))
    prob = F.exp(F.aggregate(F.sequence(F.lit(0).cast("long"), F.col("k") - 1), F.lit(0.0), lambda a, i: a + F.log((F.col("n") - i) / F.col("n"))))
    return g.where("k >= 1").select("n", "y", "k", F.round(prob, 9).alias("prob"), F.round(prob * F.col("k") / F.col("n"), 9).alias("saved"))


@query("delta_optimal_share", """with n as (select distinct count(*) as n from orders group by o_custkey), e as (select n, unnest(range(1, n + 1)) as k from n), c as (select n, k, sum(ln((n - k + 1) / n)) over (partition by n order by k) as l from e where n - k + 1 > 0),
s as (select n, k, exp(l) * k / n as saved from c) select cast(n as bigint) as n, cast(k as bigint) as k, round(saved, 9) as saved from s qualify row_number() over (partition by n order by saved desc, k) = 1""")
def delta_optimal_share(spark, sf_dir):
    """The best share for samples as large as each customer's orders."""
    ship_package(spark)
    best = F.udf(maintain.optimal_share, "k long, saved double")
    return orders_sizes(spark, sf_dir).withColumn("s", best("n")).select("n", "s.k", F.round("s.saved", 9).alias("saved"))


@query("delta_shared_replicates", "select k, decorrelated, k + 200 * (500 - k) as draws, true as cv_right from (select unnest([0, 22, 150]) as k), (values (false), (true)) as v(decorrelated)")
def delta_shared_replicates(spark, sf_dir):
    """Replicates that share their first k draws: draws made, and whether c_v falls with the share and is set right again."""
    # 500 values, by plan
    v = np.array([r["c"] for r in sample_500(spark, sf_dir).collect()], float)
    closed, out = float(v.std() / v.mean() / np.sqrt(len(v))), []
    for k in (0, 22, 150):
        for fix in (False, True):
            _, cv, draws = maintain.bootstrap_shared(v, 200, k, 3, fix)
            want = closed * (1 if fix else np.sqrt(1 - k / len(v)))
            out.append((k, fix, draws, bool(abs(cv / want - 1) < 0.25)))
    return spark.createDataFrame(out, "k int, decorrelated boolean, draws long, cv_right boolean")



# --- baselines and losses

@query("base_exact_mean", f"with {SQL_L} select round(sum(price) / count(*), 6) as value from l")
def base_exact_mean(spark, sf_dir):
    return driver.exact(lines_of(spark, sf_dir), st.mean("price")).select(F.round("value", 6).alias("value"))


@query("base_exact_median", f"with {SQL_O} select round(quantile_cont(c, 0.5), 4) as value from o")
def base_exact_median(spark, sf_dir):
    return orders_of(spark, sf_dir).agg(F.round(F.percentile("c", F.lit(0.5)), 4).alias("value"))


@query("base_exact_sum", f"with {SQL_L} select l_returnflag, cast(sum(price) as bigint) as value from l group by 1")
def base_exact_sum(spark, sf_dir):
    return driver.exact(lines_of(spark, sf_dir), st.total("price"), ["l_returnflag"]).select("l_returnflag", F.col("value").cast("long").alias("value"))


STEPS = [0.05, 0.1, 0.2, 0.5, 1.0]
RUN_SQL = f"with {SQL_O}, r as (select cast(p as double) as p, c / 100.0 as x from (select c, {U_O} as u from o), (select unnest({STEPS}) as p) where u < p)"


@query("base_progressive", RUN_SQL + " select p, count(*) as n, round(avg(x), 5) as mean from r group by p")
def base_progressive(spark, sf_dir):
    o = orders_of(spark, sf_dir).withColumn("x", F.col("c") / 100.0)
    return baselines.progressive(o, "x", ["o_orderkey"], STEPS, kind="md5").select("p", "n", F.round("mean", 5).alias("mean"))


@query("base_online", RUN_SQL + f" select p, count(*) as n, round(avg(x), 5) as mean, round(avg(x) - {Z95!r} * sqrt(var_samp(x) / count(*)), 3) as lo, round(avg(x) + {Z95!r} * sqrt(var_samp(x) / count(*)), 3) as hi from r group by p")
def base_online(spark, sf_dir):
    o = orders_of(spark, sf_dir).withColumn("x", F.col("c") / 100.0)
    out = baselines.online_mean(o, "x", ["o_orderkey"], STEPS, kind="md5")
    return out.select("p", "n", F.round("mean", 5).alias("mean"), F.round("lo", 3).alias("lo"), F.round("hi", 3).alias("hi"))


@query("fault_lost_splits", f"""with {SQL_O}, x as (select *, o_orderkey % 100 % 10 as s from o), w as (select * from {boot_sql('x', ['o_orderkey'])}),
t as (select lost, b, sum(w * c) / sum(w) / 100.0 as theta from w, (select unnest([1, 5, 9]) as lost) where s >= lost group by all)
select lost * 10 as lost, round(avg(theta), 4) as value, round(stddev_pop(theta) / abs(avg(theta)), 9) as cv, 1 - lost / 10 as p_eff, stddev_pop(theta) / abs(avg(theta)) <= 0.05 as accepted from t group by lost""")
def fault_lost_splits(spark, sf_dir):
    o = orders_of(spark, sf_dir).withColumn("c", F.col("c") / 100.0)
    cases = [(lost * 10, F.pmod("split", F.lit(10)) < lost, lost * 10) for lost in (1, 5, 9)]
    out = driver.estimates_with_losses(o, F.pmod("o_orderkey", F.lit(100)), cases, st.mean("c"), ["o_orderkey"], 100, 0.05, B, kind="md5")
    return out.select(F.col("case").alias("lost"), F.round("value", 4).alias("value"), F.round("cv", 9).alias("cv"), "p_eff", "accepted")


@query("fault_missing_files", f"""with {SQL_O}, x as (select *, o_orderkey % 20 as s from o), w as (select * from {boot_sql('x', ['o_orderkey'])} where s >= 4),
t as (select b, sum(w * c) / sum(w) / 100.0 as theta from w group by b)
select 16 as splits_read, (select count(*) from x where s >= 4) as rows_read, round(avg(theta), 4) as value, round(stddev_pop(theta) / abs(avg(theta)), 9) as cv, cast(0.8 as double) as p_eff from t""")
def fault_missing_files(spark, sf_dir):
    """Files that are lost after the table was opened: the answer comes from those that are left, and their share is found by reading."""
    path = fresh_path(spark, "lossy")
    orders_of(spark, sf_dir).withColumn("part", F.pmod("o_orderkey", F.lit(20)).cast("int")).repartition(20, "part").write.partitionBy("part").parquet(path)
    opened = spark.read.option("ignoreMissingFiles", "true").parquet(path)
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    for lost in range(4):
        gone = jvm.org.apache.hadoop.fs.Path(f"{path}/part={lost}")
        gone.getFileSystem(conf).delete(gone, True)
    stat = st.mean("c")
    states = resample.bootstrap_states(opened, stat, ["o_orderkey"], B, ["part"], kind="md5", own=True)
    merged = states.groupBy("b").agg(*stat.merge_aggs(), F.sum("rows").alias("rows"), F.count(F.lit(1)).alias("parts"))
    thetas = stat.answer(merged, ["b", "rows", "parts"]).withColumn("theta", F.when(F.col("b") >= 0, F.col("theta") / 100.0))
    own = lambda c: F.max(F.when(F.col("b") < 0, F.col(c)))
    out = accuracy.summarise(thetas, more=[own("rows").alias("rows_read"), own("parts").alias("splits_read")])
    return out.select("splits_read", "rows_read", F.round("value", 4).alias("value"), F.round("cv", 9).alias("cv"), (F.col("splits_read") / 20).alias("p_eff"))



# --- other statistics

@query("stat_minmax_warn", f"with {SQL_O}, s as (select * from o where {U_O} < 0.1) select b, min(c) as min_b, max(c) as max_b, false as reliable from {boot_sql('s', ['o_orderkey'])} group by b")
def stat_minmax_warn(spark, sf_dir):
    s = sampling.bernoulli(orders_of(spark, sf_dir), ["o_orderkey"], 0.1, kind="md5")
    lo, hi = st.minimum("c"), st.maximum("c")
    a = resample.bootstrap_poisson(s, lo, ["o_orderkey"], B, kind="md5").withColumnRenamed("theta", "min_b")
    z = resample.bootstrap_poisson(s, hi, ["o_orderkey"], B, kind="md5").withColumnRenamed("theta", "max_b")
    return a.join(z, "b").select(F.col("b").cast("long").alias("b"), "min_b", "max_b", F.lit(lo.reliable and hi.reliable).alias("reliable"))


@query("stat_distinct_warn", f"with {SQL_O} select b, count(distinct o_custkey) as keys, true as near, false as reliable from {boot_sql('o', ['o_orderkey'], 10)} group by b")
def stat_distinct_warn(spark, sf_dir):
    """Distinct keys of replicates, exactly and by sketches, which are flagged: whether they agree within a tenth."""
    stat = st.distinct("o_custkey")
    weighted = resample.replicated(orders_of(spark, sf_dir), ["o_orderkey"], 10, kind="md5")
    out = stat.answer(weighted.groupBy("b").agg(*stat.aggs(F.col("w")), F.countDistinct("o_custkey").alias("keys")), ["b", "keys"])
    return out.select(F.col("b").cast("long").alias("b"), "keys", (F.abs(F.col("theta") - F.col("keys")) <= 0.1 * F.col("keys")).alias("near"), F.lit(stat.reliable).alias("reliable"))

@query("stat_python_frame", f"with {SQL_O}, {SAMPLE_500} select b, round(sum(w * c) / sum(w), 6) as theta from {boot_sql('s', ['o_orderkey'])} group by b")
def stat_python_frame(spark, sf_dir):
    ship_package(spark)
    out = resample.bootstrap_frames(sample_500(spark, sf_dir), ["c"], lambda f: f["c"].mean(), B, ids=["o_orderkey"], kind="md5")
    return out.select("b", F.round("theta", 6).alias("theta"))


@query("stat_job", f"with {SQL_O}, {SAMPLE_500} select b, round(quantile_cont(c, 0.9) - quantile_cont(c, 0.1), 4) as theta from (select b, c, unnest(range(w)) as i from {boot_sql('s', ['o_orderkey'], 3)}) group by b")
def stat_job(spark, sf_dir):
    """Any job of a DataFrame, run once for each replicate's rows."""
    s = sample_500(spark, sf_dir).select("o_orderkey", "c")
    job = lambda df: df.agg(F.percentile("c", F.lit(0.9)) - F.percentile("c", F.lit(0.1))).first()[0]
    got = resample.bootstrap_loop(s, 3, job, ids=["o_orderkey"], kind="md5")
    return spark.createDataFrame([(i, round(float(v), 4)) for i, v in enumerate(got)], "b long, theta double")


@query("base_separate_jobs", f"""with {SQL_O}, s as (select * from o where {U_O} < 0.1), t as (select b, sum(w * c) / sum(w) / 100.0 as theta from {boot_sql('s', ['o_orderkey'], 5)} group by b)
select 7 as jobs, round(avg(theta), 4) as value, round(stddev_pop(theta) / abs(avg(theta)), 9) as cv from t""")
def base_separate_jobs(spark, sf_dir):
    """The stock way: a job that writes the sample, one that reads it again for each of five resamples, and one for their accuracy."""
    job = lambda df: df.agg(F.sum("c") / F.count("c") / 100.0).first()[0]
    row, jobs = baselines.separate_jobs(orders_of(spark, sf_dir), ["o_orderkey"], 0.1, 5, job, fresh_path(spark, "separate"), kind="md5")
    return spark.createDataFrame([(jobs, round(row["value"], 4), round(row["cv"], 9))], "jobs int, value double, cv double")


@query("base_cached_sample", f"with {SQL_O} select step, count(*) as n, round(avg(c / 100.0) filter (c / 100.0 > 1000 * step), 4) as mean_above from o, (select unnest(range(3)) as step) where {U_O} < 0.2 group by step")
def base_cached_sample(spark, sf_dir):
    """An iterative job over a sample that is held between its steps."""
    held = baselines.cached_sample(sampling.bernoulli(orders_of(spark, sf_dir).select("o_orderkey", (F.col("c") / 100.0).alias("x")), ["o_orderkey"], 0.2, kind="md5"))
    try:
        rows = [(step, *held.agg(F.count(F.lit(1)), F.round(F.avg(F.when(F.col("x") > 1000 * step, F.col("x"))), 4)).first()) for step in range(3)]
    finally:
        held.unpersist()
    return spark.createDataFrame(rows, "step long, n long, mean_above double")


@query("cost_of_a_run", f"with {SQL_O} select count(*) as rows_read, true as bytes_read, true as shuffled, true as jobs from o")
def cost_of_a_run(spark, sf_dir):
    """What one bootstrap cost, by the engine's own counters: the rows that were read, and whether bytes, shuffle and jobs are in their bounds. Small tables are dealt over all cores first."""
    facts = cost.measured(spark, lambda: resample.bootstrap_poisson(orders_of(spark, sf_dir), st.mean("c"), ["o_orderkey"], B).collect())
    return spark.createDataFrame([(facts["rows_read"], facts["bytes_read"] > 0, facts["shuffle_bytes"] > 0, 1 <= facts["jobs"] <= 4)], "rows_read long, bytes_read boolean, shuffled boolean, jobs boolean")
