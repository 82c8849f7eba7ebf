"""The experiment workloads: one row for each setting, with accuracy and cost side by side."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from approxboot import ship_package
from approxboot.catalog.methods import LINE_IDS, SAMPLE_500, SMOOTH, SQL_L, SQL_O, U_O, B, boot_sql, line_copy, lines_of, orders_of, reps, sample_500, smoothed, t
from approxboot.functions import accuracy, rng
from approxboot.functions import statistics as st
from approxboot.operators import kmeans, maintain, resample, sampling
from approxboot.plans import cost, driver, planner
from approxboot.sources import lines
from approxboot.sources.sampled import LineSource
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


def _clock(f):
    begin = time.perf_counter()
    out = f()
    return out, time.perf_counter() - begin


def _price(df: DataFrame) -> DataFrame:
    """Price of lines as the line sampler or the text reader gives them."""
    return df.withColumn("price", F.split("value", "[|]")[3].cast("long")).drop("value")


@query("wl_mean_ladder")
def wl_mean_ladder(spark, sf_dir):
    """Mean from text files that grow, for an error of 0.05: all lines loaded and averaged, against sampled lines.

    (copies, n_rows, n_bytes, mode, rows_used, rows_read, bytes_read, load_s, exact_s, early_s, speed_up, cv, rel_error). load_s: reading and
    parsing alone. bytes_read of the early run counts a block of the reader for each line. A file stands for all its
    copies, so n_bytes is what is read, not what lies on disk, and the exact plan finds it in the system's cache.
    """
    ship_package(spark)
    path, out = line_copy(spark, sf_dir), []
    for copies in (1, 8, 64):
        # the same files once for each copy of the lines: all are read so often, and take their space once
        parsed = _price(spark.read.text([path] * copies))
        _, load_s = _clock(lambda: parsed.write.format("noop").mode("overwrite").save())
        facts = cost.measured(spark, lambda: driver.exact(parsed, st.mean("price")).first()["value"])
        exact, exact_s = facts["result"], facts["seconds"]
        size = copies * sum(b for _, b in lines.list_files(path))
        early = lambda: (a := driver.early_result(LineSource(spark, path, _price, copies, copies=copies), st.mean("price"), "price", None, 0.05, whole=parsed), a.rows.first())
        (a, row), early_s = _clock(early)
        out.append((copies, facts["rows_read"], size, a.mode, a.B * a.n, a.read["rows"], a.read["bytes"], load_s, exact_s, early_s, cost.speed_up(exact_s, early_s), float(row["cv"]), abs(row["value"] - exact) / exact))
    return spark.createDataFrame(out, "copies int, n_rows long, n_bytes long, mode string, rows_used long, rows_read long, bytes_read long, load_s double, exact_s double, early_s double, speed_up double, cv double, rel_error double")


@query("wl_layout_ladder")
def wl_layout_ladder(spark, sf_dir):
    """Mean from the pre-hashed layout: (p, n_rows, rows_read, bytes_read, shuffle_bytes, jobs, exact_s, early_s, rel_error); rows and bytes read, by the engine's counters, fall with p."""
    from approxboot.sources import layout

    path = fresh_path(spark, "ladder")
    layout.write_shuffled(lines_of(spark, sf_dir), path, LINE_IDS, 50)
    whole = cost.measured(spark, lambda: spark.read.parquet(path).agg(F.avg("price")).first()[0])
    out = []
    for p in (0.02, 0.1, 0.5):
        got = cost.measured(spark, lambda: accuracy.summarise(resample.bootstrap_poisson(layout.read_fraction(spark, path, p, 50), st.mean("price"), LINE_IDS, B)).first()["value"])
        out.append((p, whole["rows_read"], got["rows_read"], got["bytes_read"], got["shuffle_bytes"], got["jobs"], whole["seconds"], got["seconds"], abs(got["result"] - whole["result"]) / whole["result"]))
    return spark.createDataFrame(out, "p double, n_rows long, rows_read long, bytes_read long, shuffle_bytes long, jobs int, exact_s double, early_s double, rel_error double")


@query("wl_median_three")
def wl_median_three(spark, sf_dir):
    """Median of events.value over 64 copies of its lines: loaded and sorted exactly; from 2,000 sampled lines with a job for each of ten resamples; and with all of them in one plan: (variant, n_rows, seconds, speed_up, value, rel_error). The samples' seconds hold the drawing of lines."""
    ship_package(spark)
    path, copies = fresh_path(spark, "medians"), 64
    e = t(spark, sf_dir, "events", "event_id", "value").select(F.concat_ws("|", F.col("event_id").cast("string"), F.col("value").cast("string")).alias("value"))
    e.withColumn("_c", F.explode(F.sequence(F.lit(1), F.lit(copies)))).repartition(8, "_c", "value").drop("_c").write.text(path)
    parse = lambda d: d.withColumn("x", F.split("value", "[|]")[1].cast("double")).drop("value")
    median = lambda d: d.agg(F.percentile("x", F.lit(0.5))).first()[0]
    exact, s0 = _clock(lambda: median(parse(spark.read.text(path))))

    def drawn():
        got = parse(lines.sample_lines(spark, path, 2_000, 3, "back", "reject", short="allow")).select("split", "offset", "x")
        # a planned number of rows
        return spark.createDataFrame(got.collect(), got.schema)

    sample, load = _clock(drawn)
    plain, s1 = _clock(lambda: float(np.mean(resample.bootstrap_loop(sample, 10, median))))
    ours, s2 = _clock(lambda: accuracy.summarise(resample.bootstrap_poisson(sample, st.quantile("x"), ["split", "offset"], 10)).first()["value"])
    rows = [("exact", s0, float(exact)), ("plain", load + s1, plain), ("one_plan", load + s2, float(ours))]
    n = copies * t(spark, sf_dir, "events").count()
    return spark.createDataFrame([(k, n if k == "exact" else 2_000, s, s0 / s, v, abs(v - exact) / exact) for k, s, v in rows], "variant string, n_rows long, seconds double, speed_up double, value double, rel_error double")


@query("km_blobs", f"select * from (select 'full' as variant, 4000 as n, true as cost_near, true as centroids_near union all select 'sample', count(*), true, true from (select unnest(range(4000)) as id) where {rng.sql_uniform('sample', 'id')} < 0.1)")
def km_blobs(spark, sf_dir):
    """K-means on planted blobs, all rows and a sample: whether cost and centroids lie within 5 % of the best."""
    df, centres = kmeans.planted_blobs(spark, 4000, 4)
    sample = sampling.bernoulli(df, ["id"], 0.1, kind="md5")
    out, full_cost = [], None
    for name, d in (("full", df), ("sample", sample)):
        found, _, _ = kmeans.fit(d.cache(), 4)
        c = kmeans.cost(df, found)
        full_cost = full_cost or c
        out.append((name, d.count(), c / full_cost <= 1.05, bool(accuracy.centroid_error(found, centres) <= 0.05)))
        d.unpersist()
    return spark.createDataFrame(out, "variant string, n long, cost_near boolean, centroids_near boolean")


@query("wl_kmeans")
def wl_kmeans(spark, sf_dir):
    """K-means through growing samples on 200,000 planted points, against all of them: (variant, n, seconds, cost_ratio, centroid_error, iterations, inner_iterations)."""
    df, centres = kmeans.planted_blobs(spark, 200_000, 5)
    df = df.cache()
    df.count()
    (full, _, inner), s0 = _clock(lambda: kmeans.fit(df, 5, restarts=1))
    (early, steps, n, inner_early), s1 = _clock(lambda: kmeans.fit_early(df, 5, ["id"], 0.01))
    best = kmeans.cost(df, full)
    rows = [("full", df.count(), s0, 1.0, float(accuracy.centroid_error(full, centres)), 1, inner), ("early", n, s1, kmeans.cost(df, early) / best, float(accuracy.centroid_error(early, centres)), steps, inner_early)]
    df.unpersist()
    return spark.createDataFrame(rows, "variant string, n long, seconds double, cost_ratio double, centroid_error double, iterations int, inner_iterations int")


@query("km_embeddings", f"select 'full' as variant, count(*) as n, true as cost_near from embeddings where embedding is not null union all select 'sample', count(*), true from embeddings where embedding is not null and {rng.sql_uniform('sample', 'vec_id')} < 0.3")
def km_embeddings(spark, sf_dir):
    """K-means on embeddings, all rows and a sample: whether the sample's cost over all rows lies within a tenth."""
    df = t(spark, sf_dir, "embeddings", "vec_id", "embedding").where("embedding is not null")
    sample = sampling.bernoulli(df, ["vec_id"], 0.3, kind="md5")
    out, full_cost = [], None
    for name, d in (("full", df), ("sample", sample)):
        found, _, _ = kmeans.fit(d.cache(), 5, "embedding", restarts=1)
        c = kmeans.cost(df, found, "embedding")
        full_cost = full_cost or c
        out.append((name, d.count(), c / full_cost <= 1.1))
        d.unpersist()
    return spark.createDataFrame(out, "variant string, n long, cost_near boolean")


@query("km_replicates", f"with p as (select unnest(range(600)) as id) select b, cast(sum(w) as bigint) as n_b, count(*) as kinds, true as cost_near from {boot_sql('p', ['id'], 3)} group by b")
def km_replicates(spark, sf_dir):
    """K-means over weighted replicates of a sample: rows and distinct rows of each, and whether its cost a row lies within a third of the sample's."""
    df, _ = kmeans.planted_blobs(spark, 600, 3)
    _, whole, _ = kmeans.fit(df, 3, restarts=1, max_iter=10)
    out = []
    for b in range(3):
        w = resample.replicated(df, ["id"], 3, kind="md5").where(F.col("b") == b).select("features", F.col("w").cast("double").alias("w")).cache()
        _, c, _ = kmeans.fit(w, 3, weight="w", restarts=3, max_iter=10)
        n, kinds = w.agg(F.sum("w").cast("long"), F.count(F.lit(1))).first()
        out.append((b, n, kinds, bool(abs((c / n) / (whole / 600) - 1) < 1 / 3)))
        w.unpersist()
    return spark.createDataFrame(out, "b long, n_b long, kinds long, cost_near boolean")


_COLUMNS = {"l_quantity": ("lineitem", "cast(l_quantity as bigint)"), "value": ("events", "value"), "n_chars": ("documents", "n_chars"), "p_retailprice": ("part", "p_retailprice")}


@query("wl_planner_vs_theory", "with x as (" + " union all ".join(f"select '{k}' as \"column\", stddev_pop({e}) / avg({e}) as cv from {tb}" for k, (tb, e) in _COLUMNS.items()) + ") select \"column\", cast(s as double) as sigma, cast(ceil(cv / cast(s as double) * (cv / cast(s as double)) - 1e-9) as bigint) as n_theory, cast(ceil(0.5 / (cast(s as double) * cast(s as double)) - 1e-9) as bigint) as resamples_theory, true as n_falls, true as resamples_right from x, (select unnest([0.01, 0.02, 0.05, 0.1, 0.2]) as s)")
def wl_planner_vs_theory(spark, sf_dir):
    """Theoretical n and resamples of a mean over tolerances, and whether the plan's n falls as the tolerance grows and its resamples are from 30 to 100, where theory asks for 12 to 5,000."""
    columns = {
        "l_quantity": (lines_of(spark, sf_dir), "qty", LINE_IDS), "value": (t(spark, sf_dir, "events", "event_id", "value"), "value", ["event_id"]),
        "n_chars": (t(spark, sf_dir, "documents", "doc_id", "n_chars"), "n_chars", ["doc_id"]), "p_retailprice": (t(spark, sf_dir, "part", "p_partkey", "p_retailprice"), "p_retailprice", ["p_partkey"]),
    }
    out = []
    for name, (df, x, ids) in columns.items():
        pilot = driver.pilot_values(df, x, ids, 1.0, 1)
        n, cv = df.agg(F.count(F.lit(1)), F.stddev_pop(x) / F.avg(x)).first()
        before = 1 << 62
        for sigma in (0.01, 0.02, 0.05, 0.1, 0.2):
            p = planner.plan(pilot, np.mean, n, sigma)
            out.append((name, sigma, planner.theory_n(cv, sigma), planner.theory_B(sigma), p.n <= before, 30 <= p.B <= 100))
            before = p.n
    return spark.createDataFrame(out, "column string, sigma double, n_theory long, resamples_theory long, n_falls boolean, resamples_right boolean")


@query("wl_sampler_compare")
def wl_sampler_compare(spark, sf_dir):
    """Sampling lines before loading against pairs after parsing: (sampler, n, seconds, rel_error)."""
    ship_package(spark)
    path = line_copy(spark, sf_dir)
    parsed = spark.read.text(path).select(F.split("value", "[|]")[2].cast("double").alias("qty"), F.xxhash64("value").alias("id"))
    truth = parsed.agg(F.avg("qty")).first()[0]
    out = []
    for n in (200, 1000):
        got, s = _clock(lambda: lines.sample_lines(spark, path, n, 1, "back", "weight", 4 << 20).select(F.split("value", "[|]")[2].cast("double").alias("q"), "ht_weight").agg(F.sum(F.col("q") * F.col("ht_weight")) / F.sum("ht_weight")).first()[0])
        out.append(("lines", n, s, abs(got - truth) / truth))
        got, s = _clock(lambda: sampling.sample_pairs(parsed, ["id"], n=n).agg(F.avg("qty")).first()[0])
        out.append(("pairs", n, s, abs(got - truth) / truth))
    return spark.createDataFrame(out, "sampler string, n int, seconds double, rel_error double")


@query("wl_update")
def wl_update(spark, sf_dir):
    """A sample that grows from half of lineitem to all of it, 30 resamples, state saved for the first half: (variant, seconds, rows_touched, same).

    weights: Poisson states, made again against merged. draws: fixed-size resamples kept as tables, drawn again,
    maintained in three steps that read the old items, and maintained through sketches that do not. same: weights
    give equal states, draws the right sizes and a mean within five standard errors.
    """
    ship_package(spark)
    df, stat = lines_of(spark, sf_dir).select(*LINE_IDS), st.mean("price")
    cursor = sampling.SampleCursor(df, LINE_IDS)
    old, new = cursor.grow(0.5), cursor.grow(1.0)
    n, half = df.count(), old.count()
    saved = driver._kept(resample.bootstrap_states(old, stat, LINE_IDS, B))
    again, s1 = _clock(lambda: {r["b"]: tuple(r) for r in resample.bootstrap_states(df, stat, LINE_IDS, B).collect()})
    kept, s2 = _clock(lambda: {r["b"]: tuple(r) for r in maintain.merge_states(saved, resample.bootstrap_states(new, stat, LINE_IDS, B), stat, ["b"]).collect()})
    rows = [("weights_again", s1, B * n, True), ("weights_merged", s2, B * (n - half), kept == again)]
    m, sd = df.agg(F.avg("price"), F.stddev_pop("price")).first()

    def right(state: DataFrame) -> bool:
        got = state.groupBy("b").agg(F.sum("n").alias("n"), F.sum("total").alias("s")).collect()
        return len(got) == B and all(r["n"] == n and abs(r["s"] / n - m) <= 5 * sd / n**0.5 for r in got)

    u = sampling.SampleCursor(df, LINE_IDS).u()
    drawn = maintain.ResampleTables(spark, fresh_path(spark, "draws"), B)
    values = df.select(F.col("price").cast("double").alias("x"), F.xxhash64(*LINE_IDS).alias("h"), u.alias("u"))
    drawn.grow(values.where("u < 0.5").select("x", "h"))
    for how in ("redraw", "items", "sketch"):
        (state, touched), s = _clock(lambda: drawn.grown(values.where("u >= 0.5").select("x", "h"), how))
        rows.append((f"draws_{how}", s, touched, right(state)))
    return spark.createDataFrame(rows, "variant string, seconds double, rows_touched long, same boolean")


@query("wl_cv_by_resamples", f"with {SQL_O}, {SAMPLE_500}, t as (select b, sum(w * c) / sum(w) / 100.0 as theta from {boot_sql('s', ['o_orderkey'], 200)} group by b), k as (select unnest([2, 3, 5, 10, 20, 30, 50, 100, 200]) as resamples) select resamples, round(stddev_pop(theta) / avg(theta), 9) as cv from t, k where b < resamples group by resamples")
def wl_cv_by_resamples(spark, sf_dir):
    """c_v of a mean at fixed n over the number of resamples."""
    steps = (2, 3, 5, 10, 20, 30, 50, 100, 200)
    d = resample.bootstrap_poisson(sample_500(spark, sf_dir), st.mean("c"), ["o_orderkey"], 200, kind="md5").withColumn("theta", F.col("theta") / 100.0)
    d = d.withColumn("resamples", F.explode(F.array(*[F.lit(k) for k in steps]))).where("b < resamples")
    return d.groupBy("resamples").agg(F.round(accuracy.cv(), 9).alias("cv"))


@query("wl_dependent", f"""with {SMOOTH}, k as (select n // 100 as k from n),
d as (select b, cast(floor({rng.sql_uniform('draw', 'b', 'j')} * k) as bigint) as blk from {reps(100)}, (select unnest(range((select k from k))) as j), k),
blocks as (select b, avg(x) as theta from m2 join d on rn // 100 = blk group by b), rows_ as (select b, sum(w * x) / sum(w) as theta from {boot_sql('m2', ['rn'], 100)} group by b)
select 'rows' as how, round(stddev_pop(theta), 7) as se, true as more_than_rows from rows_ union all select 'blocks', round(stddev_pop(theta), 7), stddev_pop(theta) >= (select stddev_pop(theta) from rows_) from blocks""")
def wl_dependent(spark, sf_dir):
    """Error of a moving mean's mean by row and by block bootstrap: rows that depend on each other look more certain than they are."""
    m = smoothed(spark, sf_dir)
    n = m.count()
    rows = float(resample.bootstrap_poisson(m, st.mean("x"), ["rn"], 100, kind="md5").agg(F.stddev_pop("theta")).first()[0])
    blocks = float(resample.bootstrap_blocks(m, "rn", n, 100, st.mean("x"), 100, "fixed", kind="md5").agg(F.stddev_pop("theta")).first()[0])
    return spark.createDataFrame([("rows", round(rows, 7), True), ("blocks", round(blocks, 7), blocks >= rows)], "how string, se double, more_than_rows boolean")


@query("wl_errors_three", f"""with {SQL_O}, s as (select o_orderkey, c / 100.0 as x, row_number() over (order by {U_O}, o_orderkey) - 1 as pos from o qualify pos < 800),
w as (select * from {boot_sql('s', ['o_orderkey'], 100)}), bm as (select b, sum(w * x) / sum(w) as theta from w group by b), bq as (select b, quantile_cont(x, 0.5) as theta from (select b, x, unnest(range(w)) as i from w) group by b),
jm as (select (sum(x) over () - x) / (count(*) over () - 1) as m, count(*) over () as n from s), jq as (select a.pos, quantile_cont(b.x, 0.5) as m, count(*) + 1 as n from s a join s b on a.pos <> b.pos group by a.pos)
select 'mean' as statistic, 'closed' as method, round(sqrt(var_samp(x) / count(*)), 5) as se from s
union all select 'mean', 'bootstrap', round(stddev_pop(theta), 5) from bm union all select 'median', 'bootstrap', round(stddev_pop(theta), 5) from bq
union all select 'mean', 'jackknife', round(sqrt((max(n) - 1) * var_pop(m)), 5) from jm union all select 'median', 'jackknife', round(sqrt((max(n) - 1) * var_pop(m)), 5) from jq""")
def wl_errors_three(spark, sf_dir):
    """Standard errors of mean and median by closed form, bootstrap and jackknife: (statistic, method, se)."""
    s = sampling.exact_n(orders_of(spark, sf_dir).select("o_orderkey", "c"), ["o_orderkey"], 800, kind="md5").select("o_orderkey", (F.col("c") / 100.0).alias("x")).cache()
    boot = lambda stat: resample.bootstrap_poisson(s, stat, ["o_orderkey"], 100, kind="md5").agg(F.stddev_pop("theta")).first()[0]
    rows = [
        ("mean", "closed", resample.analytic_se(s, "x").first()["se"]), ("mean", "bootstrap", boot(st.mean("x"))), ("mean", "jackknife", resample.jackknife_mean(s, "x").first()["se"]),
        ("median", "bootstrap", boot(st.quantile("x"))), ("median", "jackknife", resample.jackknife_median(s, "x").first()["se"]),
    ]
    s.unpersist()
    return spark.createDataFrame([(a, b, round(float(v), 5)) for a, b, v in rows], "statistic string, method string, se double")


_CORR = "select '{name}' as pair, round(avg(theta), 6) as value, round(stddev_pop(theta) / abs(avg(theta)), 6) as cv, round(var_pop(theta), 9) as variance from (select b, (n * xy - x * y) / sqrt((n * xx - x * x) * (n * yy - y * y)) as theta from (select b, cast(sum(w) as double) as n, sum(w * {x}::double) as x, sum(w * {y}::double) as y, sum(w * {x}::double * {x}) as xx, sum(w * {y}::double * {y}) as yy, sum(w * {x}::double * {y}) as xy from {source} group by b))"


@query("wl_correlation", f"with {SQL_L}, d as (select doc_id, n_chars, cast(len(string_split(text, ' ')) as bigint) as words from documents) " + _CORR.format(name="qty_price", x="qty", y="price", source=boot_sql("l", LINE_IDS)) + " union all " + _CORR.format(name="chars_words", x="n_chars", y="words", source=boot_sql("d", ["doc_id"])))
def wl_correlation(spark, sf_dir):
    """Correlations whose c_v is useless near zero: (pair, value, cv, variance)."""
    d = t(spark, sf_dir, "documents", "doc_id", "text", "n_chars").select("doc_id", "n_chars", F.size(F.split("text", " ")).alias("words"))
    double = lambda c: F.col(c).cast("double")
    a = accuracy.summarise(resample.bootstrap_poisson(lines_of(spark, sf_dir), st.correlation(double("qty"), double("price")), LINE_IDS, B, kind="md5")).withColumn("pair", F.lit("qty_price"))
    b = accuracy.summarise(resample.bootstrap_poisson(d, st.correlation(double("n_chars"), double("words")), ["doc_id"], B, kind="md5")).withColumn("pair", F.lit("chars_words"))
    return a.unionByName(b).select("pair", F.round("value", 6).alias("value"), F.round("cv", 6).alias("cv"), F.round("variance", 9).alias("variance"))


_TINY = "select '{by}' as \"by\", count(*) as groups, count(*) - count(cv) as n_missing, round(avg(cv), 8) as avg_cv, round(max(cv), 8) as max_cv from (select {by}, stddev_pop(theta) / abs(avg(theta)) as cv from (select {by}, b, sum(w * c) / sum(w) as theta from {source} group by all) group by {by})"


@query("wl_tiny_groups", f"with {SQL_O} " + " union all ".join(_TINY.format(by=by, source=boot_sql("o", ["o_orderkey"], 10)) for by in ("o_orderpriority", "o_custkey")))
def wl_tiny_groups(spark, sf_dir):
    """Errors of many small groups: (by, groups, n_missing, avg_cv, max_cv)."""
    out = None
    for by in ("o_orderpriority", "o_custkey"):
        d = accuracy.summarise(resample.bootstrap_poisson(orders_of(spark, sf_dir), st.mean("c"), ["o_orderkey"], 10, [by], kind="md5"), [by])
        one = d.agg(F.lit(by).alias("by"), F.count(F.lit(1)).alias("groups"), F.sum(F.col("cv").isNull().cast("long")).alias("n_missing"), F.round(F.avg("cv"), 8).alias("avg_cv"), F.round(F.max("cv"), 8).alias("max_cv"))
        out = one if out is None else out.unionByName(one)
    return out


@query("wl_fallback")
def wl_fallback(spark, sf_dir):
    """Cost of planning where the exact job runs in the end: by itself, after a pilot whose plan does not pay, and with tables under 64 MB answered at once: (variant, seconds, mode, value)."""
    df = lines_of(spark, sf_dir)
    rows = []
    for variant, least in (("warm-up", 0), ("plain", None), ("planned", 0), ("sized", 64 << 20)):
        if least is None:
            run = lambda: ("exact", driver.exact(df, st.mean("price")).first()["value"])
        else:
            run = lambda: (lambda a: (a.mode, a.rows.first()["value"]))(driver.early_result(df, st.mean("price"), "price", LINE_IDS, 0.0005, least_bytes=least))
        (mode, value), s = _clock(run)
        rows.append((variant, s, mode, float(value)))
    return spark.createDataFrame(rows[1:], "variant string, seconds double, mode string, value double")


@query("wl_coverage", f"with {SQL_L} select 100 as runs, round(avg(qty), 6) as mean_true, true as covered_right, true as within_right from l")
def wl_coverage(spark, sf_dir):
    """Whether intervals of 100 seeds hold the truth as often as the level of 95 % says (88 to 100 times), and errors stay within 0.05 at least four times in five."""
    # the whole column as counts of its values: rows are drawn by number, without holding them
    kinds = lines_of(spark, sf_dir).select(F.col("qty").cast("double").alias("x")).where("x is not null").groupBy("x").agg(F.count(F.lit(1)).alias("n")).orderBy("x").collect()
    x, n = np.array([r["x"] for r in kinds]), np.array([r["n"] for r in kinds], np.int64)
    ends = np.cumsum(n)
    gen, runs = np.random.Generator(np.random.PCG64(9)), []
    for _ in range(100):
        s = x[np.searchsorted(ends, gen.choice(int(ends[-1]), 300, replace=False), "right")]
        thetas = planner.replicate(s, np.mean, 100, gen)
        lo, hi = accuracy.ci(thetas, float(s.mean()))
        runs.append({"value": float(s.mean()), "lo": lo, "hi": hi})
    truth = float((x * n).sum() / ends[-1])
    c = accuracy.coverage(runs, truth, 0.05)
    return spark.createDataFrame([(c["runs"], round(truth, 6), 0.88 <= c["covered"] <= 1, c["within"] >= 0.8)], "runs int, mean_true double, covered_right boolean, within_right boolean")
