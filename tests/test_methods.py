"""Worked examples, invariants and statistical behaviour of the methods."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as hs
from pyspark.sql import functions as F

from approxboot.functions import accuracy, rng
from approxboot.functions import statistics as st
from approxboot.operators import joins, kmeans, maintain, resample, sampling
from approxboot.plans import cost, driver, planner, sqlapi
from approxboot.sources import layout, lines

from .conftest import SF


@pytest.fixture(scope="module")
def rows(spark):
    return spark.range(4000).select(F.col("id"), (F.pmod(F.xxhash64("id"), F.lit(1000)) / 10.0).alias("x"), F.pmod("id", F.lit(4)).alias("g")).cache()


# --- worked numbers

def test_exact_bootstrap_count():
    assert math.comb(2 * 15 - 1, 15 - 1) == 77_558_760


def test_shared_prefix_example():
    assert abs(maintain.shared_prefix(29, 8) - 0.3459) < 5e-4


@pytest.mark.parametrize("n,k", [(5, 2), (10, 3), (29, 5), (50, 7), (100, 10), (1000, 32), (10_000, 100)])
def test_best_share_is_near_the_root(n, k):
    best, saved = maintain.optimal_share(n)
    assert best == k == min(j for j in range(1, n + 1) if j * j + j >= n)
    assert abs(saved - max(maintain.work_saved_items(n, j) for j in range(1, min(n, 400) + 1))) < 1e-12


def test_theory():
    assert planner.theory_B(0.1) == 50
    assert planner.theory_n(0.568, 0.05) == 130
    assert planner.subsample_sizes(100, 5) == [6.25, 12.5, 25, 50, 100]
    assert planner.theory_n(0.5, 0.05, N=100) < planner.theory_n(0.5, 0.05)


def test_feasibility():
    assert planner.feasible(30, 129, 60_000)[0]
    ok, message = planner.feasible(30, 3226, 60_000)
    assert not ok and "no faster" in message
    assert planner.feasible(30, 3226, 60_000, (1.0, 0.01))[0]


def test_proportions():
    lo, hi = accuracy.prop_ci(50, 100)
    assert abs(lo - 0.402) < 1e-3 and abs(hi - 0.598) < 1e-3
    z, p = accuracy.prop_ztest(60, 100, 0.5)
    assert abs(z - 2.0) < 1e-12 and abs(p - 0.0455) < 1e-4


def test_exact_enumeration_of_three():
    mean, var = resample.bootstrap_exact([1.0, 2.0, 6.0], np.mean)
    assert abs(mean - 3) < 1e-12 and abs(var - np.var([1, 2, 6]) / 3) < 1e-12
    with pytest.raises(ValueError):
        resample.bootstrap_exact([1.0] * 9, np.mean)


# --- randomness

def test_uniforms_differ_by_salt_and_are_uniform(spark):
    df = spark.range(20_000).select(rng.uniform_md5("sample", "id").alias("a"), rng.uniform_md5("boot", "id").alias("b"), rng.uniform_xx("sample", "id").alias("c"))
    r = df.agg(F.avg("a"), F.avg("c"), F.corr("a", "b"), F.max("a"), F.min("c")).first()
    assert abs(r[0] - 0.5) < 0.01 and abs(r[1] - 0.5) < 0.01 and abs(r[2]) < 0.03 and r[3] < 1 and r[4] >= 0


def test_poisson_weights_have_mean_and_variance_one(spark):
    w = spark.range(30_000).select(rng.poisson_weight(rng.uniform_xx("boot", "id")).alias("w")).agg(F.avg("w"), F.var_pop("w")).first()
    assert abs(w[0] - 1) < 0.03 and abs(w[1] - 1) < 0.05


def test_part_sizes():
    v = np.array([rng.part_size(1000, 2000, 5, b) for b in range(3000)])
    assert abs(v.mean() - 1000) < 2 and abs(v.var() / 500 - 1) < 0.1
    assert (abs(v - 1000) <= 3 * math.sqrt(500)).mean() > 0.99


def test_split_draws_sum():
    q = rng.split_draws(1000, [10, 0, 90], 20, 3)
    assert (q.sum(1) == 1000).all() and (q[:, 1] == 0).all()


# --- samples

def test_samples_are_nested_and_increments_disjoint(rows):
    c = sampling.SampleCursor(rows, ["id"])
    a = {r["id"] for r in c.grow(0.1).collect()}
    d = {r["id"] for r in c.grow(0.3).collect()}
    assert not a & d and a | d == {r["id"] for r in c.sample().collect()}
    with pytest.raises(ValueError):
        c.grow(0.2)


@pytest.mark.parametrize("n", [1, 4, 17])
def test_partitioning_does_not_matter(rows, n):
    want = sorted(r["id"] for r in sampling.bernoulli(rows, ["id"], 0.05).collect())
    assert sorted(r["id"] for r in sampling.bernoulli(rows.repartition(n), ["id"], 0.05).collect()) == want


def test_exact_sizes(rows):
    assert sampling.exact_n(rows, ["id"], 77).count() == 77
    assert sampling.reservoir(rows, 55, 1).count() == 55
    assert sampling.exact_n(rows, ["id"], 10_000).count() == 4000
    per = sampling.sample_pairs(rows, ["id"], n=9, by=["g"]).groupBy("g").count().collect()
    assert {r["count"] for r in per} == {9}


def test_count_in_the_same_pass(rows):
    df, seen = sampling.counted(rows)
    df.where("id < 10").collect()
    assert seen.get["n"] == 4000


def test_blocks_are_worse_than_rows(spark):
    p = spark.read.parquet(f"{SF}/part.parquet").select("p_partkey", "p_retailprice")
    truth = p.agg(F.avg("p_retailprice")).first()[0]
    errors = {"blocks": [], "rows": []}
    for seed in range(12):
        for k, s in (("blocks", sampling.sample_blocks(p, F.col("p_partkey") - 1, 20, 0.3, seed)), ("rows", sampling.bernoulli(p, ["p_partkey"], 0.3, seed))):
            m = s.agg(F.avg("p_retailprice")).first()[0]
            errors[k].append(abs((m or truth) - truth))
    assert np.mean(errors["blocks"]) > np.mean(errors["rows"])


def test_sampler_choice():
    assert sampling.choose_sampler(False, 10**6, True) == "lines"
    assert sampling.choose_sampler(True, 10**6, False) == "pairs"


def test_bucket_layout_prunes(spark, rows, tmp_path):
    layout.write_shuffled(rows, str(tmp_path / "b"), ["id"], 10)
    df = layout.read_fraction(spark, str(tmp_path / "b"), 0.3, 10)
    assert df.count() == sampling.bernoulli(rows, ["id"], 0.3).count()
    assert "bucket" in cost.plan_facts(df)["text"].split("PartitionFilters: [", 1)[1].split("]", 1)[0]


# --- lines

@pytest.fixture()
def odd_file(tmp_path):
    text = b"first\r\n\nsecond \xc3\xa9\n" + b"x" * 3000 + b"\nlast without end"
    (tmp_path / "odd.txt").write_bytes(text)
    return str(tmp_path / "odd.txt")


@pytest.mark.parametrize("align", ["back", "next"])
def test_line_edges(spark, odd_file, align):
    got = lines.sample_lines(spark, odd_file, 5, 1, align, split_bytes=700, short="allow").collect()
    values = {r["value"] for r in got}
    assert values <= {"first", "", "second é", "x" * 3000, "last without end"}
    assert len({(r["split"], r["offset"]) for r in got}) == len(got)


def test_too_few_lines_are_told(spark, odd_file):
    with pytest.raises(Exception, match="distinct lines were found"):
        lines.sample_lines(spark, odd_file, 50, 1).collect()


def test_length_bias_and_its_cure(spark, tmp_path):
    sizes = [1 + (i * 37 % 50) for i in range(3000)]
    (tmp_path / "l.txt").write_text("\n".join("a" * s for s in sizes) + "\n")
    mean = {}
    for debias in ("none", "reject", "weight"):
        s = lines.sample_lines(spark, str(tmp_path / "l.txt"), 800, 2, "back", debias)
        mean[debias] = s.agg(F.sum(F.length("value") * F.col("ht_weight")) / F.sum("ht_weight")).first()[0]
    truth = np.mean(sizes)
    assert mean["none"] > 1.15 * truth
    assert abs(mean["weight"] / truth - 1) < 0.1
    assert abs(mean["reject"] / truth - 1) < 0.15


def test_row_groups(spark, tmp_path):
    spark.range(5000).withColumn("y", F.col("id") * 2).coalesce(1).write.option("parquet.block.size", 4096).parquet(str(tmp_path / "g"))
    got = lines.sample_row_groups(spark, str(tmp_path / "g"), 300, 1, ["id"])
    assert got.columns == ["id"] and got.count() == got.distinct().count() == 300
    assert lines.row_count(str(tmp_path / "g")) == 5000


def test_lines_of_no_file(spark, tmp_path):
    (tmp_path / "e.txt").write_text("")
    assert lines.sample_lines(spark, str(tmp_path / "e.txt"), 5).count() == 0


# --- resamples

def test_multinomial_weights_sum(spark):
    w = resample.multinomial_weights(spark.range(200).select(F.col("id").alias("pos")), 200, 12)
    assert {r["s"] for r in w.groupBy("b").agg(F.sum("w").alias("s")).collect()} == {200}


def test_multinomial_at_scale(spark, rows):
    out = resample.bootstrap_multinomial_at_scale(rows.select("x").repartition(5).cache(), "x", 8, 2).collect()
    assert {r["n"] for r in out} == {4000} and len(out) == 8


def test_bootstrap_error_of_the_mean_is_the_closed_form(rows):
    s = sampling.exact_n(rows, ["id"], 500)
    se = resample.analytic_se(s, "x").first()["se"]
    boot = resample.bootstrap_poisson(s, st.mean("x"), ["id"], 200).agg(F.stddev_pop("theta")).first()[0]
    assert abs(boot / se - 1) < 0.15
    jack = resample.jackknife_mean(s, "x").first()["se"]
    assert abs(jack / se - 1) < 1e-6


def test_array_bootstrap_agrees(rows):
    out = resample.bootstrap_arrow(rows, "x", F.pmod(F.xxhash64("id"), F.lit(16)), 100, 1).select((F.col("swx") / F.col("sw")).alias("theta"))
    a = out.agg(F.avg("theta"), F.stddev_pop("theta")).first()
    se = resample.analytic_se(rows, "x").first()
    assert abs(a[0] - se["mean"]) < 4 * se["se"] and abs(a[1] / se["se"] - 1) < 0.3


def test_array_bootstrap_batches_are_independent(spark):
    """Blocks of one size in many batches: replicates' weights vary as those of independent rows do."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    spark.conf.set(key, "640")
    try:
        df = spark.range(0, 64_000, 1, 4)
        sw = [r["sw"] for r in resample.bootstrap_arrow(df, "id", F.pmod("id", F.lit(64)), 400, 1).collect()]
    finally:
        spark.conf.set(key, before)
    assert abs(np.std(sw) / np.sqrt(64_000) - 1) < 0.2


def test_lines_of_copies_take_no_space(spark, tmp_path, monkeypatch):
    """The mean ladder reads 64 copies of the lines, and writes them once."""
    from approxboot.catalog import workloads
    from approxboot.sources.sampled import LineSource

    paths = []
    monkeypatch.setattr(workloads, "line_copy", lambda *a, f=workloads.line_copy: paths.append(f(*a)) or paths[-1])
    monkeypatch.setattr(workloads, "fresh_path", lambda *a, f=workloads.fresh_path: paths.append(f(*a)) or paths[-1])
    rows = {r["copies"]: r for r in workloads.QUERIES["wl_mean_ladder"](spark, SF).collect()}
    assert all(rows[c]["n_rows"] == c * rows[1]["n_rows"] and rows[c]["n_bytes"] == c * rows[1]["n_bytes"] for c in (8, 64))
    assert sum(size for p in paths for _, size in lines.list_files(p)) == rows[1]["n_bytes"]
    assert len(lines.list_splits(paths[0], 64 << 20, 8)) == 8 * len(lines.list_splits(paths[0], 64 << 20))
    assert LineSource(spark, paths[0], None, copies=8).bytes == rows[8]["n_bytes"]


def test_known_n_times_a_sum_beyond_64_bits(spark):
    df = spark.createDataFrame([(i, 4 * 10**13) for i in range(4)], "id long, x long")
    thetas = [r["theta"] for r in resample.bootstrap_poisson(df, st.total("x", known_n=36_000_000), ["id"], 10).collect()]
    assert thetas and all(v == 36_000_000 * 4e13 for v in thetas)


def test_block_bootstrap_sees_dependence(spark):
    m = spark.range(3000).select(F.col("id").alias("rn"), F.sin(F.floor(F.col("id") / 50) * 12.9898).alias("x"))
    rows = resample.bootstrap_poisson(m, st.mean("x"), ["rn"], 100).agg(F.stddev_pop("theta")).first()[0]
    for how in ("fixed", "moving", "circular"):
        blocks = resample.bootstrap_blocks(m, "rn", 3000, 100, st.mean("x"), 100, how).agg(F.stddev_pop("theta")).first()[0]
        assert blocks > 2.5 * rows


def test_min_max_are_flagged():
    assert not st.minimum("x").reliable and not st.maximum("x").reliable and not st.distinct("x").reliable and st.mean("x").reliable


def test_python_statistic(spark, rows):
    s = rows.where("id < 50")
    out = resample.bootstrap_frames(s, ["x"], lambda f: f["x"].median(), 6, ids=["id"]).collect()
    assert len(out) == 6 and all(0 <= r["theta"] <= 100 for r in out)


def test_linear_model(spark):
    df = spark.range(300).select((F.col("id") % 17).cast("double").alias("a"), (F.col("id") % 5).cast("double").alias("b")).withColumn("y", 2 + 3 * F.col("a") - F.col("b"))
    aggs, solve = st.linear_model(["a", "b"], "y")
    assert np.allclose(solve(df.agg(*aggs(F.lit(1.0))).first()), [2, 3, -1])


# --- planner and loop

def test_absolute_rule_stops_too_soon():
    pilot = np.random.Generator(np.random.PCG64(1)).integers(1, 51, 600).astype(float)
    few, _ = planner.plan_B(pilot, np.mean, 0.05, "abs")
    enough, trace = planner.plan_B(pilot, np.mean, 0.05, "rel")
    assert few <= 6 and enough >= 30
    assert accuracy.stability([c for _, c in trace])


def test_error_falls_with_the_root_of_n():
    pilot = np.random.Generator(np.random.PCG64(2)).exponential(1, 3000)
    slopes = [planner.fit_curve([50, 100, 200, 400, 800], [planner.cv_of(planner.replicate(pilot[:n], np.mean, 60, np.random.Generator(np.random.PCG64(s)))) for n in (50, 100, 200, 400, 800)])["k"] for s in range(6)]
    assert abs(np.mean(slopes) + 0.5) < 0.1


@pytest.mark.parametrize("model", ["power", "invsqrt", "invsqrt_c"])
def test_curve_inverts(model):
    sizes = [50, 100, 200, 400]
    c = planner.fit_curve(sizes, [2 / math.sqrt(n) for n in sizes], model)
    assert abs(planner.invert_curve(c, 0.05) / 1600 - 1) < 0.01


def test_doubling_trace():
    v = np.random.Generator(np.random.PCG64(3)).exponential(1, 5000)
    trace = planner.plan_doubling(v, np.mean, 0.05)
    assert trace[-1][2] <= 0.05 and all(b[0] <= 2 * a[0] for a, b in zip(trace, trace[1:]))


def test_loop_answers_within_its_error(rows):
    truth = rows.agg(F.avg("x")).first()[0]
    big = rows.withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(40))))
    a = driver.early_result(big, st.mean("x"), "x", ["id", "k"], 0.05, tau=0.05)
    r = a.rows.first()
    assert a.mode == "early" and a.error <= 0.05 and abs(r["value"] - truth) / truth < 0.2 and a.iterations >= 1 and len(a.log) == a.iterations


def test_loop_falls_back(rows):
    a = driver.early_result(rows, st.mean("x"), "x", ["id"], 0.0005)
    assert a.mode == "exact" and abs(a.rows.first()["value"] - rows.agg(F.avg("x")).first()[0]) < 1e-9 and "no faster" in a.message
    with pytest.raises(ValueError):
        driver.early_result(rows, st.mean("x"), "x", ["id"], 0)


def test_loop_by_groups(rows):
    big = rows.withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(40))))
    a = driver.early_result(big, st.mean("x"), "x", ["id", "k"], 0.1, by=["g"], tau=0.05)
    assert a.rows.count() == 4 and a.error <= 0.1


def test_error_log_gives_new_errors_only():
    log = driver.ErrorLog()
    log.add(1, 0.5)
    assert log.read() == 0.5 and log.read() is None
    log.add(2, 0.1)
    log.add(3, 0.3)
    assert abs(log.read() - 0.2) < 1e-12


@pytest.mark.parametrize("values", [[], [None, None], [5.0], [5.0] * 30, [-1.0, 1.0] * 20])
def test_degenerate_inputs(spark, values):
    df = spark.createDataFrame([(i, v) for i, v in enumerate(values)], "id long, x double")
    r = accuracy.summarise(resample.bootstrap_poisson(df, st.mean("x"), ["id"], 10)).first()
    real = [v for v in values if v is not None]
    if not real:
        assert r["value"] is None
    elif len(set(real)) == 1:
        assert r["value"] == 5.0 and r["cv"] == 0.0


def test_one_whole_sample_is_exact(rows):
    got = driver.fixed_plan(rows, st.total("x"), ["id"], 1.0, 5).first()
    assert got["n"] == 4000 and got["p"] == 1.0


def test_losses_keep_the_mean(rows):
    truth = rows.agg(F.avg("x")).first()[0]
    r = driver.estimate_with_losses(rows, F.pmod("id", F.lit(20)), F.col("split") < 10, st.mean("x"), ["id"], 20, 10, 0.05).first()
    assert abs(r["value"] / truth - 1) < 0.05 and r["p_eff"] == 0.5 and r["accepted"]


# --- maintenance

def test_additive_states_equal_recomputation(rows):
    stat = st.mean(F.floor(F.col("x")).cast("long"))
    c = sampling.SampleCursor(rows, ["id"])
    a, b = (resample.bootstrap_states(c.grow(p), stat, ["id"], 6) for p in (0.2, 0.6))
    merged = {r["b"]: (r["sw"], r["swx"]) for r in maintain.merge_states(a, b, stat, ["b"]).collect()}
    whole = {r["b"]: (r["sw"], r["swx"]) for r in resample.bootstrap_states(c.sample(), stat, ["id"], 6).collect()}
    assert merged == whole


@settings(max_examples=30, deadline=None)
@given(hs.integers(5, 200), hs.integers(0, 200), hs.integers(0, 10_000))
def test_maintained_sizes(n, m, seed):
    gen = np.random.Generator(np.random.PCG64(seed))
    s, d = np.arange(n, dtype=float), 1000.0 + np.arange(m)
    out, touched = maintain.maintain_plain(s[gen.integers(0, n, n)], s, d, seed)
    assert len(out) == n + m and set(out) <= set(s) | set(d) and touched >= 0
    store = maintain.SketchStore(3.0, seed)
    store.grow(s)
    before = np.sort(store.values())
    gone, new = store.grow(d)
    assert store.size == n + m
    assert np.array_equal(np.sort(np.concatenate([before, new])), np.sort(np.concatenate([store.values(), gone])))


def test_small_sketches_hit_the_disk(tmp_path):
    hits = {}
    for c in (0.1, 5.0):
        store = maintain.SketchStore(c, 1, str(tmp_path))
        store.grow(np.arange(400.0))
        for k in range(4):
            store.grow(np.arange(400.0) + 1000 * k)
        hits[c] = store.disk_hits
    assert hits[5.0] < hits[0.1]


def test_sketch_factor():
    assert abs(maintain.pick_c(0.9973) - 3) < 0.01


def test_shared_prefix_biases_the_error():
    v = np.random.Generator(np.random.PCG64(5)).exponential(1, 400)
    _, plain, draws = maintain.bootstrap_shared(v, 300, 200, 1)
    _, fixed, _ = maintain.bootstrap_shared(v, 300, 200, 1, True)
    _, alone, every = maintain.bootstrap_shared(v, 300, 0, 1)
    assert plain < 0.85 * alone and abs(fixed / alone - 1) < 0.25 and draws < every


# --- other operators

def test_asof_directions(spark):
    l = spark.createDataFrame([(1, 5), (1, 1), (2, 9)], "k int, ts int")
    r = spark.createDataFrame([(1, 3, "a"), (1, 5, "b"), (2, 10, "c")], "k int, ts int, v string")
    back = {(x["k"], x["ts"]): x["asof_v"] for x in joins.asof_join(l, r, "ts", ["k"], ["v"]).collect()}
    ahead = {(x["k"], x["ts"]): x["asof_v"] for x in joins.asof_join(l, r, "ts", ["k"], ["v"], "forward").collect()}
    assert back == {(1, 5): "b", (1, 1): None, (2, 9): None} and ahead == {(1, 5): "b", (1, 1): "a", (2, 9): "c"}


def test_sql_surface(spark, rows):
    rows.createOrReplaceTempView("early_rows")
    out = sqlapi.early_sql(spark, "select g, avg(x) as m, count(*) as n from early_rows group by g", ["id"], 0.5).collect()
    assert len(out) == 8 and {r["aggregate"] for r in out} == {"m", "n"}
    for bad in ("select g from early_rows", "select avg(x) from early_rows order by 1", "delete from early_rows"):
        with pytest.raises(ValueError):
            sqlapi.parse_block(bad)


def test_centroids_match_whatever_their_order():
    best = np.array([[0.0, 0], [10, 0], [0, 10]])
    assert accuracy.centroid_error(best[[2, 0, 1]], best) == 0
    assert 0 < accuracy.centroid_error(best + 0.1, best) < 0.05


def test_kmeans_on_a_sample(spark):
    df, centres = kmeans.planted_blobs(spark, 1500, 3)
    found, _, _ = kmeans.fit(sampling.bernoulli(df, ["id"], 0.3), 3, restarts=2)
    assert accuracy.centroid_error(found, centres) < 0.05


def test_one_shuffle_of_states(rows):
    facts = cost.plan_facts(resample.bootstrap_poisson(rows, st.mean("x"), ["id"], 30))
    assert facts["exchanges"] <= 1 and facts["python"] == 0


def test_coverage_is_of_the_whole_table(spark, monkeypatch):
    """The cap on pilots has no part in it."""
    from approxboot.catalog import workloads

    whole = workloads.wl_coverage(spark, SF).first()
    monkeypatch.setattr(workloads.driver, "PILOT_ROWS", 50)
    assert workloads.wl_coverage(spark, SF).first() == whole and whole["runs"] == 100 and whole["covered_right"] and whole["within_right"]


# --- sources that read less

def test_layout_source_reads_its_share(spark, rows, tmp_path):
    from approxboot.sources.sampled import LayoutSource

    path = str(tmp_path / "lay")
    layout.write_shuffled(rows, path, ["id"], 20)
    source = LayoutSource(spark, path, ["id"], 20)
    n = source.count()
    assert n == rows.count() and source.read == {"rows": 0, "bytes": 0}
    first, second = source.grow(0.1), source.grow(0.25)
    assert first.count() == sampling.bernoulli(rows, ["id"], 0.1).count()
    assert first.unionByName(second).select("id").distinct().count() == sampling.bernoulli(rows, ["id"], 0.25).count()
    assert source.read["rows"] < 0.4 * n and source.read["bytes"] > 0
    a = driver.early_result(LayoutSource(spark, path, ["id"], 20), st.mean("x"), "x", None, 0.2, fixed=(20, 150))
    assert a.mode == "early" and a.read["rows"] < n / 2


def test_line_source_answers_from_its_pilot(spark, tmp_path):
    from approxboot.sources.sampled import LineSource

    (tmp_path / "t.txt").write_text("".join(f"{i}|{1 + i % 9}\n" for i in range(200_000)))
    parse = lambda d: d.withColumn("x", F.split("value", "[|]")[1].cast("long")).drop("value")
    source = LineSource(spark, str(tmp_path), parse, 3, 1 << 20)
    a = driver.early_result(source, st.mean("x"), "x", None, 0.03)
    r = a.rows.first()
    assert a.mode == "early" and abs(r["value"] / 5 - 1) < 0.12 and r["cv"] <= 0.03 and abs(source.count() / 200_000 - 1) < 0.1
    assert a.read["rows"] == 1_000
    tight = driver.early_result(LineSource(spark, str(tmp_path), parse, 3, 1 << 20), st.mean("x"), "x", None, 0.012, fixed=(30, 3_000))
    assert tight.read["rows"] >= 3_000 and abs(tight.rows.first()["value"] / 5 - 1) < 0.05


def test_sources_are_chosen_by_the_rule(spark, rows, tmp_path):
    from approxboot.sources import sampled

    (tmp_path / "t.txt").write_text("1\n2\n")
    layout.write_shuffled(rows, str(tmp_path / "lay"), ["id"], 4)
    some = lambda **k: type(sampled.choose_source(spark, ["id"], 10**6, **k)).__name__
    assert some(df=rows) == "ScanSource" and some(df=rows, line_path=str(tmp_path)) == "LineSource"
    assert some(df=rows, line_path=str(tmp_path), needs_exact_count=True, load_critical=False) == "ScanSource"
    assert some(df=rows, layout_path=str(tmp_path / "lay"), line_path=str(tmp_path)) == "LayoutSource"
    with pytest.raises(ValueError):
        some()


@pytest.mark.parametrize("how", ["redraw", "items", "sketch"])
@pytest.mark.parametrize("c", [4.0, 0.01])
def test_resample_tables(spark, rows, tmp_path, how, c):
    u = sampling.SampleCursor(rows, ["id"]).u()
    values = rows.select(F.col("x").cast("double").alias("x"), F.xxhash64("id").alias("h"), u.alias("u"))
    n, half = values.count(), values.where("u < 0.5").count()
    kept = maintain.ResampleTables(spark, str(tmp_path / "d"), 6, c, rows_per_part=700)
    kept.grow(values.where("u < 0.5"))
    state, touched = kept.grown(values.where("u >= 0.5"), how)
    got = state.groupBy("b").agg(F.sum("n").alias("n"), F.sum("total").alias("s")).collect()
    m, s = rows.agg(F.avg("x"), F.stddev_pop("x")).first()
    assert len(got) == 6 and {r["n"] for r in got} == {n} and all(abs(r["s"] / n - m) < 6 * s / n**0.5 for r in got)
    assert touched >= 6 * (n - half) * 0.8 and (how != "sketch" or c < 1 or touched < 6 * (n - half) * 1.25)
    assert (kept.disk_hits > 0) == (how == "sketch" and c < 1)


def test_numbers_of_a_whole_table(spark):
    df = spark.range(5000).select((F.col("id") * 7919 % 5003).alias("k"))
    got = resample.numbered_table(df, ["k"]).orderBy("pos").collect()
    assert [r["pos"] for r in got] == list(range(5000)) and [r["k"] for r in got] == sorted(r["k"] for r in got)
    assert resample.numbered_table(df.limit(0), ["k"]).count() == 0


def test_small_tables_are_dealt_out(spark):
    small, large = spark.range(100), spark.range(1 << 20)
    assert resample.spread(small, ["id"]) is small
    assert resample.spread(large.coalesce(1), ["id"]).rdd.getNumPartitions() == spark.sparkContext.defaultParallelism


@pytest.mark.parametrize("n", [1, 2, 3, 10, 11, 2001])
def test_jackknife_of_a_median(spark, n):
    v = [float(i * 31 % 97) for i in range(n)]
    got = resample.jackknife_median(spark.createDataFrame([(x,) for x in v], "x double"), "x").first()
    left = np.array([np.median(np.delete(v, i)) for i in range(n)]) if n > 1 else np.array([v[0]])
    assert got["n"] == n and got["theta"] == np.median(v)
    if n > 2:
        assert abs(got["se"] - np.sqrt((n - 1) * left.var())) < 1e-9


def test_planner_maintains_its_resamples():
    v = np.random.Generator(np.random.PCG64(5)).exponential(1, 400)
    n, curve = planner.plan_n(v, np.mean, 30, 0.05, 1 / 400)
    assert curve["sizes"] == [25, 50, 100, 200, 400] and 150 < n < 1200
    # drawn anew, all sizes would be drawn in full
    assert curve["touched"] < 0.75 * 30 * sum(curve["sizes"])


def test_small_tables_are_answered_at_once(rows):
    a = driver.early_result(rows, st.mean("x"), "x", ["id"], 0.05, least_bytes=1 << 40)
    assert a.mode == "exact" and "exactly" in a.message and a.read["rows"] == 0
    assert abs(a.rows.first()["value"] - rows.agg(F.avg("x")).first()[0]) < 1e-9
