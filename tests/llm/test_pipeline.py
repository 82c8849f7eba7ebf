"""The pipeline's stages one by one and together."""

import pytest
from pyspark.sql import functions as F

pytest.importorskip("public_tokenizers")
import corpus_pipeline  # noqa: E402

from ..conftest import SF  # noqa: E402


@pytest.fixture(scope="module")
def stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    out = {"documents": docs.cache()}
    for name, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, SF).cache()
        out[name] = docs
    return out


def ids(df):
    return {r["doc_id"] for r in df.select("doc_id").collect()}


def test_stages_narrow_down(stages):
    names = list(stages)
    for a, b in zip(names, names[1:]):
        assert ids(stages[b]) <= ids(stages[a])
    for name in names[1:-1]:
        assert stages[name].columns == stages["documents"].columns
        assert stages[name].schema.simpleString() == stages["documents"].schema.simpleString()


def test_bad_documents_go_and_good_ones_stay(spark, stages):
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    kept = labels.join(stages["quality_classifier"].select("doc_id").distinct(), "doc_id", "left_semi")
    share = lambda q: kept.where(F.col("quality") == q).count() / max(1, labels.where(F.col("quality") == q).count())
    assert share(1) > 0.95 and share(0) < 0.5


def test_one_of_each_component(spark, stages):
    from approxboot.llm.jaccard import jaccard_components

    members, _ = jaccard_components(stages["quality_classifier"])
    assert ids(stages["jaccard_join"]) == {r["component_id"] for r in members.collect()}


def test_no_benchmark_is_left(spark, stages):
    bench = [r["text"] for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    texts = [r["text"] for r in stages["benchmark_decontamination"].collect()]
    assert not any(b in t for t in texts for b in bench)
    dropped = ids(stages["jaccard_join"]) - ids(stages["benchmark_decontamination"])
    assert len(dropped) < 0.2 * len(ids(stages["jaccard_join"]))


def test_secrets_are_masked(spark, stages):
    from approxboot.llm.secrets import scan

    assert ids(stages["secret_scan"]) == ids(stages["benchmark_decontamination"])
    left, _ = scan(stages["secret_scan"])
    assert left.count() == 0
    assert stages["secret_scan"].where(F.length("text") != F.col("n_chars")).count() == 0


def test_all_that_is_left_is_packed(stages):
    assert ids(stages["best_fit_packing"]) == ids(stages["secret_scan"])


def test_run_gives_the_last_stage(spark, stages):
    assert corpus_pipeline.run(spark, SF).count() == stages["best_fit_packing"].count()


def test_odd_documents_pass(spark):
    like = spark.read.parquet(f"{SF}/documents.parquet")
    odd = spark.createDataFrame([(1, None, None, None, None), (None, "", "en", "s", 0), (2, "password=hunter22", "en", "s", 17), (2, "password=hunter22", "en", "s", 17), (3, "w " * 60_000, None, None, 120_000)], like.schema)
    odd = odd.withColumn("score", F.lit(9)).withColumn("spans", F.lit("x")).withColumn("node", F.lit(0))
    for docs in (odd, odd.limit(0)):
        for _, stage in corpus_pipeline.STAGES[:-1]:
            docs = stage(spark, docs, SF)
            assert docs.columns == odd.columns
        assert corpus_pipeline.STAGES[-1][1](spark, docs, SF).count() >= 0


def test_rows_of_one_component_are_told_apart(spark):
    """Repeated rows, a doc_id that two texts share, and copies without a doc_id."""
    text = [" ".join(f"w{i}x{k}" for k in range(60)) for i in range(4)]
    rows = [(5, text[0]), (5, text[0]), (5, text[1]), (3, text[0]), (None, text[2]), (None, text[2] + " more"), (None, text[2]), (7, text[3]), (7, text[3]), (8, ""), (8, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("doc_id", "text", "1 as uid", "2 as root", "3 as _doc")
    kept = corpus_pipeline.keep_one_of_similar(spark, docs, SF)
    assert kept.columns == docs.columns
    got = sorted([(r["doc_id"], r["text"]) for r in kept.collect()], key=str)
    fixed = [(5, text[1]), (3, text[0]), (7, text[3]), (8, ""), (8, "")]
    assert len(got) == 6 and all(got.count(x) == fixed.count(x) for x in fixed)
    assert [d for d, t in got if t.startswith(text[2])] == [None]
