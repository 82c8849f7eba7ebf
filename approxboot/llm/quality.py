"""Quality scores from how well two compression dictionaries fit a text.

A zstandard dictionary is built from good labelled texts and one from bad ones. A text is compressed with
both; the difference of the sizes over their sum, and the sizes against the text's own, go into a logistic
calibration fitted on labelled texts that the dictionaries did not see.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from approxboot.llm.common import table

LEVEL = 3


@dataclass
class CompressionModel:
    """Two dictionaries and the calibration's weights; small enough to go with every task."""

    good: bytes
    bad: bytes
    weights: list[float]
    means: list[float]
    scales: list[float]


def _compressor(dictionary: bytes) -> zstandard.ZstdCompressor:
    kind = zstandard.ZstdCompressionDict(dictionary, dict_type=zstandard.DICT_TYPE_AUTO)
    kind.precompute_compress(level=LEVEL)
    return zstandard.ZstdCompressor(dict_data=kind, write_content_size=False, write_checksum=False, write_dict_id=False)


def features(texts: list[str], good: bytes, bad: bytes) -> np.ndarray:
    """Normalised difference of compressed sizes and their ratios to the text's size, for each text."""
    by_good, by_bad = _compressor(good), _compressor(bad)
    out = np.zeros((len(texts), 4))
    for i, t in enumerate(texts):
        raw = t.encode()
        a, b, n = len(by_good.compress(raw)), len(by_bad.compress(raw)), len(raw) + 1
        out[i] = (b - a) / (a + b), (b - a) / n, min(a, b) / n, np.log(n)
    return out


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, steps: int = 30) -> np.ndarray:
    w = np.zeros(x.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        h = (x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(w))
        w += np.linalg.solve(h, x.T @ (y - p) - ridge * w)
    return w


def _terms(f: np.ndarray, model: CompressionModel) -> np.ndarray:
    # clipped, so that a text far outside the sample is not scored by extrapolation
    z = np.clip((f - np.array(model.means)) / np.array(model.scales), -3, 3)
    return np.column_stack([np.ones(len(z)), z, z[:, 0] ** 2, z[:, 2] ** 2, z[:, 0] * z[:, 2]])


def score_texts(texts: list[str], model: CompressionModel) -> np.ndarray:
    f = features(texts, model.good, model.bad)
    return 1 / (1 + np.exp(-np.clip(_terms(f, model) @ np.array(model.weights), -30, 30)))


def _dictionary(texts: list[str], size: int) -> bytes:
    raws = [t.encode() for t in texts if t]
    # a long text is several samples, which cover all of it
    samples = [raw[a : a + 20_000] for raw in raws for a in range(0, len(raw), 20_000)]
    try:
        return zstandard.train_dictionary(size, samples, level=LEVEL).as_bytes()
    except zstandard.ZstdError:  # too few samples to train on: their bytes themselves
        return b"".join(samples)[-size:] or b"\0" * 8


def fit(docs: DataFrame, labels: DataFrame, max_docs_per_class: int = 2_000, max_bytes_per_class: int = 32 << 20, dictionary_bytes: int = 112_640, seed: int = 3) -> CompressionModel:
    """Fit on labelled documents chosen by a hash of doc_id: of each class at most max_docs_per_class, of max_bytes_per_class together.

    Texts are used whole; one of more than a 64th of max_bytes_per_class is not in the sample, so that what the
    driver collects is bounded. labels: doc_id, quality. Repeated labels of one doc_id count once; contradictory
    or null ones are left out. Of rows with one doc_id one is used. Half of the sample builds the dictionaries,
    the other half the calibration. Without labels of both classes (an empty table, too) every score is one half.
    """
    one = labels.where("doc_id is not null and quality is not null").groupBy("doc_id").agg(F.min("quality").alias("q"), F.max("quality").alias("_m")).where("q = _m")
    one = one.withColumn("_h", F.xxhash64(F.lit(seed), "doc_id"))
    chosen = None
    for q in (0, 1):
        some = one.where(F.col("q") == q).orderBy("_h", "doc_id").limit(max_docs_per_class)
        chosen = some if chosen is None else chosen.unionByName(some)
    # two limits bound what is broadcast and collected
    sample = docs.select("doc_id", "text").join(F.broadcast(chosen.select("doc_id", "q", "_h")), "doc_id")
    sample = sample.select("q", "_h", F.coalesce("text", F.lit("")).alias("text"), "doc_id").dropDuplicates(["doc_id"]).withColumn("_size", F.octet_length("text"))
    before = F.sum("_size").over(Window.partitionBy("q").orderBy("_h", "doc_id"))
    rows = sample.where(F.col("_size") <= max_bytes_per_class // 64).withColumn("_sum", before).where(F.col("_sum") <= max_bytes_per_class).collect()
    rows.sort(key=lambda r: (r["_h"], r["doc_id"]))
    by = {q: [r["text"] for r in rows if r["q"] == q] for q in (0, 1)}
    if len(by[0]) < 2 or len(by[1]) < 2:
        return CompressionModel(b"\0" * 8, b"\0" * 8, [0.0] * 8, [0.0] * 4, [1.0] * 4)
    good, bad = (_dictionary(by[q][::2], dictionary_bytes) for q in (1, 0))
    rest = [(t, q) for q in (0, 1) for t in by[q][1::2]]
    f = features([t for t, _ in rest], good, bad)
    model = CompressionModel(good, bad, [], f.mean(0).tolist(), (f.std(0) + 1e-9).tolist())
    y = np.array([q for _, q in rest], float)
    # classes are sampled apart: weights bring back the share of each among all labels
    share = {r["q"]: r["n"] for r in one.groupBy("q").agg(F.count(F.lit(1)).alias("n")).collect()}
    model.weights = _logistic(_terms(f, model), y).tolist()
    n = {q: sum(1 for _, x in rest if x == q) for q in (0, 1)}
    model.weights[0] += float(np.log(share[1] / share[0]) - np.log(n[1] / n[0]))
    return model


def score(docs: DataFrame, model: CompressionModel, text: str = "text", out: str = "score") -> DataFrame:
    """docs with the column out, 0 to 1, which replaces one of that name; null and empty texts are scored as empty ones, long ones whole, equal ones alike."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def quality(s: pd.Series) -> pd.Series:
        return pd.Series(score_texts([t or "" for t in s], held.value))

    return docs.withColumn(out, quality(F.col(text)))


def training_labels(labels: DataFrame, folds: int = 5) -> DataFrame:
    """Labels of rows outside the held-out fold."""
    return labels.where(F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(folds)) != 0)


def op7_compression_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores of all documents. A null doc_id is in no fold, so not held out."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = fit(docs, training_labels(table(spark, sf_dir, "labels").select("doc_id", "quality")))
    held = F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(5)) == 0
    out = score(docs, model)
    return out.select("doc_id", F.coalesce(held, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


QUERIES = {"op7_compression_quality": op7_compression_quality}
ORACLES: dict[str, str] = {}
