"""K-means on a weighted sample against all rows."""

from __future__ import annotations

import numpy as np
from pyspark.ml.clustering import KMeans
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from approxboot.functions import rng
from approxboot.operators.sampling import SampleCursor


def planted_blobs(spark: SparkSession, n: int, k: int, dims: int = 2, spread: float = 0.5, seed: int = 0) -> tuple[DataFrame, np.ndarray]:
    """(id, cluster, features) around k centres on a grid, with noise by hash; and the centres."""
    centres = np.array([[10.0 * ((c * (d + 1) * 7 + d) % (k + 1)) + 3 * c for d in range(dims)] for c in range(k)])
    df = spark.range(n).withColumn("cluster", F.pmod("id", F.lit(k)).cast("int"))
    table = F.array(*[F.array(*[F.lit(float(v)) for v in row]) for row in centres])
    noise = [sum(rng.uniform_xx("blob", "id", F.lit(d), F.lit(i), seed=seed) for i in range(6)) - 3.0 for d in range(dims)]
    features = F.array(*[table[F.col("cluster")][d] + noise[d] * spread * 1.41 for d in range(dims)])
    return df.withColumn("features", features), centres


def fit(df: DataFrame, k: int, features: str = "features", weight: str | None = None, restarts: int = 3, seed: int = 0, max_iter: int = 20) -> tuple[np.ndarray, float, int]:
    """(centroids, cost, iterations) of the best of some restarts of k-means++."""
    data = df.withColumn("_v", array_to_vector(F.col(features).cast("array<double>"))).select("_v", *([weight] if weight else []))
    best = None
    for r in range(restarts):
        model_of = KMeans(featuresCol="_v", k=k, seed=seed + r, maxIter=max_iter, initMode="k-means||")
        model = (model_of.setWeightCol(weight) if weight else model_of).fit(data)
        s = model.summary
        if best is None or s.trainingCost < best[1]:
            best = (np.array(model.clusterCenters()), float(s.trainingCost), int(s.numIter))
    return best


def fit_early(df: DataFrame, k: int, ids: list[str], sigma: float, features: str = "features", p: float = 0.005, rounds: int = 6, seed: int = 0) -> tuple[np.ndarray, int, int, int]:
    """(centroids, rounds, rows, iterations) from samples that double until the cost a row moves by sigma at most from one to the next."""
    cursor = SampleCursor(df, ids, seed)
    before, inner = None, 0
    for i in range(1, rounds + 1):
        cursor.grow(p)
        sample = cursor.sample().cache()
        n = sample.count()
        found, total, its = fit(sample, k, features, restarts=1, seed=seed) if n >= k else (None, 0.0, 0)
        sample.unpersist()
        inner += its
        now = total / n if n else 0.0
        if p >= 1 or found is not None and before is not None and abs(now - before) <= sigma * max(now, before):
            break
        before, p = (now if found is not None else before), min(1.0, 2 * p)
    return found, i, n, inner


def cost(df: DataFrame, centroids: np.ndarray, features: str = "features") -> float:
    """Sum of squared distances to the nearest centroid, in one aggregate."""
    far = [sum((F.col(features)[d] - F.lit(float(v))) ** 2 for d, v in enumerate(row)) for row in centroids]
    return float(df.agg(F.sum(F.least(*far) if len(far) > 1 else far[0]).alias("c")).first()["c"])
