"""Plain k-means on vectors, as a check on the others."""

from __future__ import annotations

from pyspark.ml.clustering import KMeans
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def fit(vectors: DataFrame, k: int, seed: int = 1) -> DataFrame:
    """``(vec_id, cluster)`` of ``(vec_id, v)``."""
    data = vectors.select("vec_id", array_to_vector("v").alias("features"))
    return KMeans(k=k, seed=seed).fit(data).transform(data).select("vec_id", F.col("prediction").alias("cluster"))
