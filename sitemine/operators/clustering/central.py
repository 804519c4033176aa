"""Central reference: one k-means over all points."""

from __future__ import annotations

from pyspark.ml.clustering import KMeans
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame


def central_kmeans(points: DataFrame, k: int, *, seed: int = 42, iterations: int = 20) -> tuple[DataFrame, float]:
    """(points plus global_id, total scatter)."""
    rows = points.withColumn("vector", array_to_vector("features"))
    model = KMeans(k=k, seed=seed, maxIter=iterations, featuresCol="vector", predictionCol="global_id").fit(rows)
    return model.transform(rows).drop("vector"), float(model.summary.trainingCost)
