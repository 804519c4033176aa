"""Choices of engine from cheap statistics, and advice on sites."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sitemine.operators.clustering.local import MAX_SITE_ROWS
from sitemine.operators.clustering.merge import TASK_ROWS
from sitemine.operators.itemsets.support import counting_engine

__all__ = ["counting_engine", "late_sync_advice", "local_engine", "merge_engine"]


def local_engine(points: DataFrame) -> str:
    """One task a site while every site fits, else the Lloyd steps of all sites together."""
    largest = points.groupBy("site").count().agg(F.max("count")).first()[0] or 0
    return "kmeans" if largest <= MAX_SITE_ROWS // 10 else "kmeans_multi"


def merge_engine(n_summaries: int, reducible: bool) -> str:
    return "task" if n_summaries <= TASK_ROWS else "rounds" if reducible else "tree"


def late_sync_advice(success: DataFrame) -> str:
    """Which miner to use, from the success rate by size: many local-only sets make late requests costly."""
    row = success.agg(F.sum("local_sets").alias("l"), F.sum("global_sets").alias("g")).first()
    rate = (row.g or 0) / row.l if row.l else 1.0
    return "latesync" if rate >= 0.1 else "levelsync"
