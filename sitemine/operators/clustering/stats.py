"""Sub-cluster summaries and totals: the only data that leaves a site."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sitemine.schemas import POINTS, require_columns

#: Up to this many dimensions the aggregates are generated columns; beyond, rows per dimension.
WIDE = 128


def clean_points(points: DataFrame) -> DataFrame:
    """``points`` without rows whose features are null, empty or hold null, NaN or infinity."""
    require_columns(points, POINTS)
    fine = F.forall("features", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return points.where(F.col("features").isNotNull() & (F.size("features") > 0) & fine)


def dimension(points: DataFrame) -> int:
    first = points.select(F.size("features").alias("d")).first()
    return first.d if first else 0


def sub_stats(labelled: DataFrame, by: tuple[str, ...] = ("site", "local_id"), d: int | None = None) -> DataFrame:
    """(*by, n, center, scatter): one partial and one final aggregation, no point is gathered."""
    d = dimension(labelled) if d is None else d
    if d > WIDE:
        return _sub_stats_long(labelled, by)
    x = [F.element_at("features", i + 1) for i in range(d)]
    means, spread = [F.avg(c) for c in x], [F.var_pop(c) for c in x]
    total: Column = F.lit(0.0)
    for s in spread:
        total = total + s
    return labelled.groupBy(*by).agg(F.count("*").alias("n"), F.array(*means).alias("center"), (total * F.count("*")).alias("scatter"))


def _sub_stats_long(labelled: DataFrame, by: tuple[str, ...]) -> DataFrame:
    each = labelled.select(*by, F.posexplode("features").alias("i", "x")).groupBy(*by, "i").agg(F.count("*").alias("n"), F.avg("x").alias("m"), F.var_pop("x").alias("v"))
    rows = each.groupBy(*by).agg(F.first("n").alias("n"), F.array_sort(F.collect_list(F.struct("i", "m"))).alias("c"), F.sum("v").alias("v"))
    return rows.select(*by, "n", F.col("c.m").alias("center"), (F.col("v") * F.col("n")).alias("scatter"))


def total_scatter(clusters: DataFrame) -> DataFrame:
    return clusters.agg(F.sum("scatter").alias("total_scatter"))
