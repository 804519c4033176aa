"""Agreement of a clustering with a planted truth."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def contingency(labelled: DataFrame, found: str, truth: str) -> DataFrame:
    return labelled.groupBy(F.col(found).alias("found"), F.col(truth).alias("truth")).agg(F.count("*").alias("n"))


def purity(labelled: DataFrame, found: str = "global_id", truth: str = "label") -> DataFrame:
    """(purity): share of points in the most common true class of their cluster."""
    best = contingency(labelled, found, truth).groupBy("found").agg(F.max("n").alias("top"), F.sum("n").alias("n"))
    return best.agg((F.sum("top") / F.sum("n")).alias("purity"))


def adjusted_rand(labelled: DataFrame, found: str = "global_id", truth: str = "label") -> DataFrame:
    """(adjusted_rand) from pair counts of the contingency table."""
    pairs = lambda n: n * (n - 1) / 2
    table = contingency(labelled, found, truth)
    both = table.agg(F.sum(pairs(F.col("n"))).alias("both"), F.sum("n").alias("n"))
    rows = table.groupBy("found").agg(F.sum("n").alias("n")).agg(F.sum(pairs(F.col("n"))).alias("rows"))
    columns = table.groupBy("truth").agg(F.sum("n").alias("n")).agg(F.sum(pairs(F.col("n"))).alias("columns"))
    one = both.crossJoin(rows).crossJoin(columns)  # three tables of one row
    expected = F.col("rows") * F.col("columns") / pairs(F.col("n"))
    most = (F.col("rows") + F.col("columns")) / 2
    return one.select(F.when(most == expected, F.lit(1.0)).otherwise((F.col("both") - expected) / (most - expected)).alias("adjusted_rand"))


def sse_ratio(total_scatter: float, central_cost: float) -> float:
    """Scatter of a clustering over that of a central one with as many clusters."""
    return total_scatter / central_cost if central_cost else float("inf") if total_scatter else 1.0
