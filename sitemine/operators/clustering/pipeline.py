"""Variance-merge clustering end to end, and its labels on points."""

from __future__ import annotations

from collections.abc import Mapping
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sitemine.operators.clustering.gap import chosen_k, gap_statistic
from sitemine.operators.clustering.local import kmeans_multi, local_cluster
from sitemine.operators.clustering.merge import labels_of, merge_bound, merge_subclusters
from sitemine.operators.clustering.perturb import perturb
from sitemine.operators.clustering.stats import clean_points, dimension, sub_stats
from sitemine.session import broadcast_if_small, materialise


@dataclass
class VMergeResult:
    """Labels are logical (per sub-cluster); ``labelled`` holds the points with local_id."""

    labels: DataFrame
    clusters: DataFrame
    substats: DataFrame
    trace: DataFrame
    labelled: DataFrame
    bound: float


def vmerge_cluster(
    points: DataFrame,
    *,
    k_local: int | Mapping[int, int] | str = 20,
    local: str = "kmeans_multi",
    iterations: int = 10,
    threshold: str | float = "twice_max",
    factor: float = 2.0,
    scope: str = "global",
    variance: str = "scatter",
    distance: str = "sqeuclidean",
    pick: str = "variance",
    same_site: bool = True,
    engine: str = "auto",
    border: int | float = 0.1,
    rule: str = "to_center",
    multi: bool = True,
    mode: str = "auto",
    max_sweeps: int = 1,
) -> VMergeResult:
    """Cluster every site alone, ship summaries, merge under the bound, repair borders.

    ``k_local`` is a number, a mapping by site, or "gap"; ``local`` is "kmeans_multi" or an
    algorithm of ``local_cluster``.
    """
    points = clean_points(points)
    if k_local == "gap":
        k_local = chosen_k(gap_statistic(points))
    labelled = kmeans_multi(points, k_local, iterations=iterations) if local == "kmeans_multi" else local_cluster(points, k_local, algo=local, iterations=iterations)
    substats = materialise(sub_stats(labelled, d=dimension(points)))
    bound = float(threshold) if not isinstance(threshold, str) else merge_bound(substats, factor, variance)
    merged = merge_subclusters(
        substats, threshold=threshold, factor=factor, scope=scope, variance=variance, distance=distance, pick=pick, same_site=same_site, engine=engine
    )
    before = merged.agg(F.sum("scatter").alias("t"), F.count("*").alias("g")).first()
    clusters, moves = perturb(merged, substats, border=border, bound=bound if multi and variance == "scatter" else None, mode=mode, distance=distance, max_sweeps=max_sweeps, rule=rule)
    head = points.sparkSession.createDataFrame([(0, "merge", substats.count(), before.g, before.t)], moves.schema)
    return VMergeResult(labels_of(clusters), clusters, substats, head.union(moves), labelled, bound)


def label_points(labelled: DataFrame, labels: DataFrame) -> DataFrame:
    """Points with their global cluster: the small labelling goes to the points."""
    return labelled.join(broadcast_if_small(labels), ["site", "local_id"])
