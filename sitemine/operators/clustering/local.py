"""Local clustering: each site's points into its own sub-clusters, sites independent.

``kmeans_multi`` runs the Lloyd steps of all sites in one job each, so a site may span
the cluster: centres (sites x k rows) are broadcast, points are assigned where they are,
and only sums per sub-cluster are shuffled.  ``local_cluster`` gives each site to one
task, for sites that fit there, and takes any local algorithm.  Both start from the
points with the lowest ids of a site, so runs agree whatever the partitioning.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Mapping

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sitemine.functions.merge_columns import squared_distance
from sitemine.operators.clustering.stats import clean_points, dimension
from sitemine.session import materialise

ITERATIONS = 10
#: Points of a site that one task may hold (``local_cluster``).
MAX_SITE_ROWS = 2_000_000
#: Numbers in the centres of a site from which matrix products pay, and in all centres up to which they may be held.
MATRIX_FROM = 64
MATRIX_TO = 4_000_000
#: Squared distances this close, relatively, are equal: where a point lies midway between two centres, the rounding of its scaled coordinates must not decide.
TIE = 1e-12

KLocal = int | Mapping[int, int]


def _k_table(points: DataFrame, k_local: KLocal) -> DataFrame:
    spark = points.sparkSession
    sites = points.select("site").distinct()
    if isinstance(k_local, int):
        return sites.withColumn("k", F.lit(k_local))
    table = spark.createDataFrame([(int(s), int(k)) for s, k in k_local.items()], "site int, k int")
    return sites.join(F.broadcast(table), "site")


def first_centers(points: DataFrame, k_local: KLocal) -> DataFrame:
    """(site, local_id, center): a site's k points of lowest id.

    Only a low stretch of each site's id range is ranked, so no site is sorted whole.
    """
    ks = _k_table(points, k_local)
    most = k_local if isinstance(k_local, int) else max([1, *k_local.values()])
    ids = _lowest_ids(points, most)
    seeds = points.join(F.broadcast(ids), ["site", "point_id"]).join(F.broadcast(ks), "site").where(F.col("turn") < F.col("k"))
    return seeds.select("site", F.col("turn").alias("local_id"), F.col("features").alias("center"))


def _lowest_ids(points: DataFrame, most: int) -> DataFrame:
    """(site, point_id, turn): the ``most`` lowest ids of each site, found by halves of the id range."""
    span = points.groupBy("site").agg(F.min("point_id").alias("lo"), F.max("point_id").alias("hi"), F.count("*").alias("n"))
    # an evenly filled id range would hold `most` ids in this window; four times that, and doubled until it does
    factor = 4.0
    span = materialise(span)
    while True:
        cut = span.withColumn("cut", F.col("lo") + F.ceil((F.col("hi") - F.col("lo") + 1) * F.least(F.lit(1.0), F.lit(factor * most) / F.col("n"))))
        near = points.select("site", "point_id").join(F.broadcast(cut), "site").where(F.col("point_id") <= F.col("cut"))
        rank = F.row_number().over(Window.partitionBy("site").orderBy("point_id")) - 1
        found = materialise(near.withColumn("turn", rank.cast("int")).where(F.col("turn") < most).select("site", "point_id", "turn"))
        short = span.join(found.groupBy("site").count(), "site", "left").where(F.coalesce("count", F.lit(0)) < F.least(F.col("n"), F.lit(most)))
        if short.isEmpty():
            return found
        factor *= 16


def assign(points: DataFrame, centers: DataFrame) -> DataFrame:
    """``points`` plus local_id: the nearest centre of the point's site, lowest id among equals (``TIE``).

    Few numbers per point are compared by column expressions; many, as long as all centres
    together are bounded, by matrix products over Arrow batches.
    """
    size = centers.agg(F.count("*").alias("rows"), F.max(F.size("center")).alias("d"), F.count_distinct("site").alias("sites")).first()
    numbers = (size.rows or 0) * (size.d or 0)
    if size.sites and numbers / size.sites > MATRIX_FROM and numbers <= MATRIX_TO:
        return _assign_by_matrix(points, centers)
    gathered = centers.groupBy("site").agg(F.array_sort(F.collect_list(F.struct("local_id", "center"))).alias("centers"))
    near = F.transform("centers", lambda c: F.struct(squared_distance(F.col("features"), c["center"]).alias("d"), c["local_id"].alias("local_id")))
    equal = F.filter("near", lambda c: c["d"] <= F.array_min("near")["d"] * (1 + TIE))
    gathered = F.broadcast(gathered) if numbers <= MATRIX_TO else gathered
    return points.join(gathered, "site").withColumn("near", near).withColumn("local_id", equal[0]["local_id"]).drop("centers", "near")


def first_least(d: np.ndarray) -> np.ndarray:
    """The first of each row's least squared distances, equal ones as ``TIE`` has it."""
    return (d <= d.min(axis=-1, keepdims=True) * (1 + TIE)).argmax(axis=-1)


def nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    """The nearest row of c for each row of x, the first among equals, as exact differences tell.

    Products are compared after centring; where the runner-up is within their rounding, the
    differences themselves decide.
    """
    middle = c.mean(axis=0)
    y, e = x - middle, c - middle
    size = (e * e).sum(axis=1)
    far = size - 2 * y @ e.T
    best = far.argmin(axis=1)
    if len(c) < 2:
        return best
    doubt = 1e-12 * ((y * y).sum(axis=1) + size.max()) * x.shape[1]
    close = far <= far[np.arange(len(x)), best][:, None] + doubt[:, None]
    for i in np.flatnonzero(close.sum(axis=1) > 1):
        some = np.flatnonzero(close[i])
        best[i] = some[first_least(((x[i] - c[some]) ** 2).sum(axis=1))]
    return best


def _assign_by_matrix(points: DataFrame, centers: DataFrame) -> DataFrame:
    held: dict[int, tuple[np.ndarray, np.ndarray]] = {}
    for r in centers.orderBy("site", "local_id").collect():
        held.setdefault(r.site, []).append((r.local_id, r.center))
    held = {site: (np.array([i for i, _ in rows], np.int32), np.array([c for _, c in rows])) for site, rows in held.items()}
    shared = points.sparkSession.sparkContext.broadcast(held)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sites = batch.column("site").to_numpy(zero_copy_only=False)
            x = batch.column("features").flatten().to_numpy().reshape(batch.num_rows, -1)
            labels = np.zeros(batch.num_rows, np.int32)
            for site in np.unique(sites):
                ids, c = shared.value[int(site)]
                own = sites == site
                labels[own] = ids[nearest(x[own], c)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(labels)], names=[*batch.schema.names, "local_id"])

    schema = ", ".join([*(f"`{c}` {t}" for c, t in points.dtypes), "local_id int"])
    return points.join(F.broadcast(centers.select("site").distinct()), "site", "left_semi").mapInArrow(run, schema)


def kmeans_multi(points: DataFrame, k_local: KLocal = 20, *, iterations: int = ITERATIONS, tolerance: float = 0.0) -> DataFrame:
    """``points`` plus local_id after at most ``iterations`` Lloyd steps at every site.

    Empty sub-clusters disappear.  The loop ends early when no centre moves by more than
    ``tolerance``.  The points are written once to the shared folder, not derived anew in
    every step.
    """
    points = materialise(clean_points(points))
    d = dimension(points)
    centers = materialise(first_centers(points, k_local))
    for _ in range(iterations):
        means = [F.avg(F.element_at("features", i + 1)) for i in range(d)]
        moved = materialise(assign(points, centers).groupBy("site", "local_id").agg(F.array(*means).alias("center")))
        far = centers.withColumnRenamed("center", "old").join(moved, ["site", "local_id"]).agg(F.max(squared_distance(F.col("old"), F.col("center")))).first()[0]
        centers = moved
        if far is None or far <= tolerance * tolerance:
            break
    return assign(points, centers)


def kmeans_np(x: np.ndarray, k: int, iterations: int = ITERATIONS) -> np.ndarray:
    """Labels of rows of x, started from its first k rows."""
    centers = x[: min(k, len(x))].copy()
    ids = np.arange(len(centers))
    labels = np.zeros(len(x), np.int64)
    for _ in range(iterations + 1):
        labels = ids[first_least(((x[:, None, :] - centers[None]) ** 2).sum(-1))]
        ids = np.unique(labels)
        new = np.stack([x[labels == i].mean(axis=0) for i in ids])
        if new.shape == centers.shape and (new == centers).all():
            break
        centers = new
    return labels


def bisecting_np(x: np.ndarray, k: int, iterations: int = ITERATIONS) -> np.ndarray:
    """Split the group of largest scatter in two until there are k."""
    labels = np.zeros(len(x), np.int64)
    for new in range(1, min(k, len(x))):
        scatter = [((x[labels == i] - x[labels == i].mean(axis=0)) ** 2).sum() for i in range(new)]
        worst = int(np.argmax(scatter))
        if scatter[worst] == 0:
            break
        own = np.flatnonzero(labels == worst)
        far = own[((x[own] - x[own].mean(axis=0)) ** 2).sum(axis=1).argmax()]
        other = own[((x[own] - x[far]) ** 2).sum(axis=1).argmax()]
        order = np.concatenate([[far, other], own[(own != far) & (own != other)]])
        labels[order[kmeans_np(x[order], 2, iterations) == 1]] = new
    return labels


def grid_density_np(x: np.ndarray, k: int, iterations: int = ITERATIONS) -> np.ndarray:
    """Connected dense cells of a grid over the widest axes; sparse points join the nearest group.

    ``k`` sets the number of cells an axis has, so that it bounds the groups' fineness.
    """
    axes = np.argsort(-x.var(axis=0), kind="stable")[:2]
    low, high = x[:, axes].min(axis=0), x[:, axes].max(axis=0)
    cells = np.minimum((x[:, axes] - low) / np.where(high > low, high - low, 1) * k, k - 1).astype(int)
    keys, inverse, counts = np.unique(cells, axis=0, return_inverse=True, return_counts=True)
    dense = counts >= max(1.0, len(x) / len(keys) / 2)
    group = np.full(len(keys), -1)
    places = {tuple(c): i for i, c in enumerate(keys) if dense[i]}
    found = 0
    for start in places.values():
        if group[start] >= 0:
            continue
        todo = [start]
        group[start] = found
        while todo:
            at = keys[todo.pop()]
            for step in np.ndindex(*[3] * len(axes)):
                i = places.get(tuple(at + np.array(step) - 1))
                if i is not None and group[i] < 0:
                    group[i] = found
                    todo.append(i)
        found += 1
    labels = group[inverse.ravel()]
    centers = np.stack([x[labels == i].mean(axis=0) for i in range(found)])
    rest = np.flatnonzero(labels < 0)
    labels[rest] = ((x[rest, None, :] - centers[None]) ** 2).sum(-1).argmin(axis=1)
    return labels


ALGORITHMS: dict[str, Callable[[np.ndarray, int, int], np.ndarray]] = {"kmeans": kmeans_np, "bisecting": bisecting_np, "grid_density": grid_density_np}


def local_cluster(points: DataFrame, k_local: KLocal = 20, *, algo: str | Callable = "kmeans", iterations: int = ITERATIONS, max_site_rows: int = MAX_SITE_ROWS) -> DataFrame:
    """``points`` plus local_id, each site in one task by ``algo(x, k, iterations) -> labels``.

    A site over ``max_site_rows`` is refused: use ``kmeans_multi``, which has no such limit.
    """
    run = ALGORITHMS[algo] if isinstance(algo, str) else algo
    points = clean_points(points)
    largest = points.groupBy("site").count().agg(F.max("count")).first()[0] or 0
    if largest > max_site_rows:
        raise ValueError(f"a site has {largest} points, one task may hold {max_site_rows}; use kmeans_multi")
    keyed = points.join(F.broadcast(_k_table(points, k_local)), "site")

    def one(site: pd.DataFrame) -> pd.DataFrame:
        site = site.sort_values("point_id", kind="stable")
        labels = run(np.stack(site["features"].to_list()), int(site["k"].iloc[0]), iterations)
        return site.drop(columns="k").assign(local_id=np.asarray(labels).astype("int32"))

    schema = ", ".join([*(f"`{c}` {t}" for c, t in points.dtypes), "local_id int"])
    return keyed.select(*points.columns, "k").groupBy("site").applyInPandas(one, schema)
