"""Summaries of point groups as columns and as NumPy: merge, take apart, distances.

A summary is a struct (n, center, scatter); scatter is the sum of squared distances of a
group's points to its centre.  With the squared distance, merging is exact: the result is
the summary of the union.  The plain distance is offered as the other reading of the
increase; it keeps no such identity.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf

DISTANCES = ("sqeuclidean", "euclidean")


def squared_distance(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def distance_of(a: Column, b: Column, distance: str = "sqeuclidean") -> Column:
    if distance not in DISTANCES:
        raise ValueError(f"distance must be one of {', '.join(DISTANCES)}")
    d = squared_distance(a, b)
    return d if distance == "sqeuclidean" else F.sqrt(d)


def merge_increase(a: Column, b: Column, distance: str = "sqeuclidean") -> Column:
    """What a merge adds to the sum of the two scatters."""
    na, nb = a["n"], b["n"]
    return na * nb / (na + nb) * distance_of(a["center"], b["center"], distance)


def merge_stats(a: Column, b: Column, distance: str = "sqeuclidean") -> Column:
    """The summary of the union of two groups."""
    n = a["n"] + b["n"]
    center = F.zip_with(a["center"], b["center"], lambda x, y: x * (a["n"] / n) + y * (b["n"] / n))
    return F.struct(n.alias("n"), center.alias("center"), (a["scatter"] + b["scatter"] + merge_increase(a, b, distance)).alias("scatter"))


def remove_stats(group: Column, part: Column, distance: str = "sqeuclidean") -> Column:
    """The summary of a group without one of its parts (the part must not be all of it)."""
    n = group["n"] - part["n"]
    center = F.zip_with(group["center"], part["center"], lambda g, x: (g * group["n"] - x * part["n"]) / n)
    rest = F.struct(n.alias("n"), center.alias("center"))
    freed = n * part["n"] / group["n"] * distance_of(part["center"], center, distance)
    return F.struct(rest["n"].alias("n"), rest["center"].alias("center"), F.greatest(F.lit(0.0), group["scatter"] - part["scatter"] - freed).alias("scatter"))


def move_gain(member: Column, own: Column, rival: Column, distance: str = "sqeuclidean") -> Column:
    """How much the total scatter falls when ``member`` goes from ``own`` to ``rival``."""
    left, joined = remove_stats(own, member, distance), merge_stats(rival, member, distance)
    return own["scatter"] + rival["scatter"] - left["scatter"] - joined["scatter"]


def distance_np(a: np.ndarray, b: np.ndarray, distance: str = "sqeuclidean") -> np.ndarray:
    d = ((a - b) ** 2).sum(-1)
    return d if distance == "sqeuclidean" else np.sqrt(d)


def merge_np(a: tuple, b: tuple, distance: str = "sqeuclidean") -> tuple:
    n = a[0] + b[0]
    return n, (a[0] * a[1] + b[0] * b[1]) / n, a[2] + b[2] + a[0] * b[0] / n * distance_np(a[1], b[1], distance)


def remove_np(group: tuple, part: tuple, distance: str = "sqeuclidean") -> tuple:
    n = group[0] - part[0]
    center = (group[0] * group[1] - part[0] * part[1]) / n
    return n, center, max(0.0, group[2] - part[2] - n * part[0] / group[0] * distance_np(part[1], center, distance))


@pandas_udf(T.DoubleType())
def scatter_of(features: pd.Series) -> float:
    """Grouped aggregate: the scatter of a group's points (a reference for tests)."""
    x = np.stack(features.to_list()) if len(features) else np.zeros((0, 1))
    return float(((x - x.mean(axis=0)) ** 2).sum()) if len(x) else 0.0


def nearest_center(centers: np.ndarray):
    """A scalar pandas UDF: position of the nearest of fixed centres, lowest among equals."""

    @pandas_udf(T.IntegerType())
    def nearest(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for features in batches:
            if not len(features):
                yield pd.Series([], dtype="int32")
                continue
            x = np.stack(features.to_list())
            yield pd.Series(((x[:, None, :] - centers[None]) ** 2).sum(-1).argmin(axis=1).astype("int32"))

    return nearest
