"""Pairs of groups that may merge, found through grids instead of all pairs.

With squared distances a merge is feasible only if d^2 < bound (1/n_a + 1/n_b), which is
at most 2 bound / n_min.  Groups are classed by their size, a factor of four to a class, and
every class has a grid whose cells have the radius of its smallest size, on the axes where
centres spread most.  A group is filed in the grids of its own and of all smaller classes,
and looks around only in its own, so that one tiny group widens no cell but those of tiny
groups; a pair meets in the grid of its smaller partner.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sitemine.functions.merge_columns import squared_distance

AXES = 2


def near_pairs(groups: DataFrame, bound: float, *, axes: int = AXES) -> DataFrame:
    """(a, b, d2, merged) for a < b with merged scatter strictly under ``bound``."""
    if bound <= 0:
        return groups.sparkSession.createDataFrame([], "a long, b long, d2 double, merged double")
    d = groups.select(F.size("center").alias("d")).first().d
    seen = groups.agg(F.sort_array(F.collect_set(F.floor(F.log2("n") / 2))).alias("classes"), *[F.stddev_pop(F.col("center")[i]).alias(f"s{i}") for i in range(d)]).first()
    on = sorted(sorted(range(d), key=lambda i: (-(seen[f"s{i}"] or 0.0), i))[:axes])
    classes = F.array(*[F.lit(int(c)) for c in seen.classes])  # a handful: powers of four
    rows = groups.select("group_id", "n", "center", "scatter", F.floor(F.log2("n") / 2).cast("int").alias("own"))
    filed = rows.withColumn("grid", F.explode(F.filter(classes, lambda c: c <= F.col("own"))))
    radius = F.sqrt(F.lit(2.0 * bound) / F.pow(F.lit(4.0), F.col("grid")))
    filed = filed.withColumn("cell", F.array(*[F.floor(F.col("center")[i] / radius) for i in on]))
    around = F.transform(F.sequence(F.lit(0), F.lit(3 ** len(on) - 1)), lambda s: F.array(*[F.element_at("cell", k + 1) + F.pmod(F.floor(s / 3**k), F.lit(3)) - 1 for k in range(len(on))]))
    left = filed.where("grid = own").select(F.col("group_id").alias("a"), F.col("n").alias("na"), F.col("center").alias("ca"), F.col("scatter").alias("va"), "grid", F.explode(around).alias("cell"))
    right = filed.select(F.col("group_id").alias("b"), F.col("n").alias("nb"), F.col("center").alias("cb"), F.col("scatter").alias("vb"), "grid", "cell", "own")
    met = left.join(right, ["grid", "cell"]).where((F.col("own") > F.col("grid")) | (F.col("a") < F.col("b")))
    merged = F.col("va") + F.col("vb") + F.col("na") * F.col("nb") / (F.col("na") + F.col("nb")) * F.col("d2")
    near = met.withColumn("d2", squared_distance(F.col("ca"), F.col("cb"))).withColumn("merged", merged).where(F.col("merged") < bound)
    return near.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), "d2", "merged")
