"""How many sub-clusters a site should have: the gap statistic.

For every k, the pooled within scatter of the site's clustering is compared with that of
uniform reference points in the site's bounding box.  A site's points go to one task, which
clusters them for every k; references need only the box and the number of points, so each
(site, k, replicate) is a task that draws its own.  Chosen is the smallest k whose gap is at
least the next one's less its standard error, or the largest k tried.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sitemine.operators.clustering.local import MAX_SITE_ROWS, kmeans_np
from sitemine.operators.clustering.stats import clean_points, dimension
from sitemine.session import materialise


def _log_within(x: np.ndarray, k: int) -> float:
    labels = kmeans_np(x, k)
    within = sum(((x[labels == i] - x[labels == i].mean(axis=0)) ** 2).sum() for i in np.unique(labels))
    return float(np.log(max(within, 1e-12)))


def gap_statistic(points: DataFrame, k_max: int = 8, *, n_ref: int = 10, seed: int = 42, max_site_rows: int = MAX_SITE_ROWS) -> DataFrame:
    """(site, k, log_w, gap, se, chosen); a site over ``max_site_rows`` is refused, as in ``local_cluster``."""
    spark = points.sparkSession
    points = clean_points(points)
    d = dimension(points)
    box = [f(F.element_at("features", i + 1)) for f in (F.min, F.max) for i in range(d)]
    boxes = materialise(points.groupBy("site").agg(F.count("*").alias("n"), F.array(*box[:d]).alias("low"), F.array(*box[d:]).alias("high")))
    largest = boxes.agg(F.max("n")).first()[0] or 0
    if largest > max_site_rows:
        raise ValueError(f"a site has {largest} points, one task may hold {max_site_rows}; give k_local a number")

    def own(site: pd.DataFrame) -> pd.DataFrame:
        x = np.stack(site.sort_values("point_id", kind="stable")["features"].to_list())
        return pd.DataFrame([(site["site"].iloc[0], k, 0, _log_within(x, k)) for k in range(1, k_max + 1)], columns=["site", "k", "replicate", "log_w"])

    def drawn(batches):
        for batch in batches:
            out = []
            for site, n, low, high, k, replicate in batch.itertuples(index=False):
                x = np.random.default_rng([seed, abs(int(site)), int(k), int(replicate)]).uniform(low, high, (int(n), len(low)))
                out.append((site, k, replicate, _log_within(x, int(k))))
            yield pd.DataFrame(out, columns=["site", "k", "replicate", "log_w"])

    schema = "site int, k int, replicate int, log_w double"
    numbers = lambda name, n: F.explode(F.sequence(F.lit(1), F.lit(n))).alias(name)
    tasks = boxes.select("*", numbers("k", k_max)).select("*", numbers("replicate", n_ref)).repartition("site", "k", "replicate")
    each = points.select("site", "point_id", "features").groupBy("site").applyInPandas(own, schema).union(tasks.select("site", "n", "low", "high", "k", "replicate").mapInPandas(drawn, schema))
    refs = F.when(F.col("replicate") > 0, F.col("log_w"))
    rows = each.groupBy("site", "k").agg(F.max(F.when(F.col("replicate") == 0, F.col("log_w"))).alias("log_w"), F.avg(refs).alias("ref"), F.stddev_pop(refs).alias("sd"))
    gaps = rows.select("site", "k", "log_w", (F.col("ref") - F.col("log_w")).alias("gap"), (F.col("sd") * (1 + 1 / n_ref) ** 0.5).alias("se"))
    by = Window.partitionBy("site").orderBy("k")
    good = F.col("gap") >= F.lead("gap").over(by) - F.lead("se").over(by)
    marked = gaps.withColumn("good", F.coalesce(good, F.lit(True)))
    first = F.min(F.when(F.col("good"), F.col("k"))).over(Window.partitionBy("site"))
    return marked.withColumn("chosen", F.col("k") == first).drop("good")


def chosen_k(gaps: DataFrame) -> dict[int, int]:
    """{site: k}; a row per site comes to the driver."""
    return {r.site: r.k for r in gaps.where("chosen").select("site", "k").collect()}
