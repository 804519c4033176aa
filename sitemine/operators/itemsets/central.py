"""Central references: all baskets as one site, by Apriori and by Spark's FP-growth."""

from __future__ import annotations

from fractions import Fraction

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sitemine.operators.itemsets.latesync import global_minimum
from sitemine.operators.itemsets.local import local_apriori


def central_apriori(baskets: DataFrame, k: int | None, share: float | str | Fraction, *, engine: str = "auto") -> DataFrame:
    """(itemset, size, support) over all baskets."""
    # the miner runs per site; with all baskets in one, (site, tid) need not stay unique
    one = baskets.select(F.lit(0).alias("site"), "tid", "items")
    return local_apriori(one, k, share, engine=engine).select("itemset", "size", F.col("cnt").alias("support"))


def central_fpgrowth(baskets: DataFrame, k: int | None, share: float | str | Fraction) -> DataFrame:
    """(itemset, size, support) by FP-growth; sets over k items are left out afterwards."""
    n = baskets.count()
    least = global_minimum(n, share)
    # a hair below the exact ratio, so that rounding cannot raise the count asked for
    model = FPGrowth(itemsCol="items", minSupport=(least - 0.5) / max(1, n), minConfidence=1.0).fit(baskets.select("items"))
    found = model.freqItemsets.select(F.array_sort("items").alias("itemset"), F.col("freq").alias("support")).where(F.col("support") >= least)
    found = found if k is None else found.where(F.size("itemset") <= k)
    return found.select("itemset", F.size("itemset").alias("size"), "support")
