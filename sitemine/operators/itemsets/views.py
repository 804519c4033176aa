"""Mining between views: a table function cannot start jobs, so the session's helper does."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from sitemine.operators.itemsets import baskets as B
from sitemine.operators.itemsets.latesync import MineResult, latesync_mine


def mine_view(spark: SparkSession, source: str, target: str, *, k: int, min_support: float | str | Fraction, **options) -> MineResult:
    """Mine the view ``source`` (site, tid, item) into the view ``target`` (itemset text, size, support)."""
    baskets, dictionary = B.from_rows(spark.table(source))
    mined = latesync_mine(baskets, k=k, min_support=min_support, **options)
    named = B.named(mined.itemsets.select("itemset", F.col("size").cast("long").alias("size"), "support"), dictionary)
    named.select("itemset", "size", "support").createOrReplaceTempView(target)
    return mined
