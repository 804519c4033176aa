"""What a site asks the others to count: its frontier of locally frequent sets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sitemine.functions.itemset_columns import all_subsets, drop_one
from sitemine.operators.itemsets.rules import maximal

KINDS = ("maximal", "size_k", "all", "bottom_up")


def first_frontier(local: DataFrame, kind: str, k: int) -> DataFrame:
    """(site, itemset) asked in the first pass.

    ``maximal``: sets without a frequent superset one larger at their site (complete).
    ``size_k``: sets of size k only; loses what lies under no such set.
    ``all``: every locally frequent set at once.  ``bottom_up``: single items first.
    """
    if kind == "maximal":
        return maximal(local, by=["site"]).select("site", "itemset")
    if kind == "size_k":
        return local.where(F.size("itemset") == k).select("site", "itemset")
    if kind == "all":
        return local.select("site", "itemset")
    if kind == "bottom_up":
        return local.where(F.size("itemset") == 1).select("site", "itemset")
    raise ValueError(f"frontier must be one of {', '.join(KINDS)}")


def requests(frontier: DataFrame) -> DataFrame:
    """(itemset, askers): the frontier's distinct sets, each with the sites that ask."""
    return frontier.groupBy("itemset").agg(F.array_sort(F.collect_set("site")).alias("askers"))


def close_down(passed: DataFrame, k: int) -> DataFrame:
    """(itemset): every non-empty subset of the sets that passed, themselves included."""
    return passed.select(F.explode(all_subsets(F.col("itemset"), k)).alias("itemset")).distinct()


def descend(frontier: DataFrame, failed: DataFrame, closed: DataFrame, asked: DataFrame) -> DataFrame:
    """(site, itemset): the next frontier, from the drop-one subsets of each site's failures.

    Subsets of passed sets need no request, and none is asked twice.
    """
    own = frontier.join(failed.select("itemset"), "itemset", "left_semi").where(F.size("itemset") > 1)
    below = own.select("site", F.explode(drop_one(F.col("itemset"))).alias("itemset")).distinct()
    return below.join(closed, "itemset", "left_anti").join(asked.select("itemset"), "itemset", "left_anti")
