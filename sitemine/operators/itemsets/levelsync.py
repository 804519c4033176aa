"""The level-sync baseline: one exchange of counts for every itemset size.

At each size a site makes candidates from the sets that are frequent both globally and at
the site, keeps those frequent at the site, and asks for their global counts; the global
decision is announced before the next size starts.  Options: ``upper`` also drops a
candidate when the sum over sites of its smallest drop-one count cannot reach the global
minimum; ``polling`` says who gathers an itemset's counts, which changes messages only.
"""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sitemine.functions.itemset_columns import drop_one
from sitemine.operators.itemsets.latesync import Clock, MineResult, global_minimum, remote_support, split_global
from sitemine.operators.itemsets.local import local_apriori
from sitemine.operators.itemsets.support import count_support
from sitemine.session import drop_shared, materialise, shared_table


def upper_bound(candidates: DataFrame, counts: DataFrame) -> DataFrame:
    """(itemset, bound): the sum over sites of the smallest count among drop-one subsets.

    ``counts`` has (site, itemset, cnt) of every set one smaller at every site.
    """
    parts = candidates.select("itemset").distinct().select("itemset", F.explode(drop_one(F.col("itemset"))).alias("part"))
    at_site = parts.join(counts.withColumnRenamed("itemset", "part"), "part").groupBy("itemset", "site").agg(F.min("cnt").alias("low"), F.count("*").alias("parts"))
    # a site that lacks one of the subsets holds none of the set
    return at_site.where(F.col("parts") == F.size("itemset")).groupBy("itemset").agg(F.sum("low").alias("bound"))


def levelsync_mine(
    baskets: DataFrame, *, min_support: float | str | Fraction, k: int | None = 4, pruning: tuple[str, ...] = ("local",), known_counts: bool = True, engine: str = "auto"
) -> MineResult:
    """Globally frequent itemsets of sizes 1 to k (``None``: until a size is empty)."""
    spark = baskets.sparkSession
    clock = Clock(spark, "levelsync")
    with clock.part("prepare"):
        baskets, path = shared_table(baskets)
    try:
        return _level(baskets, clock, min_support, k, pruning, known_counts, engine)
    finally:
        drop_shared(spark, path)


def _level(baskets: DataFrame, clock: Clock, min_support, k, pruning, known_counts, engine) -> MineResult:
    spark = baskets.sparkSession
    n, n_sites = baskets.agg(F.count("*"), F.count_distinct("site")).first()
    least = global_minimum(n, min_support)
    state: dict = {"passes": [], "found": spark.createDataFrame([], "itemset array<int>, support long"), "log": spark.createDataFrame([], "pass int, site int, itemset array<int>"), "pruned": 0}

    def settle(level: DataFrame, z: int) -> DataFrame:
        if "upper" in pruning and z > 1:
            bounds = upper_bound(level, state["by_site"])
            kept = materialise(level.join(bounds.where(F.col("bound") >= least), "itemset", "left_semi").select("site", "itemset", "cnt"))
            state["pruned"] += level.select("itemset").distinct().count()
            level = kept
        now = materialise(level.select("itemset").distinct())
        asked = now.count()
        if "upper" in pruning and z > 1:
            state["pruned"] -= asked
        if not asked:
            return level
        with clock.part("remote"):
            counts = remote_support(baskets, now, level, n_sites, [z], known_counts=known_counts, engine=engine)
        good, _ = split_global(counts, least)
        if "upper" in pruning:
            state["by_site"] = materialise(count_support(baskets, good.select("itemset"), [z], engine=engine))
        state["log"] = state["log"].union(level.select(F.lit(z).alias("pass"), "site", "itemset"))
        state["found"] = state["found"].union(good)
        passed = good.count()
        state["passes"].append({"pass": z, "kind": "level", "requested": asked, "passed": passed, "failed": asked - passed})
        return materialise(level.join(good.select("itemset"), "itemset", "left_semi").select("site", "itemset", "cnt"))

    with clock.part("all"):
        local = local_apriori(baskets, k, min_support, engine=engine, keep=settle)
    clock.seconds["local"] = clock.seconds.pop("all") - clock.seconds.get("remote", 0.0)
    found = materialise(state["found"].select("itemset", F.size("itemset").alias("size"), "support"))
    counters = {
        "baskets": n, "sites": n_sites, "minimum": least, "passes": len(state["passes"]), "requested": sum(p["requested"] for p in state["passes"]), "upper_pruned": state["pruned"],
        "seconds": clock.seconds, "groups": clock.groups | {"local": f"{clock.prefix}:all"},
    }
    return MineResult(found, materialise(local), materialise(state["log"]), state["passes"], counters)
