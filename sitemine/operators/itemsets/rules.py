"""Views of mined itemsets: maximal and closed sets, association rules, accuracy."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sitemine.functions.itemset_columns import all_subsets, drop_one


def maximal(itemsets: DataFrame, by: list[str] | None = None) -> DataFrame:
    """The sets without a frequent superset; one size up suffices, as all subsets are frequent."""
    by = by or []
    below = itemsets.where(F.size("itemset") > 1).select(*by, F.explode(drop_one(F.col("itemset"))).alias("itemset")).distinct()
    return itemsets.join(below, [*by, "itemset"], "left_anti")


def closed(itemsets: DataFrame) -> DataFrame:
    """The sets without a superset of equal support."""
    above = itemsets.where(F.size("itemset") > 1).select(F.explode(drop_one(F.col("itemset"))).alias("itemset"), "support").distinct()
    return itemsets.join(above, ["itemset", "support"], "left_anti").select(*itemsets.columns)


def association_rules(itemsets: DataFrame, n: int, min_confidence: float) -> DataFrame:
    """(antecedent, consequent, support, confidence, lift) over every split of every set.

    ``n`` is the number of baskets.
    """
    sets = itemsets.select("itemset", "support")
    longest = sets.agg(F.max(F.size("itemset"))).first()[0] or 1
    splits = sets.where(F.size("itemset") > 1).select(
        "support", "itemset", F.explode(all_subsets(F.col("itemset"), max(1, longest - 1))).alias("antecedent")
    )
    splits = splits.where(F.size("antecedent") < F.size("itemset")).withColumn("consequent", F.array_except("itemset", "antecedent"))
    base = sets.select(F.col("itemset").alias("antecedent"), F.col("support").alias("n_antecedent"))
    then = sets.select(F.col("itemset").alias("consequent"), F.col("support").alias("n_consequent"))
    joined = splits.join(base, "antecedent").join(then, "consequent")
    confidence = F.col("support") / F.col("n_antecedent")
    return (
        joined.withColumn("confidence", confidence)
        .where(F.col("confidence") >= min_confidence)
        .select("antecedent", "consequent", "support", "confidence", (F.col("confidence") * n / F.col("n_consequent")).alias("lift"))
    )


def success_by_level(local: DataFrame, global_sets: DataFrame) -> DataFrame:
    """(size, local_sets, global_sets, rate): how many locally frequent sets are so globally."""
    seen = local.select("itemset").distinct().groupBy(F.size("itemset").alias("size")).agg(F.count("*").alias("local_sets"))
    kept = global_sets.groupBy(F.size("itemset").alias("size")).agg(F.count("*").alias("global_sets"))
    both = seen.join(kept, "size", "full")
    filled = [F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("local_sets", "global_sets")]
    return both.select("size", *filled).withColumn("rate", F.when(F.col("local_sets") > 0, F.round(F.col("global_sets") / F.col("local_sets"), 6)))


def set_diff(found: DataFrame, truth: DataFrame) -> DataFrame:
    """(kind, n): shared, missed and surplus (itemset, support) rows, precision and recall with them."""
    a, b = (d.select("itemset", F.col("support").cast("long")).distinct() for d in (found, truth))
    counts = [("shared", a.join(b, ["itemset", "support"], "left_semi")), ("missed", b.join(a, ["itemset", "support"], "left_anti")), ("surplus", a.join(b, ["itemset", "support"], "left_anti"))]
    out = None
    for kind, rows in counts:
        row = rows.agg(F.lit(kind).alias("kind"), F.count("*").alias("n"))
        out = row if out is None else out.union(row)
    return out
