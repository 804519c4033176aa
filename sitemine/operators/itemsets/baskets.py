"""Baskets: rows of (site, tid, item) to coded, sorted item arrays, and back to names."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sitemine.schemas import BASKET_ROWS, require_columns
from sitemine.session import broadcast_if_small, materialise, numbered


def as_fraction(share: float | str | Fraction) -> Fraction:
    """A support threshold without binary rounding: 0.1 means one tenth."""
    return share if isinstance(share, Fraction) else Fraction(str(share))


def least_of(n: int, share: float | str | Fraction) -> int:
    """The smallest count that is at least ``share`` of ``n`` (at least 1), exactly."""
    f = as_fraction(share)
    return max(1, -(-n * f.numerator // f.denominator))


def min_count(n: Column, share: float | str | Fraction) -> Column:
    """The smallest count that is at least ``share`` of ``n`` (at least 1), in integers."""
    f = as_fraction(share)
    return F.greatest(F.lit(1).cast("long"), F.floor((n * F.lit(f.numerator) + F.lit(f.denominator - 1)) / F.lit(f.denominator)).cast("long"))


def item_codes(rows: DataFrame) -> DataFrame:
    """(item, code): dense codes from 0, rarer items first, by name among equals."""
    counts = materialise(rows.groupBy("item").agg(F.count("*").alias("rows")))
    return numbered(counts, [F.col("rows"), F.col("item")], "code").select("item", F.col("code").cast("int").alias("code"))


def item_dictionary(baskets: DataFrame, codes: DataFrame) -> DataFrame:
    """(item, code, support): in how many baskets each item is."""
    counts = baskets.select(F.explode("items").alias("code")).groupBy("code").agg(F.count("*").alias("support"))
    return codes.join(counts, "code").select("item", "code", "support")


def from_rows(rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(baskets, codes): null items are dropped, repeated items count once.

    Item names are replaced by codes before the one exchange by (site, tid).
    """
    require_columns(rows, BASKET_ROWS)
    clean = rows.where(F.col("item").isNotNull()).select(F.col("site").cast("int").alias("site"), F.col("tid").cast("long").alias("tid"), F.col("item").cast("string").alias("item"))
    codes = materialise(item_codes(clean))
    coded = clean.join(broadcast_if_small(codes), "item").select("site", "tid", "code")
    return coded.groupBy("site", "tid").agg(F.array_sort(F.collect_set("code")).alias("items")), codes


def named(itemsets: DataFrame, dictionary: DataFrame, column: str = "itemset") -> DataFrame:
    """``itemsets`` with ``column`` as text: item names in order, joined by ``|``."""
    codes = itemsets.select(column).distinct()
    names = (
        codes.select(F.col(column).alias("key"), F.explode(column).alias("code"))
        .join(broadcast_if_small(dictionary.select("item", "code")), "code")
        .groupBy("key")
        .agg(F.array_join(F.array_sort(F.collect_list("item")), "|").alias("text"))
    )
    return itemsets.join(names, F.col(column) == F.col("key")).drop("key", column).withColumnRenamed("text", column)
