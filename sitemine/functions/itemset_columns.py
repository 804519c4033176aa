"""Column expressions on sorted item arrays, and their SQL registrations."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import udtf


def drop_one(items: Column) -> Column:
    """All subsets one item smaller."""
    return F.transform(F.sequence(F.lit(1), F.size(items)), lambda i: F.concat(F.slice(items, F.lit(1), i - 1), F.slice(items, i + 1, F.size(items))))


def subsets(items: Column, z: int) -> Column:
    """All z-subsets of a sorted array of distinct items, each sorted."""
    out = F.transform(items, lambda x: F.array(x))
    for _ in range(z - 1):
        out = F.flatten(F.transform(out, lambda s: F.transform(F.filter(items, lambda x: x > F.element_at(s, -1)), lambda x: F.concat(s, F.array(x)))))
    return out


def all_subsets(items: Column, k: int) -> Column:
    """All non-empty subsets of up to k items."""
    return F.flatten(F.array(*[subsets(items, z) for z in range(1, k + 1)]))


def contains(items: Column, itemset: Column) -> Column:
    """Whether every item of ``itemset`` is in ``items``."""
    return F.size(F.array_intersect(items, itemset)) == F.size(itemset)


@udtf(returnType=T.StructType([T.StructField("itemset", T.ArrayType(T.IntegerType()))]))
class ItemsetSubsets:
    """itemset_subsets(items, z): a row for each z-subset, for lateral joins in SQL."""

    def eval(self, items: list[int], z: int) -> Iterator[tuple[list[int]]]:
        for chosen in combinations(sorted(set(items or [])), z):
            yield (list(chosen),)


def register(spark: SparkSession) -> None:
    """SQL names: itemset_subsets (table function) and drop_one (a SQL function of the session)."""
    spark.udtf.register("itemset_subsets", ItemsetSubsets)
    spark.sql(
        "create or replace temporary function drop_one(items array<int>) returns array<array<int>> return "
        "transform(sequence(1, size(items)), i -> concat(slice(items, 1, i - 1), slice(items, i + 1, size(items))))"
    )
