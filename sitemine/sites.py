"""Site keys: which site holds a row.  A site is a logical key, never a DataFrame of its own."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sitemine.session import table


def by_hash(key: Column, sites: int) -> Column:
    """``key`` modulo ``sites``; the same in any SQL engine for non-negative keys."""
    return F.pmod(key, F.lit(sites)).cast("int")


def by_chunk(key: Column, rows: int) -> Column:
    """Sites of about ``rows`` consecutive keys each."""
    return F.floor(key / rows).cast("int")


def by_value(df: DataFrame, column: str, site: str = "site") -> DataFrame:
    """A site for each value of ``column``, numbered in its order, null (if any) last; sites are few."""
    names = df.select(F.col(column).alias("of_site")).distinct()
    ranked = names.withColumn(site, (F.row_number().over(Window.orderBy(F.asc_nulls_last("of_site"))) - 1).cast("int"))
    return df.join(F.broadcast(ranked), F.col(column).eqNullSafe(F.col("of_site"))).drop("of_site")


def order_region(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(o_orderkey, site): the region of the order's customer."""
    nation = table(spark, sf_dir, "nation").select("n_nationkey", F.col("n_regionkey").cast("int").alias("site"))
    customer = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return orders.join(customer.select("c_custkey", "site"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "site")
