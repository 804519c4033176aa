"""Basket and point inputs from the given tables; each basket input has an SQL twin."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sitemine import sites
from sitemine.session import table

SITES = 5


def brand_rows(spark: SparkSession, sf_dir: str, site: Column | None = None) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    parts = table(spark, sf_dir, "part").select("p_partkey", "p_brand")
    rows = lines.join(parts, F.col("l_partkey") == F.col("p_partkey"))
    return rows.select((site if site is not None else sites.by_hash(F.col("l_orderkey"), SITES)).alias("site"), F.col("l_orderkey").alias("tid"), F.col("p_brand").alias("item"))


def brand_rows_by_region(spark: SparkSession, sf_dir: str) -> DataFrame:
    return brand_rows(spark, sf_dir).drop("site").join(sites.order_region(spark, sf_dir), F.col("tid") == F.col("o_orderkey")).select("site", "tid", "item")


def attribute_rows(spark: SparkSession, sf_dir: str, n_sites: int = SITES) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_returnflag", "l_linestatus")
    parts = table(spark, sf_dir, "part").select("p_partkey", "p_type")
    both = lines.join(parts, F.col("l_partkey") == F.col("p_partkey"))
    items = F.array(F.concat(F.lit("t="), "p_type"), F.concat(F.lit("f="), "l_returnflag", "l_linestatus"))
    return both.select(sites.by_hash(F.col("l_orderkey"), n_sites).alias("site"), F.col("l_orderkey").alias("tid"), F.explode(items).alias("item"))


def word_rows(spark: SparkSession, sf_dir: str, site: str = "hash") -> DataFrame:
    """Every word of every document."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    docs = docs.withColumn("site", sites.by_hash(F.col("doc_id"), SITES)) if site == "hash" else sites.by_value(docs, site)
    words = F.array_distinct(F.expr("regexp_extract_all(lower(text), '[a-z]+', 0)"))
    return docs.select("site", F.col("doc_id").alias("tid"), F.explode(words).alias("item"))


def user_day_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = table(spark, sf_dir, "events").select("user_id", "ts", "event_type", "value")
    item = F.concat("event_type", F.when(F.col("value") > 20, "+").otherwise("-"))
    return events.select(sites.by_hash(F.col("user_id"), SITES).alias("site"), (F.col("user_id") * 100_000 + F.unix_date(F.to_date("ts"))).alias("tid"), item.alias("item"))


def tag_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "html")
    tags = F.expr("regexp_extract_all(lower(html), '<([a-z][a-z0-9]*)', 1)")
    return pages.select(sites.by_hash(F.col("page_id"), SITES).alias("site"), F.col("page_id").alias("tid"), F.explode(F.array_distinct(tags)).alias("item"))


def chat_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    chats = table(spark, sf_dir, "conversations").select("conv_id", "text")
    words = F.expr("regexp_extract_all(lower(text), '[a-z]+', 0)")
    return chats.select(sites.by_hash(F.col("conv_id"), SITES).alias("site"), F.col("conv_id").alias("tid"), F.explode(F.array_distinct(words)).alias("item")).distinct()


def benchmark_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = table(spark, sf_dir, "benchmark").select("item_id", "text")
    words = F.expr("regexp_extract_all(lower(text), '[a-z]+', 0)")
    return items.select(sites.by_hash(F.col("item_id"), SITES).alias("site"), F.col("item_id").alias("tid"), F.explode(F.array_distinct(words)).alias("item"))


def class_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labelled documents: their class, language and source as items."""
    labels = table(spark, sf_dir, "labels").select("doc_id", "quality", "toxic")
    docs = table(spark, sf_dir, "documents").select("doc_id", "lang", "source")
    items = F.array(*[F.concat(F.lit(f"{c}="), F.col(c).cast("string")) for c in ("quality", "toxic", "lang", "source")])
    return labels.join(docs, "doc_id").select(sites.by_hash(F.col("doc_id"), SITES).alias("site"), F.col("doc_id").alias("tid"), F.explode(items).alias("item"))


def brand_sql(n_sites: int) -> str:
    return f"select l_orderkey % {n_sites} as site, l_orderkey as tid, p_brand as item from lineitem join part on l_partkey = p_partkey"


BRAND_SQL = brand_sql(SITES)
REGION_SQL = (
    "select n_regionkey as site, l_orderkey as tid, p_brand as item from lineitem join part on l_partkey = p_partkey join orders on o_orderkey = l_orderkey"
    " join customer on c_custkey = o_custkey join nation on n_nationkey = c_nationkey"
)
ATTRIBUTE_SQL = (
    "select l_orderkey % 5 as site, l_orderkey as tid, unnest(['t=' || p_type, 'f=' || l_returnflag || l_linestatus]) as item from lineitem join part on l_partkey = p_partkey"
)


def word_sql(site: str) -> str:
    words = "select distinct doc_id, lang, source, unnest(regexp_extract_all(lower(text), '[a-z]+')) as item from documents"
    key = "doc_id % 5" if site == "hash" else f"dense_rank() over (order by {site} nulls last) - 1"
    return f"select {key} as site, doc_id as tid, item from ({words})"


USER_DAY_SQL = (
    "select user_id % 5 as site, user_id * 100000 + date_diff('day', date '1970-01-01', ts::date) as tid, event_type || case when value > 20 then '+' else '-' end as item from events"
)
TAG_SQL = "select distinct page_id % 5 as site, page_id as tid, unnest(regexp_extract_all(lower(html), '<([a-z][a-z0-9]*)', 1)) as item from pages"
CHAT_SQL = "select distinct conv_id % 5 as site, conv_id as tid, unnest(regexp_extract_all(lower(text), '[a-z]+')) as item from conversations"
BENCHMARK_SQL = "select distinct item_id % 5 as site, item_id as tid, unnest(regexp_extract_all(lower(text), '[a-z]+')) as item from benchmark"
CLASS_SQL = (
    "select doc_id % 5 as site, doc_id as tid, unnest(['quality=' || quality, 'toxic=' || toxic, 'lang=' || lang, 'source=' || source]) as item"
    " from labels join documents using (doc_id)"
)


def z_scored(df: DataFrame, columns: list[str]) -> DataFrame:
    """``df`` with each column centred and scaled by the whole table's deviation."""
    aggs = [f(c).alias(f"{c}__{n}") for c in columns for n, f in (("m", F.avg), ("s", F.stddev_pop))]
    stats = df.agg(*aggs)
    scaled = {c: F.when(F.col(f"{c}__s") > 0, (F.col(c) - F.col(f"{c}__m")) / F.col(f"{c}__s")).otherwise(F.lit(0.0)) for c in columns}
    return df.crossJoin(F.broadcast(stats)).withColumns(scaled).select(*df.columns)


LINE_COLUMNS = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]


def line_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order lines as 4-dimensional points; lines of an order are numbered within it."""
    lines = table(spark, sf_dir, "lineitem")
    order = Window.partitionBy("l_orderkey").orderBy("l_linenumber", *[c for c in lines.columns if c not in ("l_orderkey", "l_linenumber")])
    numbered = lines.select("l_orderkey", *LINE_COLUMNS, F.row_number().over(order).alias("line"))
    scaled = z_scored(numbered, LINE_COLUMNS)
    return scaled.select(
        sites.by_hash(F.col("l_orderkey"), SITES).alias("site"), (F.col("l_orderkey") * 1000 + F.col("line")).alias("point_id"), F.array(*LINE_COLUMNS).alias("features")
    )


def part_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    scaled = z_scored(table(spark, sf_dir, "part").select("p_partkey", F.col("p_size").cast("double").alias("p_size"), "p_retailprice"), ["p_size", "p_retailprice"])
    return scaled.select(sites.by_hash(F.col("p_partkey"), SITES).alias("site"), F.col("p_partkey").alias("point_id"), F.array("p_size", "p_retailprice").alias("features"))


def customer_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "customer").select("c_custkey", "c_acctbal")
    return rows.select(sites.by_hash(F.col("c_custkey"), SITES).alias("site"), F.col("c_custkey").alias("point_id"), F.array("c_acctbal").alias("features"))


def supplier_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "supplier").select("s_suppkey", "s_acctbal")
    return rows.select(sites.by_hash(F.col("s_suppkey"), SITES).alias("site"), F.col("s_suppkey").alias("point_id"), F.array("s_acctbal").alias("features"))


def embedding_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings").select("vec_id", "embedding", "label")
    return rows.select(sites.by_hash(F.col("vec_id"), SITES).alias("site"), F.col("vec_id").alias("point_id"), F.col("embedding").cast("array<double>").alias("features"), "label")
