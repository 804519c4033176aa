"""Files in and out: baskets in common formats, site-partitioned tables, results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

_LONG_ROWS = "site int, tid bigint, item string"

#: Schemas of the given tables, so that no read infers one.
TABLES = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double,"
    " l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp",
    "events": "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "pages": "page_id bigint, url string, html string",
    "benchmark": "item_id bigint, text string",
    "labels": "doc_id bigint, quality int, toxic int",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table with its fixed schema."""
    return spark.read.schema(TABLES[name]).parquet(f"{sf_dir}/{name}.parquet")


def read_baskets(spark: SparkSession, path: str, fmt: str, *, sep: str = " ", n_sites: int = 1) -> DataFrame:
    """(site, tid, item) from a file or folder.

    ``text``: a line is a transaction, its items split at runs of the characters of ``sep``;
    the numbers of transactions are unique, and depend on how files are split into tasks.
    ``csv``, ``json``, ``orc``, ``parquet``: rows of (site, tid, item).
    """
    if fmt != "text":
        reader = spark.read.schema(_LONG_ROWS)
        return (reader.option("header", True) if fmt == "csv" else reader).format(fmt).load(path).select("site", "tid", "item")
    lines = spark.read.text(path).select("value", F.monotonically_increasing_id().alias("tid"))
    items = F.filter(F.split("value", "[" + "".join(f"\\x{{{ord(c):x}}}" for c in sep) + "]+"), lambda x: x != "")
    return lines.select(F.pmod("tid", F.lit(n_sites)).cast("int").alias("site"), "tid", F.explode(F.array_distinct(items)).alias("item"))


def write_sites(df: DataFrame, path: str) -> None:
    """``df`` in a directory per site; reading one site opens no other."""
    df.repartition("site").write.mode("overwrite").partitionBy("site").parquet(path)


def read_site(spark: SparkSession, path: str, site: int | None = None) -> DataFrame:
    df = spark.read.parquet(path)
    return df if site is None else df.where(F.col("site") == site)


def save(df: DataFrame, *, path: str | None = None, json_path: str | None = None, view: str | None = None, by: str | None = None) -> None:
    """A result to parquet (replacing only the partitions it holds), JSON lines, or a view."""
    if path:
        writer = df.write.mode("overwrite")
        (writer.partitionBy(by).option("partitionOverwriteMode", "dynamic") if by else writer).parquet(path)
    if json_path:
        df.write.mode("overwrite").json(json_path)
    if view:
        df.createOrReplaceTempView(view)


EVENT = T.StructType(
    [
        T.StructField("Event", T.StringType()),
        T.StructField("Timestamp", T.LongType()),
        T.StructField("Stage ID", T.LongType()),
        T.StructField("Stage IDs", T.ArrayType(T.LongType())),
        T.StructField("Submission Time", T.LongType()),
        T.StructField("Properties", T.MapType(T.StringType(), T.StringType())),
        T.StructField(
            "Task Info",
            T.StructType([T.StructField("Index", T.IntegerType()), T.StructField("Launch Time", T.LongType()), T.StructField("Finish Time", T.LongType())]),
        ),
    ]
)


def read_event_log(spark: SparkSession, path: str, run: str = "run") -> DataFrame:
    """(run, stage, process, seconds): task times of an uncompressed event log; stage is the job group and stage id."""
    events = spark.read.schema(EVENT).json(path)
    jobs = events.where("Event = 'SparkListenerJobStart'").select(F.explode("Stage IDs").alias("id"), F.col("Properties")["spark.jobGroup.id"].alias("group"))
    names = jobs.groupBy("id").agg(F.max("group").alias("group"))
    tasks = events.where("Event = 'SparkListenerTaskEnd'").select(
        F.col("Stage ID").alias("id"), F.col("Task Info.Index").alias("process"), ((F.col("Task Info.Finish Time") - F.col("Task Info.Launch Time")) / 1000).alias("seconds")
    )
    stage = F.concat_ws(":", F.coalesce("group", F.lit("-")), F.col("id").cast("string"))
    return tasks.join(F.broadcast(names), "id", "left").select(F.lit(run).alias("run"), stage.alias("stage"), "process", "seconds")


def first_task_latency(spark: SparkSession, path: str) -> float:
    """Seconds from the application's start to its first task (the preparation latency)."""
    events = spark.read.schema(EVENT).json(path)
    row = events.agg(
        F.min(F.when(F.col("Event") == "SparkListenerApplicationStart", F.col("Timestamp"))).alias("start"), F.min("Task Info.Launch Time").alias("task")
    ).first()
    return (row.task - row.start) / 1000
