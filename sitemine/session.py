"""Work with the session as given: checkpoints, size-checked broadcasts, table paths.

Nothing here starts or reconfigures a session.  Lineage is cut with reliable
checkpoints in the folder named by ``spark.checkpoint.dir``; a private folder is used
only where that setting is absent (tests on one machine).
"""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Rows of a narrow table (ids, hashes, counts) that one broadcast may hold.
BROADCAST_ROWS = 500_000
#: Rows that one task may rank.
RANK_ROWS = 1_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The parquet table ``name`` below ``sf_dir`` (any path Spark can read)."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        shared = context.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
        context.setCheckpointDir(shared or tempfile.mkdtemp(prefix="sitemine-checkpoints-"))


def materialise(df: DataFrame) -> DataFrame:
    """``df`` computed once and kept in the shared checkpoint folder."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def broadcast_if_small(df: DataFrame, max_rows: int = BROADCAST_ROWS) -> DataFrame:
    """Hint a broadcast of ``df`` only when it is seen to hold at most ``max_rows`` rows.

    The count stops at the limit.  Beyond it no hint is given and the join is a
    shuffled one, which adaptive execution splits where a key is hot.
    """
    if df.limit(max_rows + 1).count() <= max_rows:
        return F.broadcast(df)
    return df


def numbered(df: DataFrame, order: list[Column], name: str, few: int = RANK_ROWS) -> DataFrame:
    """``df`` with its rows numbered from 0 in ``order`` as long ``name``.

    Up to ``few`` rows are ranked in one task; more are sorted by ranges, and a row's number
    is its place in its range after all the ranges before it.
    """
    if df.limit(few + 1).count() <= few:
        return df.withColumn(name, (F.row_number().over(Window.orderBy(*order)) - 1).cast("long"))
    placed = materialise(df.orderBy(*order).withColumn(name, F.monotonically_increasing_id()))
    part = F.shiftright(F.col(name), 33)
    sizes = placed.groupBy(part.alias("range_no")).agg(F.count("*").alias("rows")).orderBy("range_no").collect()  # a row a range
    starts, before = [], 0
    for r in sizes:
        starts.append((r.range_no, before))
        before += r.rows
    start = df.sparkSession.createDataFrame(starts, "range_no long, before_it long")
    within = F.col(name).bitwiseAND(F.lit((1 << 33) - 1))
    return placed.withColumn("range_no", part).join(F.broadcast(start), "range_no").withColumn(name, F.col("before_it") + within).drop("range_no", "before_it")


def shared_table(df: DataFrame) -> tuple[DataFrame, str]:
    """``df`` written as parquet below the shared checkpoint folder and read again, with its path."""
    spark = df.sparkSession
    ensure_checkpoint_dir(spark)
    path = f"{spark.sparkContext.getCheckpointDir()}/tables/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), path


def drop_shared(spark: SparkSession, path: str) -> None:
    """Remove a table that ``shared_table`` wrote and nothing reads any more."""
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def ship_code(spark: SparkSession) -> None:
    """Send this package to the Python workers, once a context.

    Nothing is sent where PYTHONPATH names the package's folder: workers then find it.
    """
    root = Path(__file__).resolve().parent.parent
    if str(root) in os.environ.get("PYTHONPATH", "").split(os.pathsep):
        return
    context = spark.sparkContext
    if getattr(context, "_sitemine_shipped", False):
        return
    target = Path(tempfile.mkdtemp(prefix="sitemine-code-")) / "sitemine.zip"
    with zipfile.ZipFile(target, "w") as out:
        for path in sorted((root / "sitemine").rglob("*.py")):
            out.write(path, path.relative_to(root))
    context.addPyFile(str(target))
    context._sitemine_shipped = True
