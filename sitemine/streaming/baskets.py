"""Streams of events as baskets, windowed support, incremental summaries and labels.

State holds windows, counts and summaries, never points.  Rows later than the watermark
are dropped by Spark and counted in the query's progress.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from sitemine.functions.merge_columns import merge_np
from sitemine.sources.files import TABLES

WATERMARK = "1 hour"


def event_stream(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """A file stream over a folder of event files."""
    return spark.readStream.schema(TABLES["events"]).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def deduplicated(events: DataFrame, delay: str = WATERMARK) -> DataFrame:
    """Replayed rows (same event_id) go while the watermark remembers them."""
    if not events.isStreaming:
        return events.dropDuplicates(["event_id"])
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def item_of(events: DataFrame) -> DataFrame:
    """Events with an item column: the type, + or - for values over 20 or not, and props' k."""
    sign = F.when(F.col("value") > 20, "+").otherwise("-")
    return events.withColumns({"item": F.concat("event_type", sign), "k": F.from_json("props", "k int")["k"]})


def _marked(events: DataFrame, delay: str) -> DataFrame:
    return item_of(events).withWatermark("ts", delay) if events.isStreaming else item_of(events)


def stream_baskets(events: DataFrame, length: str = "1 day", slide: str | None = None, delay: str = WATERMARK) -> DataFrame:
    """(start, user_id, items): a basket for each user and tumbling or sliding window."""
    window = F.window("ts", length, slide) if slide else F.window("ts", length)
    grouped = _marked(events, delay).groupBy(window.alias("w"), "user_id").agg(F.array_sort(F.collect_set("item")).alias("items"))
    return grouped.select(F.col("w.start").alias("start"), "user_id", "items")


def session_baskets(events: DataFrame, gap: str = "2 hours", delay: str = WATERMARK) -> DataFrame:
    """(start, end, user_id, items, n): a basket for each user's burst of events."""
    grouped = _marked(events, delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.array_sort(F.collect_set("item")).alias("items"), F.count("*").alias("n"))
    return grouped.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "items", "n")


def stream_support(events: DataFrame, length: str = "1 day", slide: str | None = None, delay: str = WATERMARK) -> DataFrame:
    """(start, item, support): events of each item in each window."""
    window = F.window("ts", length, slide) if slide else F.window("ts", length)
    grouped = _marked(events, delay).groupBy(window.alias("w"), "item").agg(F.count("*").alias("support"))
    return grouped.select(F.col("w.start").alias("start"), "item", "support")


SUMMARY = "site int, local_id int, n long, center array<double>, scatter double"


def stream_substats(labelled: DataFrame) -> DataFrame:
    """Running (site, local_id, n, center, scatter) of a stream of labelled points.

    State is one summary per sub-cluster; each batch's points are summarised and merged in.
    """

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        total = None
        if state.exists:
            n, center, scatter = state.get
            total = (n, np.asarray(center), scatter)
        for batch in batches:
            x = np.stack(batch["features"].to_list())
            new = (len(x), x.mean(axis=0), float(((x - x.mean(axis=0)) ** 2).sum()))
            total = new if total is None else merge_np(total, new)
        if total is not None:
            state.update((int(total[0]), [float(v) for v in total[1]], float(total[2])))
            yield pd.DataFrame({"site": [key[0]], "local_id": [key[1]], "n": [int(total[0])], "center": [list(total[1])], "scatter": [float(total[2])]})

    return labelled.groupBy("site", "local_id").applyInPandasWithState(update, SUMMARY, "n long, center array<double>, scatter double", "update", GroupStateTimeout.NoTimeout)


def latest_summaries(updates: DataFrame) -> DataFrame:
    """The last row of each sub-cluster from an update-mode sink: sizes only grow."""
    best = updates.groupBy("site", "local_id").agg(F.max_by(F.struct("n", "center", "scatter"), "n").alias("s"))
    return best.select("site", "local_id", "s.*")


def remerge_on_batch(merge: Callable[[DataFrame], DataFrame], sink: Callable[[DataFrame, int], None]) -> Callable[[DataFrame, int], None]:
    """A ``foreachBatch`` function: each batch's summaries merged into a new global clustering."""

    def run(batch: DataFrame, batch_id: int) -> None:
        if not batch.isEmpty():
            sink(merge(batch), batch_id)

    return run


def label_stream(points: DataFrame, centers: DataFrame, labels: DataFrame) -> DataFrame:
    """A stream of points joined to the current labelling: nearest local centre, then its global id."""
    from sitemine.operators.clustering.local import assign

    return assign(points, centers).join(F.broadcast(labels), ["site", "local_id"])


def late_rows(query: StreamingQuery) -> int:
    """Rows that a finished or running query has dropped for being behind the watermark."""
    return sum(int(op.numRowsDroppedByWatermark) for progress in query.recentProgress for op in progress.stateOperators)


def as_of_version(points: DataFrame, versions: DataFrame) -> DataFrame:
    """``points`` (ts, ...) with the latest version (from_ts, version) at or before their time, null before the first.

    Versions are one each time summaries were merged again; their spans are looked up by a
    binary search over a sorted array.
    """
    gathered = versions.groupBy().agg(F.array_sort(F.collect_list(F.struct("from_ts", "version"))).alias("all"))
    steps = F.sequence(F.lit(1), F.ceil(F.log2(F.size("all") + 1)).cast("int") + 1)
    # (lo, hi): versions before lo are early enough, versions from hi on are too late
    found = F.aggregate(
        steps,
        F.struct(F.lit(0).alias("lo"), F.size("all").alias("hi")),
        lambda span, _: F.when(
            span["lo"] < span["hi"],
            F.when(
                F.get("all", F.floor((span["lo"] + span["hi"]) / 2).cast("int"))["from_ts"] <= F.col("ts"),
                F.struct((F.floor((span["lo"] + span["hi"]) / 2) + 1).cast("int").alias("lo"), span["hi"].alias("hi")),
            ).otherwise(F.struct(span["lo"].alias("lo"), F.floor((span["lo"] + span["hi"]) / 2).cast("int").alias("hi"))),
        ).otherwise(span),
    )
    return points.crossJoin(F.broadcast(gathered)).withColumn("version", F.get("all", found["lo"] - 1)["version"]).drop("all")
