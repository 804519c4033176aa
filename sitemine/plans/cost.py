"""Cost measures: traffic of the miners, transfer times over site links, the stage-max model."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from sitemine.schemas import LINKS, STAGE_TIMES

# Mb/s and ms from each site (row) to each other (column), sites 1 to 5.
_LINKS = {
    1: {2: (16.15, 15), 3: (57.73, 8), 4: (90.77, 5), 5: (17.63, 28)},
    2: {1: (38.97, 15), 3: (26.08, 19), 4: (28.89, 17), 5: (35.74, 14)},
    3: {1: (66.33, 8), 2: (12.71, 19), 4: (44.63, 11), 5: (26.96, 19)},
    4: {1: (106.63, 5), 2: (14.13, 17), 3: (44.54, 11), 5: (30.01, 17)},
    5: {1: (21.45, 28), 2: (17.41, 14), 3: (26.93, 19), 4: (30.14, 17)},
}
# Nodes of each site, GHz, GB.
NODES = ((1, 200, 2.0, 2), (5, 70, 2.0, 2), (3, 64, 2.2, 2), (2, 58, 2.2, 2), (4, 46, 2.2, 2))
# Measured and modelled times of the baseline (clustering in seconds, mining in minutes).
BASELINE = (("clustering", 1050.0, 19.52), ("latesync", 521.0, 424.0), ("levelsync", 687.0, 518.0))


def links(spark: SparkSession) -> DataFrame:
    rows = [(a, b, float(m), float(ms)) for a, to in _LINKS.items() for b, (m, ms) in to.items()]
    return spark.createDataFrame(rows, LINKS)


def nodes(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(NODES), "site int, nodes int, ghz double, mem_gb int")


def transfer_seconds(size: Column, mbit_s: Column, latency_ms: Column) -> Column:
    """Latency plus bits over bandwidth."""
    return latency_ms / 1000 + size * 8 / (mbit_s * 1_000_000)


def register_functions(spark: SparkSession) -> None:
    spark.sql(
        "create or replace temporary function transfer_seconds(size double, mbit_s double, latency_ms double) returns double "
        "return latency_ms / 1000 + size * 8 / (mbit_s * 1000000)"
    )


def worst_transfer(traffic: DataFrame, site_links: DataFrame) -> DataFrame:
    """(pass, seconds): the slowest link's time for what each pass sends over it."""
    sizes = traffic.groupBy("pass", "src", "dst").agg(F.sum("bytes").alias("bytes"))
    timed = sizes.join(F.broadcast(site_links), ["src", "dst"]).withColumn("seconds", transfer_seconds(F.col("bytes"), F.col("mbit_s"), F.col("latency_ms")))
    return timed.groupBy("pass").agg(F.max("seconds").alias("seconds"))


def traffic(requests: DataFrame, sites: DataFrame, *, polling: str = "none") -> DataFrame:
    """(pass, src, dst, rows, bytes) of requests (pass, site, itemset) and their answers.

    ``none``: an asking site writes to every other site, which answers it.  ``hash``: it
    writes to the set's polling site, which asks the others once for all askers and
    tells the askers.  A set costs 4 bytes an item, a count 8.
    """
    size = F.size("itemset") * 4
    everyone = F.broadcast(sites.select(F.col("site").alias("other")))
    own = requests.select("pass", "site", "itemset")
    if polling == "none":
        ask = own.join(everyone, F.col("site") != F.col("other")).select("pass", F.col("site").alias("src"), F.col("other").alias("dst"), size.alias("bytes"))
        answer = own.join(everyone, F.col("site") != F.col("other")).select("pass", F.col("other").alias("src"), F.col("site").alias("dst"), F.lit(8).alias("bytes"))
        parts = [ask, answer]
    elif polling == "hash":
        n = sites.count()
        order = sites.select(F.array_sort(F.collect_list("site")).alias("all"))
        poll = lambda d: d.crossJoin(F.broadcast(order)).withColumn("poll", F.element_at("all", F.pmod(F.xxhash64("itemset"), F.lit(n)).cast("int") + 1))
        polled = poll(own)
        sets = poll(own.select("pass", "itemset").distinct())
        parts = [
            polled.where("site <> poll").select("pass", F.col("site").alias("src"), F.col("poll").alias("dst"), (size + 8).alias("bytes")),
            sets.join(everyone, F.col("poll") != F.col("other")).select("pass", F.col("poll").alias("src"), F.col("other").alias("dst"), size.alias("bytes")),
            sets.join(everyone, F.col("poll") != F.col("other")).select("pass", F.col("other").alias("src"), F.col("poll").alias("dst"), F.lit(8).alias("bytes")),
            polled.where("site <> poll").select("pass", F.col("poll").alias("src"), F.col("site").alias("dst"), F.lit(8).alias("bytes")),
        ]
    else:
        raise ValueError("polling must be none or hash")
    rows = parts[0]
    for p in parts[1:]:
        rows = rows.union(p)
    return rows.groupBy("pass", "src", "dst").agg(F.count("*").alias("rows"), F.sum("bytes").cast("long").alias("bytes"))


def cluster_traffic(substats: DataFrame, aggregator: int) -> DataFrame:
    """(pass, src, dst, rows, bytes): summaries of (d + 2) numbers to the merging site, once."""
    size = (F.size("center") + 2) * 8
    rows = substats.where(F.col("site") != aggregator)
    return rows.groupBy(F.lit(1).alias("pass"), F.col("site").alias("src"), F.lit(aggregator).alias("dst")).agg(F.count("*").alias("rows"), F.sum(size).cast("long").alias("bytes"))


def choose_aggregator(site_links: DataFrame, bytes_by_site: DataFrame, rule: str = "min_worst_link", fixed: int | None = None) -> int:
    """The site that merges: the one whose slowest incoming transfer is shortest, a fixed one, or any (the lowest)."""
    if rule == "fixed":
        if fixed is None:
            raise ValueError("rule fixed needs a site")
        return fixed
    if rule == "any":
        return bytes_by_site.agg(F.min("site")).first()[0]
    timed = site_links.join(F.broadcast(bytes_by_site.withColumnRenamed("site", "src")), "src")
    worst = timed.groupBy("dst").agg(F.max(transfer_seconds(F.col("bytes"), F.col("mbit_s"), F.col("latency_ms"))).alias("s"))
    return worst.orderBy("s", "dst").first().dst


def stagemax(stage_times: DataFrame, communication: float = 0.0) -> DataFrame:
    """(run, est_seconds): the sum over stages of the slowest process, plus communication."""
    slowest = stage_times.groupBy("run", "stage").agg(F.max("seconds").alias("seconds"))
    return slowest.groupBy("run").agg((F.sum("seconds") + F.lit(communication)).alias("est_seconds"))


def overhead(estimated: float | Column, measured: float | Column) -> float | Column:
    return 1 - estimated / measured


def gain(new: float | Column, base: float | Column) -> float | Column:
    return 1 - new / base


def compute_share(local_max: float, merge: float, total: float) -> float:
    return (local_max + merge) / total


def stage_count(kind: str, k: int | Column, passes: int = 0) -> int | Column:
    """Parallel stages: 2k + 1 for the level-sync miner; local, and two a pass, for the late one."""
    return 2 * k + 1 if kind == "levelsync" else 1 + 2 * max(1, passes)


def share(stage_times: DataFrame, word: str) -> DataFrame:
    """(run, share): part of all task seconds spent in stages whose name holds ``word``."""
    return stage_times.groupBy("run").agg((F.sum(F.when(F.col("stage").contains(word), F.col("seconds")).otherwise(0.0)) / F.sum("seconds")).alias("share"))


@contextmanager
def stage(spark: SparkSession, name: str) -> Iterator[None]:
    """Jobs inside carry ``name`` as their group, for the event log."""
    spark.sparkContext.setJobGroup(name, name)
    try:
        yield
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


def timed(run: Callable[[], object], repeats: int = 3, warm_up: int = 1) -> float:
    """Mean wall seconds of ``run`` after ``warm_up`` runs."""
    for _ in range(warm_up):
        run()
    began = time.perf_counter()
    for _ in range(repeats):
        run()
    return (time.perf_counter() - began) / repeats


def observed_times(spark: SparkSession, run: str, groups: dict[str, str]) -> DataFrame:
    """(run, stage, process, seconds) of every task that ran under the job groups {part: group}; stages are named part:number.

    Read from the session's own status store, by tasks: stages whose output was there already ran
    none, and they are the first that the store forgets.  Where it has forgotten a stage that did
    run, the times would not be whole, and an error says so.
    """
    context = spark.sparkContext
    context._jsc.sc().listenerBus().waitUntilEmpty()
    tracker, store = context.statusTracker(), context._jsc.sc().statusStore()
    rows, seen = [], {}
    for part, group in groups.items():
        for job in sorted(tracker.getJobIdsForGroup(group)):
            for stage_id in sorted(tracker.getJobInfo(job).stageIds):
                if stage_id in seen:
                    continue
                seen[stage_id] = attempt = 0
                while (tasks := store.taskList(stage_id, attempt, 100_000)).size():
                    name = f"{part}:{stage_id}" + (f".{attempt}" if attempt else "")
                    for i in range(tasks.size()):
                        if tasks.apply(i).duration().isDefined():
                            rows.append((run, name, tasks.apply(i).index(), tasks.apply(i).duration().get() / 1000))
                    attempt += 1
                seen[stage_id] = attempt
            held = sum(seen[s] > 0 for s in tracker.getJobInfo(job).stageIds)
            if held < store.job(job).numCompletedStages():
                raise RuntimeError(f"the session's status store has dropped stages of job {job}; raise spark.ui.retainedStages")
    return stage_times(spark, rows)


def stage_times(spark: SparkSession, rows: list[tuple[str, str, int, float]]) -> DataFrame:
    return spark.createDataFrame(rows, STAGE_TIMES)
