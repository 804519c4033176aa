"""The late-sync miner: all local work first, one late top-down phase of global counting.

Every site mines its own frequent sets up to size k alone.  Then, pass by pass, sites ask
for the global support of their frontier; sets that reach the global minimum are settled
with all their subsets, and only the subsets of failures are asked next.  With equal
local and global thresholds each globally frequent set is locally frequent at some site,
so the answer is exact; sizes shrink from pass to pass, so there are at most k passes.

Membership alone (``with_support=False``) ends there.  Subsets settled by a passed set were
never asked, so their supports cost one more pass, the support pass, which is logged,
counted and charged like the others.  With it every set that is frequent at some site has
been asked once.  The passes say what travels between sites; here the counts of all those
sets are then taken in one job, and what each pass would ask is read off them.

A counting job runs over all sites: sets that every site counted while mining are answered
from their tables, the others are counted in one scan.
"""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field
from fractions import Fraction
from itertools import combinations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sitemine.functions.itemset_columns import drop_one
from sitemine.operators.itemsets.baskets import least_of
from sitemine.operators.itemsets.frontier import KINDS, close_down, descend, first_frontier
from sitemine.operators.itemsets.local import local_apriori
from sitemine.operators.itemsets.support import count_support
from sitemine.session import drop_shared, materialise, shared_table

#: Locally frequent sets (a row a site) up to which the passes are worked out in one task.
SETTLE_ROWS = 200_000


@dataclass
class MineResult:
    """What a miner found and what it took."""

    itemsets: DataFrame  # itemset, size, support
    local: DataFrame  # site, itemset, size, cnt
    requests: DataFrame  # pass, site, itemset: what each site asked in each pass
    passes: list[dict] = field(default_factory=list)
    counters: dict = field(default_factory=dict)

    def trace(self) -> DataFrame:
        """(pass, kind, requested, passed, failed)."""
        rows = [(p["pass"], p.get("kind", "frontier"), p["requested"], p["passed"], p["failed"]) for p in self.passes]
        return self.itemsets.sparkSession.createDataFrame(rows, "pass int, kind string, requested long, passed long, failed long")


class Clock:
    """Seconds by part of a run; jobs inside a part carry its name as their job group."""

    def __init__(self, spark, prefix: str):
        self.spark, self.prefix, self.seconds = spark, f"{prefix}:{uuid.uuid4().hex[:8]}", {}

    @property
    def groups(self) -> dict[str, str]:
        """The job group of each part."""
        return {name: f"{self.prefix}:{name}" for name in self.seconds}

    @contextmanager
    def part(self, name: str) -> Iterator[None]:
        context = self.spark.sparkContext
        outer = context.getLocalProperty("spark.jobGroup.id")
        context.setLocalProperty("spark.jobGroup.id", f"{self.prefix}:{name}")
        began = time.perf_counter()
        try:
            yield
        finally:
            self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - began
            context.setLocalProperty("spark.jobGroup.id", outer)


def global_minimum(n: int, share: float | str | Fraction) -> int:
    return least_of(n, share)


def remote_support(baskets: DataFrame, asked: DataFrame, local: DataFrame, n_sites: int, sizes: list[int], *, known_counts: bool = True, engine: str = "auto") -> DataFrame:
    """(itemset, support): global counts of the sets in ``asked``.

    A set that all sites counted while mining is summed from their tables; the others are
    counted at every site in one scan.
    """
    asked = asked.select("itemset")
    rest = asked
    if known_counts:
        known = local.join(asked, "itemset", "left_semi").groupBy("itemset").agg(F.sum("cnt").alias("told"), F.count("*").alias("sites")).where(F.col("sites") == n_sites)
        known = materialise(known.select("itemset", "told"))
        rest = materialise(asked.join(known, "itemset", "left_anti"))
        out = asked.join(known, "itemset", "left")
    else:
        out = asked.withColumn("told", F.lit(None).cast("long"))
    if not rest.isEmpty():
        scanned = count_support(baskets, rest, sizes, engine=engine, by_site=False).select("itemset", F.col("cnt").alias("scanned"))
        out = out.join(scanned, "itemset", "left")
    else:
        out = out.withColumn("scanned", F.lit(None).cast("long"))
    return materialise(out.select("itemset", F.coalesce("told", "scanned", F.lit(0)).cast("long").alias("support")))


def split_global(counts: DataFrame, least: int) -> tuple[DataFrame, DataFrame]:
    return counts.where(F.col("support") >= least), counts.where(F.col("support") < least)


def sizes_of(sets: DataFrame) -> list[int]:
    return sorted(r[0] for r in sets.select(F.size("itemset")).distinct().collect())


def passes_of(rows: list[tuple[int, tuple[int, ...], int]], kind: str, k: int, least: int) -> tuple[list[list[tuple[int, tuple[int, ...]]]], list[tuple[int, tuple[int, ...]]], dict[tuple[int, ...], int]]:
    """What each pass asks, what the support pass asks, and the answer with supports, of (site, itemset, support) rows.

    Rows are all locally frequent sets with their global supports.
    """
    support = {s: n for _, s, n in rows}
    local = {(site, s) for site, s, _ in rows}
    below = lambda s: combinations(s, len(s) - 1)
    if kind == "maximal":
        front = local - {(site, x) for site, s in local if len(s) > 1 for x in below(s)}
    elif kind == "all":
        front = set(local)
    else:
        front = {(site, s) for site, s in local if len(s) == (k if kind == "size_k" else 1)}
    passes, asked, closed = [], set(), set()
    while front:
        now = {s for _, s in front}
        passes.append(sorted(front))
        asked |= now
        good = {s for s in now if support[s] >= least}
        if kind == "bottom_up":
            closed |= good
            z = len(passes) + 1
            front = {(site, s) for site, s in local if len(s) == z and all(x in good for x in below(s))}
            continue
        for s in good:
            closed.update(x for z in range(1, len(s) + 1) for x in combinations(s, z))
        if kind == "all":
            break
        failed = {(site, s) for site, s in front if s not in good and len(s) > 1}
        front = {(site, x) for site, s in failed for x in below(s) if x not in closed and x not in asked}
    unasked = closed - asked
    return passes, sorted(x for x in local if x[1] in unasked), {s: support[s] for s in closed}


def settle(local: DataFrame, supports: DataFrame, kind: str, k: int, least: int) -> DataFrame:
    """(pass, site, itemset, support) of every request, the support pass numbered 0, and of the answer (pass -1, site null); one task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [(site, tuple(s), n) for batch in batches for site, s, n in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True)]
        support = {s: n for _, s, n in rows}
        passes, more, answer = passes_of(rows, kind, k, least)
        out = [(i, site, s) for i, front in enumerate(passes, 1) for site, s in front] + [(0, site, s) for site, s in more] + [(-1, None, s) for s in answer]
        if out:
            columns = list(zip(*out, strict=True))
            yield pa.RecordBatch.from_arrays(
                [pa.array(columns[0], pa.int32()), pa.array(columns[1], pa.int32()), pa.array(list(map(list, columns[2])), pa.list_(pa.int32())), pa.array([support[s] for s in columns[2]], pa.int64())],
                names=["pass", "site", "itemset", "support"],
            )

    rows = local.select("site", "itemset").join(supports, "itemset").select("site", "itemset", "support")
    return rows.coalesce(1).mapInArrow(run, "pass int, site int, itemset array<int>, support long")


def descend_passes(
    local: DataFrame, kind: str, k: int, least: int, counts_of: Callable[[DataFrame], DataFrame], clock: Clock
) -> tuple[DataFrame, DataFrame, DataFrame, list[dict]]:
    """(answer, asked with supports, log, passes) of the passes as joins, each pass counted by ``counts_of``."""
    spark = local.sparkSession
    with clock.part("frontier"):
        front = materialise(first_frontier(local, kind, k))
    asked = spark.createDataFrame([], "itemset array<int>, support long")
    log = spark.createDataFrame([], "pass int, site int, itemset array<int>")
    passed, passes, closed = asked, [], asked.select("itemset")
    while not front.isEmpty():
        now = materialise(front.select("itemset").distinct())
        counts = counts_of(now)
        good, bad = split_global(counts, least)
        log = log.union(front.select(F.lit(len(passes) + 1).alias("pass"), "site", "itemset"))
        asked, passed = asked.union(counts), passed.union(good)  # small tables, already kept
        requested, n_good = counts.agg(F.count("*"), F.coalesce(F.sum((F.col("support") >= least).cast("long")), F.lit(0))).first()
        passes.append({"pass": len(passes) + 1, "kind": "frontier", "requested": requested, "passed": n_good, "failed": requested - n_good})
        if kind == "bottom_up":
            front = materialise(_ascend(local, good, len(passes) + 1))
            continue
        with clock.part("frontier"):
            closed = materialise(close_down(passed, k))
            front = materialise(descend(front, bad, closed, asked)) if kind != "all" else front.limit(0)
    answer = passed.select("itemset") if kind == "bottom_up" else closed.distinct()
    return answer, asked, log, passes


def latesync_mine(
    baskets: DataFrame,
    *,
    min_support: float | str | Fraction,
    k: int | None = 4,
    local_support: float | str | Fraction | None = None,
    frontier: str = "maximal",
    engine: str = "auto",
    known_counts: bool = True,
    with_support: bool = True,
) -> MineResult:
    """Globally frequent itemsets of sizes 1 to k; see the module's text.

    ``local_support`` other than ``min_support``: looser stays complete, stricter may miss.
    Without ``with_support`` the supports of sets that were never asked are null.
    """
    if frontier not in KINDS:
        raise ValueError(f"frontier must be one of {', '.join(KINDS)}")
    spark = baskets.sparkSession
    clock = Clock(spark, "latesync")
    with clock.part("prepare"):
        baskets, path = shared_table(baskets)
    try:
        return _late(baskets, clock, min_support, k, local_support, frontier, engine, known_counts, with_support)
    finally:
        drop_shared(spark, path)


def _late(baskets: DataFrame, clock: Clock, min_support, k, local_support, frontier, engine, known_counts, with_support) -> MineResult:
    with clock.part("local"):
        n, n_sites = baskets.agg(F.count("*"), F.count_distinct("site")).first()
        least = global_minimum(n, min_support)
        local = local_apriori(baskets, k, local_support or min_support, engine=engine)
        by_size = {r.z: r.rows for r in local.groupBy(F.size("itemset").alias("z")).agg(F.count("*").alias("rows")).collect()}
    k = k or max([1, *by_size])
    rows = sum(by_size.values())

    def counted(sets: DataFrame) -> DataFrame:
        with clock.part("remote"):
            return remote_support(baskets, sets, local, n_sites, sizes_of(sets), known_counts=known_counts, engine=engine)

    if with_support and rows <= SETTLE_ROWS:
        supports = counted(materialise(local.select("itemset").distinct()))
        with clock.part("frontier"):
            told = materialise(settle(local, supports, frontier, k, least))
            answer, log = told.where(F.col("pass") == -1), told.where(F.col("pass") >= 0)
            good = (F.col("support") >= least).cast("long")
            found = log.select("pass", "itemset", good.alias("good")).distinct().groupBy("pass").agg(F.count("*").alias("requested"), F.sum("good").alias("passed")).collect()
        result = answer.select("itemset", F.size("itemset").alias("size"), "support")
        passes = [{"pass": r["pass"], "kind": "frontier", "requested": r.requested, "passed": r.passed, "failed": r.requested - r.passed} for r in sorted(found) if r["pass"]]
        last = len(passes) + 1
        passes += [{"pass": last, "kind": "support", "requested": r.requested, "passed": r.passed, "failed": 0} for r in found if not r["pass"]]
        log = log.select(F.when(F.col("pass") == 0, last).otherwise(F.col("pass")).alias("pass"), "site", "itemset")
    else:
        if with_support:
            supports = counted(materialise(local.select("itemset").distinct()))
            counts_of = lambda sets: materialise(sets.select("itemset").join(supports, "itemset"))
        else:
            counts_of = counted
        answer, asked, log, passes = descend_passes(local, frontier, k, least, counts_of, clock)
        known = materialise(answer.join(asked, "itemset", "left"))
        unknown = materialise(known.where(F.col("support").isNull()).select("itemset"))
        if with_support and (n_unknown := unknown.count()):
            known = known.where(F.col("support").isNotNull()).union(counts_of(unknown))
            log = log.union(local.join(unknown, "itemset", "left_semi").select(F.lit(len(passes) + 1).alias("pass"), "site", "itemset"))
            passes.append({"pass": len(passes) + 1, "kind": "support", "requested": n_unknown, "passed": n_unknown, "failed": 0})
        result = materialise(known.select("itemset", F.size("itemset").alias("size"), "support"))
        log = materialise(log)
    frontier_passes = sum(p["kind"] == "frontier" for p in passes)
    counters = {
        "baskets": n, "sites": n_sites, "minimum": least, "passes": len(passes), "frontier_passes": frontier_passes, "support_passes": len(passes) - frontier_passes,
        "requested": sum(p["requested"] for p in passes), "seconds": clock.seconds, "groups": clock.groups,
    }
    return MineResult(result, local, log, passes, counters)


def _ascend(local: DataFrame, passed: DataFrame, z: int) -> DataFrame:
    """Locally frequent sets of size z whose every smaller subset just passed."""
    ready = local.where(F.size("itemset") == z).select("site", "itemset")
    parts = ready.select("site", "itemset", F.explode(drop_one(F.col("itemset"))).alias("part"))
    blocked = parts.join(passed.select(F.col("itemset").alias("part")), "part", "left_anti").select("site", "itemset").distinct()
    return ready.join(blocked, ["site", "itemset"], "left_anti")
