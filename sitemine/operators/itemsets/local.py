"""Local Apriori: every site's frequent itemsets of sizes 1 to k, with no global pruning.

The site is part of every key, so all sites are mined by the same few jobs and none
waits for another.  Where every site fits a worker, each is mined whole by one task, all
sizes in one job.  A site may also be as large as the cluster: then each size is a job over
all sites.  At each level candidates come from joining sets that share all but their last
item, and leave when a smaller subset is not frequent; the survivors are counted.
"""

from __future__ import annotations

from collections.abc import Callable
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sitemine.functions.itemset_columns import drop_one
from sitemine.operators.itemsets.baskets import least_of, min_count
from sitemine.operators.itemsets.support import count_sets, count_support, flat, lists_of, shrink
from sitemine.session import materialise

#: A level that would count more candidates than this stops with an error that says so.
MAX_CANDIDATES = 50_000_000
#: A site is mined in one task up to so many baskets, items in them, and candidates of a level.
SITE_BASKETS = 500_000
SITE_ITEMS = 5_000_000
SITE_CANDIDATES = 3_000_000


def site_minimums(baskets: DataFrame, share: float | str | Fraction) -> DataFrame:
    """(site, n, least): baskets and minimum count of each non-empty site."""
    return baskets.groupBy("site").agg(F.count("*").alias("n")).withColumn("least", min_count(F.col("n"), share))


def join_step(frequent: DataFrame) -> DataFrame:
    """(site, itemset): candidates one item larger than the sets of ``frequent``."""
    left = frequent.select("site", F.expr("slice(itemset, 1, size(itemset) - 1)").alias("stem"), F.element_at("itemset", -1).alias("a"))
    right = left.withColumnRenamed("a", "b")
    return left.join(right, ["site", "stem"]).where("a < b").select("site", F.concat("stem", F.array("a", "b")).alias("itemset"))


def prune_step(candidates: DataFrame, frequent: DataFrame) -> DataFrame:
    """``candidates`` whose every drop-one subset is in ``frequent`` at the same site."""
    parts = candidates.select("site", "itemset", F.explode(drop_one(F.col("itemset"))).alias("part"))
    missing = parts.join(frequent.select("site", F.col("itemset").alias("part")), ["site", "part"], "left_anti").select("site", "itemset").distinct()
    return candidates.join(missing, ["site", "itemset"], "left_anti")


def level_one(baskets: DataFrame) -> DataFrame:
    return baskets.select("site", F.explode("items").alias("code")).groupBy("site", "code").agg(F.count("*").alias("cnt")).select("site", F.array("code").alias("itemset"), "cnt")


def _ids(sets: np.ndarray) -> np.ndarray:
    """A number for each row; rows that share one by chance cost a needless count, no more."""
    out = np.zeros(len(sets), np.uint64)
    for j in range(sets.shape[1]):
        out = (out ^ sets[:, j].astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        out ^= out >> np.uint64(31)
    return out


def candidates_of(level: np.ndarray, limit: int) -> np.ndarray | int:
    """Sets one larger than the sorted rows of ``level`` whose drop-one subsets are all rows; past ``limit`` their number before pruning."""
    m, z = level.shape
    stem = np.ones(m, bool)
    stem[1:] = (level[1:, :-1] != level[:-1, :-1]).any(axis=1)
    ends = np.append(np.flatnonzero(stem)[1:], m)[np.cumsum(stem) - 1]
    more = ends - np.arange(m) - 1
    if (total := int(more.sum())) > limit:
        return total
    left = np.repeat(np.arange(m), more)
    right = left + 1 + np.arange(total) - np.repeat(np.cumsum(more) - more, more)
    made = np.column_stack([level[left], level[right, -1]])
    known = _ids(level)
    for drop in range(z - 1):
        made = made[np.isin(_ids(np.delete(made, drop, axis=1)), known)]
    return made


def mine_site(offsets: np.ndarray, values: np.ndarray, k: int | None, least: int, limit: int = SITE_CANDIDATES) -> list[tuple[np.ndarray, np.ndarray]]:
    """(sets, counts) of each size; a last pair (empty, number) tells of a level with more candidates than ``limit``."""
    codes, counts = np.unique(values, return_counts=True)
    often = counts >= least
    out = [(codes[often][:, None].astype(np.int32), counts[often])]
    while len(out[-1][0]) > 1 and (k is None or len(out) < k):
        made = candidates_of(out[-1][0], limit)
        if isinstance(made, int):
            return [*out, (np.empty((0, 1), np.int32), np.array([made]))]
        counts = count_sets(offsets, values, made)
        out.append((made[counts >= least], counts[counts >= least]))
    return [pair for pair in out if len(pair[0])]


def _by_task(baskets: DataFrame, k: int | None, share: float | str | Fraction, max_candidates: int) -> DataFrame | None:
    """``local_apriori`` with a task a site, or None where a site has too many candidates for one."""
    limit = min(max_candidates, SITE_CANDIDATES)

    def run(key: tuple, table: pa.Table) -> pa.Table:
        offsets, values = flat(table.column("items"))
        found = mine_site(offsets, values, k, least_of(table.num_rows, share), limit)
        schema = pa.schema([("site", pa.int32()), ("itemset", pa.list_(pa.int32())), ("size", pa.int32()), ("cnt", pa.int64())])
        parts = []
        for sets, counts in found:
            size = sets.shape[1] if len(sets) else -1
            shown = lists_of(sets) if len(sets) else pa.array([[]], pa.list_(pa.int32()))
            site = pa.array([key[0].as_py()] * len(counts), pa.int32())
            parts.append(pa.Table.from_arrays([site, shown, pa.array([size] * len(counts), pa.int32()), pa.array(counts, pa.int64())], schema=schema))
        return pa.concat_tables(parts) if parts else schema.empty_table()

    mined = materialise(baskets.select("site", "items").groupBy("site").applyInArrow(run, "site int, itemset array<int>, size int, cnt long"))
    most = mined.where("size < 0").agg(F.max("cnt")).first()[0]
    if most is None:
        return mined
    if most > max_candidates:
        raise ValueError(f"{most} candidates of one size: raise the support or max_candidates")
    return None


def local_apriori(
    baskets: DataFrame,
    k: int | None,
    share: float | str | Fraction,
    *,
    engine: str = "auto",
    keep: Callable[[DataFrame, int], DataFrame] | None = None,
    max_candidates: int = MAX_CANDIDATES,
) -> DataFrame:
    """(site, itemset, size, cnt) of the sets frequent at their site; ``k=None``: all sizes.

    ``keep(level, z)`` may thin a level's frequent sets before they make candidates
    (level-synchronised mining does).  ``engine`` other than auto counts every level in a job.
    """
    if engine == "auto" and keep is None:
        sizes = baskets.groupBy("site").agg(F.count("*").alias("n"), F.sum(F.size("items")).alias("items"))
        n, items = sizes.agg(F.coalesce(F.max("n"), F.lit(0)), F.coalesce(F.max("items"), F.lit(0))).first()
        if n <= SITE_BASKETS and items <= SITE_ITEMS and (mined := _by_task(baskets, k, share, max_candidates)) is not None:
            return mined
    least = F.broadcast(materialise(site_minimums(baskets, share).select("site", "least")))
    frequent = lambda counts: materialise(counts.join(least, "site").where("cnt >= least").select("site", "itemset", "cnt"))
    level = frequent(level_one(baskets))
    if keep:
        level = keep(level, 1)
    out = [level.withColumn("size", F.lit(1))]
    live = baskets if engine in ("auto", "bitmap", "trie") else shrink(baskets, level.select("site", F.explode("itemset").alias("code")), by_site=True)
    z = 2
    while k is None or z <= k:
        candidates = materialise(prune_step(join_step(level), level) if z > 2 else join_step(level))
        n = candidates.count()
        if n > max_candidates:
            raise ValueError(f"{n} candidates of size {z}: raise the support or max_candidates")
        if not n:
            break
        level = frequent(count_support(live, candidates, [z], engine=engine))
        if keep:
            level = keep(level, z)
        out.append(level.withColumn("size", F.lit(z)))
        z += 1
    result = out[0]
    for more in out[1:]:
        result = result.union(more)
    return result.select("site", "itemset", "size", "cnt")
