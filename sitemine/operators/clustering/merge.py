"""Merging sub-clusters under a bound on the merged scatter.

State is a set of groups, each the union of some sub-clusters; a pair of groups may merge
while its merged scatter stays strictly under the bound.  Which pair goes first is the
``pick``: least merged variance (default; the bound is on it), closest centres, or least
increase.  Three engines:

* ``task``: the whole summary table (not the points) in one task, exact for every setting;
* ``rounds``: all mutually best pairs merge together, round by round, as joins; equals
  ``task`` where scatter is bounded globally and picks are by variance, since the scatter
  of a union is never below that of a part (other settings are refused);
* ``tree``: within sites, then within groups of sites, then over all; approximate, for
  more summaries than one task should hold.  Where a level's share is still over
  ``TASK_ROWS`` it is cut along the first axis, again at other places until nothing merges.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sitemine.functions.merge_columns import distance_np, merge_np, merge_stats
from sitemine.operators.clustering.pairs import near_pairs
from sitemine.session import broadcast_if_small, materialise, numbered

#: Summaries that one task merges; more go to ``tree``.
TASK_ROWS = 20_000
PICKS = ("variance", "distance", "increase")
VARIANCES = ("scatter", "mean")
SCOPES = ("global", "pair")
MEMBERS = "array<struct<site:int,local_id:int>>"
GROUPS = f"group_id long, n long, center array<double>, scatter double, limit double, members {MEMBERS}"


def merge_bound(substats: DataFrame, factor: float = 2.0, variance: str = "scatter") -> float:
    """``factor`` times the highest individual variance of the sub-clusters."""
    value = F.col("scatter") if variance == "scatter" else F.col("scatter") / F.col("n")
    return float(factor) * float(substats.agg(F.max(value)).first()[0] or 0.0)


class Merger:
    """The greedy loop over summaries held in arrays.

    Every group keeps its best feasible partner of a higher index; a merge costs one pass
    over the groups and a new search for those whose partner is gone.
    """

    def __init__(self, n, center, scatter, site, limit, *, bound, pick, variance, scope, distance, same_site):
        self.n, self.c, self.v = (np.array(x, float) for x in (n, center, scatter))
        self.site, self.limit = np.asarray(site), np.array(limit, float)
        self.bound, self.pick, self.variance, self.scope, self.distance, self.same_site = bound, pick, variance, scope, distance, same_site
        size = len(self.n)
        self.alive, self.single = np.ones(size, bool), np.ones(size, bool)
        self.members = [[i] for i in range(size)]
        self.key, self.partner = np.full(size, np.inf), np.full(size, -1)

    def keys(self, i: int, j: np.ndarray) -> np.ndarray:
        """What merging i with each of j ranks by; infinite where it is not allowed."""
        d = distance_np(self.c[j], self.c[i], self.distance)
        n = self.n[j] + self.n[i]
        more = self.n[j] * self.n[i] / n * d
        merged = self.v[j] + self.v[i] + more
        if self.variance == "mean":
            merged = merged / n
        allowed = merged < (self.bound if self.scope == "global" else np.maximum(self.limit[j], self.limit[i]))
        if not self.same_site and self.single[i]:
            allowed &= ~(self.single[j] & (self.site[j] == self.site[i]))
        return np.where(allowed, {"variance": merged, "distance": d, "increase": more}[self.pick], np.inf)

    def search(self, i: int) -> None:
        j = i + 1 + np.flatnonzero(self.alive[i + 1 :])
        self.key[i], self.partner[i] = np.inf, -1
        if len(j):
            keys = self.keys(i, j)
            at = int(keys.argmin())
            if np.isfinite(keys[at]):
                self.key[i], self.partner[i] = keys[at], j[at]

    def run(self) -> None:
        for i in range(len(self.n)):
            self.search(i)
        while len(self.n):
            i = int(self.key.argmin())
            if not np.isfinite(self.key[i]):
                break
            j = int(self.partner[i])
            self.n[i], self.c[i], self.v[i] = merge_np((self.n[i], self.c[i].copy(), self.v[i]), (self.n[j], self.c[j], self.v[j]), self.distance)
            self.limit[i] = max(self.limit[i], self.limit[j])
            self.alive[j] = self.single[i] = False
            self.key[j] = np.inf
            self.members[i] += self.members[j]
            self.search(i)
            below = np.flatnonzero(self.alive[:j])
            below = below[below != i]
            lost = np.isin(self.partner[below], (i, j)) & np.isfinite(self.key[below])
            for a in below[lost]:
                self.search(int(a))
            rest = below[~lost & (below < i)]
            if len(rest):
                keys = self.keys(i, rest)
                better = (keys < self.key[rest]) | ((keys == self.key[rest]) & np.isfinite(keys) & (i < self.partner[rest]))
                self.key[rest[better]], self.partner[rest[better]] = keys[better], i


def _groups_frame(m: Merger, ids: list[tuple[int, int]]) -> list[dict]:
    order = sorted(np.flatnonzero(m.alive), key=lambda g: min(ids[x] for x in m.members[g]))
    return [
        {"group_id": k, "n": int(m.n[g]), "center": m.c[g].tolist(), "scatter": float(m.v[g]), "limit": float(m.limit[g]), "members": sorted(ids[x] for x in m.members[g])}
        for k, g in enumerate(order)
    ]


def as_groups(substats: DataFrame, factor: float, variance: str) -> DataFrame:
    """A group for each sub-cluster; ``limit`` is its own bound under the pair scope."""
    own = F.col("scatter") if variance == "scatter" else F.col("scatter") / F.col("n")
    return substats.select(
        (F.col("site").cast("long") * F.lit(1 << 20) + F.col("local_id")).alias("group_id"), "n", "center", "scatter", (own * factor).alias("limit"),
        F.array(F.struct(F.col("site").cast("int").alias("site"), F.col("local_id").cast("int").alias("local_id"))).alias("members"),
    )


def _merge_in_task(groups: DataFrame, by: list[str] | None, bound: float, options: dict) -> DataFrame:
    """Greedy merging of each ``by`` group of the table (all of it when None), one task each."""

    def one(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values("group_id", kind="stable")
        members = [[(int(x["site"]), int(x["local_id"])) for x in ms] for ms in part["members"]]
        m = Merger(part["n"], np.stack(part["center"].to_list()), part["scatter"], [ms[0][0] for ms in members], part["limit"], bound=bound, **options)
        m.run()
        low = [min(ms) for ms in members]
        rows = _groups_frame(m, low)
        for row in rows:
            row["members"] = [{"site": s, "local_id": i} for s, i in sorted(x for ms, first in zip(members, low, strict=True) if first in row["members"] for x in ms)]
            row["group_id"] = row["members"][0]["site"] * (1 << 20) + row["members"][0]["local_id"]
        return pd.DataFrame(rows, columns=["group_id", "n", "center", "scatter", "limit", "members"])

    keyed = groups.groupBy() if by is None else groups.groupBy(*by)
    return keyed.applyInPandas(one, GROUPS)


def _merge_in_slices(groups: DataFrame, bound: float, options: dict, shift: int) -> tuple[DataFrame, int]:
    """Greedy merging of each ``bucket``, those over ``TASK_ROWS`` cut along the first axis; and how many groups are left."""
    placed = numbered(groups, [F.col("bucket"), F.col("center")[0], F.col("group_id")], "place")
    sliced = placed.withColumn("slice", F.struct("bucket", F.floor((F.col("place") + shift) / TASK_ROWS).alias("part")))
    # a bucket that fits one task stays whole wherever its places fall
    whole = groups.groupBy("bucket").count().where(F.col("count") <= TASK_ROWS).select(F.col("bucket").alias("of"), F.lit(True).alias("fits"))
    sliced = sliced.join(broadcast_if_small(whole), F.col("bucket") == F.col("of"), "left")
    part = F.when(F.col("fits"), F.lit(0).cast("long")).otherwise(F.col("slice.part"))
    merged = materialise(_merge_in_task(sliced.select(*groups.columns, part.alias("part")), ["bucket", "part"], bound, options))
    return merged, merged.count()


def _merge_in_rounds(groups: DataFrame, bound: float) -> DataFrame:
    """Mutually best pairs merge together until no pair is feasible."""
    groups = materialise(groups)
    while True:
        radius = near_pairs(groups, bound)
        best_a = F.row_number().over(Window.partitionBy("a").orderBy("merged", "b"))
        both = radius.select("a", "b", "merged").union(radius.select(F.col("b").alias("a"), F.col("a").alias("b"), "merged"))
        first = both.withColumn("place", best_a).where("place = 1").select("a", "b")
        mutual = first.join(first.select(F.col("a").alias("b"), F.col("b").alias("a")), ["a", "b"], "left_semi").where("a < b")
        chosen = materialise(mutual)
        if chosen.isEmpty():
            return groups
        side = lambda s: groups.select(F.col("group_id").alias(s), F.struct("n", "center", "scatter", "limit", "members").alias(f"g_{s}"))
        pairs = chosen.join(side("a"), "a").join(side("b"), "b")
        merged = merge_stats(F.col("g_a"), F.col("g_b"))
        new = pairs.select(
            F.col("a").alias("group_id"), merged["n"].alias("n"), merged["center"].alias("center"), merged["scatter"].alias("scatter"),
            F.greatest(F.col("g_a.limit"), F.col("g_b.limit")).alias("limit"), F.array_sort(F.concat(F.col("g_a.members"), F.col("g_b.members"))).alias("members"),
        )
        gone = chosen.select(F.explode(F.array("a", "b")).alias("group_id"))
        groups = materialise(groups.join(gone, "group_id", "left_anti").select(*new.columns).union(new))


def merge_subclusters(
    substats: DataFrame,
    *,
    threshold: str | float = "twice_max",
    factor: float = 2.0,
    scope: str = "global",
    variance: str = "scatter",
    distance: str = "sqeuclidean",
    pick: str = "variance",
    same_site: bool = True,
    engine: str = "auto",
    fan_in: int = 16,
) -> DataFrame:
    """(global_id, n, center, scatter, n_members, members) from (site, local_id, n, center, scatter).

    ``threshold`` is "twice_max" (``factor`` times the highest individual variance) or a number.
    """
    for value, allowed in ((pick, PICKS), (variance, VARIANCES), (scope, SCOPES)):
        if value not in allowed:
            raise ValueError(f"{value!r} is none of {', '.join(allowed)}")
    substats = materialise(substats)
    bound = float(threshold) if not isinstance(threshold, str) else merge_bound(substats, factor, variance)
    groups = as_groups(substats, factor if isinstance(threshold, str) else 0.0, variance)
    if not isinstance(threshold, str):
        groups = groups.withColumn("limit", F.lit(bound))
    reducible = (pick, variance, scope, distance, same_site) == ("variance", "scatter", "global", "sqeuclidean", True)
    if engine == "auto":
        engine = "task" if substats.count() <= TASK_ROWS else "rounds" if reducible else "tree"
    options = {"pick": pick, "variance": variance, "scope": scope, "distance": distance, "same_site": same_site}
    if engine == "task":
        merged = _merge_in_task(groups, None, bound, options)
    elif engine == "rounds":
        if not reducible:
            raise ValueError("rounds equal the greedy order only for squared distances, global scatter bounds and picks by variance")
        merged = _merge_in_rounds(groups, bound)
    elif engine == "tree":
        merged, n = groups, substats.agg(F.max("site")).first()[0] + 1
        bucket = F.col("members")[0]["site"]
        while True:
            merged, _ = _merge_in_slices(merged.withColumn("bucket", bucket.cast("long")), bound, options, 0)
            if n <= 1:
                break
            n = -(-n // fan_in)
            bucket = F.floor(bucket / fan_in) if n > 1 else F.lit(0)
        left, shift = merged.count(), 0
        while left > TASK_ROWS:  # more than a task holds: slices half a slice off, until they find nothing
            before, shift = left, TASK_ROWS // 2 - shift
            merged, left = _merge_in_slices(merged.withColumn("bucket", F.lit(0).cast("long")), bound, options, shift)
            if left == before and not shift:
                break
    else:
        raise ValueError("engine must be auto, task, rounds or tree")
    ranked = numbered(materialise(merged), [F.col("group_id")], "global_id").withColumn("global_id", F.col("global_id").cast("int"))
    return materialise(ranked.select("global_id", "n", "center", "scatter", F.size("members").alias("n_members"), "members"))


def labels_of(clusters: DataFrame) -> DataFrame:
    """(site, local_id, global_id): the logical labelling; no point moves."""
    return clusters.select("global_id", F.explode("members").alias("m")).select("m.site", "m.local_id", "global_id")


def remerge(clusters: DataFrame, new_substats: DataFrame, **options) -> DataFrame:
    """Merge existing clusters with a site's new summaries; clusters enter as summaries of site -1."""
    old = clusters.select(F.lit(-1).alias("site"), F.col("global_id").alias("local_id"), "n", "center", "scatter")
    return merge_subclusters(old.unionByName(new_substats.select("site", "local_id", "n", "center", "scatter")), **options)
