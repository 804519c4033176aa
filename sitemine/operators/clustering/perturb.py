"""Repairing borders: members at a cluster's edge move to a neighbour when that pays.

Candidates of a cluster are its ``border`` members furthest out (a number, or a share of
its members) and, with ``multi``, those that would also stay under the bound in another
cluster.  A candidate moves to the nearest other cluster if the total scatter strictly
falls.  Only two clusters change in a move, so the test needs only their summaries.

``sequential`` mode lets each accepted move change the summaries seen by the next, in one
task over up to ``TASK_ROWS`` summaries.  ``batch`` mode evaluates all candidates at once as
joins and accepts the best gains that share no cluster, round by round, until no candidate
gains (``max_sweeps`` bounds sequential mode only).  ``auto`` is sequential where the
summaries fit a task and batch beyond.  Clusters meet candidates block by block, each block
small enough to be broadcast.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sitemine.functions.merge_columns import distance_np, merge_np, move_gain, remove_np, squared_distance
from sitemine.operators.clustering.merge import MEMBERS, TASK_ROWS, labels_of
from sitemine.operators.clustering.stats import dimension
from sitemine.session import materialise, shared_table

CLUSTERS = f"global_id int, n long, center array<double>, scatter double, n_members int, members {MEMBERS}"
TRACE = "step int, kind string, a int, b int, total_scatter double"
#: Numbers in the centres of a block of clusters that is broadcast.
BLOCK_NUMBERS = 4_000_000


def _blocks(others: DataFrame) -> list[DataFrame]:
    """``others`` (rival, r: its summary) in blocks, each broadcast."""
    size = others.agg(F.count("*").alias("rows"), F.max(F.size("r.center")).alias("d")).first()
    n = max(1, -(-(size.rows or 0) * ((size.d or 0) + 2) // BLOCK_NUMBERS))
    return [F.broadcast(others if n == 1 else others.where(F.pmod("rival", F.lit(n)) == i)) for i in range(n)]


def members_with_stats(clusters: DataFrame, substats: DataFrame) -> DataFrame:
    """(global_id, site, local_id, n, center, scatter, own): each member beside its cluster's summary."""
    own = clusters.select("global_id", "n_members", F.struct("n", "center", "scatter").alias("own"), F.explode("members").alias("m"))
    return own.select("global_id", "n_members", "own", "m.site", "m.local_id").join(substats.select("site", "local_id", "n", "center", "scatter"), ["site", "local_id"])


def border(clusters: DataFrame, substats: DataFrame, b: int | float, *, rule: str = "to_center") -> DataFrame:
    """Each cluster's candidates: its members furthest from the centre (``to_center``), or
    nearest to another cluster (``to_rival``); clusters of one member have none."""
    rows = members_with_stats(clusters, substats).where("n_members > 1")
    far = squared_distance(F.col("center"), F.col("own.center"))
    if rule == "to_rival":
        near = closest_rival(rows, clusters).select("site", "local_id", F.col("rival_d2"))
        rows = rows.join(near, ["site", "local_id"]).withColumn("far", -F.col("rival_d2"))
    else:
        rows = rows.withColumn("far", far)
    wanted = F.lit(int(b)) if isinstance(b, int) else F.greatest(F.lit(1), F.round(F.col("n_members") * float(b)).cast("int"))
    place = F.row_number().over(Window.partitionBy("global_id").orderBy(F.desc("far"), "site", "local_id"))
    return rows.withColumn("place", place).where(F.col("place") <= wanted).where(wanted > 0)


def closest_rival(candidates: DataFrame, clusters: DataFrame) -> DataFrame:
    """``candidates`` plus rival, rival_d2, rival_stats: the nearest other cluster of each."""
    others = clusters.select(F.col("global_id").alias("rival"), F.struct("n", "center", "scatter").alias("r"))
    keys, found = ["site", "local_id"], None
    for block in _blocks(others):
        near = candidates.join(block, F.col("rival") != F.col("global_id")).withColumn("rival_d2", squared_distance(F.col("center"), F.col("r.center")))
        best = near.groupBy(*keys).agg(F.min_by(F.struct("rival", "rival_d2", F.col("r").alias("rival_stats")), F.struct("rival_d2", "rival")).alias("best"))
        found = best if found is None else found.union(best)
    found = found.groupBy(*keys).agg(F.min_by("best", F.struct("best.rival_d2", "best.rival")).alias("best"))
    return candidates.join(found, keys).select(*candidates.columns, "best.*")


def multi_attributed(clusters: DataFrame, substats: DataFrame, bound: float) -> DataFrame:
    """Members that would stay under ``bound`` in at least one other cluster."""
    rows = members_with_stats(clusters, substats).where("n_members > 1")
    others = clusters.select(F.col("global_id").alias("rival"), F.struct("n", "center", "scatter").alias("r"))
    d2 = squared_distance(F.col("center"), F.col("r.center"))
    merged = F.col("scatter") + F.col("r.scatter") + F.col("n") * F.col("r.n") / (F.col("n") + F.col("r.n")) * d2
    fits = None
    for block in _blocks(others):
        some = rows.join(block, (F.col("rival") != F.col("global_id")) & (merged < bound)).select("site", "local_id")
        fits = some if fits is None else fits.union(some)
    return rows.join(fits.distinct(), ["site", "local_id"], "left_semi")


def moves(clusters: DataFrame, substats: DataFrame, b: int | float, bound: float | None = None, *, rule: str = "to_center") -> DataFrame:
    """(global_id, site, local_id, rival, gain) of every candidate, summaries as they stand."""
    chosen = border(clusters, substats, b, rule=rule).select("site", "local_id", "global_id", "n_members", "own", "n", "center", "scatter")
    if bound is not None:
        chosen = chosen.union(multi_attributed(clusters, substats, bound).select(*chosen.columns)).dropDuplicates(["site", "local_id"])
    rivals = closest_rival(chosen, clusters)
    member = F.struct("n", "center", "scatter")
    return rivals.select("global_id", "site", "local_id", "rival", move_gain(member, F.col("own"), F.col("rival_stats")).alias("gain"))


def _sequential(clusters: DataFrame, substats: DataFrame, b: int | float, bound: float | None, distance: str, sweeps: int, rule: str) -> tuple[DataFrame, DataFrame]:
    """One task over the summaries; both results come from the same rows."""
    rows = members_with_stats(clusters, substats).select("global_id", "site", "local_id", "n", "center", "scatter", F.col("own.n").alias("gn"), F.col("own.center").alias("gc"), F.col("own.scatter").alias("gv"))

    def one(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values(["site", "local_id"], kind="stable").reset_index(drop=True)
        items = [(int(n), np.asarray(c, float), float(v)) for n, c, v in zip(part["n"], part["center"], part["scatter"], strict=True)]
        at = part["global_id"].to_numpy().copy()
        first = part.drop_duplicates("global_id")
        group = {int(g): (int(n), np.asarray(c, float), float(v)) for g, n, c, v in zip(first["global_id"], first["gn"], first["gc"], first["gv"], strict=True)}
        total = sum(v for _, _, v in group.values())
        log = []
        for _ in range(sweeps):
            accepted = 0
            for g in sorted(group):
                own = np.flatnonzero(at == g)
                if len(own) < 2 or len(group) < 2:
                    continue
                ids = np.array([h for h in sorted(group) if h != g])
                rn, rc, rv = (np.array([group[h][j] for h in ids]) for j in range(3))
                if rule == "to_rival":
                    far = np.array([-distance_np(rc, items[i][1]).min() for i in own])
                else:
                    far = distance_np(np.stack([items[i][1] for i in own]), group[g][1])
                wanted = int(b) if isinstance(b, int) else max(1, int(np.floor(len(own) * float(b) + 0.5)))
                ranked = [int(own[i]) for i in np.lexsort((own, -far))]
                picked = ranked[:wanted]
                if bound is not None:
                    fits = lambda i: (rv + items[i][2] + rn * items[i][0] / (rn + items[i][0]) * distance_np(rc, items[i][1], distance) < bound).any()
                    picked += [i for i in ranked[wanted:] if fits(i)]
                for i in picked:
                    if (at == g).sum() < 2:
                        break
                    rival = min((h for h in group if h != g), key=lambda h: (float(distance_np(group[h][1], items[i][1])), h))
                    less, more = remove_np(group[g], items[i], distance), merge_np(group[rival], items[i], distance)
                    after = total - group[g][2] - group[rival][2] + less[2] + more[2]
                    won = less[2] + more[2] < group[g][2] + group[rival][2]
                    log.append(("move_accept" if won else "move_try", g, rival, after if won else total))
                    if won:
                        group[g], group[rival], at[i], total = less, more, rival, after
                        accepted += 1
            if not accepted:
                break
        out = [{"what": "cluster", "step": 0, "kind": "", "a": g, "b": 0, "total": 0.0, "n": group[g][0], "center": group[g][1].tolist(), "scatter": group[g][2],
                "members": [{"site": int(part["site"][i]), "local_id": int(part["local_id"][i])} for i in np.flatnonzero(at == g)]} for g in sorted(group)]
        out += [{"what": "move", "step": s, "kind": k, "a": a, "b": h, "total": t, "n": 0, "center": [], "scatter": 0.0, "members": []} for s, (k, a, h, t) in enumerate(log, 1)]
        return pd.DataFrame(out, columns=["what", "step", "kind", "a", "b", "total", "n", "center", "scatter", "members"])

    schema = f"what string, step int, kind string, a int, b int, total double, n long, center array<double>, scatter double, members {MEMBERS}"
    done = materialise(rows.groupBy().applyInPandas(one, schema))
    repaired = done.where("what = 'cluster'").select(F.col("a").alias("global_id"), "n", "center", "scatter", F.size("members").alias("n_members"), "members")
    return repaired, done.where("what = 'move'").select("step", "kind", "a", "b", F.col("total").alias("total_scatter"))


def regroup(substats: DataFrame, labels: DataFrame) -> DataFrame:
    """Cluster summaries recomputed from their members' summaries."""
    rows = labels.join(substats, ["site", "local_id"])
    d = dimension(rows.select(F.col("center").alias("features")))
    n = F.sum("n")
    means = F.array(*[F.sum(F.col("n") * F.col("center")[i]) / n for i in range(d)])
    sums = rows.groupBy("global_id").agg(n.alias("n"), means.alias("center"), F.array_sort(F.collect_list(F.struct("site", "local_id"))).alias("members"))
    spread = rows.join(sums.select("global_id", F.col("center").alias("mean")), "global_id").groupBy("global_id").agg(
        F.sum(F.col("scatter") + F.col("n") * squared_distance(F.col("center"), F.col("mean"))).alias("scatter")
    )
    return sums.join(spread, "global_id").select("global_id", "n", "center", "scatter", F.size("members").alias("n_members"), "members")


def _batch(clusters: DataFrame, substats: DataFrame, b: int | float, bound: float | None, rule: str) -> tuple[DataFrame, DataFrame]:
    log = []
    total = reached = clusters.agg(F.sum("scatter")).first()[0]
    while True:
        options = materialise(moves(clusters, substats, b, bound, rule=rule).where("gain > 0"))
        # a move stands if it is the best of both clusters that it touches
        touched = options.select("global_id", "rival", "site", "local_id", "gain", F.explode(F.array("global_id", "rival")).alias("touched"))
        order = Window.partitionBy("touched").orderBy(F.desc("gain"), "site", "local_id")
        best = touched.withColumn("place", F.row_number().over(order)).groupBy("global_id", "rival", "site", "local_id").agg(F.max("place").alias("worst"), F.first("gain").alias("gain"))
        chosen = materialise(best.where("worst = 1"))
        accepted = chosen.select("global_id", "rival", "gain").orderBy("global_id").collect()  # at most half the clusters
        if not accepted:
            break
        labels = labels_of(clusters).join(chosen.select("site", "local_id", "rival"), ["site", "local_id"], "left")
        # read from a table: a checkpoint's size estimate is a product that doubles its digits every round
        moved, _ = shared_table(regroup(substats, labels.select("site", "local_id", F.coalesce("rival", "global_id").alias("global_id"))))
        # the recomputed total has to fall strictly, or gains of rounding size could go round for ever
        now = moved.agg(F.sum("scatter")).first()[0]
        if not now < reached:
            break
        clusters, reached = moved, now
        for r in accepted:
            total -= r.gain
            log.append((len(log) + 1, "move_accept", r.global_id, r.rival, total))
    return clusters, clusters.sparkSession.createDataFrame(log, TRACE)


def perturb(
    clusters: DataFrame, substats: DataFrame, *, border: int | float = 0.1, bound: float | None = None, mode: str = "auto", distance: str = "sqeuclidean", max_sweeps: int = 1, rule: str = "to_center"
) -> tuple[DataFrame, DataFrame]:
    """(clusters, trace) after the repair; ``bound`` switches multi-attributed members on, ``rule`` says what the border is."""
    if rule not in ("to_center", "to_rival"):
        raise ValueError("rule must be to_center or to_rival")
    if not border:
        return clusters, clusters.sparkSession.createDataFrame([], TRACE)
    if mode in ("auto", "sequential"):
        rows = substats.count()
        if mode == "sequential" and rows > TASK_ROWS:
            raise ValueError(f"{rows} summaries, one task may hold {TASK_ROWS}; use batch")
        mode = "sequential" if rows <= TASK_ROWS else "batch"
    if mode == "sequential":
        return _sequential(clusters, substats, border, bound, distance, max_sweeps, rule)
    if mode == "batch":
        if distance != "sqeuclidean":
            raise ValueError("batch mode needs squared distances")
        return _batch(clusters, substats, border, bound, rule)
    raise ValueError("mode must be auto, sequential or batch")
