"""Clustering: formulas, merging, repair and local steps against recomputation."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from sitemine.functions import agreement
from sitemine.functions.merge_columns import merge_np, merge_stats, move_gain, nearest_center, remove_np, remove_stats, scatter_of
from sitemine.operators.clustering import gap, local, merge, perturb, stats
from sitemine.operators.clustering.pairs import near_pairs
from sitemine.operators.clustering.pipeline import label_points, vmerge_cluster

STATS = "site int, local_id int, n long, center array<double>, scatter double"
HAND = [(0, 0, 4, [0.0], 2.0), (0, 1, 4, [10.0], 2.0), (1, 0, 2, [1.0], 1.0), (1, 1, 6, [11.0], 3.0)]


def summary(x):
    return len(x), x.mean(axis=0), float(((x - x.mean(axis=0)) ** 2).sum())


def groups(clusters):
    return sorted((r.n, round(r.center[0], 4), round(r.scatter, 4)) for r in clusters.collect())


def test_merging_is_exact_and_removal_inverts_it():
    rng = np.random.default_rng(1)
    for _ in range(100):
        a, b, c = (rng.normal(size=(rng.integers(1, 9), 3)) * 5 for _ in range(3))
        ab = merge_np(summary(a), summary(b))
        whole = summary(np.concatenate([a, b]))
        assert ab[0] == whole[0] and np.allclose(ab[1], whole[1]) and ab[2] == pytest.approx(whole[2])
        left, right = merge_np(ab, summary(c)), merge_np(summary(a), merge_np(summary(b), summary(c)))
        assert np.allclose(left[1], right[1]) and left[2] == pytest.approx(right[2])
        back = remove_np(ab, summary(b))
        assert np.allclose(back[1], summary(a)[1]) and back[2] == pytest.approx(summary(a)[2], abs=1e-9)


def test_columns_equal_numpy(spark):
    rng = np.random.default_rng(2)
    parts = [rng.normal(size=(n, 2)) for n in (3, 4, 5)]
    row = spark.createDataFrame([tuple({"n": s[0], "center": s[1].tolist(), "scatter": s[2]} for s in map(summary, parts))], ", ".join(f"{c} struct<n:long,center:array<double>,scatter:double>" for c in "abc"))
    a, b, c = (F.col(x) for x in "abc")
    got = row.select(merge_stats(a, b).alias("m"), remove_stats(merge_stats(a, b), b).alias("r"), move_gain(b, merge_stats(a, b), c).alias("g")).first()
    sa, sb, sc = map(summary, parts)
    assert got.m.scatter == pytest.approx(merge_np(sa, sb)[2]) and got.r.scatter == pytest.approx(sa[2])
    assert got.g == pytest.approx(merge_np(sa, sb)[2] + sc[2] - sa[2] - merge_np(sc, sb)[2])


def test_sub_stats_both_ways(spark, monkeypatch):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(200, 5)) + 1000
    df = spark.createDataFrame([(i % 2, i, v.tolist(), i % 3) for i, v in enumerate(x)], "site int, point_id long, features array<double>, local_id int")
    read = lambda d: {(r.site, r.local_id): r for r in d.collect()}
    wide = read(stats.sub_stats(df))
    monkeypatch.setattr(stats, "WIDE", 2)
    tall = read(stats.sub_stats(df))
    for key, r in wide.items():
        own = x[[i for i in range(200) if (i % 2, i % 3) == key]]
        assert r.n == len(own) and r.scatter == pytest.approx(summary(own)[2], rel=1e-9) and tall[key].scatter == pytest.approx(r.scatter, rel=1e-9)
        assert np.allclose(r.center, own.mean(axis=0)) and np.allclose(tall[key].center, r.center)
    by_udf = {(r.site, r.local_id): r.s for r in df.groupBy("site", "local_id").agg(scatter_of("features").alias("s")).collect()}
    assert all(by_udf[k] == pytest.approx(r.scatter, rel=1e-9) for k, r in wide.items())


def test_merge_by_hand(spark):
    s = spark.createDataFrame(HAND, STATS)
    three, two = [(4, 10.0, 2.0), (6, 0.3333, 4.3333), (6, 11.0, 3.0)], [(6, 0.3333, 4.3333), (10, 10.6, 7.4)]
    for engine in ("task", "rounds", "tree"):
        assert groups(merge.merge_subclusters(s, engine=engine)) == three
        assert groups(merge.merge_subclusters(s, factor=3.0, engine=engine)) == two
    assert groups(merge.merge_subclusters(s, variance="mean")) == two
    assert groups(merge.merge_subclusters(s, threshold=500.0)) == [(16, 6.75, 407.0)]
    assert groups(merge.merge_subclusters(s, threshold=0.0)) == [(2, 1.0, 1.0), (4, 0.0, 2.0), (4, 10.0, 2.0), (6, 11.0, 3.0)]
    assert len(groups(merge.merge_subclusters(s, factor=3.0, scope="pair"))) == 2
    for pick in merge.PICKS:
        assert groups(merge.merge_subclusters(s, factor=3.0, pick=pick)) == two
    with pytest.raises(ValueError):
        merge.merge_subclusters(s, pick="distance", engine="rounds")
    with pytest.raises(ValueError):
        merge.merge_subclusters(s, pick="luck")


def naive(parts, bound, variance="scatter", same_site=True, sites=None):
    """Greedy merging with everything recomputed, least merged variance first."""
    own = [([i], summary(p), p) for i, p in enumerate(parts)]
    while True:
        best = None
        for a in range(len(own)):
            for b in range(a + 1, len(own)):
                if not same_site and len(own[a][0]) == len(own[b][0]) == 1 and sites[own[a][0][0]] == sites[own[b][0][0]]:
                    continue
                s = summary(np.concatenate([own[a][2], own[b][2]]))
                v = s[2] if variance == "scatter" else s[2] / s[0]
                if v < bound and (best is None or v < best[0]):
                    best = (v, a, b, s)
        if best is None:
            return sorted(sorted(o[0]) for o in own)
        _, a, b, s = best
        own[a] = (own[a][0] + own[b][0], s, np.concatenate([own[a][2], own[b][2]]))
        del own[b]


@pytest.mark.parametrize("seed", range(4))
def test_engines_equal_the_naive_greedy(spark, seed):
    rng = np.random.default_rng(seed)
    parts = [rng.normal(size=(rng.integers(2, 6), 2)) + rng.normal(size=2) * 6 for _ in range(25)]
    rows = [(i % 3, i, *(lambda s: (s[0], s[1].tolist(), s[2]))(summary(p))) for i, p in enumerate(parts)]
    s = spark.createDataFrame(rows, STATS)
    bound = 4 * max(r[4] for r in rows)
    read = lambda c: sorted(sorted(m.local_id for m in r.members) for r in c.collect())
    want = naive(parts, bound)
    assert read(merge.merge_subclusters(s, threshold=bound, engine="task")) == want
    assert read(merge.merge_subclusters(s, threshold=bound, engine="rounds")) == want
    mean = 4 * max(r[4] / r[2] for r in rows)
    assert read(merge.merge_subclusters(s, threshold=mean, variance="mean")) == naive(parts, mean, "mean")
    assert read(merge.merge_subclusters(s, threshold=bound, same_site=False)) == naive(parts, bound, same_site=False, sites=[i % 3 for i in range(25)])


def test_near_pairs_are_the_feasible_pairs(spark):
    rng = np.random.default_rng(5)
    rows = [(i, int(rng.integers(1, 9)), (rng.normal(size=3) * 4).tolist(), float(rng.random())) for i in range(80)]
    df = spark.createDataFrame(rows, "group_id long, n long, center array<double>, scatter double")
    want = set()
    for a in range(80):
        for b in range(a + 1, 80):
            if merge_np((rows[a][1], np.array(rows[a][2]), rows[a][3]), (rows[b][1], np.array(rows[b][2]), rows[b][3]))[2] < 6.0:
                want.add((a, b))
    got = near_pairs(df, 6.0)
    assert {(r.a, r.b) for r in got.collect()} == want and got.count() == len(want)
    assert "CartesianProduct" not in got._jdf.queryExecution().executedPlan().toString()


def test_near_pairs_of_unlike_sizes(spark):
    """One tiny group among large ones: all feasible pairs, each once."""
    rng = np.random.default_rng(15)
    rows = [(i, int(4 ** rng.integers(0, 7)), (rng.normal(size=2) * 3).tolist(), float(rng.random())) for i in range(70)]
    df = spark.createDataFrame(rows, "group_id long, n long, center array<double>, scatter double")
    stat = lambda r: (r[1], np.array(r[2]), r[3])
    want = {(a, b) for a in range(70) for b in range(a + 1, 70) if merge_np(stat(rows[a]), stat(rows[b]))[2] < 8.0}
    got = near_pairs(df, 8.0).collect()
    assert {(r.a, r.b) for r in got} == want and len(got) == len(want)


def test_tree_in_slices(spark, monkeypatch):
    """Where a task holds few summaries, slices lose none and stay under the bound."""
    rng = np.random.default_rng(16)
    rows = [(i % 5, i, 3, (rng.normal(size=2) + 20 * (i % 4)).tolist(), 1.0) for i in range(120)]
    s = spark.createDataFrame(rows, STATS)
    monkeypatch.setattr(merge, "TASK_ROWS", 16)
    merged = merge.merge_subclusters(s, threshold=60.0, engine="tree", fan_in=2).collect()
    assert sum(r.n for r in merged) == 360 and sorted(m.local_id for r in merged for m in r.members) == list(range(120))
    assert all(r.scatter < 60.0 for r in merged) and len(merged) < 60 and sorted(r.global_id for r in merged) == list(range(len(merged)))


def test_repair_beyond_a_task(spark, monkeypatch):
    rows = [(0, i, 50, [0.0], 0.0) for i in range(2)] + [(0, 10 + i, 1, [9.0 + i / 100], 0.0) for i in range(5)] + [(1, 0, 50, [10.0], 0.0)]
    s = spark.createDataFrame(rows, STATS)
    clusters = perturb.regroup(s, spark.createDataFrame([(r[0], r[1], r[0]) for r in rows], "site int, local_id int, global_id int"))
    want, _ = perturb.perturb(clusters, s, border=5)
    monkeypatch.setattr(perturb, "TASK_ROWS", 3)
    monkeypatch.setattr(perturb, "BLOCK_NUMBERS", 1)  # a block a cluster
    got, _ = perturb.perturb(clusters, s, border=5)
    assert groups(got) == groups(want)
    with pytest.raises(ValueError, match="use batch"):
        perturb.perturb(clusters, s, border=5, mode="sequential")
    with pytest.raises(ValueError, match="rule"):
        perturb.perturb(clusters, s, rule="inwards")


def test_options_reach_every_step(spark):
    rng = np.random.default_rng(17)
    points = spark.createDataFrame([(i % 2, i, (rng.normal(size=2) * 4).tolist()) for i in range(200)], "site int, point_id long, features array<double>")
    apart = vmerge_cluster(points, k_local=6, local="kmeans", same_site=False, border=0)
    # a group that two sub-clusters of one site share was merged over a group of several
    assert all(len({m.site for m in r.members}) == 2 for r in apart.clusters.collect() if r.n_members == 2)
    for rule in ("to_center", "to_rival"):
        r = vmerge_cluster(points, k_local=6, local="kmeans", border=0.5, rule=rule)
        assert r.clusters.agg(F.sum("n")).first()[0] == 200
    with pytest.raises(ValueError, match="one task may hold"):
        gap.gap_statistic(points, 2, n_ref=1, max_site_rows=50)


def test_equal_distances_go_to_the_first(spark):
    x, c = np.array([[1e8 + 0.5, 3.0], [5.0, 5.0]]), np.array([[1e8, 3.0], [1e8 + 1, 3.0], [5.0, 4.0], [5.0, 6.0]])
    assert local.nearest(x, c).tolist() == [0, 2]


def test_rounding_does_not_decide_ties(spark):
    """A point midway between two centres goes to the first, on whichever side the last bit of a coordinate lies."""
    far = float(np.nextafter(0.6, 0))
    points = spark.createDataFrame([(0, i, [x]) for i, x in enumerate((0.0, far, 0.3, 0.5))], "site int, point_id long, features array<double>")
    centers = spark.createDataFrame([(0, 0, [0.0]), (0, 1, [far])], "site int, local_id int, center array<double>")
    want = {0: 0, 1: 1, 2: 0, 3: 1}
    for way in (local.assign, local._assign_by_matrix):
        assert {r.point_id: r.local_id for r in way(points, centers).collect()} == want
    x = np.array([[r.features[0]] for r in points.orderBy("point_id").collect()])
    assert local.first_least((x - x[:2].T) ** 2).tolist() == [0, 1, 0, 1]


def test_repair_by_hand(spark):
    clusters = spark.createDataFrame([(0, 6, [1.0], 31.0, 2, [(0, 0), (0, 1)]), (1, 5, [10.0], 1.0, 1, [(1, 0)])], perturb.CLUSTERS)
    s = spark.createDataFrame([(0, 0, 5, [0.0], 1.0), (0, 1, 1, [6.0], 0.0), (1, 0, 5, [10.0], 1.0)], STATS)
    for mode in ("sequential", "batch"):
        after, trace = perturb.perturb(clusters, s, border=1, mode=mode)
        assert groups(after) == [(5, 0.0, 1.0), (6, 9.3333, 14.3333)]
        assert trace.where("kind = 'move_accept'").first().total_scatter == pytest.approx(15.3333, abs=1e-3)
    plain, trace = perturb.perturb(clusters, s, border=1, distance="euclidean")
    assert trace.where("kind = 'move_accept'").count() == 1
    same, trace = perturb.perturb(clusters, s, border=0)
    assert groups(same) == groups(clusters) and trace.count() == 0
    assert perturb.border(clusters, s, 1).select("local_id").collect()[0][0] == 1
    assert perturb.border(clusters, s, 1, rule="to_rival").select("local_id").collect()[0][0] == 1
    assert perturb.multi_attributed(clusters, s, 1000.0).count() == 2 and perturb.multi_attributed(clusters, s, 0.5).count() == 0


def test_batch_repair_goes_on_while_moves_gain(spark):
    # twelve members of cluster 0 belong to cluster 1; a round moves one of them
    rows = [(0, i, 50, [0.0], 0.0) for i in range(2)] + [(0, 10 + i, 1, [9.0 + i / 100], 0.0) for i in range(12)] + [(1, 0, 50, [10.0], 0.0)]
    s = spark.createDataFrame(rows, STATS)
    labels = spark.createDataFrame([(r[0], r[1], r[0]) for r in rows], "site int, local_id int, global_id int")
    after, trace = perturb.perturb(perturb.regroup(s, labels), s, border=12, mode="batch")
    assert trace.where("kind = 'move_accept'").count() == 12
    assert sorted(r.n for r in after.collect()) == [62, 100]


def test_repair_never_raises_the_total(spark):
    rng = np.random.default_rng(6)
    x = rng.normal(size=(600, 2)) * 5
    points = spark.createDataFrame([(i % 3, i, v.tolist()) for i, v in enumerate(x)], "site int, point_id long, features array<double>")
    before = vmerge_cluster(points, k_local=8, local="kmeans", border=0)
    start = before.clusters.agg(F.sum("scatter")).first()[0]
    for options in ({"border": 0.5}, {"border": 3, "max_sweeps": 5}, {"border": 0.5, "mode": "batch"}):
        after = vmerge_cluster(points, k_local=8, local="kmeans", **options)
        totals = [r.total_scatter for r in after.trace.orderBy("step").collect()]
        assert all(b <= a + 1e-9 for a, b in zip(totals, totals[1:], strict=False)) and totals[-1] <= start + 1e-9
        assert after.clusters.agg(F.sum("n")).first()[0] == 600
        assert after.clusters.agg(F.sum("scatter")).first()[0] == pytest.approx(totals[-1])
        labelled = label_points(after.labelled, after.labels)
        assert labelled.count() == 600
        within = stats.sub_stats(labelled, by=("global_id",), d=2).agg(F.sum("scatter")).first()[0]
        assert within == pytest.approx(totals[-1])
        assert "BroadcastHashJoin" in labelled._jdf.queryExecution().executedPlan().toString()


def test_local_steps_agree(spark):
    rng = np.random.default_rng(7)
    x = rng.normal(size=(300, 2)) + rng.integers(0, 3, (300, 1)) * 8
    points = spark.createDataFrame([(i % 2, i, v.tolist()) for i, v in enumerate(x)], "site int, point_id long, features array<double>")
    read = lambda d: {r.point_id: r.local_id for r in d.collect()}
    one = read(local.local_cluster(points, 5, iterations=6))
    assert one == read(local.kmeans_multi(points, 5, iterations=6)) == read(local.kmeans_multi(points.repartition(7), 5, iterations=6))
    per_site = local.kmeans_multi(points, {0: 2, 1: 4}, iterations=3).groupBy("site").agg(F.countDistinct("local_id").alias("k")).collect()
    assert {r.site: r.k for r in per_site} == {0: 2, 1: 4}
    for algo in ("bisecting", "grid_density", lambda x, k, i: np.arange(len(x)) % k):
        assert local.local_cluster(points, 4, algo=algo).count() == 300
    with pytest.raises(ValueError):
        local.local_cluster(points, 4, max_site_rows=10)


def test_dirty_and_few_points(spark):
    rows = [(0, 1, [1.0, 2.0]), (0, 2, None), (0, 3, [float("nan"), 1.0]), (0, 4, [None, 1.0]), (1, 5, [3.0, 4.0]), (1, 6, [3.0, 4.0])]
    points = spark.createDataFrame(rows, "site int, point_id long, features array<double>")
    assert stats.clean_points(points).count() == 3
    r = vmerge_cluster(points, k_local=5)
    # identical points: scatter 0, bound 0, and a strict bound merges nothing
    assert r.bound == 0 and r.clusters.count() == r.substats.count() and r.clusters.agg(F.sum("n")).first()[0] == 3


def test_gap_statistic_finds_planted_groups(spark):
    rng = np.random.default_rng(8)
    x = np.concatenate([rng.normal(size=(40, 2)) * 0.3 + c for c in ((0, 0), (10, 0), (0, 10))])
    rng.shuffle(x)
    points = spark.createDataFrame([(0, i, v.tolist()) for i, v in enumerate(x)], "site int, point_id long, features array<double>")
    assert gap.chosen_k(gap.gap_statistic(points, 6)) == {0: 3}


def test_agreement(spark):
    df = spark.createDataFrame([(0, 0)] * 5 + [(1, 1)] * 5, "global_id int, label int")
    assert agreement.purity(df).first()[0] == 1 and agreement.adjusted_rand(df).first()[0] == 1
    mixed = spark.createDataFrame([(i % 2, i // 5) for i in range(10)], "global_id int, label int")
    assert agreement.purity(mixed).first()[0] == 0.6 and agreement.adjusted_rand(mixed).first()[0] < 0.1


def test_remerge_and_nearest(spark):
    s = spark.createDataFrame(HAND, STATS)
    old = merge.merge_subclusters(s, factor=3.0)
    new = spark.createDataFrame([(5, 0, 3, [10.5], 1.0)], STATS)
    assert groups(merge.remerge(old, new, threshold=12.0)) == [(6, 0.3333, 4.3333), (13, 10.5769, 8.4231)]
    near = nearest_center(np.array([[0.0], [10.0]]))
    assert [r[0] for r in s.orderBy("site", "local_id").select(near("center")).collect()] == [0, 1, 0, 1]


def test_assignment_by_matrix_equals_expressions(spark, monkeypatch):
    rng = np.random.default_rng(9)
    points = spark.createDataFrame([(i % 3, i, v.tolist()) for i, v in enumerate(rng.normal(size=(200, 12)))], "site int, point_id long, features array<double>")
    centers = local.first_centers(points, 8)
    by_matrix = local.assign(points, centers)
    assert "MapInArrow" in by_matrix._jdf.queryExecution().executedPlan().toString()
    monkeypatch.setattr(local, "MATRIX_FROM", 10**9)
    by_columns = local.assign(points, centers)
    read = lambda d: {r.point_id: r.local_id for r in d.collect()}
    assert read(by_matrix) == read(by_columns)
