"""The miners against hand counts, each other and brute force."""

from __future__ import annotations

import itertools
import random
from fractions import Fraction

import numpy as np
import pytest
from pyspark.sql import functions as F

from sitemine.functions.itemset_columns import all_subsets, drop_one, register, subsets
from sitemine.operators.itemsets import baskets as B
from sitemine.operators.itemsets import central, frontier, latesync, local, rules, support
from sitemine.operators.itemsets.latesync import global_minimum, latesync_mine
from sitemine.operators.itemsets.levelsync import levelsync_mine

HAND = [(0, i, t) for i, t in enumerate(["abc", "abc", "ab", "cd"])] + [(1, 10 + i, t) for i, t in enumerate(["ad", "bd", "cd", "abc"])]


def rows_of(spark, baskets):
    return spark.createDataFrame([(s, i, c) for s, i, t in baskets for c in t], "site int, tid long, item string")


@pytest.fixture(scope="module")
def hand(spark):
    baskets, dictionary = B.from_rows(rows_of(spark, HAND))
    return baskets.cache(), dictionary


def answer(itemsets, dictionary):
    return {r.itemset: r.support for r in B.named(itemsets, dictionary).collect()}


WANT = {"a": 5, "b": 5, "c": 5, "d": 4, "a|b": 4}


@pytest.mark.parametrize("k", [3, 4])
def test_late_sync_by_hand(hand, k):
    mined = latesync_mine(hand[0], min_support="0.5", k=k)
    assert answer(mined.itemsets, hand[1]) == WANT
    assert [(p["requested"], p["passed"]) for p in mined.passes] == [(5, 4), (3, 1)]
    assert mined.trace().count() == 2


def test_frontiers_by_hand(hand):
    every = latesync_mine(hand[0], min_support="0.5", k=3, frontier="all")
    assert answer(every.itemsets, hand[1]) == WANT and [p["requested"] for p in every.passes] == [8]
    up = latesync_mine(hand[0], min_support="0.5", k=3, frontier="bottom_up")
    assert answer(up.itemsets, hand[1]) == WANT and [p["requested"] for p in up.passes] == [4, 3]
    # the documented loss: d stands under no set of size 3, and with size 4 nothing is asked
    assert answer(latesync_mine(hand[0], min_support="0.5", k=3, frontier="size_k").itemsets, hand[1]) == {k: v for k, v in WANT.items() if k != "d"}
    assert latesync_mine(hand[0], min_support="0.5", k=4, frontier="size_k").itemsets.count() == 0
    with pytest.raises(ValueError):
        frontier.first_frontier(every.local, "sideways", 3)


def test_level_sync_by_hand(hand):
    for pruning in (("local",), ("local", "upper")):
        mined = levelsync_mine(hand[0], min_support="0.5", k=4, pruning=pruning)
        assert answer(mined.itemsets, hand[1]) == WANT and [p["requested"] for p in mined.passes] == [4, 3]


def brute(baskets, share, k):
    least = global_minimum(len(baskets), share)
    counts = {}
    for _, _, t in baskets:
        for z in range(1, k + 1):
            for s in itertools.combinations(sorted(set(t)), z):
                counts["|".join(s)] = counts.get("|".join(s), 0) + 1
    return {s: c for s, c in counts.items() if c >= least}


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_all_miners_agree_on_random_baskets(spark, seed):
    rng = random.Random(seed)
    baskets = []
    for i in range(60):
        site = rng.randrange(4)
        items = "abcdefgh" if site else "abcd"
        baskets.append((site, i, "".join(rng.choices(items, k=rng.randint(1, 6)))))
    share = rng.choice(["0.1", "0.2", "0.3"])
    coded, dictionary = B.from_rows(rows_of(spark, baskets))
    coded = coded.cache()
    want = brute(baskets, share, 4)
    late = latesync_mine(coded, min_support=share)
    assert answer(late.itemsets, dictionary) == want and late.counters["frontier_passes"] <= 4 and late.counters["passes"] <= 5
    asked = [tuple(r.itemset) for r in late.requests.select("itemset", "pass").distinct().collect()]
    assert len(asked) == len(set(asked))
    assert answer(levelsync_mine(coded, min_support=share, pruning=("local", "upper")).itemsets, dictionary) == want
    assert answer(central.central_apriori(coded, 4, share), dictionary) == want
    assert answer(central.central_fpgrowth(coded, 4, share), dictionary) == want
    assert answer(latesync_mine(coded.repartition(7), min_support=share, known_counts=False).itemsets, dictionary) == want


@pytest.mark.parametrize("kind", ["maximal", "all", "bottom_up", "size_k"])
def test_passes_in_one_task_and_by_joins_agree(spark, monkeypatch, kind):
    """Both ways ask the same, and with supports every locally frequent set is asked exactly once."""
    rng = random.Random(7)
    baskets = [(rng.randrange(3), i, "".join(rng.choices("abcdefg" if i % 3 else "abc", k=rng.randint(1, 6)))) for i in range(60)]
    coded, dictionary = B.from_rows(rows_of(spark, baskets))
    coded = coded.cache()
    told = []
    for limit in (latesync.SETTLE_ROWS, 0):
        monkeypatch.setattr(latesync, "SETTLE_ROWS", limit)
        mined = latesync_mine(coded, min_support="0.2", frontier=kind)
        log = sorted((r["pass"], r.site, tuple(r.itemset)) for r in mined.requests.collect())
        told.append((answer(mined.itemsets, dictionary), [(p["kind"], p["requested"], p["passed"]) for p in mined.passes], log))
        assert mined.counters["requested"] == len({(p, s) for p, _, s in log})
        if kind == "maximal":
            everything = {tuple(r.itemset) for r in mined.local.collect()}
            assert {s for _, _, s in log} == everything and mined.counters["requested"] == len(everything)
    assert told[0] == told[1]
    member = latesync_mine(coded, min_support="0.2", frontier=kind, with_support=False)
    assert set(answer(member.itemsets, dictionary)) == set(told[0][0]) and member.counters["support_passes"] == 0
    assert [(p["kind"], p["requested"], p["passed"]) for p in member.passes] == [p for p in told[0][1] if p[0] == "frontier"]


def test_local_sets_by_task_and_by_level_agree(spark, monkeypatch):
    rng = random.Random(8)
    baskets = [(rng.randrange(3), i, "".join(rng.choices("abcdefghij", k=rng.randint(1, 8)))) for i in range(150)]
    coded, _ = B.from_rows(rows_of(spark, baskets))
    coded = coded.cache()
    read = lambda df: {(r.site, tuple(r.itemset), r.size, r.cnt) for r in df.collect()}
    for k in (3, None):
        want = read(local.local_apriori(coded, k, "0.1"))
        assert want and all(len(s) == z for _, s, z, _ in want)
        assert read(local.local_apriori(coded, k, "0.1", engine="expand")) == want == read(local.local_apriori(coded, k, "0.1", engine="bitmap"))
    monkeypatch.setattr(local, "SITE_CANDIDATES", 5)  # too many for a task: the sites are mined level by level
    assert read(local.local_apriori(coded, None, "0.1")) == want
    monkeypatch.setattr(local, "SITE_BASKETS", 5)
    assert read(local.local_apriori(coded, None, "0.1")) == want


def test_bit_columns_in_blocks(monkeypatch):
    rng = np.random.default_rng(9)
    baskets = [np.sort(rng.choice(40, rng.integers(0, 12), replace=False)) for _ in range(3000)]
    offsets = np.concatenate([[0], np.cumsum([len(b) for b in baskets])])
    sets = np.array(sorted(itertools.combinations(range(0, 40, 3), 3)), np.int32)
    want = [sum(set(s) <= set(b.tolist()) for b in baskets) for s in sets.tolist()]
    monkeypatch.setattr(support, "_BLOCK_BASKETS", 700)
    assert support.count_sets(offsets, np.concatenate(baskets), sets).tolist() == want


def test_counting_engines_agree(hand):
    baskets, _ = hand
    sets = baskets.select(F.explode(all_subsets(F.col("items"), 3)).alias("itemset")).distinct()
    by_site = baskets.select("site", F.explode(all_subsets(F.col("items"), 2)).alias("itemset")).distinct()
    read = lambda df: {(r.site, tuple(r.itemset)): r.cnt for r in df.collect()}
    want, want_site = read(support.count_support(baskets, sets, [1, 2, 3])), read(support.count_support(baskets, by_site, [1, 2]))
    for engine in support.ENGINES[1:]:
        assert read(support.count_support(baskets, sets, [1, 2, 3], engine=engine)) == want
        assert read(support.count_support(baskets, by_site, [1, 2], engine=engine)) == want_site
    with pytest.raises(ValueError):
        support.count_support(baskets, sets, [1], engine="guess")


def test_thresholds_are_exact(spark):
    df = spark.createDataFrame([(n,) for n in (1, 9, 10, 11, 30, 1000)], "n long")
    got = [r[0] for r in df.select(B.min_count(F.col("n"), "0.1")).collect()]
    assert got == [1, 1, 1, 2, 3, 100]
    assert global_minimum(30, 0.1) == 3 and global_minimum(7, Fraction(1, 3)) == 3


def test_edges(spark):
    empty, _ = B.from_rows(rows_of(spark, []))
    assert latesync_mine(empty, min_support="0.5").itemsets.count() == 0
    rows = spark.createDataFrame([(0, 1, "a"), (0, 1, "a"), (0, 1, None), (0, 2, "a")], "site int, tid long, item string")
    one, dictionary = B.from_rows(rows)
    assert answer(latesync_mine(one, min_support=1, k=1).itemsets, dictionary) == {"a": 2}
    with pytest.raises(ValueError):
        B.from_rows(rows.drop("tid"))
    with pytest.raises(ValueError):
        local.local_apriori(B.from_rows(rows_of(spark, HAND))[0], 3, "0.1", max_candidates=1)


def test_looser_local_support_stays_complete(hand):
    assert answer(latesync_mine(hand[0], min_support="0.5", local_support="0.25").itemsets, hand[1]) == WANT


def test_dictionary(hand):
    told = {r["item"]: (r.code, r.support) for r in B.item_dictionary(*hand).collect()}
    assert told == {"d": (0, 4), "a": (1, 5), "b": (2, 5), "c": (3, 5)}


def test_views_and_rules(hand):
    mined = latesync_mine(hand[0], min_support="0.375", k=3)
    sets = answer(mined.itemsets, hand[1])
    assert set(sets) == {"a", "b", "c", "d", "a|b", "a|c", "b|c", "a|b|c"}
    assert set(answer(rules.maximal(mined.itemsets), hand[1])) == {"d", "a|b|c"}
    assert set(answer(rules.closed(mined.itemsets), hand[1])) == {"a", "b", "c", "d", "a|b", "a|b|c"}
    found = rules.association_rules(mined.itemsets, 8, 0.7).collect()
    for r in found:
        assert r.confidence >= 0.7 and r.lift == pytest.approx(r.confidence * 8 / 5)
    assert len(found) == 5  # a and b both ways, and any two of a, b, c to the third
    level = {r["size"]: (r.local_sets, r.global_sets) for r in rules.success_by_level(mined.local, mined.itemsets).collect()}
    assert level[1] == (4, 4) and level[3] == (1, 1)
    diff = {r.kind: r.n for r in rules.set_diff(mined.itemsets, mined.itemsets.where("size = 1")).collect()}
    assert diff == {"shared": 4, "missed": 0, "surplus": 4}


def test_array_functions_and_sql(spark):
    df = spark.createDataFrame([([1, 2, 3],)], "items array<int>")
    row = df.select(drop_one(F.col("items")).alias("d"), subsets(F.col("items"), 2).alias("s"), F.size(all_subsets(F.col("items"), 3)).alias("n")).first()
    assert sorted(map(tuple, row.d)) == sorted(map(tuple, row.s)) == [(1, 2), (1, 3), (2, 3)] and row.n == 7
    register(spark)
    df.createOrReplaceTempView("some_baskets")
    assert spark.sql("select itemset from some_baskets, lateral itemset_subsets(items, 2)").count() == 3
    assert len(spark.sql("select drop_one(items) as d from some_baskets").first().d) == 3


def test_plan_has_no_cartesian_product(hand):
    sets = hand[0].select(F.explode(subsets(F.col("items"), 2)).alias("itemset")).distinct()
    plan = support.count_support(hand[0], sets, [2])._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BroadcastHashJoin" in plan
