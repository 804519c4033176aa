"""Queries of the itemset methods, and the SQL that must give the same rows."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sitemine import sites
from sitemine.operators.itemsets import baskets as B
from sitemine.operators.itemsets import central, rules
from sitemine.operators.itemsets.latesync import MineResult, latesync_mine
from sitemine.operators.itemsets.levelsync import levelsync_mine
from sitemine.operators.itemsets.local import local_apriori
from sitemine.session import drop_shared, shared_table
from sitemine.workloads import inputs

Rows = Callable[[SparkSession, str], DataFrame]


def _named(itemsets: DataFrame, dictionary: DataFrame) -> DataFrame:
    return B.named(itemsets.select("itemset", F.col("size").cast("long").alias("size"), "support"), dictionary).select("itemset", "size", "support")


def late(rows: Rows, share: str, **options) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        baskets, dictionary = B.from_rows(rows(spark, sf_dir))
        return _named(latesync_mine(baskets, min_support=share, **options).itemsets, dictionary)

    return query


def level(rows: Rows, share: str, **options) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        baskets, dictionary = B.from_rows(rows(spark, sf_dir))
        return _named(levelsync_mine(baskets, min_support=share, **options).itemsets, dictionary)

    return query


def whole(rows: Rows, share: str, miner: Callable[..., DataFrame], k: int | None = 4) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        baskets, dictionary = B.from_rows(rows(spark, sf_dir))
        return _named(miner(baskets, k, share), dictionary)

    return query


def local_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    baskets, dictionary = B.from_rows(inputs.brand_rows(spark, sf_dir))
    found = local_apriori(baskets, 4, "0.005")
    return B.named(found, dictionary).select(F.col("site").cast("long").alias("site"), "itemset", F.col("size").cast("long").alias("size"), "cnt")


def site_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of locally frequent sets by site and size, with totals."""
    found = local_sets(spark, sf_dir)
    totals = found.rollup("site", "size").agg(F.count("*").alias("n_sets"), F.sum("cnt").alias("n_counts"), F.grouping_id().cast("long").alias("level"))
    return totals.withColumns({c: F.coalesce(c, F.lit(-1)) for c in ("site", "size")})


def _mined(spark: SparkSession, sf_dir: str) -> tuple[MineResult, DataFrame]:
    baskets, dictionary = B.from_rows(inputs.brand_rows(spark, sf_dir))
    return latesync_mine(baskets, min_support="0.005"), dictionary


def success(spark: SparkSession, sf_dir: str) -> DataFrame:
    mined, _ = _mined(spark, sf_dir)
    return rules.success_by_level(mined.local, mined.itemsets).withColumn("size", F.col("size").cast("long"))


def maximal_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    mined, dictionary = _mined(spark, sf_dir)
    return _named(rules.maximal(mined.itemsets), dictionary)


def closed_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    mined, dictionary = _mined(spark, sf_dir)
    return _named(rules.closed(mined.itemsets), dictionary)


def brand_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    mined, dictionary = _mined(spark, sf_dir)
    found = rules.association_rules(mined.itemsets, mined.counters["baskets"], 0.1)
    sides = B.named(B.named(found, dictionary, "antecedent"), dictionary, "consequent")
    return sides.select("antecedent", "consequent", "support", F.round("confidence", 6).alias("confidence"), F.round("lift", 6).alias("lift"))


def top_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The five best supported sets of each size (a report)."""
    mined, dictionary = _mined(spark, sf_dir)
    rank = F.row_number().over(Window.partitionBy("size").orderBy(F.desc("support"), "itemset"))
    return _named(mined.itemsets, dictionary).withColumn("place", rank.cast("long")).where("place <= 5")


#: What both miners are held to: the frequent sets alone, or with their supports.
OUTPUTS = ("sets", "supports")


def _asked(mined: MineResult, output: str) -> tuple[int, int, int, int]:
    """Passes, distinct sets asked, and the messages and bytes of asking every other site and being answered."""
    last = mined.counters["passes"] if output == "supports" else mined.counters.get("frontier_passes", mined.counters["passes"])
    others = mined.counters["sites"] - 1
    log = mined.requests.where(F.col("pass") <= last)
    asks, size = log.agg(F.count("*"), F.coalesce(F.sum(F.size("itemset") * 4 + 8), F.lit(0))).first()
    return last, sum(p["requested"] for p in mined.passes[:last]), 2 * others * asks, others * size


_COSTS = "passes long, requested long, messages long, bytes long"


def passes_by_frontier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Passes, requests and messages of every frontier and of the baseline on the dense workload, by what is asked for."""
    baskets, _ = B.from_rows(inputs.attribute_rows(spark, sf_dir))
    found = {f"late-{kind}": latesync_mine(baskets, min_support="0.1", frontier=kind) for kind in ("maximal", "all", "bottom_up")}
    found["level"] = levelsync_mine(baskets, min_support="0.1")
    out = [(name, output, *_asked(mined, output)) for name, mined in found.items() for output in OUTPUTS]
    return spark.createDataFrame(out, f"method string, output string, {_COSTS}")


SITE_COUNTS = (1, 2, 5, 20, 200)


def process_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Passes, requests and messages of both miners against the number of sites, and how many locally frequent sets are so globally."""
    out = []
    for n in SITE_COUNTS:
        baskets, _ = B.from_rows(inputs.brand_rows(spark, sf_dir, sites.by_hash(F.col("l_orderkey"), n)))
        found = {"late": latesync_mine(baskets, min_support="0.005"), "level": levelsync_mine(baskets, min_support="0.005")}
        n_local, n_global = found["late"].local.select("itemset").distinct().count(), found["late"].itemsets.count()
        out += [(n, name, output, *_asked(mined, output), n_local, n_global) for name, mined in found.items() for output in OUTPUTS]
    return spark.createDataFrame(out, f"sites long, method string, output string, {_COSTS}, local_sets long, global_sets long")


SIZES = (1, 2, 3, 4, 5, 6)


def size_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Passes, requests and messages of both miners against the largest size asked for."""
    baskets, _ = B.from_rows(inputs.brand_rows(spark, sf_dir))
    out = []
    for k in SIZES:
        for name, miner in (("late", latesync_mine), ("level", levelsync_mine)):
            mined = miner(baskets, min_support="0.005", k=k)
            out += [(k, name, output, *_asked(mined, output)) for output in OUTPUTS]
    return spark.createDataFrame(out, f"k long, method string, output string, {_COSTS}")


def gain_by_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of both miners against the largest size asked for, and the late one's gain (after a warm run)."""
    baskets, _ = B.from_rows(inputs.attribute_rows(spark, sf_dir))
    baskets, path = shared_table(baskets)
    latesync_mine(baskets, min_support="0.05", k=2)
    out = []
    for k in SIZES:
        took = []
        for miner in (latesync_mine, levelsync_mine):
            began = time.perf_counter()
            miner(baskets, min_support="0.05", k=k)
            took.append(time.perf_counter() - began)
        out.append((k, *took, 1 - took[0] / took[1]))
    drop_shared(spark, path)
    return spark.createDataFrame(out, "k long, late_seconds double, level_seconds double, gain double")


def stricter_local(spark: SparkSession, sf_dir: str) -> DataFrame:
    """With a local bound above the global one sets are lost: those frequent in all, and those found, by size."""
    baskets, _ = B.from_rows(inputs.brand_rows(spark, sf_dir))
    truth = latesync_mine(baskets, min_support="0.005").itemsets
    found = latesync_mine(baskets, min_support="0.005", local_support="0.01").itemsets.select("itemset", F.lit(1).alias("hit"))
    both = truth.join(found, "itemset", "left").groupBy("size").agg(F.count("*").alias("frequent"), F.count("hit").alias("found"))
    return both.withColumn("size", F.col("size").cast("long"))


def accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Late-sync, level-sync and FP-growth sets against central Apriori: shared, missed, surplus."""
    baskets, _ = B.from_rows(inputs.brand_rows(spark, sf_dir))
    truth = central.central_apriori(baskets, 4, "0.005")
    found = {
        "late": latesync_mine(baskets, min_support="0.005").itemsets,
        "level": levelsync_mine(baskets, min_support="0.005").itemsets,
        "level_upper": levelsync_mine(baskets, min_support="0.005", pruning=("local", "upper")).itemsets,
        "fpgrowth": central.central_fpgrowth(baskets, 4, "0.005"),
    }
    out = None
    for name, sets in found.items():
        row = rules.set_diff(sets, truth).select(F.lit(name).alias("method"), "kind", F.col("n").cast("long").alias("n"))
        out = row if out is None else out.union(row)
    return out


def _count_sql(share: str, total: str) -> str:
    f = B.as_fraction(share)
    return f"count(*) * {f.denominator} >= {f.numerator} * {total}"


def itemset_sql(rows: str, share: str, k: int = 4) -> str:
    """DuckDB: globally frequent itemsets by self-joins of the frequent items' rows."""
    test = _count_sql(share, "(select n from n)")
    levels = []
    for z in range(1, k + 1):
        names = [f"x{i}" for i in range(1, z + 1)]
        source = "x x1 " + " ".join(f"join x {b} on {a}.tid = {b}.tid and {a}.item < {b}.item" for a, b in zip(names, names[1:], strict=False))
        text = " || '|' || ".join(f"{n}.item" for n in names)
        levels.append(f"select {text} as itemset, {z}::bigint as size, count(*)::bigint as support from {source} group by {', '.join(f'{n}.item' for n in names)} having {test}")
    return f"""with b as (select distinct tid, item from ({rows}) where item is not null),
n as (select count(distinct tid) as n from b),
x as (select * from b where item in (select item from b group by item having {test}))
{" union all ".join(levels)}"""


def local_sql(rows: str, share: str, k: int = 4) -> str:
    """DuckDB: locally frequent itemsets of every site."""
    f = B.as_fraction(share)
    levels = []
    for z in range(1, k + 1):
        names = [f"x{i}" for i in range(1, z + 1)]
        source = "x x1 " + " ".join(f"join x {b} on {a}.site = {b}.site and {a}.tid = {b}.tid and {a}.item < {b}.item" for a, b in zip(names, names[1:], strict=False))
        text = " || '|' || ".join(f"{n}.item" for n in names)
        levels.append(
            f"select x1.site::bigint as site, {text} as itemset, {z}::bigint as size, count(*)::bigint as cnt from {source} join n on n.site = x1.site"
            f" group by x1.site, n.n, {', '.join(f'{n}.item' for n in names)} having count(*) * {f.denominator} >= {f.numerator} * n.n"
        )
    return f"""with b as (select distinct site, tid, item from ({rows}) where item is not null),
n as (select site, count(distinct tid) as n from b group by site),
x as (select b.* from b join (select b.site, item from b join n on n.site = b.site group by b.site, item, n.n having count(*) * {f.denominator} >= {f.numerator} * n.n) using (site, item))
{" union all ".join(levels)}"""


def log_sql(rows: str, share: str, k: int = 4) -> str:
    """DuckDB: (method, pass, kind, site, s, z), a row for each set that a site asks for in a pass, from local and global sets."""
    part = "array_to_string(list_filter(l, lambda x, j: j <> i), '|')"
    ctes = [
        f"loc as materialized (select site, itemset as s, size as z from ({local_sql(rows, share, k)}))",
        f"everywhere as materialized (select itemset as s from ({itemset_sql(rows, share, k)}))",
        "u as materialized (select distinct s, z, string_split(s, '|') as l from loc)",
        f"part as materialized (select s, {part} as t from (select s, l, unnest(range(1, z + 1)) as i from u where z > 1))",
        "sub1 as (select s, s as t from u)",
    ]
    ctes += [f"sub{i + 1} as (select distinct a.s, p.t from sub{i} a join part p on p.s = a.t)" for i in range(1, k)]
    ctes.append("sub as materialized (" + " union ".join(f"select * from sub{i}" for i in range(1, k + 1)) + ")")
    ctes.append("f1 as materialized (select site, s from loc where (site, s) not in (select l.site, p.t from loc l join part p on p.s = l.s))")
    for p in range(1, k + 1):
        ctes.append(f"a{p} as materialized (" + " union ".join(f"select s from f{i}" for i in range(1, p + 1)) + ")")
        ctes.append(f"c{p} as materialized (select distinct t as s from sub where s in (select s from a{p}) and s in (select s from everywhere))")
        ctes.append(
            f"f{p + 1} as materialized (select distinct f.site, p.t as s from f{p} f join part p on p.s = f.s where f.s not in (select s from everywhere)"
            f" and p.t not in (select s from c{p}) and p.t not in (select s from a{p}))"
        )
    logs = [f"select 'late' as method, {p} as pass, 'frontier' as kind, site, s from f{p}" for p in range(1, k + 1)]
    last = " + ".join(f"(select (count(*) > 0)::int from f{p})" for p in range(1, k + 1))
    logs.append(f"select 'late', {last} + 1, 'support', site, s from loc where s in (select s from c{k}) and s not in (select s from a{k})")
    logs.append("select 'level', z, 'frontier', site, s from loc l where not exists (select 1 from part p where p.s = l.s and p.t not in (select s from everywhere))")
    logs.append("select 'late-all', 1, 'frontier', site, s from loc")
    ctes.append("log as materialized (" + " union all ".join(logs) + ")")
    return f"with {', '.join(ctes)} select method, pass::bigint as pass, kind, site, s, len(string_split(s, '|'))::bigint as z from log"


def asked_sql(rows: str, share: str, n_sites: int, k: int = 4, names: dict[str, str] | None = None) -> str:
    """DuckDB: what ``_asked`` says of both miners, by output; ``names``: other names of methods, and methods that ask alike."""
    names = names or {"late": "late", "level": "level"}
    shown = " union all ".join(f"select '{name}' as method, '{of}' as of" for name, of in names.items())
    return f"""select m.method, o.output, count(distinct pass)::bigint as passes, count(distinct (pass, s))::bigint as requested,
        (2 * {n_sites - 1} * count(*))::bigint as messages, ({n_sites - 1} * sum(4 * z + 8))::bigint as bytes
        from ({shown}) m, (select unnest(['sets', 'supports']) as output) o, ({log_sql(rows, share, k)}) l
        where l.method = m.of and (o.output = 'supports' or l.kind = 'frontier') group by m.method, o.output"""


_W1 = itemset_sql(inputs.BRAND_SQL, "0.005")
_LOCAL = local_sql(inputs.BRAND_SQL, "0.005")
_BELOW = "len(string_split({a}, '|')) = len(string_split({b}, '|')) + 1 and len(list_filter(string_split({b}, '|'), lambda i: not list_contains(string_split({a}, '|'), i))) = 0"

QUERIES = {
    "itemsets_attrs": late(inputs.attribute_rows, "0.05"),
    "itemsets_brand": late(inputs.brand_rows, "0.005"),
    "itemsets_brand_region": late(inputs.brand_rows_by_region, "0.005"),
    "itemsets_brand_rare": late(inputs.brand_rows, "0.02"),
    "itemsets_attrs_switch": late(inputs.attribute_rows, "0.1"),
    "itemsets_words": late(lambda s, d: inputs.word_rows(s, d), "0.55"),
    "itemsets_words_lang": late(lambda s, d: inputs.word_rows(s, d, "lang"), "0.55"),
    "itemsets_words_source": late(lambda s, d: inputs.word_rows(s, d, "source"), "0.55"),
    "itemsets_userday": late(inputs.user_day_rows, "0.1"),
    "itemsets_tags": late(inputs.tag_rows, "0.5"),
    "itemsets_chats": late(inputs.chat_rows, "0.4"),
    "itemsets_benchmark": late(inputs.benchmark_rows, "0.3"),
    "itemsets_classes": late(inputs.class_rows, "0.05"),
    "itemsets_brand_loose_local": late(inputs.brand_rows, "0.02", local_support="0.015"),
    "frontier_all_brand": late(inputs.brand_rows, "0.02", frontier="all"),
    "frontier_bottom_up_brand": late(inputs.brand_rows, "0.02", frontier="bottom_up"),
    "frontier_size_k_attrs": late(inputs.attribute_rows, "0.05", frontier="size_k"),
    "counting_extend_brand": late(inputs.brand_rows, "0.02", engine="extend"),
    "counting_trie_brand": late(inputs.brand_rows, "0.02", engine="trie"),
    "counting_contains_attrs": late(inputs.attribute_rows, "0.1", engine="contains"),
    "counting_bitmap_attrs": late(inputs.attribute_rows, "0.1", engine="bitmap"),
    "counting_expand_attrs": late(inputs.attribute_rows, "0.1", engine="expand"),
    "counting_scan_all_brand": late(inputs.brand_rows, "0.02", known_counts=False),
    "levelsync_brand": level(inputs.brand_rows, "0.005"),
    "levelsync_attrs": level(inputs.attribute_rows, "0.05"),
    "levelsync_words": level(lambda s, d: inputs.word_rows(s, d), "0.55"),
    "levelsync_upper_brand": level(inputs.brand_rows, "0.005", pruning=("local", "upper")),
    "levelsync_all_sizes_brand": level(inputs.brand_rows, "0.02", k=None),
    "central_brand": whole(inputs.brand_rows, "0.005", central.central_apriori),
    "fpgrowth_brand": whole(inputs.brand_rows, "0.005", central.central_fpgrowth),
    "local_itemsets_brand": local_sets,
    "site_rollup": site_rollup,
    "success_by_level": success,
    "maximal_sets": maximal_sets,
    "closed_sets": closed_sets,
    "rules_brand": brand_rules,
    "top_sets": top_sets,
    "passes_by_frontier": passes_by_frontier,
    "process_sweep": process_sweep,
    "size_sweep": size_sweep,
    "gain_by_size": gain_by_size,
    "stricter_local_misses": stricter_local,
    "itemset_accuracy": accuracy,
}

_RARE = itemset_sql(inputs.BRAND_SQL, "0.02")
ORACLES = {
    "itemsets_attrs": itemset_sql(inputs.ATTRIBUTE_SQL, "0.05"),
    "itemsets_brand": _W1,
    "itemsets_brand_region": itemset_sql(inputs.REGION_SQL, "0.005"),
    "itemsets_brand_rare": _RARE,
    "itemsets_attrs_switch": itemset_sql(inputs.ATTRIBUTE_SQL, "0.1"),
    "itemsets_words": itemset_sql(inputs.word_sql("hash"), "0.55"),
    "itemsets_words_lang": itemset_sql(inputs.word_sql("lang"), "0.55"),
    "itemsets_words_source": itemset_sql(inputs.word_sql("source"), "0.55"),
    "itemsets_userday": itemset_sql(inputs.USER_DAY_SQL, "0.1"),
    "itemsets_tags": itemset_sql(inputs.TAG_SQL, "0.5"),
    "itemsets_chats": itemset_sql(inputs.CHAT_SQL, "0.4"),
    "itemsets_benchmark": itemset_sql(inputs.BENCHMARK_SQL, "0.3"),
    "itemsets_classes": itemset_sql(inputs.CLASS_SQL, "0.05"),
    "itemsets_brand_loose_local": _RARE,
    "frontier_all_brand": _RARE,
    "frontier_bottom_up_brand": _RARE,
    "frontier_size_k_attrs": itemset_sql(inputs.ATTRIBUTE_SQL, "0.05"),
    "counting_extend_brand": _RARE,
    "counting_trie_brand": _RARE,
    "counting_contains_attrs": itemset_sql(inputs.ATTRIBUTE_SQL, "0.1"),
    "counting_scan_all_brand": _RARE,
    "counting_bitmap_attrs": itemset_sql(inputs.ATTRIBUTE_SQL, "0.1"),
    "counting_expand_attrs": itemset_sql(inputs.ATTRIBUTE_SQL, "0.1"),
    "levelsync_attrs": itemset_sql(inputs.ATTRIBUTE_SQL, "0.05"),
    "levelsync_words": itemset_sql(inputs.word_sql("hash"), "0.55"),
    "passes_by_frontier": asked_sql(inputs.ATTRIBUTE_SQL, "0.1", 5, names={"late-maximal": "late", "late-all": "late-all", "late-bottom_up": "level", "level": "level"}),
    "process_sweep": " union all ".join(
        f"""select {n}::bigint as sites, a.*, u.local_sets, g.global_sets from ({asked_sql(inputs.brand_sql(n), "0.005", n)}) a,
        (select count(distinct itemset)::bigint as local_sets from ({local_sql(inputs.brand_sql(n), "0.005")})) u, (select count(*)::bigint as global_sets from ({_W1})) g"""
        for n in SITE_COUNTS
    ),
    "size_sweep": " union all ".join(f"select {k}::bigint as k, a.* from ({asked_sql(inputs.BRAND_SQL, '0.005', 5, k)}) a" for k in SIZES),
    "stricter_local_misses": f"""with l as materialized ({local_sql(inputs.BRAND_SQL, "0.01")}), w as ({_W1})
        select size, count(*)::bigint as frequent, (count(*) filter (where itemset in (select itemset from l)))::bigint as found from w group by size""",
    "levelsync_brand": _W1,
    "levelsync_upper_brand": _W1,
    "levelsync_all_sizes_brand": _RARE,
    "central_brand": _W1,
    "fpgrowth_brand": _W1,
    "local_itemsets_brand": _LOCAL,
    "site_rollup": f"""select coalesce(site, -1) as site, coalesce(size, -1) as size, count(*)::bigint as n_sets, sum(cnt)::bigint as n_counts, grouping(site, size)::bigint as level
        from ({_LOCAL}) group by rollup (site, size)""",
    "success_by_level": f"""select size, count(distinct l.itemset)::bigint as local_sets, count(distinct g.itemset)::bigint as global_sets,
        round(count(distinct g.itemset) / count(distinct l.itemset)::double, 6) as rate
        from ({_LOCAL}) l left join ({_W1}) g using (itemset, size) group by size""",
    "maximal_sets": f"with w as materialized ({_W1}) select * from w where not exists (select 1 from w v where v.size = w.size + 1 and {_BELOW.format(a='v.itemset', b='w.itemset')})",
    "closed_sets": f"with w as materialized ({_W1}) select * from w where not exists (select 1 from w v where v.size = w.size + 1 and v.support = w.support and {_BELOW.format(a='v.itemset', b='w.itemset')})",
    "rules_brand": f"""with w as materialized ({_W1}), n as (select count(distinct l_orderkey) as n from lineitem),
        s as (select f.support, a.itemset as antecedent, a.support as na,
               array_to_string(list_filter(string_split(f.itemset, '|'), lambda i: not list_contains(string_split(a.itemset, '|'), i)), '|') as consequent
        from w f join w a on a.size < f.size and len(list_filter(string_split(a.itemset, '|'), lambda i: not list_contains(string_split(f.itemset, '|'), i))) = 0)
        select antecedent, consequent, s.support, round(s.support / na::double, 6) as confidence, round(s.support / na::double * n / c.support, 6) as lift
        from s join w c on c.itemset = s.consequent cross join n where s.support / na::double >= 0.1""",
    "top_sets": f"select *, row_number() over (partition by size order by support desc, itemset)::bigint as place from ({_W1}) qualify place <= 5",
    "itemset_accuracy": f"""with w as ({_W1}) select m as method, k as kind, case when k = 'shared' then (select count(*) from w) else 0 end::bigint as n
        from (select unnest(['late', 'level', 'level_upper', 'fpgrowth']) as m), (select unnest(['shared', 'missed', 'surplus']) as k)""",
}
