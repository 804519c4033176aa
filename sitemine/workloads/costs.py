"""Queries of the cost measures, the stream operators' batch forms and the SQL surface."""

from __future__ import annotations

import time
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sitemine import sites
from sitemine.functions import itemset_columns
from sitemine.operators.clustering.local import kmeans_multi
from sitemine.operators.clustering.pipeline import vmerge_cluster
from sitemine.operators.clustering.stats import sub_stats
from sitemine.operators.itemsets import baskets as B
from sitemine.operators.itemsets.latesync import latesync_mine
from sitemine.operators.itemsets.levelsync import levelsync_mine
from sitemine.operators.itemsets.views import mine_view
from sitemine.plans import cost
from sitemine.session import drop_shared, ensure_checkpoint_dir, table
from sitemine.sources import gaussian
from sitemine.streaming import baskets as S
from sitemine.workflow.dag import Dag
from sitemine.workloads import inputs
from sitemine.workloads.clustering import _kmeans_sql
from sitemine.workloads.itemsets import OUTPUTS, itemset_sql, log_sql

def _line_traffic(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(pass, src, dst, bytes): order lines sent from their supplier's site to their order's, eight bytes a unit, a pass a line number."""
    lines = table(spark, sf_dir, "lineitem").select("l_linenumber", "l_suppkey", "l_orderkey", "l_quantity")
    ends = lines.select(
        F.col("l_linenumber").alias("pass"), (sites.by_hash(F.col("l_suppkey"), inputs.SITES) + 1).alias("src"), (sites.by_hash(F.col("l_orderkey"), inputs.SITES) + 1).alias("dst"), "l_quantity"
    )
    return ends.where("src <> dst").groupBy("pass", "src", "dst").agg((F.sum("l_quantity") * 8).cast("long").alias("bytes"))


def worst_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The slowest link's transfer time for what each pass of order lines sends."""
    sent = _line_traffic(spark, sf_dir)
    worst = cost.worst_transfer(sent, cost.links(spark)).join(sent.groupBy("pass").agg(F.sum("bytes").alias("bytes")), "pass")
    return worst.select(F.col("pass").cast("long").alias("pass"), "bytes", F.round("seconds", 6).alias("seconds"))


def _line_times(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(run, stage, process, seconds) of task-like times made from order lines: a run a return flag, a stage a line number, a process a site, a second a unit."""
    lines = table(spark, sf_dir, "lineitem").select("l_returnflag", "l_linenumber", "l_orderkey", "l_quantity")
    keys = [F.col("l_returnflag").alias("run"), F.col("l_linenumber").cast("string").alias("stage"), sites.by_hash(F.col("l_orderkey"), inputs.SITES).alias("process")]
    return lines.groupBy(*keys).agg(F.sum("l_quantity").alias("seconds"))


def _line_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(task, measured, estimated): a run's seconds when one process works after the other, and by the stage-max model of all at once."""
    times = _line_times(spark, sf_dir)
    one = times.groupBy("run").agg(F.sum("seconds").alias("measured"))
    return one.join(cost.stagemax(times), "run").select(F.col("run").alias("task"), "measured", F.col("est_seconds").alias("estimated"))


def overheads(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What of each run of order lines the model does not explain."""
    return _line_runs(spark, sf_dir).withColumn("overhead", F.round(cost.overhead(F.col("estimated"), F.col("measured")), 6))


def gains(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The gain of the run of lines sent back over the run of lines kept, measured and modelled."""
    kinds = F.array(*[F.struct(F.lit(k).alias("kind"), F.col(c).alias("seconds")) for k, c in (("measured", "measured"), ("modelled", "estimated"))])
    of = lambda flag: F.max(F.when(F.col("task") == flag, F.col("seconds")))
    runs = _line_runs(spark, sf_dir).select("task", F.explode(kinds).alias("of")).select("task", "of.*")
    return runs.groupBy("kind").agg(F.round(cost.gain(of("R"), of("N")), 6).alias("gain"))


def stage_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parallel stages of both miners for every size of basket among the orders: sets can be as large as that."""
    baskets = table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("k"))
    level, late = cost.stage_count("levelsync", F.col("k")), F.lit(cost.stage_count("latesync", 0, 2)).cast("long")
    return baskets.select("k").distinct().select("k", level.alias("levelsync"), late.alias("latesync"))


def stagemax_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The model over task-like times made from order lines: stage is the line number, process the site."""
    lines = table(spark, sf_dir, "lineitem").select("l_linenumber", "l_orderkey", "l_quantity")
    times = lines.groupBy(F.col("l_linenumber").cast("string").alias("stage"), F.pmod("l_orderkey", F.lit(5)).cast("int").alias("process")).agg(F.sum("l_quantity").alias("seconds"))
    return cost.stagemax(times.withColumn("run", F.lit("w1")), 0.5).select("run", F.round("est_seconds", 4).alias("est_seconds"))


def miner_traffic(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Requests, message rows and bytes of both miners by output, every site asking every other, with the worst transfers."""
    return _traffic(spark, sf_dir, "none")


def miner_traffic_polled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same by polling sites."""
    return _traffic(spark, sf_dir, "hash")


def _traffic(spark: SparkSession, sf_dir: str, polling: str) -> DataFrame:
    baskets, _ = B.from_rows(inputs.attribute_rows(spark, sf_dir))
    everyone = spark.createDataFrame([(i,) for i in range(5)], "site int")
    shift = cost.links(spark).select((F.col("src") - 1).alias("src"), (F.col("dst") - 1).alias("dst"), "mbit_s", "latency_ms")
    out = []
    for name, miner in (("late", latesync_mine), ("level", levelsync_mine)):
        mined = miner(baskets, min_support="0.1")
        for output in OUTPUTS:
            last = mined.counters["passes"] if output == "supports" else mined.counters.get("frontier_passes", mined.counters["passes"])
            sent = cost.traffic(mined.requests.where(F.col("pass") <= last), everyone, polling=polling)
            total = sent.agg(F.sum("rows").alias("rows"), F.sum("bytes").alias("bytes")).first()
            seconds = cost.worst_transfer(sent, shift).agg(F.sum("seconds")).first()[0]
            out.append((name, output, last, sum(p["requested"] for p in mined.passes[:last]), total.rows, total.bytes, round(seconds, 6)))
    return spark.createDataFrame(out, "miner string, output string, passes long, requested long, messages long, bytes long, transfer_seconds double")


def _runs(spark: SparkSession, sf_dir: str) -> list[tuple[str, float, DataFrame]]:
    """(task, wall seconds, task times) of each method on its workload."""
    baskets, _ = B.from_rows(inputs.brand_rows(spark, sf_dir))
    out = []
    for name, miner in (("latesync", latesync_mine), ("levelsync", levelsync_mine)):
        began = time.perf_counter()
        counters = miner(baskets, min_support="0.005").counters
        out.append((name, time.perf_counter() - began, cost.observed_times(spark, name, counters["groups"])))
    gaussian.register(spark)
    group = f"clustering:{uuid.uuid4().hex[:8]}"
    began = time.perf_counter()
    with cost.stage(spark, group):
        found = vmerge_cluster(spark.read.format("gaussian_mixture").option("points", 1200).load(), k_local=20)
        found.clusters.count()
    out.append(("clustering", time.perf_counter() - began, cost.observed_times(spark, "clustering", {"all": group})))
    return out


def model_against_run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each method's run here against the stage-max model of its own tasks, beside the published pair.

    ``compute_share`` is the modelled part of the run, ``remote_share`` the part of all task
    seconds that counting for other sites took.
    """
    published = {name: (measured, estimated) for name, measured, estimated in cost.BASELINE}
    out = []
    for name, wall, times in _runs(spark, sf_dir):
        estimate = cost.stagemax(times).first().est_seconds
        remote = cost.share(times, "remote").first().share
        measured, modelled = published[name]
        out.append((name, round(wall, 3), round(estimate, 3), round(cost.overhead(estimate, wall), 4), round(cost.compute_share(estimate, 0.0, wall), 4), round(remote, 4), round(cost.overhead(modelled, measured), 4)))
    return spark.createDataFrame(out, "task string, measured double, estimated double, overhead double, compute_share double, remote_share double, published_overhead double")


def model_holds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What must hold of any run against its model: no stage beyond the run, shares of stages that add up to one."""
    out = []
    for name, wall, times in _runs(spark, sf_dir):
        longest = times.groupBy("stage").agg(F.max("seconds").alias("s")).agg(F.max("s")).first()[0]
        parts = times.groupBy(F.split("stage", ":")[0].alias("part")).agg(F.sum("seconds").alias("s")).collect()
        total = times.agg(F.sum("seconds")).first()[0]
        out.append((name, longest <= wall, abs(sum(r.s for r in parts) / total - 1) < 1e-9))
    return spark.createDataFrame(out, "task string, stages_within_run boolean, shares_add_up boolean")


def time_shares(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of both miners by part, and what remote counting takes of the whole."""
    baskets, _ = B.from_rows(inputs.brand_rows(spark, sf_dir))
    out = []
    for name, miner in (("late", latesync_mine), ("level", levelsync_mine)):
        seconds = miner(baskets, min_support="0.005").counters["seconds"]
        total = sum(seconds.values())
        out += [(name, part, round(s, 4), round(s / total, 4)) for part, s in sorted(seconds.items())]
    return spark.createDataFrame(out, "miner string, part string, seconds double, share double")


def workflow_latency(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of an empty job and of a workflow of two jobs over the orders, launch to first job and in all."""
    ensure_checkpoint_dir(spark)
    path = f"{spark.sparkContext.getCheckpointDir()}/workflow-{uuid.uuid4().hex}"
    began = time.time()
    spark.range(1).count()
    empty = time.time() - began
    began = time.time()
    first = lambda s: table(s, sf_dir, "orders").groupBy("o_orderpriority").agg(F.count_distinct("o_custkey").alias("customers"), F.sum("o_totalprice").alias("price"))
    dag = Dag(path).add("first", first).add("second", lambda s, first: first.groupBy().agg(F.sum("customers"), F.sum("price")), after=["first"])
    _, info = dag.run(spark)
    rows = [("empty_job", empty), ("workflow_to_first_job", info.times["first"][0] - began), ("workflow", time.time() - began)]
    drop_shared(spark, path)
    return spark.createDataFrame(rows, "what string, seconds double")


def sql_mining(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The miner from a view to a view, for use from SQL."""
    inputs.attribute_rows(spark, sf_dir).createOrReplaceTempView("attribute_rows")
    mine_view(spark, "attribute_rows", "attribute_sets", k=4, min_support="0.1")
    return spark.sql("select size, count(*) as n, max(support) as top from attribute_sets group by size")


def clustering_traffic(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the sites send to the merging site, and the choice of that site."""
    s = sub_stats(kmeans_multi(inputs.part_points(spark, sf_dir), 4, iterations=2), d=2)
    sent = s.groupBy((F.col("site") + 1).alias("site")).agg(F.sum((F.size("center") + 2) * 8).cast("long").alias("bytes"))
    chosen = cost.choose_aggregator(cost.links(spark), sent)
    return cost.cluster_traffic(s.withColumn("site", F.col("site") + 1), chosen).select("src", "dst", "rows", "bytes")


def tumbling_support(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.stream_support(table(spark, sf_dir, "events"))


def sliding_support(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.stream_support(table(spark, sf_dir, "events"), "1 day", "6 hours")


def tumbling_baskets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.stream_baskets(table(spark, sf_dir, "events")).select("start", "user_id", F.array_join("items", "|").alias("items"))


def session_baskets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.session_baskets(table(spark, sf_dir, "events")).select("start", "end", "user_id", F.array_join("items", "|").alias("items"), "n")


def json_props(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.item_of(table(spark, sf_dir, "events")).groupBy("k").agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(
        F.col("k").cast("long").alias("k"), "n", F.round("total", 4).alias("total")
    )


def replayed_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = table(spark, sf_dir, "events")
    again = events.union(events.where(F.col("event_id") % 3 == 0))
    return S.deduplicated(again).groupBy("event_type").agg(F.count("*").alias("n"))


def subsets_in_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The table function and the SQL functions, from SQL."""
    itemset_columns.register(spark)
    cost.register_functions(spark)
    baskets, _ = B.from_rows(inputs.attribute_rows(spark, sf_dir))
    baskets.createOrReplaceTempView("sitemine_baskets")
    return spark.sql(
        "select size(itemset) as z, count(*) as n, sum(size(drop_one(itemset))) as parts, round(max(transfer_seconds(size(itemset) * 1000, 12.71, 19)), 6) as worst "
        "from sitemine_baskets, lateral itemset_subsets(items, 2) group by 1"
    ).select(F.col("z").cast("long").alias("z"), "n", "parts", "worst")


def link_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bandwidths as a matrix of sites, as the order lines' traffic gets them: what a link carries in all over its time for it, in Mb/s."""
    sent = _line_traffic(spark, sf_dir).groupBy("src", "dst").agg(F.sum("bytes").alias("bytes"))
    seconds = cost.transfer_seconds(F.col("bytes"), F.col("mbit_s"), F.col("latency_ms"))
    got = sent.join(F.broadcast(cost.links(spark)), ["src", "dst"]).withColumn("mbit_s", F.col("bytes") * 8 / 1_000_000 / seconds)
    wide = got.groupBy(F.col("src").cast("long").alias("src")).pivot("dst", [1, 2, 3, 4, 5]).agg(F.first("mbit_s"))
    return wide.select("src", *[F.coalesce(F.round(F.col(str(i)), 6), F.lit(-1.0)).alias(f"to_{i}") for i in range(1, 6)])


_ITEM = "event_type || case when value > 20 then '+' else '-' end"
_LINK_VALUES = ", ".join(f"({a}, {b}, {m}, {ms})" for a, to in cost._LINKS.items() for b, (m, ms) in to.items())

QUERIES = {
    "link_worst_transfer": worst_links,
    "link_matrix": link_matrix,
    "overhead_table": overheads,
    "gain_table": gains,
    "stage_counts": stage_counts,
    "stagemax_model": stagemax_model,
    "miner_traffic": miner_traffic,
    "miner_traffic_polled": miner_traffic_polled,
    "model_against_run": model_against_run,
    "model_holds": model_holds,
    "time_shares": time_shares,
    "workflow_latency": workflow_latency,
    "sql_mining": sql_mining,
    "clustering_traffic": clustering_traffic,
    "tumbling_support": tumbling_support,
    "sliding_support": sliding_support,
    "tumbling_baskets": tumbling_baskets,
    "session_baskets": session_baskets,
    "json_props_baskets": json_props,
    "replayed_events": replayed_events,
    "subsets_in_sql": subsets_in_sql,
}

_SHIFTED = f"(select c0 - 1 as src, c1 - 1 as dst, c2::double as mbit, c3::double as ms from (values {_LINK_VALUES}) v(c0, c1, c2, c3))"
_TRAFFIC = f"""with log as materialized ({log_sql(inputs.ATTRIBUTE_SQL, "0.1")}),
l as materialized (select o.output, l.* from log l, (select unnest(['sets', 'supports']) as output) o where l.method in ('late', 'level') and (o.output = 'supports' or l.kind = 'frontier')),
sites as (select unnest(range(5)) as site),
own as (select method, output, pass, site, sum(4 * z) as ask, count(*) as n from l group by all),
sent as (select p.method, p.output, p.pass, a.site as src, b.site as dst, coalesce(x.ask, 0) + 8 * coalesce(y.n, 0) as bytes
    from (select distinct method, output, pass from l) p, sites a join sites b on a.site <> b.site
    left join own x on (x.method, x.output, x.pass, x.site) = (p.method, p.output, p.pass, a.site)
    left join own y on (y.method, y.output, y.pass, y.site) = (p.method, p.output, p.pass, b.site)),
worst as (select method, output, pass, max(ms / 1000 + bytes * 8 / (mbit * 1000000)) as s from sent join {_SHIFTED} k using (src, dst) where bytes > 0 group by all)
select method as miner, output, count(distinct pass)::bigint as passes, count(distinct (pass, s))::bigint as requested, (8 * count(*))::bigint as messages,
    (4 * sum(4 * z + 8))::bigint as bytes, (select round(sum(w.s), 6) from worst w where w.method = l.method and w.output = l.output) as transfer_seconds
from l group by method, output"""

_LINKS = f"(select c0 as src, c1 as dst, c2::double as mbit, c3::double as ms from (values {_LINK_VALUES}) v(c0, c1, c2, c3))"
_LINE_TRAFFIC = """select l_linenumber as pass, l_suppkey % 5 + 1 as src, l_orderkey % 5 + 1 as dst, sum(l_quantity) * 8 as bytes from lineitem
    where l_suppkey % 5 <> l_orderkey % 5 group by 1, 2, 3"""
_LINE_RUNS = """select task, sum(total) as measured, sum(top) as estimated from (select task, stage, sum(s) as total, max(s) as top
    from (select l_returnflag as task, l_linenumber as stage, l_orderkey % 5 as p, sum(l_quantity) as s from lineitem group by 1, 2, 3) group by 1, 2) group by 1"""

ORACLES = {
    "miner_traffic": _TRAFFIC,
    "model_holds": "select unnest(['latesync', 'levelsync', 'clustering']) as task, true as stages_within_run, true as shares_add_up",
    "clustering_traffic": f"""with k as materialized ({_kmeans_sql()}), sent as (select site + 1 as site, count(distinct local_id) as n, count(distinct local_id) * 32 as bytes from k group by site),
        worst as (select dst, max(ms / 1000 + bytes * 8 / (mbit * 1000000)) as s from (select c0 as src, c1 as dst, c2::double as mbit, c3::double as ms from (values {_LINK_VALUES}) v(c0, c1, c2, c3)) l
          join sent on site = src group by dst),
        best as (select dst from worst order by s, dst limit 1)
        select site::int as src, (select dst from best)::int as dst, n::bigint as rows, bytes::bigint as bytes from sent where site <> (select dst from best)""",
    "sql_mining": f"select size, count(*)::bigint as n, max(support)::bigint as top from ({itemset_sql(inputs.ATTRIBUTE_SQL, '0.1')}) group by size",
    "link_worst_transfer": f"""select pass::bigint as pass, sum(bytes)::bigint as bytes, round(max(ms / 1000 + bytes * 8 / (mbit * 1000000)), 6) as seconds
        from ({_LINE_TRAFFIC}) join {_LINKS} using (src, dst) group by pass""",
    "link_matrix": "select src::bigint as src, " + ", ".join(f"coalesce(round(max(m) filter (where dst = {i}), 6), -1)::double as to_{i}" for i in range(1, 6))
    + f""" from (select src, dst, bytes * 8 / 1000000 / (ms / 1000 + bytes * 8 / (mbit * 1000000)) as m
        from (select src, dst, sum(bytes) as bytes from ({_LINE_TRAFFIC}) group by src, dst) join {_LINKS} using (src, dst)) group by src""",
    "overhead_table": f"select task, measured, estimated, round(1 - estimated / measured, 6) as overhead from ({_LINE_RUNS})",
    "gain_table": f"""with r as ({_LINE_RUNS}) select 'measured' as kind, round(1 - a.measured / b.measured, 6) as gain from r a, r b where a.task = 'R' and b.task = 'N'
        union all select 'modelled', round(1 - a.estimated / b.estimated, 6) from r a, r b where a.task = 'R' and b.task = 'N'""",
    "stage_counts": "select distinct k, 2 * k + 1 as levelsync, 5::bigint as latesync from (select count(*)::bigint as k from lineitem group by l_orderkey)",
    "stagemax_model": """select 'w1' as run, round(sum(top) + 0.5, 4) as est_seconds from (select l_linenumber, max(s) as top from
        (select l_linenumber, l_orderkey % 5 as p, sum(l_quantity) as s from lineitem group by 1, 2) group by 1)""",
    "tumbling_support": f"select date_trunc('day', ts)::timestamp as start, {_ITEM} as item, count(*)::bigint as support from events group by 1, 2",
    "sliding_support": f"""select w as start, {_ITEM} as item, count(*)::bigint as support from (
        select *, time_bucket(interval '6 hours', ts, timestamp '2000-01-01') - to_hours(6 * unnest([0, 1, 2, 3])) as w from events) group by 1, 2""",
    "tumbling_baskets": f"select date_trunc('day', ts)::timestamp as start, user_id, array_to_string(list_sort(list(distinct {_ITEM})), '|') as items from events group by 1, 2",
    "session_baskets": f"""with m as (select *, {_ITEM} as item, case when ts < lag(ts) over o + interval '2 hours' then 0 else 1 end as fresh from events window o as (partition by user_id order by ts)),
        g as (select *, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) as s from m)
        select min(ts) as start, max(ts) + interval '2 hours' as end, user_id, array_to_string(list_sort(list(distinct item)), '|') as items, count(*)::bigint as n from g group by user_id, s""",
    "json_props_baskets": "select (props->>'k')::bigint as k, count(*)::bigint as n, round(sum(value), 4) as total from events group by 1",
    "replayed_events": "select event_type, count(*)::bigint as n from events group by 1",
    "subsets_in_sql": f"""with b as (select distinct tid, item from ({inputs.ATTRIBUTE_SQL}))
        select 2::bigint as z, count(*)::bigint as n, 2 * count(*)::bigint as parts, round(0.019 + 2000 * 8 / 12710000.0::double, 6) as worst from b x join b y on x.tid = y.tid and x.item < y.item""",
}
