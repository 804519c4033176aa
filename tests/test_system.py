"""Sources, costs, workflow, streams, plans and the registry."""

from __future__ import annotations

import shutil
import subprocess
import sys
from pathlib import Path

import duckdb
import pytest
from py4j.protocol import Py4JJavaError
from pyspark.errors import AnalysisException
from pyspark.sql import functions as F

import __spark_entry__
from sitemine import schemas, sites
from sitemine.plans import choose, cost
from sitemine.session import broadcast_if_small
from sitemine.sources import files, gaussian
from sitemine.streaming import baskets as S
from sitemine.workflow.dag import Dag
from sitemine.workloads import inputs


def test_registry():
    queries, oracles = __spark_entry__.queries(), __spark_entry__.oracle_sql()
    assert set(oracles) <= set(queries) and len(queries) > 60


def test_core_stands_alone(tmp_path):
    """Without the optional subpackage the entry points work, whether or not the pipeline's file was left."""
    root = Path(__spark_entry__.__file__).resolve().parent
    shutil.copytree(root / "sitemine", tmp_path / "sitemine", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    for name in ("__spark_entry__.py", "corpus_pipeline.py"):
        if (root / name).exists():
            shutil.copy(root / name, tmp_path / name)
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert 'pipeline' not in q and len(q) > 60 and set(o) <= set(q)"
    said = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env={"PYTHONPATH": str(tmp_path), "PATH": "/usr/bin:/bin"}, capture_output=True, text=True, timeout=120)
    assert said.returncode == 0, said.stderr[-1500:]


LINE_QUERIES = ("gain_table", "link_matrix", "link_worst_transfer", "overhead_table", "stage_counts")


@pytest.mark.parametrize("name", [*LINE_QUERIES, "site_sweep", "vmerge_planted", "workflow_latency"])
def test_cost_queries_need_their_table(spark, tmp_path, name):
    with pytest.raises(AnalysisException, match="PATH_NOT_FOUND"):
        __spark_entry__.queries()[name](spark, str(tmp_path)).collect()


@pytest.mark.parametrize("name", LINE_QUERIES)
def test_cost_queries_equal_their_sql(spark, sf, name):
    con = duckdb.connect()
    con.execute(f"create view lineitem as select * from '{sf}/lineitem.parquet'")
    made = con.execute(__spark_entry__.oracle_sql()[name])
    got = __spark_entry__.queries()[name](spark, sf)
    assert got.columns == [c[0] for c in made.description] and sorted(map(tuple, got.collect())) == sorted(made.fetchall())


def test_flagship(spark):
    assert __spark_entry__.entry(spark).columns == ["itemset", "size", "support"]


def test_links_and_model(spark):
    links = cost.links(spark)
    assert links.count() == 20
    sent = links.select("src", "dst").crossJoin(spark.createDataFrame([(0, 1000), (1, 1_000_000)], "pass int, bytes long"))
    worst = {r["pass"]: r.seconds for r in cost.worst_transfer(sent, links).collect()}
    assert worst[0] == pytest.approx(0.028454, abs=1e-6) and worst[1] == pytest.approx(0.648426, abs=1e-6)
    times = cost.stage_times(spark, [("r", "a", 0, 1.0), ("r", "a", 1, 3.0), ("r", "remote", 0, 2.0)])
    assert cost.stagemax(times, 0.5).first().est_seconds == 5.5
    assert cost.share(times, "remote").first().share == pytest.approx(1 / 3)
    assert [round(cost.overhead(e, m), 3) for _, m, e in cost.BASELINE] == [0.981, 0.186, 0.246]
    assert cost.stage_count("levelsync", 4) == 9 and cost.compute_share(1, 1, 100) == 0.02
    assert cost.nodes(spark).agg(F.sum("nodes")).first()[0] == 438
    sizes = spark.createDataFrame([(i, 1000) for i in range(1, 6)], "site int, bytes long")
    assert cost.choose_aggregator(links, sizes) in range(1, 6) and cost.choose_aggregator(links, sizes, "any") == 1 and cost.choose_aggregator(links, sizes, "fixed", 3) == 3
    cost.register_functions(spark)
    assert spark.sql("select transfer_seconds(1000, 8, 1) as s").first().s == pytest.approx(0.002)


def test_traffic_counts_messages(spark):
    requests = spark.createDataFrame([(1, 0, [1, 2]), (1, 1, [1, 2]), (1, 0, [3])], "pass int, site int, itemset array<int>")
    three = spark.createDataFrame([(i,) for i in range(3)], "site int")
    plain = cost.traffic(requests, three)
    assert plain.agg(F.sum("rows")).first()[0] == 3 * 2 * 2 and plain.agg(F.sum("bytes")).first()[0] == 2 * (8 + 8 + 4) + 3 * 2 * 8
    polled = cost.traffic(requests, three, polling="hash").agg(F.sum("rows")).first()[0]
    assert polled <= 2 * 3 + 2 * 2 * 2


def test_sources(spark, sf, tmp_path):
    assert all(files.load(spark, sf, n).limit(1).count() == 1 for n in files.TABLES)
    gaussian.register(spark)
    points = spark.read.format("gaussian_mixture").option("points", 500).option("sites", 3).option("rowsperpartition", 200).load()
    assert points.count() == 1500 and points.select("point_id").distinct().count() == 1500 and points.select("label").distinct().count() == 6
    assert sorted(map(str, points.collect())) == sorted(map(str, points.repartition(3).collect()))
    made = spark.read.format("basket_gen").option("baskets", 300).option("sites", 2).load()
    assert made.count() == 600 and made.where(F.size("items") == 0).count() == 0
    (tmp_path / "t.txt").write_text("a b c\na  b\n\na b c\n")
    assert files.read_baskets(spark, str(tmp_path / "t.txt"), "text").groupBy("tid").count().count() == 3
    (tmp_path / "u.txt").write_text("a]b^c\n")
    assert {r["item"] for r in files.read_baskets(spark, str(tmp_path / "u.txt"), "text", sep="]^").collect()} == {"a", "b", "c"}
    rows = spark.createDataFrame([(0, 1, "x"), (1, 2, "y")], "site int, tid long, item string")
    for fmt in ("csv", "json", "orc", "parquet"):
        rows.write.option("header", True).format(fmt).save(str(tmp_path / fmt))
        assert sorted(files.read_baskets(spark, str(tmp_path / fmt), fmt).collect()) == sorted(rows.collect())
    files.write_sites(rows, str(tmp_path / "sites"))
    one = files.read_site(spark, str(tmp_path / "sites"), 1)
    assert one.count() == 1 and "PartitionFilters: [isnotnull(site" in one._jdf.queryExecution().executedPlan().toString()
    files.save(rows, path=str(tmp_path / "out"), json_path=str(tmp_path / "out.json"), view="saved", by="site")
    files.save(rows.where("site = 1").withColumn("item", F.lit("z")), path=str(tmp_path / "out"), by="site")
    assert {r.item for r in spark.read.parquet(str(tmp_path / "out")).collect()} == {"x", "z"} and spark.table("saved").count() == 2


def test_event_log(spark, tmp_path):
    (tmp_path / "log").write_text(
        '{"Event":"SparkListenerApplicationStart","Timestamp":1000}\n'
        '{"Event":"SparkListenerJobStart","Stage IDs":[3],"Properties":{"spark.jobGroup.id":"remote"}}\n'
        '{"Event":"SparkListenerTaskEnd","Stage ID":3,"Task Info":{"Index":0,"Launch Time":3500,"Finish Time":5500}}\n'
    )
    assert files.read_event_log(spark, str(tmp_path / "log")).collect() == [("run", "remote:3", 0, 2.0)]
    assert files.first_task_latency(spark, str(tmp_path / "log")) == 2.5


def test_observed_times_outlive_forgotten_stages(spark):
    """Stages that were skipped leave the status store first; the tasks of a run are read without them."""
    context = spark.sparkContext
    tracker, store = context.statusTracker(), context._jsc.sc().statusStore()

    def skips(group):
        with cost.stage(spark, group):
            pairs = context.parallelize(range(40), 2).map(lambda i: (i % 3, 1)).reduceByKey(lambda a, b: a + b, 2)
            pairs.count()
            pairs.count()  # its first stage is skipped
        ids = {s for j in tracker.getJobIdsForGroup(group) for s in tracker.getJobInfo(j).stageIds}
        times = sorted(cost.observed_times(spark, "r", {"all": group}).collect())
        assert len(times) == 6
        return (ids - {int(r.stage.split(":")[1]) for r in times}).pop(), times

    def forgotten(stage):
        rdd = context._jsc.parallelize(context._jvm.java.util.ArrayList(), 1)
        for _ in range(1500):
            rdd.count()
            context._jsc.sc().listenerBus().waitUntilEmpty()
            try:
                store.lastStageAttempt(stage)
            except Py4JJavaError:
                return True
        return False

    assert forgotten(skips("filler")[0])  # the store is full
    skipped, times = skips("observed")
    assert forgotten(skipped) and sorted(cost.observed_times(spark, "r", {"all": "observed"}).collect()) == times


def test_site_keys(spark, sf):
    df = spark.createDataFrame([(7, "b"), (12, "a"), (3, "b")], "k long, v string")
    assert [r[0] for r in df.select(sites.by_hash(F.col("k"), 5)).collect()] == [2, 2, 3]
    assert [r[0] for r in df.select(sites.by_chunk(F.col("k"), 5)).collect()] == [1, 2, 0]
    assert {(r.k, r.site) for r in sites.by_value(df, "v").collect()} == {(7, 1), (12, 0), (3, 1)}
    assert {r.site for r in sites.by_value(df.union(df.limit(1).select("k", F.lit(None))), "v").collect()} == {0, 1, 2}
    assert sites.order_region(spark, sf).select("site").distinct().count() == 5
    with pytest.raises(ValueError, match="tid, item"):
        schemas.require_columns(df.withColumn("site", F.lit(1)), schemas.BASKET_ROWS)


def test_broadcast_only_when_small(spark):
    a, b = spark.range(100).withColumnRenamed("id", "k"), spark.range(50).withColumnRenamed("id", "k")
    plan = lambda n: a.join(broadcast_if_small(b, n), "k")._jdf.queryExecution().optimizedPlan().toString()
    assert "strategy=broadcast" in plan(50) and "strategy=broadcast" not in plan(49)


def test_inputs_prune_columns(spark, sf):
    plan = inputs.brand_rows(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<l_orderkey:bigint,l_partkey:bigint>" in plan


def test_workflow_runs_in_order_and_resumes(spark, tmp_path):
    ran = []

    def job(name):
        def run(s, *before):
            ran.append(name)
            return s.createDataFrame([(name, sum(b.count() for b in before))], "name string, n long")

        return run

    dag = lambda: Dag(str(tmp_path / "w")).add("a", job("a")).add("b", job("b")).add("c", job("c"), after=["a", "b"])
    results, info = dag().run(spark)
    assert results["c"].first().n == 2 and set(ran[:2]) == {"a", "b"} and not info.resumed
    shutil.rmtree(tmp_path / "w" / "c")
    _, info = dag().run(spark)
    assert set(info.resumed) == {"a", "b"} and ran.count("a") == 1 and ran.count("c") == 2
    with pytest.raises(ValueError):
        Dag("x").add("d", job("d"), after=["nowhere"])


def test_choices(spark):
    short = spark.createDataFrame([(0, 1, [1, 2, 3])], "site int, tid long, items array<int>")
    long = spark.createDataFrame([(0, 1, list(range(60)))], "site int, tid long, items array<int>")
    assert choose.counting_engine(short) == "expand" and choose.counting_engine(long) == "extend" and choose.counting_engine(long, 1000) == "bitmap"
    assert choose.counting_engine(long, 10**9) == "extend"
    assert choose.merge_engine(10, False) == "task" and choose.merge_engine(10**6, True) == "rounds" and choose.merge_engine(10**6, False) == "tree"
    level = spark.createDataFrame([(1, 100, 1)], "size int, local_sets long, global_sets long")
    assert choose.late_sync_advice(level) == "levelsync"
    assert choose.local_engine(spark.createDataFrame([(0, 1, [1.0])], schemas.POINTS)) == "kmeans"


@pytest.fixture(scope="module")
def event_files(spark, sf, tmp_path_factory):
    """Events in time order over five files, and one late file."""
    folder = tmp_path_factory.mktemp("events")
    events = spark.read.parquet(f"{sf}/events.parquet")
    days = events.withColumn("part", F.ntile(5).over(__import__("pyspark.sql.window", fromlist=["Window"]).Window.orderBy("ts")))
    for i in range(1, 6):
        days.where(F.col("part") == i).drop("part").coalesce(1).write.mode("append").parquet(str(folder))
    return str(folder), events


def drain(df, mode, name, tmp_path):
    query = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
    query.awaitTermination(120)
    return df.sparkSession.table(name)


def test_stream_equals_batch(spark, event_files, tmp_path):
    folder, events = event_files
    live = S.event_stream(spark, folder)
    got = drain(S.stream_support(live), "complete", "support", tmp_path)
    assert sorted(got.collect()) == sorted(S.stream_support(events).collect())
    # append mode gives the windows that the watermark has closed
    closed = drain(S.stream_baskets(S.event_stream(spark, folder)), "append", "baskets", tmp_path)
    whole = {(r.start, r.user_id): r["items"] for r in S.stream_baskets(events).collect()}
    rows = closed.collect()
    assert rows and all(whole[r.start, r.user_id] == r["items"] for r in rows)
    sessions = drain(S.session_baskets(S.event_stream(spark, folder)), "append", "sessions", tmp_path).collect()
    assert {(r.start, r.user_id, r.n) for r in sessions} <= {(r.start, r.user_id, r.n) for r in S.session_baskets(events).collect()}
    clean = drain(S.deduplicated(S.event_stream(spark, folder)).select("event_id"), "append", "clean", tmp_path)
    assert clean.count() == clean.distinct().count() == events.count()


def test_stream_summaries_and_remerge(spark, sf, tmp_path):
    folder = tmp_path / "points"
    points = inputs.part_points(spark, sf).withColumn("local_id", F.pmod("point_id", F.lit(3)).cast("int"))
    for i in range(3):
        points.where(F.pmod("point_id", F.lit(7)) % 3 == i).coalesce(1).write.mode("append").parquet(str(folder))
    live = spark.readStream.schema(points.schema).option("maxFilesPerTrigger", 1).parquet(str(folder))
    updates = drain(S.stream_substats(live), "update", "substats", tmp_path)
    from sitemine.operators.clustering.stats import sub_stats

    want = {(r.site, r.local_id): r for r in sub_stats(points).collect()}
    got = {(r.site, r.local_id): r for r in S.latest_summaries(updates).collect()}
    assert set(got) == set(want)
    assert all(got[k].n == want[k].n and got[k].scatter == pytest.approx(want[k].scatter, rel=1e-9) for k in want)
    seen = []
    run = S.remerge_on_batch(lambda batch: batch.groupBy().count(), lambda out, i: seen.append(out.first()[0]))
    run(updates, 0)
    assert seen == [updates.count()]


def test_late_rows_are_dropped_and_counted(spark, sf, tmp_path):
    folder = tmp_path / "late"
    events = spark.read.parquet(f"{sf}/events.parquet")
    cut = events.agg(F.expr("percentile(unix_timestamp(ts), 0.5)")).first()[0]
    late = F.unix_timestamp("ts") < cut
    for part in (events.where(~late), events.where(late), events.where(~late).limit(1)):
        part.coalesce(1).write.mode("append").parquet(str(folder))
    # files in the order of their writing: the earlier half of time arrives second
    live = S.event_stream(spark, str(folder))
    df = S.stream_support(live)
    query = df.writeStream.format("memory").queryName("late").outputMode("append").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    query.awaitTermination(120)
    assert S.late_rows(query) > 0
    kept = spark.table("late").agg(F.sum("support")).first()[0] or 0
    assert kept + S.late_rows(query) <= events.count() + 1


def test_stream_labels(spark, tmp_path):
    points = spark.createDataFrame([(0, 1, [0.1]), (0, 2, [9.0])], "site int, point_id long, features array<double>")
    points.write.parquet(str(tmp_path / "p"))
    centers = spark.createDataFrame([(0, 0, [0.0]), (0, 1, [10.0])], "site int, local_id int, center array<double>")
    labels = spark.createDataFrame([(0, 0, 7), (0, 1, 8)], "site int, local_id int, global_id int")
    live = S.label_stream(spark.readStream.schema(points.schema).parquet(str(tmp_path / "p")), centers, labels)
    assert {r.point_id: r.global_id for r in drain(live, "append", "labelled", tmp_path).collect()} == {1: 7, 2: 8}


def test_versions_as_of(spark):
    points = spark.createDataFrame([(1, 5), (2, 15), (3, 1)], "id int, ts int")
    versions = spark.createDataFrame([(2, "a"), (10, "b")], "from_ts int, version string")
    assert {r.id: r.version for r in S.as_of_version(points, versions).collect()} == {1: "a", 2: "b", 3: None}
    for n in (0, 1, 2, 5, 8, 33):
        times = [7 * i + 3 for i in range(n)]
        many = spark.createDataFrame([(t, f"v{t}") for t in times], "from_ts int, version string")
        got = {r.ts: r.version for r in S.as_of_version(spark.range(250).select(F.col("id").cast("int").alias("ts")), many).collect()}
        assert got == {ts: next((f"v{t}" for t in reversed(times) if t <= ts), None) for ts in range(250)}


def test_numbered_by_ranges(spark):
    """Ranks of a sort by ranges are those of one task."""
    from sitemine.session import numbered

    rows = spark.range(500).select(F.pmod(F.col("id") * 37, F.lit(101)).alias("a"), "id")
    few, many = (sorted(map(tuple, numbered(rows, [F.col("a"), F.col("id")], "place", limit).collect())) for limit in (10**6, 10))
    assert few == many and sorted(r[2] for r in few) == list(range(500))
