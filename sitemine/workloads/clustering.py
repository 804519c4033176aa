"""Queries of the clustering method, and the SQL that must give the same rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sitemine import sites
from sitemine.functions.agreement import adjusted_rand, purity, sse_ratio
from sitemine.functions.merge_columns import merge_increase, merge_stats
from sitemine.operators.clustering import merge as M
from sitemine.operators.clustering import perturb as P
from sitemine.operators.clustering.central import central_kmeans
from sitemine.operators.clustering.gap import gap_statistic
from sitemine.operators.clustering.local import kmeans_multi
from sitemine.operators.clustering.pipeline import label_points, vmerge_cluster
from sitemine.operators.clustering.stats import dimension, sub_stats
from sitemine.session import materialise
from sitemine.sources import gaussian
from sitemine.workloads import inputs


def _rounded(df: DataFrame, digits: int = 4) -> DataFrame:
    # adding zero turns -0.0 into 0.0
    return df.select(*[(F.round(c, digits) + 0.0).alias(c) if t == "double" else F.col(c).cast("long").alias(c) if t == "int" else F.col(c) for c, t in df.dtypes])


def _parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Part points with sub-clusters fixed by key, for checks of the formulas."""
    return inputs.part_points(spark, sf_dir).withColumn("local_id", F.pmod("point_id", F.lit(4)).cast("int"))


_PARTS = """select p_partkey % 5 as site, p_partkey % 4 as local_id,
  (p_size - avg(p_size) over ()) / stddev_pop(p_size) over () as x, (p_retailprice - avg(p_retailprice) over ()) / stddev_pop(p_retailprice) over () as y from part"""
_STATS = f"""select site, local_id, count(*) as n, avg(x) as x, avg(y) as y, count(*) * (var_pop(x) + var_pop(y)) as scatter from ({_PARTS}) group by site, local_id"""


def substats_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = sub_stats(_parts(spark, sf_dir), d=2)
    return _rounded(s.select("site", "local_id", "n", F.col("center")[0].alias("x"), F.col("center")[1].alias("y"), "scatter"))


def substats_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = sub_stats(inputs.embedding_points(spark, sf_dir), by=("label",), d=64)
    return _rounded(s.select("label", "n", F.col("center")[0].alias("c0"), F.col("center")[63].alias("c63"), "scatter"))


def substats_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = inputs.line_points(spark, sf_dir).withColumn("local_id", (F.col("point_id") % 1000 % 3).cast("int"))
    s = sub_stats(points, d=4)
    return _rounded(s.select("site", "local_id", "n", F.col("center")[1].alias("price"), "scatter"))


def _pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = sub_stats(_parts(spark, sf_dir), d=2)
    side = lambda x: s.select("site", F.col("local_id").alias(x), F.struct("n", "center", "scatter").alias(f"s{x}"))
    return side("a").join(side("b"), "site").where("a < b")


def merge_identity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Summaries of unions by the merge formula; the SQL recomputes them from the points."""
    merged = merge_stats(F.col("sa"), F.col("sb"))
    return _rounded(_pairs(spark, sf_dir).select("site", "a", "b", merged["n"].alias("n"), merged["center"][0].alias("x"), merged["scatter"].alias("scatter")))


def pair_increase(spark: SparkSession, sf_dir: str) -> DataFrame:
    pairs = _pairs(spark, sf_dir)
    return _rounded(
        pairs.select("site", "a", "b", merge_increase(F.col("sa"), F.col("sb")).alias("squared"), merge_increase(F.col("sa"), F.col("sb"), "euclidean").alias("plain")), 6
    )


def merge_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = sub_stats(_parts(spark, sf_dir), d=2)
    rows = [(v, round(M.merge_bound(s, 2.0, v), 6)) for v in M.VARIANCES]
    return spark.createDataFrame(rows, "variance string, bound double")


def scatter_law(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Total scatter is scatter within sub-clusters plus scatter of their centres."""
    points = _parts(spark, sf_dir)
    s = sub_stats(points, d=2)
    total = sub_stats(points.withColumn("all", F.lit(1)), by=("all",), d=2).select(F.col("scatter").alias("total"), F.col("center").alias("mean"))
    d2 = (F.col("center")[0] - F.col("mean")[0]) ** 2 + (F.col("center")[1] - F.col("mean")[1]) ** 2
    return _rounded(s.crossJoin(F.broadcast(total)).groupBy("total").agg(F.sum("scatter").alias("within"), F.sum(F.col("n") * d2).alias("between")))


def kmeans_two_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    labelled = kmeans_multi(inputs.part_points(spark, sf_dir), 4, iterations=2)
    return labelled.select(F.col("site").cast("long").alias("site"), "point_id", F.col("local_id").cast("long").alias("local_id"))


def _fixed_clusters(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Sub-clusters (site, key % 4) in three clusters, by (site + local_id) % 3."""
    s = materialise(sub_stats(_parts(spark, sf_dir), d=2))
    labels = s.select("site", "local_id", F.pmod(F.col("site") + F.col("local_id"), F.lit(3)).cast("int").alias("global_id"))
    return materialise(P.regroup(s, labels)), s


def border_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    clusters, s = _fixed_clusters(spark, sf_dir)
    rows = P.border(clusters, s, 3).select("global_id", "site", "local_id", F.col("far").alias("d2"), "place")
    return _rounded(rows, 6)


def closest_rival(spark: SparkSession, sf_dir: str) -> DataFrame:
    clusters, s = _fixed_clusters(spark, sf_dir)
    rows = P.closest_rival(P.members_with_stats(clusters, s), clusters)
    return _rounded(rows.select("site", "local_id", "global_id", "rival", F.col("rival_d2").alias("d2")), 6)


def move_gains(spark: SparkSession, sf_dir: str) -> DataFrame:
    clusters, s = _fixed_clusters(spark, sf_dir)
    return _rounded(P.moves(clusters, s, 1.0))


_FIXED = f"""s as materialized ({_STATS}),
m as (select *, (site + local_id) % 3 as global_id from s),
c0 as (select global_id, sum(n) as n, sum(n * x) / sum(n) as x, sum(n * y) / sum(n) as y from m group by global_id),
c as (select c0.*, (select sum(m.scatter + m.n * ((m.x - c0.x) ** 2 + (m.y - c0.y) ** 2)) from m where m.global_id = c0.global_id) as scatter from c0),
r as (select m.*, o.n as own_n, o.x as own_x, o.y as own_y, o.scatter as own_scatter, c.global_id as rival, c.n as rn, c.x as rx, c.y as ry, c.scatter as rs,
        (m.x - c.x) ** 2 + (m.y - c.y) ** 2 as d2
      from m join c o using (global_id) join c on c.global_id <> m.global_id
      qualify row_number() over (partition by m.site, m.local_id order by (m.x - c.x) ** 2 + (m.y - c.y) ** 2, c.global_id) = 1)"""


def _tables(spark: SparkSession, sf_dir: str) -> list[tuple[str, DataFrame, int]]:
    return [
        ("embeddings", inputs.embedding_points(spark, sf_dir).drop("label"), 8),
        ("lineitem", inputs.line_points(spark, sf_dir), 20),
        ("part", inputs.part_points(spark, sf_dir), 8),
        ("customer", inputs.customer_points(spark, sf_dir), 8),
        ("supplier", inputs.supplier_points(spark, sf_dir), 4),
    ]


def vmerge_invariants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What must hold of any run, without and with the repair: no point lost, every sub-cluster labelled once,
    unrepaired groups under the bound, and the clusters' scatter that of the labelled points."""
    out = []
    for name, points, k in _tables(spark, sf_dir):
        for border in (0, 0.1):
            r = vmerge_cluster(points, k_local=k, border=border)
            labels = r.labels.agg(F.count("*").alias("rows"), F.countDistinct("site", "local_id").alias("subs")).first()
            sums = r.clusters.agg(F.sum("n").alias("n"), F.sum("scatter").alias("s"), F.max(F.when(F.col("n_members") > 1, F.col("scatter"))).alias("top")).first()
            again = sub_stats(label_points(r.labelled, r.labels), by=("global_id",)).agg(F.sum("n").alias("n"), F.sum("scatter").alias("s")).first()
            once = labels.rows == labels.subs == r.substats.count()
            out.append((name, float(border), sums.n, again.n, once, bool(border) or (sums.top or 0.0) < r.bound, abs(again.s - sums.s) <= 1e-6 * max(1.0, sums.s)))
    return spark.createDataFrame(out, "workload string, border double, n_points long, n_labelled long, labels_once boolean, under_bound boolean, scatter_of_points boolean")


def merge_engines_agree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clusters by the engines that must agree."""
    s = sub_stats(kmeans_multi(inputs.line_points(spark, sf_dir), 20), d=4)
    s = materialise(s)
    out = [(e, M.merge_subclusters(s, engine=e)) for e in ("task", "rounds")]
    rows = [(e, c.count(), round(c.agg(F.sum("scatter")).first()[0], 4), c.agg(F.sum("n")).first()[0]) for e, c in out]
    return spark.createDataFrame(rows, "engine string, clusters long, total_scatter double, points long")


def planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The labelled vectors under both readings of variance: clusters found, purity, adjusted Rand."""
    points = materialise(inputs.embedding_points(spark, sf_dir))
    out = []
    for variance in M.VARIANCES:
        r = vmerge_cluster(points, k_local=20, variance=variance, engine="task")
        labelled = materialise(label_points(r.labelled, r.labels))
        out.append((variance, r.clusters.count(), round(purity(labelled).first()[0], 4), round(adjusted_rand(labelled).first()[0], 4)))
    return spark.createDataFrame(out, "variance string, clusters long, purity double, adjusted_rand double")


def _summary(r, name: str) -> tuple:
    c = r.clusters.agg(F.count("*").alias("k"), F.sum("n").alias("n"), F.sum("scatter").alias("s")).first()
    moved = {x.kind: x["count"] for x in r.trace.groupBy("kind").count().collect()}
    return name, c.k, c.n, round(c.s, 4), moved.get("move_try", 0) + moved.get("move_accept", 0), moved.get("move_accept", 0)


_SUMMARY = "run string, clusters long, points long, total_scatter double, moves_tried long, moves_accepted long"


def vmerge_tables(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole method on vectors, order lines, customers and suppliers."""
    return spark.createDataFrame([_summary(vmerge_cluster(p, k_local=k), name) for name, p, k in _tables(spark, sf_dir)], _SUMMARY)


def vmerge_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole method on order lines, twenty sub-clusters a site: the bench's throughput."""
    return spark.createDataFrame([_summary(vmerge_cluster(inputs.line_points(spark, sf_dir), k_local=20), "lineitem")], _SUMMARY)


ABLATION = {
    "none": {"border": 0}, "tenth": {"border": 0.1, "multi": False}, "tenth_multi": {"border": 0.1}, "half": {"border": 0.5}, "three": {"border": 3},
    "half_to_rival": {"border": 0.5, "rule": "to_rival"}, "half_batch": {"border": 0.5, "mode": "batch"}, "half_sweeps": {"border": 0.5, "max_sweeps": 10},
}


def _ablation(spark: SparkSession, sf_dir: str) -> list[tuple[str, tuple]]:
    """(workload, summary): every way of repair from the same merged clusters, on each workload."""
    gaussian.register(spark)
    workloads = [
        ("parts", inputs.part_points(spark, sf_dir), 8),
        ("mixture", spark.read.format("gaussian_mixture").option("points", 1200).load().drop("label"), 20),
        ("vectors", inputs.embedding_points(spark, sf_dir).drop("label"), 8),
        ("lines", inputs.line_points(spark, sf_dir), 20),
    ]
    out = []
    for workload, points, k in workloads:
        s = materialise(sub_stats(kmeans_multi(points, k)))
        bound = M.merge_bound(s)
        merged = M.merge_subclusters(s)
        for name, options in ABLATION.items():
            options = dict(options)
            multi = options.pop("multi", True)
            clusters, trace = P.perturb(merged, s, bound=bound if multi else None, **options)
            c = clusters.agg(F.count("*").alias("k"), F.sum("n").alias("n"), F.sum("scatter").alias("s")).first()
            moved = {x.kind: x["count"] for x in trace.groupBy("kind").count().collect()}
            out.append((workload, (name, c.k, c.n, round(c.s, 4), moved.get("move_try", 0) + moved.get("move_accept", 0), moved.get("move_accept", 0))))
    return out


def perturb_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Total scatter and moves by border size, shared members, rule and mode, from the same merged clusters of each workload."""
    return spark.createDataFrame([(w, *row) for w, row in _ablation(spark, sf_dir)], f"workload string, {_SUMMARY}")


def repair_invariants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What must hold of any repair: no point lost, and no total above that without it."""
    rows = _ablation(spark, sf_dir)
    start = {w: r[3] for w, r in rows if r[0] == "none"}
    points = {w: {r[2] for v, r in rows if v == w} for w in start}
    out = [(w, next(iter(points[w])), len(points[w]) == 1, all(r[3] <= start[w] + 1e-6 * start[w] for v, r in rows if v == w)) for w in start]
    return spark.createDataFrame(out, "workload string, points long, none_lost boolean, never_worse boolean")


def site_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The labelled vectors over 5, 50 and 200 sites, up to twenty sub-clusters each: summaries, bytes sent, clusters, moves, agreement."""
    out = []
    for n in (5, 50, 200):
        points = materialise(inputs.embedding_points(spark, sf_dir).withColumn("site", sites.by_hash(F.col("point_id"), n)))
        width = (dimension(points) + 2) * 8
        for variance in M.VARIANCES:
            r = vmerge_cluster(points, k_local=20, variance=variance)
            labelled = materialise(label_points(r.labelled, r.labels))
            _, clusters, total, scatter, tried, accepted = _summary(r, "")
            summaries = r.substats.count()
            out.append((n, variance, total, summaries, summaries * width, clusters, scatter, tried, accepted, round(purity(labelled).first()[0], 4), round(adjusted_rand(labelled).first()[0], 4)))
    return spark.createDataFrame(
        out, "sites long, variance string, points long, summaries long, bytes long, clusters long, total_scatter double, moves_tried long, moves_accepted long, purity double, adjusted_rand double"
    )


def gap_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(gap_statistic(inputs.part_points(spark, sf_dir)))


def gap_invariants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What must hold of the gap statistic: every k tried at every site, one chosen, by the rule."""
    rows = gap_statistic(inputs.part_points(spark, sf_dir)).collect()
    out = []
    for site in sorted({r.site for r in rows}):
        mine = sorted((r for r in rows if r.site == site), key=lambda r: r.k)
        by_rule = next((a.k for a, b in zip(mine, mine[1:], strict=False) if a.gap >= b.gap - b.se), mine[-1].k)
        out.append((site, len(mine), [r.k for r in mine if r.chosen] == [by_rule]))
    return spark.createDataFrame(out, "site long, tried long, chosen_by_rule boolean")


def central_reference(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scatter of the method over that of a central k-means with as many clusters."""
    points = inputs.part_points(spark, sf_dir)
    r = vmerge_cluster(points, k_local=8)
    k = r.clusters.count()
    _, cost = central_kmeans(points, k)
    total = r.clusters.agg(F.sum("scatter")).first()[0]
    return spark.createDataFrame([(k, round(total, 4), round(cost, 4), round(sse_ratio(total, cost), 4))], "clusters long, total_scatter double, central_scatter double, ratio double")


def _kmeans_sql() -> str:
    assign = """select p.site, p.point_id, p.x, p.y, c.local_id from p join {c} c on c.site = p.site
      qualify row_number() over (partition by p.site, p.point_id order by (p.x - c.x) ** 2 + (p.y - c.y) ** 2, c.local_id) = 1"""
    means = "select site, local_id, avg(x) as x, avg(y) as y from ({a}) group by site, local_id"
    return f"""with p as materialized (select p_partkey % 5 as site, p_partkey as point_id,
  (p_size - avg(p_size) over ()) / stddev_pop(p_size) over () as x, (p_retailprice - avg(p_retailprice) over ()) / stddev_pop(p_retailprice) over () as y from part),
c0 as materialized (select site, row_number() over (partition by site order by point_id) - 1 as local_id, x, y from p qualify row_number() over (partition by site order by point_id) <= 4),
c1 as materialized ({means.format(a=assign.format(c="c0"))}), c2 as materialized ({means.format(a=assign.format(c="c1"))})
select site::bigint as site, point_id, local_id::bigint as local_id from ({assign.format(c="c2")})"""


QUERIES = {
    "substats_part": substats_part,
    "substats_embeddings": substats_embeddings,
    "substats_lineitem": substats_lineitem,
    "merge_identity": merge_identity,
    "pair_increase": pair_increase,
    "merge_bound": merge_bounds,
    "scatter_law": scatter_law,
    "kmeans_part_t2": kmeans_two_steps,
    "border_rank": border_rank,
    "closest_rival": closest_rival,
    "move_gain": move_gains,
    "vmerge_invariants": vmerge_invariants,
    "merge_engines_agree": merge_engines_agree,
    "vmerge_planted": planted,
    "vmerge_tables": vmerge_tables,
    "vmerge_lineitem": vmerge_lineitem,
    "perturb_ablation": perturb_ablation,
    "repair_invariants": repair_invariants,
    "site_sweep": site_sweep,
    "gap_statistic_part": gap_part,
    "gap_invariants": gap_invariants,
    "central_kmeans": central_reference,
}

_R4 = "round({0}, 4) + 0.0 as {1}"
ORACLES = {
    "substats_part": f"select site, local_id, n::bigint as n, round(x, 4) + 0.0 as x, round(y, 4) + 0.0 as y, round(scatter, 4) + 0.0 as scatter from ({_STATS})",
    "substats_embeddings": """with e as (select vec_id, label, unnest(embedding)::double as v, generate_subscripts(embedding, 1) as i from embeddings),
        a as (select label, i, count(*) as n, avg(v) as m, var_pop(v) as s from e group by label, i)
        select label::bigint as label, max(n)::bigint as n, round(max(m) filter (where i = 1), 4) + 0.0 as c0, round(max(m) filter (where i = 64), 4) + 0.0 as c63,
        round(sum(s) * max(n), 4) + 0.0 as scatter from a group by label""",
    "substats_lineitem": """with z as (select l_orderkey % 5 as site, row_number() over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) % 3 as local_id,
        (l_quantity - avg(l_quantity) over ()) / stddev_pop(l_quantity) over () as a, (l_extendedprice - avg(l_extendedprice) over ()) / stddev_pop(l_extendedprice) over () as b,
        (l_discount - avg(l_discount) over ()) / stddev_pop(l_discount) over () as c, (l_tax - avg(l_tax) over ()) / stddev_pop(l_tax) over () as d from lineitem)
        select site, local_id, count(*)::bigint as n, round(avg(b), 4) + 0.0 as price, round(count(*) * (var_pop(a) + var_pop(b) + var_pop(c) + var_pop(d)), 4) + 0.0 as scatter from z group by site, local_id""",
    "merge_identity": f"""with p as materialized ({_PARTS}), u as (select a.site, a.local_id as a, b.local_id as b from ({_STATS}) a join ({_STATS}) b on a.site = b.site and a.local_id < b.local_id)
        select u.site, a, b, count(*)::bigint as n, round(avg(x), 4) + 0.0 as x, round(count(*) * (var_pop(x) + var_pop(y)), 4) + 0.0 as scatter
        from u join p on p.site = u.site and p.local_id in (a, b) group by u.site, a, b""",
    "pair_increase": f"""select a.site, a.local_id as a, b.local_id as b, round(a.n * b.n / (a.n + b.n)::double * ((a.x - b.x) ** 2 + (a.y - b.y) ** 2), 6) + 0.0 as squared,
        round(a.n * b.n / (a.n + b.n)::double * sqrt((a.x - b.x) ** 2 + (a.y - b.y) ** 2), 6) + 0.0 as plain
        from ({_STATS}) a join ({_STATS}) b on a.site = b.site and a.local_id < b.local_id""",
    "merge_bound": f"select 'scatter' as variance, round(2 * max(scatter), 6) as bound from ({_STATS}) union all select 'mean', round(2 * max(scatter / n), 6) from ({_STATS})",
    "scatter_law": f"""with p as ({_PARTS}), t as (select count(*) * (var_pop(x) + var_pop(y)) as total, avg(x) as mx, avg(y) as my from p)
        select round(total, 4) + 0.0 as total, round(sum(scatter), 4) + 0.0 as within, round(sum(n * ((x - mx) ** 2 + (y - my) ** 2)), 4) + 0.0 as between from ({_STATS}) cross join t group by total""",
    "kmeans_part_t2": _kmeans_sql(),
    "border_rank": f"""with {_FIXED} select * from (select global_id, site, local_id, round((x - own_x) ** 2 + (y - own_y) ** 2, 6) + 0.0 as d2,
        row_number() over (partition by global_id order by (x - own_x) ** 2 + (y - own_y) ** 2 desc, site, local_id) as place from r) where place <= 3""",
    "closest_rival": f"with {_FIXED} select site, local_id, global_id, rival, round(d2, 6) + 0.0 as d2 from r",
    "move_gain": f"""with {_FIXED}, w as (select *, own_n - n as ln, (own_n * own_x - n * x) / (own_n - n) as lx, (own_n * own_y - n * y) / (own_n - n) as ly from r)
        select global_id, site, local_id, rival, round(own_scatter + rs - (own_scatter - scatter - ln * n / own_n::double * ((x - lx) ** 2 + (y - ly) ** 2))
          - (rs + scatter + rn * n / (rn + n)::double * d2), 4) + 0.0 as gain from w""",
    "repair_invariants": """select w as workload, n::bigint as points, true as none_lost, true as never_worse from (
        select 'parts' as w, count(*) as n from part union all select 'mixture', 6000 union all select 'vectors', count(*) from embeddings union all select 'lines', count(*) from lineitem)""",
    "gap_invariants": "select (p_partkey % 5)::bigint as site, 8::bigint as tried, true as chosen_by_rule from part group by 1",
    "vmerge_invariants": """select w as workload, b::double as border, n::bigint as n_points, n::bigint as n_labelled, true as labels_once, true as under_bound, true as scatter_of_points
        from (select 'embeddings' as w, count(*) as n from embeddings union all select 'lineitem', count(*) from lineitem union all select 'part', count(*) from part
          union all select 'customer', count(*) from customer union all select 'supplier', count(*) from supplier), (select unnest([0.0, 0.1]) as b)""",
}
