"""Mixing sources to target weights: capped water-filling and seeded repetitions.

Targets: the mix holds ``share`` times all words.  Each source asks for its weight's part
of it, but no source gives more than ``max_epochs`` times its own size; what a clamped
source cannot give goes to the others in proportion to their weights until none is above
its cap.  Ordering sources by cap / weight turns that loop into one pass of window sums:
with the first j sources clamped the water level is (total - their caps) / (weights of
the rest), and source j is clamped when its cap is at most the level times its weight.

Sampling: a source at e epochs takes each document floor(e) times whole; for the
fraction left, documents are lined up by a seeded digest of their id and taken once more until the
source's target is met to within half a document.  The cut is found without lining up
any source in one task: digests fall in 256 cells, sums per cell pick the one cell
holding the cut, and that cell is split again, three levels deep, before its few
documents are ordered.  A source's cut is one digest, so the documents themselves are
never shuffled.

Everything is DataFrame expressions; the only table that meets in one task has a row per
source.

Defined cases: null text has size 0 (taken 0); null source is a source, last in order;
sources of size 0 have target 0; rows that repeat an id share a digest and are taken or left together; an empty table gives an empty table; other columns pass
through.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sitemine.llm.common import WORD, fresh_name
from sitemine.session import broadcast_if_small, materialise

WEIGHTS = (3, 1, 2)
SHARE = 1.5
MAX_EPOCHS = 2
SEED = 42
LEVELS = 3


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def digest(id_col: Column, seed: int) -> Column:
    return F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(id_col.cast("string"), F.lit("null"))))


def source_targets(
    sized: DataFrame, *, source: str = "source", weights: Sequence[int] = WEIGHTS, share: float = SHARE, max_epochs: float = MAX_EPOCHS
) -> DataFrame:
    """One row per source: source_size, target, whole (epochs taken in full), part (words still due)."""
    everything = Window.partitionBy()
    by_name = Window.orderBy(F.col("mix_source").asc_nulls_last())
    sizes = sized.groupBy(F.col(source).alias("mix_source")).agg(F.sum("mix_size").alias("source_size"))
    turn = (F.row_number().over(by_name) - 1).cast("long")
    weighed = sizes.withColumn("turn", turn).withColumn(
        "weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.col("turn") % len(weights) + 1).cast("int"))
    )
    order = Window.orderBy(F.col("cap") / F.col("weight"), F.col("turn"))
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    levels = (
        weighed.withColumn("cap", F.col("source_size") * F.lit(float(max_epochs)))
        .withColumn("total", F.sum("source_size").over(everything) * F.lit(float(share)))
        .withColumn("spent", F.coalesce(F.sum("cap").over(before), F.lit(0.0)))
        .withColumn("rest", F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
        .withColumn("level", (F.col("total") - F.col("spent")) / F.col("rest"))
        .withColumn("open", F.col("cap") > F.col("level") * F.col("weight"))
        .withColumn("water", F.max(F.when(F.col("open"), F.col("level"))).over(everything))
    )
    target = F.when(F.col("open"), F.col("water") * F.col("weight")).otherwise(F.col("cap"))
    epochs = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0)
    return (
        levels.withColumn("target", target)
        .withColumn("whole", epochs.cast("long"))
        .withColumn("part", F.col("target") - F.col("whole") * F.col("source_size"))
        .select("mix_source", "source_size", "target", "whole", "part")
    )


def extra_cuts(narrow: DataFrame, targets: DataFrame, *, levels: int = LEVELS) -> DataFrame:
    """(mix_source, cut): a source's documents with digest <= cut are taken once more.

    ``narrow`` has mix_source, mix_size, mix_digest; ``targets`` has part per source.
    """
    state = targets.select(F.col("mix_source").alias("of"), "part", F.lit("").alias("prefix"), F.lit(0).cast("long").alias("below"))
    for level in range(1, levels + 1):
        known = broadcast_if_small(state)
        inside = narrow.join(
            known, F.col("mix_source").eqNullSafe(F.col("of")) & (F.substring("mix_digest", 1, 2 * level - 2) == F.col("prefix"))
        )
        cells = inside.groupBy("of", "part", "below", F.substring("mix_digest", 1, 2 * level).alias("cell")).agg(F.sum("mix_size").alias("held"))
        upto = Window.partitionBy("of").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
        start = F.col("below") + F.coalesce(F.sum("held").over(upto), F.lit(0))
        state = materialise(
            cells.withColumn("start", start)
            .where(F.col("start") <= F.col("part"))
            .groupBy("of", "part")
            .agg(F.max_by(F.struct("cell", "start"), "cell").alias("last"))
            .select("of", "part", F.col("last.cell").alias("prefix"), F.col("last.start").alias("below"))
        )
    inside = narrow.join(
        broadcast_if_small(state), F.col("mix_source").eqNullSafe(F.col("of")) & (F.substring("mix_digest", 1, 2 * levels) == F.col("prefix"))
    )
    each = inside.groupBy("of", "part", "below", "prefix", "mix_digest").agg(F.sum("mix_size").alias("held"))
    upto = Window.partitionBy("of").orderBy("mix_digest").rowsBetween(Window.unboundedPreceding, -1)
    middle = F.col("below") + F.coalesce(F.sum("held").over(upto), F.lit(0)) + F.col("held") / 2
    return (
        each.withColumn("middle", middle)
        .groupBy("of", "prefix")
        .agg(F.max(F.when(F.col("middle") <= F.col("part"), F.col("mix_digest"))).alias("cut"))
        .select(F.col("of").alias("mix_source"), F.coalesce("cut", "prefix").alias("cut"))
    )


def mix(
    docs: DataFrame,
    *,
    id_col: str = "doc_id",
    text: str = "text",
    source: str = "source",
    weights: Sequence[int] = WEIGHTS,
    share: float = SHARE,
    max_epochs: float = MAX_EPOCHS,
    seed: int = SEED,
) -> DataFrame:
    """``docs`` plus mix_size, mix_source_size, mix_target (of the row's source) and mix_times.

    ``mix_times`` is how often the mix takes the document; names are extended if taken.
    """
    sized = docs.select(
        F.col(source).alias("mix_source"), word_count(F.col(text)).alias("mix_size"), digest(F.col(id_col), seed).alias("mix_digest")
    )
    narrow = materialise(sized)
    targets = materialise(source_targets(narrow, source="mix_source", weights=weights, share=share, max_epochs=max_epochs))
    cuts = extra_cuts(narrow, targets)
    plan = materialise(
        targets.join(cuts.withColumnRenamed("mix_source", "of"), F.col("mix_source").eqNullSafe(F.col("of")), "left").drop("of")
    )
    plan_source, plan_whole, plan_cut = (fresh_name(docs, x) for x in ("plan_source", "plan_whole", "plan_cut"))
    names = {k: fresh_name(docs, v) for k, v in (("size", "mix_size"), ("source_size", "mix_source_size"), ("target", "mix_target"), ("times", "mix_times"))}
    rows = plan.select(
        F.col("mix_source").alias(plan_source), F.col("source_size").alias(names["source_size"]), F.col("target").alias(names["target"]),
        F.col("whole").alias(plan_whole), F.col("cut").alias(plan_cut),
    )
    once_more = F.coalesce(digest(F.col(id_col), seed) <= F.col(plan_cut), F.lit(False)).cast("long")
    return (
        docs.join(broadcast_if_small(rows), F.col(source).eqNullSafe(F.col(plan_source)), "left")
        .withColumn(names["size"], word_count(F.col(text)))
        .withColumn(names["times"], F.when(F.col(names["size"]) > 0, F.col(plan_whole) + once_more).otherwise(0).cast("long"))
        .drop(plan_source, plan_whole, plan_cut)
    )


def repeat_rows(mixed: DataFrame, times: str = "mix_times") -> DataFrame:
    """The mix itself: each row as often as ``times`` says, its other columns unchanged."""
    turn = fresh_name(mixed, "mix_turn")
    many = mixed.where(F.col(times) > 0).withColumn(turn, F.explode(F.sequence(F.lit(1).cast("long"), F.col(times))))
    return many.drop(turn)


def op5_mixing(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source")
    return mix(docs).select(
        "doc_id",
        F.col("mix_size").alias("size"),
        F.col("mix_source_size").alias("source_size"),
        F.col("mix_target").alias("target"),
        (F.col("mix_size") * F.col("mix_times")).alias("taken"),
    )


ORACLE = """
with d as (
  select doc_id, source, md5('42:' || doc_id::varchar) as dig,
         coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::bigint as size
  from documents),
s as (
  select source, sum(size)::bigint as source_size from d group by source),
w as (
  select source, source_size, row_number() over (order by encode(source) nulls last) - 1 as turn from s),
c as (
  select *, (case turn % 3 when 0 then 3.0 when 1 then 1.0 else 2.0 end)::double as weight,
         source_size * 2.0::double as cap from w),
l as (
  select *, (sum(source_size) over ())::double * 1.5::double as total,
         coalesce(sum(cap) over o, 0) as spent,
         sum(weight) over () - coalesce(sum(weight) over o, 0) as rest
  from c window o as (order by cap / weight, turn rows between unbounded preceding and 1 preceding)),
v as (
  select *, cap > (total - spent) / rest * weight as is_open, (total - spent) / rest as lev from l),
t as (
  select source, source_size,
         case when is_open then (max(case when is_open then lev end) over ()) * weight else cap end as target
  from v),
e as (
  select *, case when source_size > 0 then floor(target / source_size)::bigint else 0 end as whole from t),
r as (
  select d.doc_id, d.size, e.source_size, e.target, e.whole, e.target - e.whole * e.source_size as part,
         coalesce(sum(d.size) over (partition by d.source order by d.dig
                  rows between unbounded preceding and 1 preceding), 0) + d.size / 2 as middle
  from d join e on d.source is not distinct from e.source)
select doc_id, size, source_size, target::double as target,
       (size * (whole + case when middle <= part then 1 else 0 end))::bigint as taken
from r
"""
