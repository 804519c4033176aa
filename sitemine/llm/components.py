"""Distributed connected components over a link table, by contraction.

A round hooks every node to the smallest of itself and its neighbours, moves pointers up to
the roots of the trees so made (doubling their reach each time), and replaces the ends of
each link by their roots.  Links inside a tree vanish, so the table shrinks from round to
round; when it is empty the rounds' pointers are joined from the last to the first.  A
component's smallest node is never moved and ends as its name.  Minima combine before the
shuffle, and both sides of the joins that meet a hub are plain exchanges, which adaptive
execution can split; none is a broadcast, of which the driver would hold one a step.
Nothing is collected there but a sum a step.

Steps are cut by tables in the shared folder: a checkpoint keeps the size estimate of its
plan, which over a chain of self-joins becomes a number of millions of digits.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from sitemine.session import drop_shared, materialise, shared_table


def connected_components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component) for every node of a link between two different nodes.

    ``component`` is the smallest node reachable.  Self links, null ends and repeated
    links are allowed and change nothing.  No links give an empty table.
    """
    written: list[str] = []

    def kept(df: DataFrame) -> DataFrame:
        df, path = shared_table(df)
        written.append(path)
        return df

    def summed(pointers: DataFrame) -> tuple[DataFrame, object]:
        seen = Observation()
        df = kept(pointers.observe(seen, F.sum(F.col("root").cast("decimal(38,0)")).alias("total")))
        return df, seen.get["total"]

    def contracted(ends: DataFrame) -> DataFrame:
        return kept(ends.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())

    def roots(pointers: DataFrame) -> DataFrame:
        """Pointers (node, root) moved up until they stand still; they only fall, so their sum tells."""
        now, total = summed(pointers)
        while True:
            above = now.select(F.col("node").alias("up"), F.col("root").alias("top"))
            before = total
            now, total = summed(now.join(above.hint("merge"), F.col("root") == F.col("up")).select("node", F.col("top").alias("root")))
            if total == before:
                return now

    known = links.where(F.col(a).isNotNull() & F.col(b).isNotNull())
    edges = contracted(known.select(F.col(a).alias("u"), F.col(b).alias("v")))
    rounds: list[DataFrame] = []
    while True:
        ends = edges.select(F.explode(F.array(F.struct("u", "v"), F.struct(F.col("v").alias("u"), F.col("u").alias("v")))).alias("e"))
        rounds.append(roots(ends.groupBy(F.col("e.u").alias("node")).agg(F.min("e.v").alias("near")).select("node", F.least("node", "near").alias("root"))))
        side = lambda end: rounds[-1].select(F.col("node").alias(end), F.col("root").alias(f"root_{end}")).hint("merge")
        edges = contracted(edges.join(side("u"), "u").join(side("v"), "v").select(F.col("root_u").alias("u"), F.col("root_v").alias("v")))
        if edges.isEmpty():
            break
    out = rounds.pop()
    while rounds:
        above = out.select(F.col("node").alias("up"), F.col("root").alias("top")).hint("merge")
        out = kept(rounds.pop().join(above, F.col("root") == F.col("up"), "left").select("node", F.coalesce("top", "root").alias("root")))
    out = materialise(out.select("node", F.col("root").alias("component")))
    for path in written:
        drop_shared(links.sparkSession, path)
    return out
