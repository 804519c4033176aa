"""Buckets of an inverted index, read as runs of equal keys from sorted Arrow batches.

A bucket is never collected by Spark: rows are dealt by key, sorted within their
partition and streamed; only one bucket at a time is in a worker's memory.  Keys too
common for that are found on a hashed sixteenth-of-a-sixteenth of the nodes (which only
decides how rows are laid out, never which are compared) and split into blocks; each
pair of blocks becomes a bucket of its own, so every two rows of the key still meet.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sitemine.session import broadcast_if_small, materialise

#: Rows of one bucket or block that a worker takes at a time.
BLOCK_ROWS = 16_384
_SAMPLED = 256


def deal(make_index: Callable[[DataFrame], DataFrame], nodes: DataFrame, *, key: str = "key", node: str = "node", block_rows: int = BLOCK_ROWS) -> DataFrame:
    """``make_index(nodes)`` plus (side, bi, bj), dealt and sorted by (key, bi, bj).

    Rows of an ordinary key have bi = bj = side = 0.  A hot key's rows carry their block
    in ``side`` and appear once for every pair of blocks that contains it.
    """
    sample = make_index(nodes.where(F.pmod(F.xxhash64(node), F.lit(_SAMPLED)) == 0))
    hot = materialise(
        sample.groupBy(F.col(key).alias("hot_key"))
        .agg(F.count("*").alias("seen"))
        .where(F.col("seen") * _SAMPLED >= block_rows)
        .select("hot_key", F.ceil(F.col("seen") * _SAMPLED * 2 / block_rows).cast("int").alias("blocks"))
    )
    index = make_index(nodes)
    if hot.isEmpty():
        laid = index.withColumns({c: F.lit(0) for c in ("side", "bi", "bj")})
    else:
        laid = (
            index.join(broadcast_if_small(hot), F.col(key) == F.col("hot_key"), "left")
            .withColumn("blocks", F.coalesce("blocks", F.lit(1)))
            .withColumn("side", F.pmod(F.xxhash64(F.lit(3), F.col(node)), F.col("blocks")).cast("int"))
            .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
            .withColumn("bi", F.least("side", "other"))
            .withColumn("bj", F.greatest("side", "other"))
            .drop("hot_key", "blocks", "other")
        )
    return laid.repartition(key, "bi", "bj").sortWithinPartitions(key, "bi", "bj")


def runs(batches: Iterator[pa.RecordBatch], keys: tuple[str, ...] = ("key", "bi", "bj")) -> Iterator[tuple[pa.Table, np.ndarray]]:
    """(table, bounds): whole runs of equal keys; run i is rows bounds[i]..bounds[i+1]."""
    held: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        columns = [batch.column(k).to_numpy(zero_copy_only=False) for k in keys]
        first = tuple(c[0] for c in columns)
        change = np.zeros(batch.num_rows, bool)
        change[0] = last is not None and first != last
        for c in columns:
            change[1:] |= c[1:] != c[:-1]
        cuts = np.flatnonzero(change)
        last = tuple(c[-1] for c in columns)
        if not len(cuts):
            held.append(batch)
            continue
        held.append(batch.slice(0, cuts[-1]))
        yield _bounded(held, keys)
        held = [batch.slice(cuts[-1])]
    if held:
        yield _bounded(held, keys)


def _bounded(parts: list[pa.RecordBatch], keys: tuple[str, ...]) -> tuple[pa.Table, np.ndarray]:
    table = pa.Table.from_batches([p for p in parts if p.num_rows]).combine_chunks()
    change = np.ones(table.num_rows, bool)
    change[1:] = False
    for k in keys:
        c = table.column(k).to_numpy()
        change[1:] |= c[1:] != c[:-1]
    return table, np.append(np.flatnonzero(change), table.num_rows)
