"""Embedding near-dedup: random-hyperplane sign hashing, exact cosines, components.

Signatures.  ``tables`` x ``bits`` seeded hyperplanes give each vector one bucket key per
table.  The number of bits follows the number of vectors (about 16 to a bucket), and the
number of tables follows the bits so that a pair exactly at the threshold shares a bucket
with chance ``recall``; pairs above it do so more surely.

Candidates.  An index row is a key, an id and a sketch of 128 further signs; vectors stay
where they are.  Pairs of a bucket whose sketches differ in no more bits than a pair at the
threshold may (``SIGMAS`` standard deviations) join families, of which a bucket emits the
links of a spanning forest.

Verification.  A vector is in one family at most and is sent there once.  Within a family
cosines are blocks of matrix products in double precision: every pair is compared once,
counted, and only the links of a spanning forest leave, for distributed connected
components.  Buckets and families too large for one task are split into pairs of blocks.
Equal vectors collapse to one before any of this and are counted by multiplicity.

Defined cases: null or zero vectors, vectors with null or non-finite components, and empty
ones link with nothing; vectors of different lengths never link; null ids keep their row
(component null unless linked); repeated ids share a component; an empty table gives an
empty table; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sitemine.llm.buckets import deal, runs
from sitemine.llm.components import connected_components
from sitemine.llm.simhash import forest
from sitemine.session import materialise

THRESHOLD = 0.9
RECALL = 0.995
SEED = 42
BUCKET = 16
#: Vectors of one family or block that a worker compares at a time.
BLOCK_ROWS = 4096
#: Signs of a sketch, and standard deviations by which a pair's differing signs may pass the expected number.
SKETCH = 128
SIGMAS = 4
_TILE = 512


def lsh_shape(n: int, threshold: float = THRESHOLD, recall: float = RECALL) -> tuple[int, int]:
    """(bits, tables) for n vectors."""
    bits = max(6, math.ceil(math.log2(max(2, n) / BUCKET)))
    agree = (1 - math.acos(threshold) / math.pi) ** bits
    return bits, math.ceil(math.log(1 - recall) / math.log(1 - agree))


def hyperplanes(dim: int, bits: int, tables: int, seed: int = SEED) -> np.ndarray:
    return np.random.default_rng([seed, dim]).standard_normal((dim, tables * bits))


def table_keys(x: np.ndarray, bits: int, tables: int, seed: int = SEED) -> np.ndarray:
    """(n, tables) bucket numbers of the rows of x."""
    signs = (x @ hyperplanes(x.shape[1], bits, tables, seed) > 0).reshape(len(x), tables, bits)
    return signs @ (1 << np.arange(bits, dtype=np.int64))


def unit_rows(x: np.ndarray) -> np.ndarray:
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def signed(nodes: DataFrame, bits: int, tables: int, seed: int = SEED) -> DataFrame:
    """(node, keys, s0, s1): bucket keys and sketch of each vector."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            dims = batch.column("dim").to_numpy()
            for dim in np.unique(dims):
                some = batch.filter(pa.array(dims == dim))
                for part in (some.slice(i, 256) for i in range(0, some.num_rows, 256)):
                    x = unit_rows(part.column("vector").flatten().to_numpy().reshape(-1, dim).astype(np.float64))
                    keys = (np.int64(dim) << 16 | np.arange(tables)) << bits | table_keys(x, bits, tables, seed)
                    signs = np.packbits(x @ hyperplanes(dim, SKETCH, 1, seed + 1) > 0, axis=1, bitorder="little").view("<i8")
                    lists = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * tables), pa.array(keys.ravel()))
                    yield pa.RecordBatch.from_arrays(
                        [part.column("node"), lists, pa.array(np.ascontiguousarray(signs[:, 0])), pa.array(np.ascontiguousarray(signs[:, 1]))], names=["node", "keys", "s0", "s1"]
                    )

    return nodes.select("node", F.size("vector").alias("dim"), "vector").mapInArrow(run, "node long, keys array<long>, s0 long, s1 long")


def family_links(index: DataFrame, threshold: float) -> DataFrame:
    """(a, b): a spanning forest of every bucket, of pairs whose sketches may belong to a link."""
    share = math.acos(threshold) / math.pi
    most = math.floor(SKETCH * share + SIGMAS * math.sqrt(SKETCH * share * (1 - share)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table, bounds in runs(batches):
            nodes = table.column("node").to_numpy()
            sketch = np.stack([table.column(c).to_numpy() for c in ("s0", "s1")], axis=1).view(np.uint64)
            close = lambda x, y: np.bitwise_count(x ^ y).sum(axis=1, dtype=np.int64) <= most
            found = []
            for i in np.flatnonzero(np.diff(bounds) > 1):
                mine = sketch[bounds[i] : bounds[i + 1]]
                found += forest(nodes[bounds[i] : bounds[i + 1]], lambda left, at, mine=mine: close(mine[left], mine[at]))
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([f[j] for f in found])) for j in (0, 1)], names=["a", "b"])

    dealt = deal(lambda some: some.select(F.explode("keys").alias("key"), "node", "s0", "s1"), index)
    return dealt.select("key", "bi", "bj", "node", "s0", "s1").mapInArrow(run, "a long, b long")


def compare_family(x: np.ndarray, side: np.ndarray | None, copies: np.ndarray, threshold: float) -> tuple[np.ndarray, list]:
    """Links counted for each row of unit vectors x, and (row, row) links of a spanning forest.

    With ``side`` only rows of different sides are compared.
    """
    n = len(x)
    counts, label = np.zeros(n, np.int64), np.arange(n)
    links: list[tuple[int, int]] = []
    for i in range(0, n, _TILE):
        for j in range(i, n, _TILE):
            a, b = slice(i, i + _TILE), slice(j, j + _TILE)
            near = x[a] @ x[b].T >= threshold
            if i == j:
                near &= np.triu(np.ones(near.shape, bool), 1)
            if side is not None:
                near &= side[a][:, None] != side[b][None, :]
            if not near.any():
                continue
            counts[a] += near @ copies[b]
            counts[b] += copies[a] @ near
            for r in i + np.flatnonzero(near.any(axis=1)):
                hits = j + np.flatnonzero(near[r - i])
                for other in hits[label[hits] != label[r]]:
                    if label[other] != label[r]:
                        label[label == label[other]] = label[r]
                        links.append((r, other))
    return counts, links


def _compared(members: DataFrame, number: str, threshold: float) -> DataFrame:
    """(a, b, n) of (family, node, copies, vector): n > 0 links counted for a (b is -1), or n = 0 and a link of a forest."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table, bounds in runs(batches, ("family", "bi", "bj")):
            nodes, copies, side = (table.column(c).to_numpy() for c in ("node", "copies", "side"))
            pair = table.column("bi").to_numpy() != table.column("bj").to_numpy()
            vectors = table.column("vector").combine_chunks()
            a: list[np.ndarray] = []
            b: list[np.ndarray] = []
            n: list[np.ndarray] = []
            for lo, hi in zip(bounds[:-1], bounds[1:], strict=True):
                x = np.stack([np.frombuffer(v.as_buffer(), number) for v in vectors[lo:hi]]).astype(np.float64)
                counts, links = compare_family(unit_rows(x), side[lo:hi] if pair[lo] else None, copies[lo:hi], threshold)
                some = np.flatnonzero(counts)
                a.append(nodes[lo:hi][some]); b.append(np.full(len(some), -1)); n.append(counts[some])  # fmt: skip  # noqa: E702
                if links:
                    ends = nodes[lo:hi][np.array(links)]
                    a.append(ends[:, 0]); b.append(ends[:, 1]); n.append(np.zeros(len(ends), np.int64))  # fmt: skip  # noqa: E702
            if sum(map(len, a)):
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in (a, b, n)], names=["a", "b", "n"])

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw = [v.values.to_numpy().astype(number).tobytes() for v in batch.column("vector")]
            yield pa.RecordBatch.from_arrays([batch.column(c) for c in ("family", "node", "copies")] + [pa.array(raw, pa.binary())], names=["family", "node", "copies", "vector"])

    rows = members.select("family", "node", "copies", "vector").mapInArrow(packed, "family long, node long, copies long, vector binary")
    dealt = deal(lambda some: some, rows, key="family", block_rows=BLOCK_ROWS)
    return dealt.select("family", "bi", "bj", "side", "node", "copies", "vector").mapInArrow(run, "a long, b long, n long")


def near_duplicates(
    vectors: DataFrame, *, id_col: str = "vec_id", vector: str = "embedding", threshold: float = THRESHOLD, recall: float = RECALL, seed: int = SEED
) -> DataFrame:
    """(vec_id, n_links, component_id, kept), one row per row of ``vectors``."""
    number = "float" if dict(vectors.dtypes)[vector] == "array<float>" else "double"
    exact = F.col(vector).cast(f"array<{number}>")
    usable = (
        F.col(vector).isNotNull()
        & (F.size(vector) > 0)
        & F.forall(exact, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
        & F.exists(exact, lambda v: v != 0)
    )
    rows = vectors.select(F.col(id_col).alias("vec_id"), F.when(usable, exact).alias("vector"))
    groups = materialise(
        rows.where(F.col("vector").isNotNull())
        .groupBy("vector")
        .agg(F.min("vec_id").cast("long").alias("node"), F.count("*").alias("copies"))
    )
    n = groups.count()
    bits, tables = lsh_shape(n, threshold, recall)
    nodes = groups.where(F.col("node").isNotNull()).select("node", "copies", "vector")
    families = connected_components(family_links(signed(nodes, bits, tables, seed), threshold)).select("node", F.col("component").alias("family"))
    found = materialise(_compared(nodes.join(families, "node"), {"float": "<f4", "double": "<f8"}[number], threshold))
    counts = found.where("n > 0").groupBy(F.col("a").alias("node")).agg(F.sum("n").alias("others"))
    parts = connected_components(found.where("n = 0").select("a", "b"))
    known = materialise(
        groups.join(counts, "node", "left")
        .join(parts, "node", "left")
        .select(
            F.col("vector").alias("of"), (F.coalesce("others", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("component", "node").alias("component_id")
        )
    )
    joined = rows.join(known, F.col("vector") == F.col("of"), "left")
    component = F.coalesce("component_id", "vec_id")
    return joined.select(
        "vec_id",
        F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"),
        component.alias("component_id"),
        F.coalesce(F.col("vec_id") == component, F.lit(True)).alias("kept"),
    )


def op2_embedding_dedup(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding"))


ORACLE = """
with v as (
  select vec_id, embedding::double[] as e from embeddings),
ok as (
  select vec_id, e from v
  where e is not null and len(e) > 0 and len(list_filter(e, lambda x: x is null or not isfinite(x))) = 0
    and len(list_filter(e, lambda x: x <> 0)) > 0),
links as (
  select p.vec_id as a, q.vec_id as b
  from ok p join ok q on p.vec_id <> q.vec_id and len(p.e) = len(q.e)
  where list_cosine_similarity(p.e, q.e) >= 0.9),
reach as (
  with recursive r(a, b) as (
    select a, b from links
    union
    select r.a, l.b from r join links l on r.b = l.a)
  select a, min(b) as low from r group by a),
n as (select a, count(*) as n_links from links group by a)
select v.vec_id, coalesce(n.n_links, 0)::bigint as n_links,
       least(v.vec_id, coalesce(reach.low, v.vec_id))::bigint as component_id,
       v.vec_id = least(v.vec_id, coalesce(reach.low, v.vec_id)) as kept
from v left join n on v.vec_id = n.a left join reach on v.vec_id = reach.a
"""
