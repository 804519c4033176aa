"""Support counting: how many baskets of each site hold each of given itemsets.

Five engines with equal results, for different shapes of data:

* ``bitmap``: the sets asked for are held in the worker; baskets become a bit column an
  item, block by block, and a set's count is the number of bits its columns share.
* ``trie``: the same bound, sets as a prefix tree walked basket by basket; for few, very
  long baskets.
* ``expand``: each basket lists its subsets of the sizes asked for, those not asked for
  are filtered by a join, the rest are counted; pure Catalyst, for short baskets.
* ``extend``: itemsets grow by one item inside the row that carries the basket, so that
  only prefixes of what is asked for survive; pure Catalyst, for longer baskets.
* ``contains``: every set against every basket; for a handful of sets.

``auto`` takes ``bitmap`` where the sets fit a worker and else one of the Catalyst engines
by the length of baskets.  Baskets are never shuffled by the first two; for the others they
are first cut to the items that occur in the sets asked for.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sitemine.functions.itemset_columns import subsets
from sitemine.session import broadcast_if_small

#: Sets that the ``bitmap``, ``trie`` and ``contains`` engines may hold in a worker.
MAX_HELD_SETS = 200_000
ENGINES = ("expand", "extend", "trie", "contains", "bitmap")
#: Items in a basket up to which listing its subsets is cheaper than growing them.
EXPAND_LENGTH = 25
#: Flags (one an item code and site) that the cutting of baskets may broadcast.
MAX_FLAGS = 10_000_000
#: Bytes of an uncompressed block of bit columns, and baskets of a block.
_BLOCK_BYTES = 1 << 26
_BLOCK_BASKETS = 1 << 16


def shrink(baskets: DataFrame, items: DataFrame, *, by_site: bool = False) -> DataFrame:
    """``baskets`` cut to ``items`` (code, and site with ``by_site``); emptied baskets go.

    Flags by item code are looked up inside the row, so a basket costs its length and is not
    shuffled.  Cutting only saves work: where the flags would pass ``MAX_FLAGS`` it is left out.
    """
    keys = ["site", "code"] if by_site else ["code"]
    held = items.select(*keys).distinct().limit(MAX_FLAGS + 1)
    sites, top = held.agg(F.count_distinct("site") if by_site else F.lit(1), F.coalesce(F.max("code"), F.lit(-1))).first()
    if max(1, sites) * (top + 1) > MAX_FLAGS:
        return baskets
    flags = held.groupBy(*keys[:-1]).agg(F.collect_list("code").alias("codes"))
    width = [f.name for f in flags.schema if f.name == "site"]
    rows = []
    for r in flags.collect():
        on = [False] * (top + 1)
        for code in r.codes:
            on[code] = True
        rows.append((*[r[w] for w in width], on))
    flagged = baskets.sparkSession.createDataFrame(rows, ("site int, " if by_site else "") + "flags array<boolean>")
    joined = baskets.join(F.broadcast(flagged), "site") if by_site else baskets.crossJoin(F.broadcast(flagged))  # one row
    return joined.select("site", "tid", F.filter("items", lambda x: F.coalesce(F.get("flags", x), F.lit(False))).alias("items")).where(F.size("items") > 0)


def counting_engine(baskets: DataFrame, n_sets: int | None = None) -> str:
    """bitmap where the sets fit a worker, else expand for short baskets and extend for long ones."""
    if n_sets is not None and n_sets <= MAX_HELD_SETS:
        return "bitmap"
    long = baskets.agg(F.percentile_approx(F.size("items"), 0.99, 1000)).first()[0] or 0
    return "expand" if long <= EXPAND_LENGTH else "extend"


def count_support(baskets: DataFrame, sets: DataFrame, sizes: list[int], *, engine: str = "auto", by_site: bool = True) -> DataFrame:
    """(site, itemset, cnt) of ``sets`` (itemset, and site if only that site is asked).

    ``by_site=False`` gives (itemset, cnt) over all sites.
    """
    keys = ["site", "itemset"] if "site" in sets.columns else ["itemset"]
    wanted = sets.select(*keys).distinct()
    if engine not in (*ENGINES, "auto"):
        raise ValueError(f"engine must be auto or one of {', '.join(ENGINES)}")
    if engine in ("auto", "bitmap", "trie"):
        held = wanted.limit(MAX_HELD_SETS + 1).collect()
        if len(held) <= MAX_HELD_SETS:
            counted = (_trie if engine == "trie" else _bitmap)(baskets, held, "site" in keys, by_site)
            return counted if by_site else counted.groupBy("itemset").agg(F.sum("cnt").alias("cnt"))
        if engine != "auto":
            raise ValueError(f"the {engine} engine holds at most {MAX_HELD_SETS} sets; use expand or extend")
        engine = counting_engine(baskets)
    codes = wanted.select(*[k for k in keys if k == "site"], F.explode("itemset").alias("code")).distinct()
    cut = shrink(baskets, codes, by_site="site" in keys)
    if engine == "contains":
        held = broadcast_if_small(wanted, MAX_HELD_SETS)
        near = cut.join(held, "site") if "site" in keys else cut.crossJoin(held)
        counted = near.where(F.size(F.array_intersect("items", "itemset")) == F.size("itemset")).groupBy("site", "itemset").agg(F.count("*").alias("cnt"))
    else:
        counted = (_expand if engine == "expand" else _extend)(cut, wanted, keys, sizes)
    return counted if by_site else counted.groupBy("itemset").agg(F.sum("cnt").alias("cnt"))


def count_sets(offsets: np.ndarray, values: np.ndarray, sets: np.ndarray) -> np.ndarray:
    """How many baskets (items ``values[offsets[i]:offsets[i + 1]]``) hold each row of ``sets``."""
    counts = np.zeros(len(sets), np.int64)
    if not sets.size or len(offsets) < 2:
        return counts
    codes, spot = np.unique(sets, return_inverse=True)
    spot = spot.reshape(sets.shape)
    block = int(min(_BLOCK_BASKETS, max(1024, _BLOCK_BYTES // len(codes))))
    for first in range(0, len(offsets) - 1, block):
        ends = offsets[first : first + block + 1]
        mine = values[ends[0] : ends[-1]]
        basket = np.repeat(np.arange(len(ends) - 1), np.diff(ends))
        at = np.minimum(np.searchsorted(codes, mine), len(codes) - 1)
        there = codes[at] == mine
        dense = np.zeros((len(codes), -(-(len(ends) - 1) // 64) * 64), bool)
        dense[at[there], basket[there]] = True
        bits = np.packbits(dense, axis=1).view(np.uint64)
        step = max(1, (1 << 21) // bits.shape[1])
        for i in range(0, len(sets), step):
            some = spot[i : i + step]
            shared = bits[some[:, 0]]
            for j in range(1, sets.shape[1]):
                shared &= bits[some[:, j]]
            counts[i : i + step] += np.bitwise_count(shared).sum(axis=1, dtype=np.int64)
    return counts


def lists_of(sets: np.ndarray) -> pa.Array:
    """The rows of a matrix as an Arrow array of lists."""
    ends = np.arange(len(sets) + 1, dtype=np.int32) * sets.shape[1]
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(sets.ravel().astype(np.int32)))


def flat(lists: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """(offsets, values) of an Arrow array of lists."""
    if isinstance(lists, pa.ChunkedArray):
        lists = lists.combine_chunks()
    if isinstance(lists, pa.ChunkedArray):
        lists = lists.chunk(0) if lists.num_chunks else pa.array([], lists.type)
    sizes = np.diff(lists.offsets.to_numpy())
    return np.concatenate([[0], np.cumsum(sizes)]), lists.flatten().to_numpy()


def _bitmap(baskets: DataFrame, held: list, of_site: bool, by_site: bool) -> DataFrame:
    asked: dict[int | None, dict[int, list]] = {}
    for r in held:
        asked.setdefault(r["site"] if of_site else None, {}).setdefault(len(r["itemset"]), []).append(r["itemset"])
    matrices = {site: [np.array(sets, np.int32) for _, sets in sorted(by.items())] for site, by in asked.items()}
    shared = baskets.sparkSession.sparkContext.broadcast(matrices)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matrices = shared.value
        totals: dict[int, list[np.ndarray]] = {}

        def add(some: list[pa.RecordBatch]) -> None:
            table = pa.Table.from_batches(some)
            site = table.column("site").to_numpy() if by_site or of_site else np.zeros(table.num_rows, np.int32)
            for s in np.unique(site).tolist():
                mine = matrices.get(s if of_site else None)
                if mine:
                    offsets, values = flat(table.filter(pa.array(site == s)).column("items"))
                    found = [count_sets(offsets, values, m) for m in mine]
                    totals[s] = [a + b for a, b in zip(totals[s], found, strict=True)] if s in totals else found

        waiting: list[pa.RecordBatch] = []
        for batch in batches:
            waiting.append(batch)
            if sum(b.num_rows for b in waiting) >= _BLOCK_BASKETS:
                add(waiting)
                waiting = []
        if waiting:
            add(waiting)
        for s, counts in totals.items():
            for sets, n in zip(matrices[s if of_site else None], counts, strict=True):
                some = np.flatnonzero(n)
                if len(some):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), s, np.int32)), lists_of(sets[some]), pa.array(n[some])], names=["site", "itemset", "cnt"])

    found = baskets.select("site", "items").mapInArrow(run, "site int, itemset array<int>, cnt long")
    return found.groupBy("site", "itemset").agg(F.sum("cnt").alias("cnt")) if by_site else found.select("itemset", "cnt")


def _expand(cut: DataFrame, wanted: DataFrame, keys: list[str], sizes: list[int]) -> DataFrame:
    longest = min(sizes)
    every = F.flatten(F.array(*[subsets(F.col("items"), z) for z in sizes]))
    rows = cut.where(F.size("items") >= longest).select("site", F.explode(every).alias("itemset"))
    return rows.join(broadcast_if_small(wanted), keys, "left_semi").groupBy("site", "itemset").agg(F.count("*").alias("cnt"))


def _extend(cut: DataFrame, wanted: DataFrame, keys: list[str], sizes: list[int]) -> DataFrame:
    site = [k for k in keys if k == "site"]
    rows = cut.select("site", "items", F.explode("items").alias("x")).select("site", "items", F.array("x").alias("itemset"))
    out = None
    for z in range(1, max(sizes) + 1):
        if z > 1:
            more = F.filter("items", lambda x: x > F.element_at("itemset", -1))
            rows = rows.select("site", "items", "itemset", F.explode(more).alias("x")).select("site", "items", F.concat("itemset", F.array("x")).alias("itemset"))
        prefixes = wanted.where(F.size("itemset") >= z).select(*site, F.slice("itemset", 1, z).alias("itemset")).distinct()
        rows = rows.join(broadcast_if_small(prefixes), keys, "left_semi")
        if z in sizes:
            exact = wanted.where(F.size("itemset") == z)
            found = rows.join(broadcast_if_small(exact), keys, "left_semi").groupBy("site", "itemset").agg(F.count("*").alias("cnt"))
            out = found if out is None else out.union(found)
    return out


def _trie(baskets: DataFrame, held: list, of_site: bool, by_site: bool) -> DataFrame:
    trees: dict = {}
    for r in held:
        at = trees.setdefault(r["site"] if of_site else None, {})
        for x in r["itemset"]:
            at = at.setdefault(x, {})
        at[None] = tuple(r["itemset"])
    shared = baskets.sparkSession.sparkContext.broadcast(trees)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trees = shared.value
        seen: Counter = Counter()
        for batch in batches:
            for site, items in zip(batch.column("site").to_pylist(), batch.column("items").to_pylist(), strict=True):
                tree = trees.get(site if of_site else None, {})
                todo = [(tree, 0)]
                while todo:
                    at, start = todo.pop()
                    if None in at:
                        seen[site, at[None]] += 1
                    for i in range(start, len(items)):
                        if items[i] in at:
                            todo.append((at[items[i]], i + 1))
        yield pa.RecordBatch.from_arrays(
            [pa.array([s for s, _ in seen], pa.int32()), pa.array([list(x) for _, x in seen], pa.list_(pa.int32())), pa.array(list(seen.values()), pa.int64())],
            names=["site", "itemset", "cnt"],
        )

    return baskets.select("site", "items").mapInArrow(run, "site int, itemset array<int>, cnt long").groupBy("site", "itemset").agg(F.sum("cnt").alias("cnt"))
