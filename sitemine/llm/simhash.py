"""SimHash near-dedup over a byte-position inverted index with count filtering.

Fingerprints.  A text's words (A-Z lower-cased) form shingles of ``shingle`` words,
repeats included; a fingerprint bit is 1 when more than half of the shingle hashes have
it set.  One 64-bit word comes from XXH64 with seed 42; further words, where asked for,
remix the same hash.

Index.  Equal fingerprints collapse to one node (the smallest id), so groups of exact
copies cost one row each.  A node is filed under the values of its bytes at chosen
positions: two 64-bit fingerprints that differ in at most d = 4 bits agree in at least
8 - d = 4 bytes, and of the first seven bytes in at least 3; all 35 triples of those
seven positions are keys, so every link meets in some bucket.

Filtering.  In a bucket the shared positional bytes of each pair are tallied, pairs
below the guaranteed minimum leave, and the rest are verified by their differing bits.
A breadth-first sweep emits only the links of a spanning forest: a bucket of n
neighbours yields n - 1 links, not n^2.

Similarity mode.  Two texts whose sets of shingles are similar at 0.8 differ in a fifth of
their bits, so no byte of one short fingerprint is sure to agree and a tally of its bytes
guarantees nothing.  Here the shingles are dealt by their hash to positions, and each
position holds the SimHash word of its few shingles: where no shingle differs the word is
the same.  A set is filed under its words at the first ``POSITIONS`` positions, a number
that does not grow with the text; a pair at the threshold agrees in about a third of them
and in none with a chance below 0.0001.  A row of the index carries a byte of each of the
first ``TALLIED`` positions.  In a bucket the positional bytes that each pair shares are
tallied and pairs below ``LEAST`` leave: a pair at the threshold shares fifteen or more on
average, and fewer than ``LEAST`` with a chance below 0.00001.  Of the rest, pairs whose
256-bit fingerprints are within ``SIGMAS`` standard deviations of the difference expected
at the threshold join families; inside a family every two sets are compared exactly, in
blocks.  Sets of at most
``SHORT`` shingles are compared exactly wherever they share one of their smallest shingle
hashes, which two similar sets always do.

Defined cases: null, empty and blank texts have the zero fingerprint and are linked like
any other; fewer words than a shingle form one shingle of them all; rows with a null id
get a fingerprint but no component unless their fingerprint is shared; repeated ids
share a component; an empty table gives an empty table; other columns are not touched.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sitemine.llm.buckets import deal, runs
from sitemine.llm.common import bounded_batches, fresh_name
from sitemine.llm.components import connected_components
from sitemine.session import broadcast_if_small, materialise

SEED = 42
SHINGLE = 4
MAX_BITS = 4
#: Similarity mode.
STAGE_SHINGLE = 5
SIMILARITY = 0.8
WORDS = 4
#: Positions a set is filed under, of ``FEWEST`` times a power of four in all: at most ``CROWD`` shingles to each on average.
POSITIONS = 32
FEWEST = 64
CROWD = 3
#: Positions whose bytes are tallied (all sets have so many), and the fewest shared ones of a candidate pair.
TALLIED = FEWEST
LEAST = 3
#: Standard deviations by which a pair's differing bits may pass the expected number.
SIGMAS = 4
#: Sets of so few shingles also meet by the shingles themselves: their bits differ more than expected.
SHORT = 32
#: Shingle sets (eight bytes a shingle) that a worker compares at a time.
SET_ROWS = 2048
_CHUNK = 65_536
#: Ids (eight bytes each) that a broadcast may hold.
ID_ROWS = 4_000_000


def shingle_hashes(text: bytes, shingle: int) -> np.ndarray:
    words = text.lower().split()  # bytes.lower() and bytes.split() know ASCII only, as asked
    if not words:
        return np.empty(0, np.uint64)
    if len(words) < shingle:
        joined: Iterator[bytes] = iter([b" ".join(words)])
        n = 1
    else:
        joined = map(b" ".join, zip(*(words[i:] for i in range(shingle)), strict=False))
        n = len(words) - shingle + 1
    digest = xxhash.xxh64_intdigest
    return np.fromiter((digest(s, SEED) for s in joined), np.uint64, n)


def remix(h: np.ndarray, turn: int) -> np.ndarray:
    """Independent-looking 64 bits from a hash (a 64-bit finaliser over a shifted start)."""
    if not turn:
        return h
    x = h + np.uint64((turn * 0x9E3779B97F4A7C15) % 2**64)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _lanes() -> np.ndarray:
    """For each byte value, its eight bits as the eight bytes of a word."""
    bits = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little")
    return np.ascontiguousarray(bits).view("<u8").ravel()


_LANES = _lanes()


def bit_counts(h: np.ndarray) -> np.ndarray:
    """How often each of the 64 bits is set: bits are added eight to a word, 255 rows at a time."""
    spread = _LANES[h.astype("<u8").view(np.uint8).reshape(-1, 8)]
    sums = np.add.reduceat(spread, np.arange(0, len(h), 255), axis=0)
    return np.ascontiguousarray(sums).view(np.uint8).reshape(-1, 64).sum(axis=0, dtype=np.int64)


def fingerprint(text: bytes | None, shingle: int = SHINGLE, words: int = 1) -> list[int]:
    """``words`` unsigned 64-bit words of the text's SimHash."""
    return fingerprint_of(shingle_hashes(text or b"", shingle), words)


def fingerprint_of(h: np.ndarray, words: int) -> list[int]:
    if not len(h):
        return [0] * words
    out = []
    for turn in range(words):
        ones = sum((bit_counts(remix(h[i : i + _CHUNK], turn)) for i in range(0, len(h), _CHUNK)), np.zeros(64, np.int64))
        out.append(int.from_bytes(np.packbits(2 * ones > len(h), bitorder="little").tobytes(), "little"))
    return out


def fingerprints(docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", shingle: int = SHINGLE) -> DataFrame:
    """(id, w0): the 64-bit fingerprint of each row of ``docs`` as a signed long."""
    kind = dict(docs.dtypes)[id_col]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made = [fingerprint(t, shingle)[0] for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.array(made, np.uint64).view(np.int64))], names=["id", "w0"])

    rows = bounded_batches(docs).select(F.col(id_col).alias("id"), F.col(text).cast("binary").alias("text"))
    return rows.mapInArrow(run, f"id {kind}, w0 long")


def position_words(h: np.ndarray, positions: int) -> tuple[np.ndarray, np.ndarray]:
    """(position, word): SimHash words of the shingles dealt to each of the first ``TALLIED`` of ``positions``."""
    at = (remix(h, 7) >> np.uint64(32)) * np.uint64(positions) >> np.uint64(32)
    own = np.flatnonzero(at < TALLIED)
    own = own[np.argsort(at[own], kind="stable")]
    where, starts, sizes = np.unique(at[own], return_index=True, return_counts=True)
    if not len(where):
        return where, where
    ones = np.zeros((len(where), 64), np.int64)
    np.add.at(ones, np.repeat(np.arange(len(where)), sizes), np.unpackbits(remix(h[own], 8).astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"))
    return where, np.packbits(2 * ones > sizes[:, None], axis=1, bitorder="little").view("<u8").ravel()


def position_filings(h: np.ndarray, ratio: float) -> list[tuple[np.ndarray, np.ndarray]]:
    """(keys, positional bytes) of each filing of a set of shingle hashes; two sets whose sizes differ by no more than ``ratio`` use the same number of positions in one.

    A position without shingles has the byte zero, which agrees with nothing.
    """
    if len(h) <= ratio * SHORT:
        return []  # its partners are short as well
    positions = FEWEST
    while len(h) >= CROWD * positions:
        positions *= 4
    out = []
    for many in (positions, 4 * positions) if len(h) >= ratio * CROWD * positions else (positions,):
        where, words = position_words(h, many)
        octets = np.zeros(TALLIED, np.uint8)
        octets[where] = remix(words, 11) % np.uint64(255) + np.uint64(1)
        where, words = where[where < POSITIONS], words[where < POSITIONS]
        out.append((remix(words ^ remix(np.uint64(many * POSITIONS) + where, 9), 10), octets))
    return out


def position_keys(h: np.ndarray, ratio: float) -> np.ndarray:
    """The keys of all filings of a set of shingle hashes."""
    return np.concatenate([np.empty(0, np.uint64), *(keys for keys, _ in position_filings(h, ratio))])


def enough_shared(octets: np.ndarray, of: np.ndarray, least: int = LEAST) -> np.ndarray:
    """Whether rows of positional bytes share at least so many with ``of``."""
    return ((octets == of) & (of != 0)).sum(axis=-1) >= least


def set_fingerprints(docs: DataFrame, *, id_col: str, text: str, shingle: int, ratio: float) -> DataFrame:
    """(id, w0.., size, digest, filings): fingerprint words of the distinct shingles, their number, the sum of their hashes, keys and positional bytes of the index."""
    names = [f"w{i}" for i in range(WORDS)]
    kind = dict(docs.dtypes)[id_col]
    kind_of_filings = pa.list_(pa.struct([("keys", pa.list_(pa.int64())), ("octets", pa.binary())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made, sizes, digests, filings = [], [], [], []
            for t in batch.column(1).to_pylist():
                h = np.unique(shingle_hashes(t or b"", shingle))
                made.append(fingerprint_of(h, WORDS))
                sizes.append(len(h))
                digests.append(h.sum(dtype=np.uint64))
                filings.append([{"keys": keys.view(np.int64), "octets": octets.tobytes()} for keys, octets in position_filings(h, ratio)])
            signed = lambda x: pa.array(np.array(x, np.uint64).view(np.int64))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *(signed([m[i] for m in made]) for i in range(WORDS)), pa.array(sizes, pa.int64()), signed(digests), pa.array(filings, kind_of_filings)],
                names=["id", *names, "size", "digest", "filings"],
            )

    rows = bounded_batches(docs).select(F.col(id_col).alias("id"), F.col(text).cast("binary").alias("text"))
    return rows.mapInArrow(run, f"id {kind}, " + ", ".join(f"{n} long" for n in [*names, "size", "digest"]) + ", filings array<struct<keys:array<long>,octets:binary>>")


def exact_keys(max_bits: int = MAX_BITS) -> list[tuple[int, ...]]:
    """Byte positions to file a 64-bit fingerprint under so that no link is missed.

    With ``max_bits`` differing bits at least 8 - max_bits bytes agree; leaving one
    position aside still leaves one less among the other seven.
    """
    agree = 8 - max_bits
    if agree < 2:
        raise ValueError("at most 6 differing bits can be indexed by bytes")
    return list(itertools.combinations(range(7), agree - 1))


MEASURES = ("jaccard", "cosine")


def similar(shared: np.ndarray, a: np.ndarray, b: int, similarity: float, measure: str) -> np.ndarray:
    """Whether sets of a and b shingles that share so many reach the similarity; two empty sets do."""
    union = a + b - shared
    if measure == "jaccard":
        return (union == 0) | (shared / np.maximum(union, 1) >= similarity)
    return (union == 0) | (shared / np.sqrt(np.maximum(a * b, 1)) >= similarity)


def size_ratio(similarity: float, measure: str) -> float:
    """The least share of its partner's size, and of its own shingles, that a similar set has."""
    if measure not in MEASURES:
        raise ValueError(f"measure must be one of {', '.join(MEASURES)}")
    return similarity if measure == "jaccard" else similarity**2


def similarity_bits(similarity: float, measure: str = "jaccard") -> float:
    """Expected share of differing bits between sets at this similarity (sets of one size differ most)."""
    return math.acos(2 * similarity / (1 + similarity) if measure == "jaccard" else similarity) / math.pi


def index_rows(nodes: DataFrame, positions: list[tuple[int, ...]]) -> DataFrame:
    """(key, node, probe): a node under each of its keys; probe is its fingerprint."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in (batch.slice(i, 1000) for i in range(0, batch.num_rows, 1000)):
                fps = part.column("w0").to_numpy()
                octets = fps.astype("<i8").view(np.uint8).reshape(len(fps), 8).astype(np.int64)
                keys = np.empty((len(fps), len(positions)), np.int64)
                for i, where in enumerate(positions):
                    key = np.full(len(fps), i, np.int64)
                    for p in where:
                        key = key << 8 | octets[:, p]
                    keys[:, i] = key
                k = len(positions)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(keys.ravel()), pa.array(np.repeat(part.column("node").to_numpy(), k)), pa.array(np.repeat(fps, k))], names=["key", "node", "probe"]
                )

    return nodes.select("node", "w0").mapInArrow(run, "key long, node long, probe long")


def forest(nodes: np.ndarray, near: Callable[[np.ndarray, int], np.ndarray]) -> list[tuple[np.ndarray, np.ndarray]]:
    """Links of a spanning forest of one bucket: arrays (nodes reached, node reached from); ``near(rows, row)`` tests links."""
    left, found = np.argsort(nodes, kind="stable"), []
    while len(left) > 1:
        queue, left = [left[0]], left[1:]
        while queue and len(left):
            at = queue.pop()
            hit = near(left, at)
            if hit.any():
                found.append((nodes[left[hit]], np.full(int(hit.sum()), nodes[at])))
                queue.extend(left[hit])
                left = left[~hit]
    return found


def sweep(nodes: np.ndarray, prints: np.ndarray, max_bits: int, min_shared: int) -> list[tuple[np.ndarray, np.ndarray]]:
    return forest(nodes, lambda left, at: linked(prints[left], prints[at], max_bits, min_shared))


def linked(x: np.ndarray, y, max_bits: int, min_shared: int) -> np.ndarray:
    differ = np.bitwise_xor(x, y)
    shared = np.zeros(len(differ), np.int8)
    for i in range(8):
        shared += (differ >> np.uint64(8 * i) & np.uint64(255)) == 0
    out = shared >= min_shared
    out[out] = np.bitwise_count(differ[out]) <= max_bits
    return out


def bucket_links(nodes: DataFrame, positions: list[tuple[int, ...]], max_bits: int, min_shared: int) -> DataFrame:
    """(a, b): links of a spanning forest of every bucket; a node without id has no place."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table, bounds in runs(batches):
            size = np.diff(bounds)
            nodes, prints = table.column("node").to_numpy(), table.column("probe").to_numpy().view(np.uint64)
            two = bounds[:-1][size == 2]
            near = linked(prints[two], prints[two + 1], max_bits, min_shared)
            found = [(nodes[two[near]], nodes[two[near] + 1])]
            for i in np.flatnonzero(size > 2):
                found += sweep(nodes[bounds[i] : bounds[i + 1]], prints[bounds[i] : bounds[i + 1]], max_bits, min_shared)
            if sum(len(x) for x, _ in found):
                yield _link_batch(found)

    dealt = deal(lambda some: index_rows(some, positions), nodes.where(F.col("node").isNotNull()))
    return dealt.select("key", "bi", "bj", "node", "probe").mapInArrow(run, "a long, b long")


def _link_batch(found: list[tuple[np.ndarray, np.ndarray]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.concatenate([f[j] for f in found])) for j in (0, 1)], names=["a", "b"])


def family_links(nodes: DataFrame, max_bits: int) -> DataFrame:
    """(a, b): a spanning forest of every bucket of (node, w0.., keys, octets), a row a filing, of pairs that share ``LEAST`` positional bytes and whose fingerprints differ in at most ``max_bits``.

    Rows without octets are compared by their fingerprints alone.
    """
    names = [f"w{i}" for i in range(WORDS)]
    carried = [*names, *(["octets"] if "octets" in nodes.columns else [])]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table, bounds in runs(batches):
            size = np.diff(bounds)
            nodes = table.column("node").to_numpy()
            prints = np.stack([table.column(n).to_numpy() for n in names], axis=1).view(np.uint64)
            octets = np.frombuffer(b"".join(table.column("octets").to_pylist()), np.uint8).reshape(-1, TALLIED) if len(carried) > WORDS else None

            def close(x: np.ndarray, y: np.ndarray | int) -> np.ndarray:
                out = np.ones(len(x), bool) if octets is None else enough_shared(octets[x], octets[y])  # noqa: B023
                y = y[out] if np.ndim(y) else y
                out[out] = np.bitwise_count(prints[x[out]] ^ prints[y]).sum(axis=1, dtype=np.int64) <= max_bits  # noqa: B023
                return out

            two = bounds[:-1][size == 2]
            two = two[close(two, two + 1)]
            found = [(nodes[two], nodes[two + 1])]
            for i in np.flatnonzero(size > 2):
                low = bounds[i]
                found += forest(nodes[low : bounds[i + 1]], lambda left, at, low=low: close(low + left, low + at))
            if sum(len(x) for x, _ in found):
                yield _link_batch(found)

    dealt = deal(lambda some: some.select(F.explode("keys").alias("key"), "node", *carried), nodes)
    return dealt.select("key", "bi", "bj", "node", *carried).mapInArrow(run, "a long, b long")


def prefix(hashes: np.ndarray, ratio: float) -> np.ndarray:
    """The smallest hashes of a sorted set: two sets that share at least ``ratio`` of either share one of theirs."""
    return hashes[: len(hashes) - math.ceil(ratio * len(hashes) - 1e-9) + 1]


def set_rows(texts: DataFrame, shingle: int, ratio: float) -> DataFrame:
    """(key, node, shingles) from (node, family, text): a set under its family, a short one under its prefix too."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in (batch.slice(i, 100) for i in range(0, batch.num_rows, 100)):
                keys, nodes, sets = [], [], []
                for node, family, text in zip(*(part.column(c).to_pylist() for c in ("node", "family", "text")), strict=True):
                    hashes = np.unique(shingle_hashes(text or b"", shingle))
                    under = [] if family is None else [family]
                    if len(hashes) <= SHORT:
                        under += prefix(hashes, ratio).view(np.int64).tolist()
                    keys += under
                    nodes += [node] * len(under)
                    sets += [hashes.astype("<u8").tobytes()] * len(under)
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(nodes, pa.int64()), pa.array(sets, pa.binary())], names=["key", "node", "shingles"])

    return texts.select("node", "family", F.col("text").cast("binary").alias("text")).mapInArrow(run, "key long, node long, shingles binary")


def alike(sets: list[np.ndarray], similarity: float, measure: str = "jaccard") -> Callable[[np.ndarray, int], np.ndarray]:
    """The link test of ``forest``: exact similarity of sorted sets of hashes."""
    size = np.array([len(x) for x in sets])
    known, ids = np.unique(np.concatenate(sets), return_inverse=True)
    ends = np.cumsum(size)
    marked = np.zeros(len(known), bool)

    def near(left: np.ndarray, at: int) -> np.ndarray:
        own = ids[ends[at] - size[at] : ends[at]]
        marked[own] = True
        upto = np.concatenate([[0], np.cumsum(marked[ids])])
        marked[own] = False
        shared = upto[ends[left]] - upto[ends[left] - size[left]]
        return similar(shared, size[left], size[at], similarity, measure)

    return near


def set_links(texts: DataFrame, shingle: int, similarity: float, measure: str) -> DataFrame:
    """(a, b): a spanning forest, of links whose similarity is reached, of the rows that meet under a key."""
    ratio = size_ratio(similarity, measure)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table, bounds in runs(batches):
            nodes, shingles, found = table.column("node").to_numpy(), table.column("shingles"), []
            for i in np.flatnonzero(np.diff(bounds) > 1):
                low, high = bounds[i], bounds[i + 1]
                sets = [np.frombuffer(x, "<u8") for x in shingles.slice(low, high - low).to_pylist()]
                found += forest(nodes[low:high], alike(sets, similarity, measure))
            if found:
                yield _link_batch(found)

    dealt = deal(lambda some: set_rows(some, shingle, ratio), texts, block_rows=SET_ROWS)
    return dealt.select("key", "bi", "bj", "node", "shingles").mapInArrow(run, "a long, b long")


def near_duplicates(
    docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", shingle: int = SHINGLE, max_bits: int = MAX_BITS
) -> DataFrame:
    """(id, fingerprint long, component): exact 64-bit mode, one row per row of ``docs``."""
    prints = materialise(fingerprints(docs, id_col=id_col, text=text, shingle=shingle))
    nodes = materialise(prints.groupBy("w0").agg(F.min("id").cast("long").alias("node")))
    joined = connected_components(bucket_links(nodes, exact_keys(max_bits), max_bits, 8 - max_bits).distinct())
    return _with_components(prints, nodes, joined, ["w0"]).withColumnRenamed("w0", "fingerprint")


def similar_texts(
    docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", shingle: int = STAGE_SHINGLE, similarity: float = SIMILARITY, measure: str = "jaccard"
) -> DataFrame:
    """(id, component): texts whose sets of shingles reach ``similarity`` are linked.

    ``measure``: jaccard, or cosine (shared shingles over the root of the product of the
    sizes), which is what SimHash bits estimate.
    """
    names = [f"w{i}" for i in range(WORDS)]
    prints = materialise(set_fingerprints(docs, id_col=id_col, text=text, shingle=shingle, ratio=size_ratio(similarity, measure)))
    nodes = materialise(prints.groupBy(*names, "size", "digest").agg(F.min("id").cast("long").alias("node")))
    share, bits = similarity_bits(similarity, measure), 64 * WORDS
    max_bits = math.floor(bits * share + SIGMAS * math.sqrt(bits * share * (1 - share)))
    own = prints.select(F.col("id").cast("long").alias("node"), *names, F.explode("filings").alias("filing")).select("node", *names, "filing.keys", "filing.octets")
    ids = broadcast_if_small(nodes.where(F.col("node").isNotNull()).select("node"), ID_ROWS)
    families = connected_components(family_links(own.join(ids, "node", "left_semi"), max_bits)).select("node", F.col("component").alias("family"))
    short = nodes.where((F.col("size") <= SHORT) & F.col("node").isNotNull()).select("node", F.lit(None).cast("long").alias("family"))
    wanted = materialise(families.union(short).groupBy("node").agg(F.max("family").alias("family")))
    own = bounded_batches(docs).select(F.col(id_col).alias("own_id"), F.col(text).alias("text"))
    texts = own.join(broadcast_if_small(wanted, ID_ROWS), F.col("own_id") == F.col("node")).select("node", "family", "text")
    prints = prints.drop("filings")
    return _with_components(prints, nodes, connected_components(set_links(texts, shingle, similarity, measure)), [*names, "size", "digest"]).drop("size", "digest")


def _with_components(prints: DataFrame, nodes: DataFrame, components: DataFrame, names: list[str]) -> DataFrame:
    known = nodes.join(components, "node", "left").select(*[F.col(n).alias(f"of_{n}") for n in names], F.coalesce("component", "node").alias("component_id"))
    same = [prints[n] == known[f"of_{n}"] for n in names]
    return prints.join(known, same).drop(*[f"of_{n}" for n in names])


def drop_near_duplicates(docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", measure: str = "cosine") -> DataFrame:
    """``docs`` with one document (the smallest id) of each group of similar texts.

    Rows that repeat the id that stays are reduced to one; rows with a null id stay.
    """
    own = fresh_name(docs, "dup_id")
    groups = materialise(similar_texts(docs, id_col=id_col, text=text, measure=measure).select(F.col("id").alias(own), "component_id"))
    gone = groups.where(F.col(own) != F.col("component_id")).select(own)
    kept = docs.join(broadcast_if_small(gone, ID_ROWS), F.col(id_col) == F.col(own), "left_anti")
    repeated = groups.where(F.col(own).isNotNull()).groupBy(own).count().where("count > 1")
    if repeated.isEmpty():
        return kept
    return kept.where(F.col(id_col).isNotNull()).dropDuplicates([id_col]).unionByName(kept.where(F.col(id_col).isNull()))


def op8_simhash(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out = near_duplicates(docs)
    return out.select(F.col("id").alias("doc_id"), F.lower(F.lpad(F.hex("fingerprint"), 16, "0")).alias("fingerprint"), "component_id")
