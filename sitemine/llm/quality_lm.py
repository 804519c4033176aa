"""Quality classifier: interpolated modified Kneser-Ney over trusted text.

Trusted documents (labelled good and not toxic) train models of four code points each, one
pair for each language and, where texts of no or an unknown language are there, a pooled
pair.  Any code point counts as itself: the tables grow with the trusted text.

Two halves.  Documents are halved by a hash of their text.  Each half's trusted texts train
a model that scores the other half, so no document, trusted or not, is scored by a model
that has seen it, and copies of a text are scored alike.

Counting reads every trusted document in place: a task adds n-grams up per language and
half and emits each once, and Spark sums them.  Everything after is joins of count tables
keyed by (model, context): counts with the totals and freed mass of their context and with
the lower order's probabilities; lower orders use continuation counts, discounts come from
counts of counts per model and order.

Scoring joins documents' n-grams with those tables, backing off where one was not seen.
Tables of up to ``TABLE_ROWS`` rows in all are broadcast as sorted hashes and met in place,
so no document leaves its task; larger ones meet the documents' distinct n-grams, emitted
once, in joins dealt by (model, context, point).  Both give the same sums.  A document's
perplexity is the exponential of its mean negative log probability.  Its own perplexity is
that of its points under its own pairs of points: a text that repeats itself predicts itself.

Thresholds are quantiles over trusted documents of a language, by bands of text length (a
band of fewer than ``MIN_BAND`` trusted documents uses the whole language's perplexities and
no threshold of own perplexity).  A document is kept unless its perplexity exceeds the
``quantile`` or its own perplexity is below the opposite one.

Defined cases: null or empty text is kept, with null perplexities; null languages and those
without trusted text in both halves use the pooled models, and without those two halves
a text that its half's model would have to score is kept; without trusted documents everything is kept,
with null perplexities; null ids are scored and never trusted; repeated rows are scored
alike; other columns pass through; an empty table gives an empty table.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sitemine.llm.common import HashTable, bounded_batches, fresh_name, mixed
from sitemine.session import broadcast_if_small, drop_shared, materialise, shared_table

#: Code points of an n-gram; a context of three fits a long.
ORDER = 4
#: Bits of a code point, and the point that stands for what is before and after a text.
POINT = 21
EDGE = (1 << POINT) - 1
QUANTILE = 0.998
#: Bands are powers of two of the number of n-grams, the outer ones open.
BANDS = (5, 14)
MIN_BAND = 50
POOLED = "*"
#: Rows of all tables together that a worker holds (16 bytes each and an index).
TABLE_ROWS = 6_000_000
#: Points of a text that are looked up at a time.
CHUNK = 1 << 18
#: N-grams that a task gathers before it adds them up.
GATHER = 1 << 19
#: Ids (eight bytes each) that a broadcast may hold.
ID_ROWS = 4_000_000


def trusted_ids(labels: DataFrame) -> DataFrame:
    """doc_id of the rows labelled good and not toxic."""
    good = (F.col("quality") == 1) & (F.coalesce("toxic", F.lit(0)) == 0)
    return labels.where(good & F.col("doc_id").isNotNull()).select("doc_id").distinct()


def points_of(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "replace"), "<u4").astype(np.int64)


def grams(points: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(contexts, points that follow) of a text's n-grams, ``CHUNK`` at a time: three edges before it and one after."""
    edges = np.full(ORDER - 1, EDGE)
    x = np.concatenate([edges, points, edges[:1]])
    for i in range(0, len(points) + 1, CHUNK):
        part = x[i : i + CHUNK + ORDER - 1]
        n = len(part) - ORDER + 1
        context = np.zeros(n, np.int64)
        for k in range(ORDER - 1):
            context = context << POINT | part[k : k + n]
        yield context, part[ORDER - 1 :]


def half_of(text: Column) -> Column:
    return F.pmod(F.xxhash64(text), F.lit(2)).cast("int")


def languages_of(trusted: DataFrame) -> list[str]:
    """The languages with trusted text in both halves, in order.

    A model's number is twice the place of its language, plus the half that trained it.
    """
    halves = trusted.where(F.col("lang").isNotNull()).groupBy("lang").agg(F.min("half").alias("low"), F.max("half").alias("high"))
    return sorted(r.lang for r in halves.where("low < high").collect())


def count_grams(trusted: DataFrame, languages: list[str], *, pooled: bool = True, gather: int = GATHER) -> DataFrame:
    """(number, context, point, n) from (lang, half, text): n-grams of each language and half, and of all languages if ``pooled``."""
    place = {name: i for i, name in enumerate(languages)}
    none = len(languages)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        waiting = size = 0

        def added() -> list[tuple[np.ndarray, ...]]:
            number, context, point, n = (np.concatenate([h[i] for h in held]) for i in range(4))
            _, first, inverse = np.unique(mixed(number, context, point), return_index=True, return_inverse=True)
            return [(number[first], context[first], point[first], np.bincount(inverse, n).astype(np.int64))]

        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(x) for x in held[0]], names=["number", "context", "point", "n"])

        for batch in batches:
            for lang, half, text in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                number = 2 * place.get(lang, none) + half
                for context, point in grams(points_of(text or "")):
                    held.append((np.full(len(point), number), context, point, np.ones(len(point), np.int64)))
                    waiting += len(point)
                    if waiting >= gather:
                        held = added()
                        waiting, size = 0, len(held[0][0])
                        if size >= gather:
                            yield out()
                            held = []
        if held:
            held = added()
            yield out()

    keys = ["number", "context", "point"]
    each = trusted.select("lang", "half", "text").mapInArrow(run, "number long, context long, point long, n long").groupBy(*keys).agg(F.sum("n").alias("n"))
    own = F.col("number") < 2 * none
    if not pooled:
        return materialise(each.where(own))
    each = materialise(each)
    together = each.groupBy((F.pmod("number", F.lit(2)) + 2 * none).alias("number"), "context", "point").agg(F.sum("n").alias("n"))
    return materialise(each.where(own).union(together))


def discounts(counts: DataFrame) -> DataFrame:
    """(number, d1, d2, d3) of one order: the modified discounts from counts of counts."""
    n = [None, *(F.sum((F.col("n") == i).cast("long")) for i in range(1, 5))]
    found = counts.groupBy("number").agg(*[n[i].alias(f"n{i}") for i in range(1, 5)])
    base = F.col("n1") / F.nullif(F.col("n1") + 2 * F.col("n2"), F.lit(0))

    def d(i: int) -> Column:
        raw = i - (i + 1) * base * F.col(f"n{i + 1}") / F.nullif(F.col(f"n{i}"), F.lit(0))
        # tiny samples leave the estimate outside its range or undefined: half a count then
        return F.when((raw > 0) & (raw < i), raw).otherwise(F.lit(0.5))

    return found.select("number", *[d(i).alias(f"d{i}") for i in (1, 2, 3)])


def discount_of(n: Column) -> Column:
    return F.when(n == 1, F.col("d1")).when(n == 2, F.col("d2")).otherwise(F.col("d3"))


def shorter(context: Column, points: int) -> Column:
    """The last ``points`` points of a context."""
    return context.bitwiseAND(F.lit((1 << POINT * points) - 1))


@dataclass
class Model:
    """Tables of the cluster, order by order, from one point to ``ORDER``."""

    seen: list[DataFrame]  # number, context, point, p: the n-grams counted
    contexts: list[DataFrame]  # number, context, held: the mass that a context leaves to the lower order
    floor: DataFrame  # number, p: of a point never counted


def kneser_ney(counts: DataFrame) -> Model:
    """The models from counts of the longest n-grams."""
    tables = [counts]
    for k in range(ORDER - 2, -1, -1):  # a shorter n-gram counts in how many n-grams one longer it ends
        tables.append(materialise(tables[-1].groupBy("number", shorter(F.col("context"), k).alias("context"), "point").agg(F.count("*").alias("n"))))
    tables.reverse()
    floor = materialise(tables[0].groupBy("number").agg((1 / (F.count("*") + 1)).alias("p")))  # all its points and one unknown
    lower, seen, contexts = floor.withColumnRenamed("p", "p_lower"), [], []
    for k, table in enumerate(tables):
        keyed = table.join(F.broadcast(discounts(table)), "number").withColumn("off", discount_of(F.col("n")))  # two rows a language
        freed = materialise(keyed.groupBy("number", "context").agg(F.sum("n").alias("total"), (F.sum("off") / F.sum("n")).alias("held")))
        joined = keyed.join(broadcast_if_small(freed), ["number", "context"])
        if k:
            joined = joined.withColumn("below", shorter(F.col("context"), k - 1)).join(broadcast_if_small(lower), ["number", "below", "point"])
        else:
            joined = joined.join(F.broadcast(lower), "number")
        p = (F.col("n") - F.col("off")) / F.col("total") + F.col("held") * F.col("p_lower")
        seen.append(materialise(joined.select("number", "context", "point", p.alias("p"))))
        contexts.append(freed.select("number", "context", "held"))
        lower = seen[-1].select("number", F.col("context").alias("below"), "point", F.col("p").alias("p_lower"))
    return Model(seen, contexts, floor)


def probabilities(asked: DataFrame, model: Model) -> DataFrame:
    """(number, context, point, p) of any n-grams (number, context, point), backing off where one was not seen."""
    out = asked.select("number", "context", "point").join(F.broadcast(model.floor.withColumnRenamed("p", "p0")), "number")
    p = F.col("p0")
    for k, (seen, contexts) in enumerate(zip(model.seen, model.contexts, strict=True)):
        end = f"end{k}"
        out = out.withColumn(end, shorter(F.col("context"), k))
        out = out.join(broadcast_if_small(seen.select("number", F.col("context").alias(end), "point", F.col("p").alias(f"p{k + 1}"))), ["number", end, "point"], "left")
        out = out.join(broadcast_if_small(contexts.select("number", F.col("context").alias(end), F.col("held").alias(f"held{k}"))), ["number", end], "left")
        p = F.coalesce(F.col(f"p{k + 1}"), F.coalesce(F.col(f"held{k}"), F.lit(1.0)) * p)
    return out.select("number", "context", "point", p.alias("p"))


_SEEN, _CONTEXT, _FLOOR = 0, 10, 20


def log_costs(table: HashTable, number: int, context: np.ndarray, point: np.ndarray) -> np.ndarray:
    """Negative log probabilities of a text's n-grams, backing off where one was not seen."""
    out, left, weight = np.empty(len(point)), np.arange(len(point)), np.ones(len(point))
    for k in range(ORDER, 0, -1):
        end = context[left] & ((1 << POINT * (k - 1)) - 1)
        p = table.find(mixed(_SEEN + k, number, end, point[left]))
        hit = ~np.isnan(p)
        out[left[hit]] = weight[hit] * p[hit]
        left, weight, end = left[~hit], weight[~hit], end[~hit]
        if not len(left):
            return -np.log(out)
        held = table.find(mixed(_CONTEXT + k, number, end))
        weight = weight * np.where(np.isnan(held), 1.0, held)
    out[left] = weight * table.find(mixed(_FLOOR, number))
    return -np.log(out)


def own_cost(points: np.ndarray) -> float:
    """Sum of the negative log probabilities of a text's points under its own pairs of points."""
    x = np.concatenate([[EDGE], points, [EDGE]])
    pairs = total = None
    for i in range(0, len(x) - 1, CHUNK):
        found, n = np.unique(x[i : i + CHUNK + 1][:-1] << POINT | x[i : i + CHUNK + 1][1:], return_counts=True)
        if pairs is not None:
            found, inverse = np.unique(np.concatenate([pairs, found]), return_inverse=True)
            n = np.bincount(inverse, np.concatenate([total, n]))
        pairs, total = found, n
    starts = np.flatnonzero(np.diff(pairs >> POINT, prepend=-1))
    sums = np.add.reduceat(total, starts)
    return float((sums * np.log(sums)).sum() - (total * np.log(total)).sum())


_SCORED = "number long, n long, cost double, own double"


def _numbered(docs: DataFrame, languages: list[str], run: Callable, schema: str) -> DataFrame:
    """``run(part, numbers, texts)`` over (id, lang, half, text, ..): a document is scored by the model of the other half."""
    place = {name: i for i, name in enumerate(languages)}
    kind = dict(docs.dtypes)["id"]

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            told = zip(batch.column("lang").to_pylist(), batch.column("half").to_pylist(), strict=True)
            yield from run(batch, [2 * place.get(lang, len(languages)) + 1 - half for lang, half in told], batch.column("text").to_pylist())

    return docs.mapInArrow(rows, f"id {kind}, {schema}")


def _in_place(docs: DataFrame, model: Model, languages: list[str]) -> DataFrame:
    """(id, number, n, cost, own): documents meet the broadcast tables where they are."""

    def hashed(kind: int, columns: list[str], value: str, table: DataFrame) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                keys = mixed(kind, *(batch.column(c).to_numpy() for c in columns))
                yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), batch.column(value)], names=["key", "value"])

        return table.select(*columns, value).mapInArrow(run, "key long, value double")

    parts = [hashed(_FLOOR, ["number"], "p", model.floor)]
    for k, (seen, contexts) in enumerate(zip(model.seen, model.contexts, strict=True), 1):
        parts += [hashed(_SEEN + k, ["number", "context", "point"], "p", seen), hashed(_CONTEXT + k, ["number", "context"], "held", contexts)]
    rows = reduce(DataFrame.union, parts).toArrow()
    shared = docs.sparkSession.sparkContext.broadcast((rows.column("key").to_numpy().view(np.uint64), rows.column("value").to_numpy()))
    del rows
    unfolded: list[HashTable] = []

    def run(part: pa.RecordBatch, numbers: list[int], texts: list[str | None]) -> Iterator[pa.RecordBatch]:
        if not unfolded:
            unfolded.append(HashTable(*shared.value))
        sums = []
        for number, text in zip(numbers, texts, strict=True):
            points = points_of(text or "")
            cost = sum(float(log_costs(unfolded[0], number, c, p).sum()) for c, p in grams(points)) if len(points) else 0.0
            sums.append((number, len(points) + 1 if len(points) else 0, cost, own_cost(points) if len(points) else 0.0))
        yield pa.RecordBatch.from_arrays([part.column("id"), *(pa.array(x) for x in zip(*sums, strict=True))], names=["id", "number", "n", "cost", "own"])

    return _numbered(docs, languages, run, _SCORED)


def _by_joins(docs: DataFrame, model: Model, languages: list[str]) -> tuple[DataFrame, str]:
    """(id, number, n, cost, own): documents' distinct n-grams, written once, meet the tables in joins; and the written table's path."""

    def run(part: pa.RecordBatch, numbers: list[int], texts: list[str | None]) -> Iterator[pa.RecordBatch]:
        for i, (number, text) in enumerate(zip(numbers, texts, strict=True)):
            points = points_of(text or "")
            whole = (len(points) + 1, own_cost(points)) if len(points) else (0, 0.0)
            # a first row without an n-gram stands for the document
            parts = [(np.full(1, -1), np.full(1, -1), np.zeros(1, np.int64))]
            for context, point in grams(points) if len(points) else ():
                _, first, n = np.unique(mixed(context, point), return_index=True, return_counts=True)
                parts.append((context[first], point[first], n))
            context, point, n = (np.concatenate([x[j] for x in parts]) for j in range(3))
            spot = pa.array(np.zeros(len(n), np.int64))
            yield pa.RecordBatch.from_arrays(
                [part.column("id").slice(i, 1).take(spot), pa.array(np.full(len(n), number)), pa.array(np.full(len(n), whole[0])), pa.array(np.full(len(n), whole[1])),
                 pa.array(context), pa.array(point), pa.array(n), part.column("rid").slice(i, 1).take(spot)],
                names=["id", "number", "n", "own", "context", "point", "times", "rid"],
            )

    named = docs.select(F.monotonically_increasing_id().alias("rid"), "id", "lang", "half", "text")
    emitted, path = shared_table(_numbered(named, languages, run, "number long, n long, own double, context long, point long, times long, rid long"))
    keys = ["number", "context", "point"]
    costs = probabilities(emitted.where("times > 0").select(*keys).distinct(), model).select(*keys, (-F.log("p")).alias("each"))
    met = emitted.join(costs, keys, "left")
    sums = met.groupBy("rid", "id", "number", "n", "own").agg(F.sum(F.col("times") * F.coalesce("each", F.lit(0.0))).alias("cost"))
    return sums.select("id", "number", "n", "cost", "own"), path


def score(docs: DataFrame, model: Model, languages: list[str], *, table_rows: int = TABLE_ROWS) -> DataFrame:
    """(id, model, length, perplexity, own_perplexity) of documents (id, lang, half, text), one row per row, computed."""
    sizes = sum(t.count() for t in [*model.seen, *model.contexts])
    path = None
    if sizes <= table_rows:
        sums = _in_place(docs, model, languages)
    else:
        sums, path = _by_joins(docs, model, languages)
    trained = [r.number for r in model.floor.select("number").collect()]  # two a language
    some = (F.col("n") > 0) & F.col("number").isin(trained)
    names = F.array(*[F.concat(F.lit("="), F.lit(x)) for x in languages], F.lit(POOLED))
    place = F.floor(F.col("number") / 2).cast("int")
    out = materialise(
        sums.select(
            "id", F.element_at(names, place + 1).alias("model"), F.col("n").alias("length"),
            F.when(some, F.exp(F.col("cost") / F.col("n"))).alias("perplexity"), F.when(some, F.exp(F.col("own") / F.col("n"))).alias("own_perplexity"),
        )
    )
    if path:
        drop_shared(docs.sparkSession, path)
    return out


def band_of(length: Column) -> Column:
    low, high = BANDS
    return F.least(F.greatest(F.floor(F.log2(F.greatest(length, F.lit(1)))), F.lit(low)), F.lit(high)).cast("int")


def thresholds(scored: DataFrame, quantile: float, min_band: int = MIN_BAND) -> tuple[DataFrame, DataFrame]:
    """(model, band, threshold, least_own) of bands with enough documents, and (model, any_threshold)."""
    some = scored.where(F.col("perplexity").isNotNull())
    upper = F.percentile_approx("perplexity", quantile, 10_000)
    lower = F.percentile_approx("own_perplexity", 1 - quantile, 10_000)
    by_band = some.groupBy("model", band_of(F.col("length")).alias("band")).agg(upper.alias("threshold"), lower.alias("least_own"), F.count("*").alias("docs"))
    return by_band.where(F.col("docs") >= min_band).drop("docs"), some.groupBy("model").agg(upper.alias("any_threshold"))


def judge(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text: str = "text", lang: str = "lang", quantile: float = QUANTILE, table_rows: int = TABLE_ROWS) -> DataFrame:
    """(id, model, perplexity, own_perplexity, threshold, least_own, keep), one row per row of ``docs``."""
    trusted = broadcast_if_small(materialise(trusted_ids(labels)), ID_ROWS)
    own = bounded_batches(docs).select(F.col(id_col).alias("id"), F.col(lang).cast("string").alias("lang"), half_of(F.col(text)).alias("half"), F.col(text).alias("text"))
    good = own.join(trusted, F.col("id") == F.col("doc_id"), "left_semi")
    if good.isEmpty():
        missing = [F.lit(None).cast("double").alias(c) for c in ("perplexity", "own_perplexity", "threshold", "least_own")]
        return docs.select(F.col(id_col).alias("id"), F.lit(POOLED).alias("model"), *missing, F.lit(True).alias("keep"))
    languages = languages_of(good)
    known = F.coalesce(F.col("lang").isin(languages), F.lit(False)) if languages else F.lit(False)
    pooled = not own.where(~known).select("id").isEmpty()
    model = kneser_ney(count_grams(good, languages, pooled=pooled))
    scored = score(own, model, languages, table_rows=table_rows)
    held = scored.where(F.col("model") != POOLED).join(trusted, F.col("id") == F.col("doc_id"), "left_semi")
    if pooled:
        # texts of no known language are held against all trusted ones under the same, pooled models
        held = held.union(score(good.withColumn("lang", F.lit(None).cast("string")), model, languages, table_rows=table_rows))
    by_band, by_model = thresholds(held, quantile)
    joined = scored.withColumn("band", band_of(F.col("length"))).join(F.broadcast(by_band), ["model", "band"], "left").join(F.broadcast(by_model), "model", "left")  # rows per language
    limit = F.coalesce("threshold", "any_threshold")
    keep = F.coalesce(F.col("perplexity") <= limit, F.lit(True)) & F.coalesce(F.col("own_perplexity") >= F.col("least_own"), F.lit(True))
    return joined.select("id", "model", "perplexity", "own_perplexity", limit.alias("threshold"), "least_own", keep.alias("keep"))


def keep_good(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text: str = "text", lang: str = "lang") -> DataFrame:
    """``docs`` without the documents that the classifier rejects (rows with a null id stay)."""
    gone = fresh_name(docs, "gone_id")
    rejected = materialise(judge(docs, labels, id_col=id_col, text=text, lang=lang).where(~F.col("keep")).select(F.col("id").alias(gone)).distinct())
    return docs.join(broadcast_if_small(rejected, ID_ROWS), F.col(id_col) == F.col(gone), "left_anti")


def op9_quality_lm(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "quality", "toxic")
    told = judge(docs, labels)
    return told.select(F.col("id").alias("doc_id"), "model", "perplexity", "threshold", "own_perplexity", "least_own", "keep")
