"""Language ID by string kernels: Nyström landmarks and kernel ridge regression.

The blended-spectrum presence kernel of two texts is the number of character n-grams
(n = 1 to 3, of lower-cased code points, none left out) that stand in both, over the
geometric mean of the numbers in each.

Training takes at most ``max_rows`` labelled rows, as many of each language as far as
they go, chosen by a hash of the id: a documented bound, the same at every size.  Some of
them, evenly over languages, are landmarks.  Only the landmarks' n-grams come to the driver,
up to ``MARK_GRAMS`` (longer samples are refused); every training row meets them where it
is and sends its kernel with each.  The landmarks' kernel matrix gives the Nyström map, and
one ridge regression per language (+1 for its rows, -1 for others) is solved in closed
form: small dense algebra on the driver.

Scoring is exact for that model: a batch of texts is a matrix of n-gram presences; its
product with the landmarks' presences, the Nyström map and the regression weights (folded
into one matrix beforehand) gives a score per language.  Every whole text is read.

Defined cases: null text and text without a letter are ``und`` with score 0; ties go to
the language first in code point order; null languages and null ids are not learned
from; with no language to learn, every text is ``und``; repeated rows, ids and extra
columns are kept; an empty table gives an empty table.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sitemine.llm.common import HashTable, bounded_batches, fresh_name, mixed
from sitemine.session import broadcast_if_small, materialise

ORDERS = 3
#: Bits of a code point in an n-gram's number.
POINT = 21
#: N-grams of all landmarks together that the driver may hold.
MARK_GRAMS = 20_000_000
#: Points of a text whose n-grams are made distinct at a time.
CHUNK = 1 << 20
MAX_ROWS = 2000
LANDMARKS = 256
RIDGE = 1e-2
UNKNOWN = "und"
_LETTER = re.compile(r"[^\W\d_]")


def has_letter(text: str) -> bool:
    return any(m[0].isalpha() for m in _LETTER.finditer(text))


def held_out(id_col: Column) -> Column:
    return F.coalesce(F.crc32(id_col.cast("string")) % 4 == 2, F.lit(False))


def ngrams(text: str) -> np.ndarray:
    """The distinct n-grams of a text as sorted numbers: their points, each plus one, side by side."""
    points = np.frombuffer(text.lower().encode("utf-32-le", "replace"), "<u4").astype(np.int64) + 1
    found: list[np.ndarray] = []
    for i in range(0, len(points), CHUNK):
        part = points[i : i + CHUNK + ORDERS - 1]
        code = part
        made = [part]
        for n in range(1, min(ORDERS, len(part))):
            code = code[:-1] << POINT | part[n:]
            made.append(code)
        found = [np.unique(np.concatenate([*found, *made]))]
    return found[0] if found else np.empty(0, np.int64)


@dataclass
class Model:
    languages: list[str]
    codes: np.ndarray  # n-grams of the landmarks, a row each
    weights: np.ndarray  # (n-grams, languages)


class Scorer:
    """A model unfolded for a worker."""

    def __init__(self, model: Model):
        self.weights = model.weights
        self.table = HashTable(mixed(model.codes), np.arange(len(model.codes), dtype=np.float64))

    def scores(self, texts: list[str]) -> np.ndarray:
        """(texts, languages) regression values."""
        out = np.zeros((len(texts), self.weights.shape[1]))
        for i, text in enumerate(texts):
            codes = ngrams(text)
            row = self.table.find(mixed(codes))
            out[i] = self.weights[row[~np.isnan(row)].astype(np.int64)].sum(axis=0, dtype=np.float64) / np.sqrt(max(1, len(codes)))
        return out


def sample_rows(docs: DataFrame, *, id_col: str, text: str, lang: str, max_rows: int) -> DataFrame:
    """(lang, text): at most ``max_rows`` training rows, balanced over languages."""
    rows = docs.where(~held_out(F.col(id_col)) & F.col(id_col).isNotNull() & F.col(lang).isNotNull() & F.col(text).isNotNull())
    sizes = rows.groupBy(F.col(lang).alias("l")).agg(F.count("*").alias("n"))
    sizes = materialise(sizes)
    each = max(1, max_rows // max(1, sizes.count()))
    turn = F.pmod(F.xxhash64(F.lit(11), F.col(id_col)), F.lit(1 << 40))
    # a hash threshold first leaves about twice what is wanted of a large language; the ranking is then of few rows
    share = sizes.select("l", F.least(F.lit(1.0), F.lit(2.0 * each + 20) / F.col("n")).alias("share"))
    near = rows.join(broadcast_if_small(share), F.col(lang) == F.col("l")).where(turn < F.col("share") * (1 << 40))
    ids = near.select(F.col("l"), F.col(text).alias("text"), turn.alias("turn"), F.col(id_col).alias("id"))
    rank = F.row_number().over(Window.partitionBy("l").orderBy("turn", "id"))
    return materialise(ids.withColumn("rank", rank).where(F.col("rank") <= each).select(F.col("l").cast("string").alias("lang"), "rank", "turn", "text"))


def _grams_of(rows: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            codes = [ngrams(t) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("lang"), batch.column("rank"), pa.array(codes, pa.list_(pa.int64()))], names=["lang", "rank", "codes"])

    return rows.select("lang", "rank", "text").mapInArrow(run, "lang string, rank int, codes array<long>")


def kernel_rows(sample: DataFrame, marks: list[np.ndarray]) -> DataFrame:
    """(lang, rank, kernel): each training row's kernel with every landmark."""
    codes = np.unique(np.concatenate(marks))
    spot = np.concatenate([np.searchsorted(codes, m) for m in marks])
    owner = np.repeat(np.arange(len(marks)), [len(m) for m in marks])
    order = np.argsort(spot, kind="stable")
    # the landmarks that hold each n-gram, as an inverted list
    held = codes, np.searchsorted(spot[order], np.arange(len(codes) + 1)), owner[order], np.array([max(1, len(m)) for m in marks])
    shared = sample.sparkSession.sparkContext.broadcast(held)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes, starts, owner, sizes = shared.value
        for batch in batches:
            out = []
            ends, values = batch.column("codes").offsets.to_numpy(), batch.column("codes").values.to_numpy()
            for own in (values[a:b] for a, b in zip(ends[:-1], ends[1:], strict=True)):
                at = np.minimum(np.searchsorted(codes, own), len(codes) - 1)
                at = at[codes[at] == own]
                n = starts[at + 1] - starts[at]
                lists = owner[np.repeat(starts[at] - np.cumsum(n) + n, n) + np.arange(n.sum())]
                out.append(np.bincount(lists, minlength=len(sizes)) / np.sqrt(sizes * max(1, len(own))))
            yield pa.RecordBatch.from_arrays([batch.column("lang"), batch.column("rank"), pa.array(out, pa.list_(pa.float64()))], names=["lang", "rank", "kernel"])

    return _grams_of(sample).mapInArrow(run, "lang string, rank int, kernel array<double>")


def nystrom(kernel: np.ndarray) -> np.ndarray:
    """The map from kernels with the landmarks to features, of the landmarks' own kernel matrix."""
    values, vectors = np.linalg.eigh(kernel)
    good = values > values.max() * 1e-8
    return vectors[:, good] / np.sqrt(values[good])


def regression(features: np.ndarray, target: np.ndarray, ridge: float) -> np.ndarray:
    return np.linalg.solve(features.T @ features + ridge * len(features) * np.eye(features.shape[1]), features.T @ target)


def train(docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", lang: str = "lang", max_rows: int = MAX_ROWS, landmarks: int = LANDMARKS, ridge: float = RIDGE) -> Model:
    sample = sample_rows(bounded_batches(docs), id_col=id_col, text=text, lang=lang, max_rows=max_rows)
    chosen = materialise(_grams_of(sample.orderBy("rank", "turn", "lang").limit(landmarks)))
    if (total := chosen.agg(F.sum(F.size("codes"))).first()[0] or 0) > MARK_GRAMS:
        raise ValueError(f"the landmarks hold {total} n-grams, the driver may hold {MARK_GRAMS}: use fewer landmarks")
    marked = sorted(((r["rank"], r.lang, np.array(r.codes, np.int64)) for r in chosen.collect()), key=lambda m: m[:2])
    if not marked or not total:
        return Model([], np.empty(0, np.int64), np.zeros((0, 0), np.float32))
    marks = [codes for _, _, codes in marked]
    rows = sorted(kernel_rows(sample, marks).collect(), key=lambda r: (r["rank"], r.lang))
    kernel = np.array([r.kernel for r in rows])
    place = {(r["rank"], r.lang): i for i, r in enumerate(rows)}
    root = nystrom(kernel[[place[m[:2]] for m in marked]])
    languages = sorted({r.lang for r in rows})
    target = np.array([[1.0 if r.lang == name else -1.0 for name in languages] for r in rows])
    by_mark = root @ regression(kernel @ root, target, ridge)
    codes = np.unique(np.concatenate(marks))
    folded = np.zeros((len(codes), len(languages)))
    for own, weight in zip(marks, by_mark, strict=True):
        folded[np.searchsorted(codes, own)] += weight / np.sqrt(max(1, len(own)))
    return Model(languages, codes, folded.astype(np.float32))


def predict(docs: DataFrame, model: Model, *, text: str = "text") -> DataFrame:
    """``docs`` without ``text``, plus lang_pred and score (renamed if taken)."""
    keep = bounded_batches(docs).drop(text)
    names = [fresh_name(keep, "lang_pred"), fresh_name(keep, "score")]
    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = ", ".join([*(f"`{c}` {t}" for c, t in keep.dtypes), f"`{names[0]}` string, `{names[1]}` double"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        scorer = Scorer(model)
        for batch in batches:
            for part in (batch.slice(i, 64) for i in range(0, batch.num_rows, 64)):
                texts = [t or "" for t in part.column(part.num_columns - 1).to_pylist()]
                known = np.array([bool(model.languages) and has_letter(t) for t in texts])
                pred, score = [UNKNOWN] * len(texts), np.zeros(len(texts))
                if known.any():
                    values = scorer.scores([t for t, k in zip(texts, known, strict=True) if k])
                    for i, best, value in zip(np.flatnonzero(known), values.argmax(axis=1), values.max(axis=1), strict=True):
                        pred[i], score[i] = model.languages[best], min(1.0, max(0.0, (1 + float(value)) / 2))
                yield pa.RecordBatch.from_arrays([*part.columns[:-1], pa.array(pred, pa.string()), pa.array(score)], names=[*part.schema.names[:-1], *names])

    return docs.select(*keep.columns, F.col(text).alias(fresh_name(keep, "whole_text"))).mapInArrow(run, schema)


def op10_language_id(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = train(docs.select("doc_id", "text", "lang"))
    told = predict(docs.select("doc_id", "text"), model)
    return told.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
