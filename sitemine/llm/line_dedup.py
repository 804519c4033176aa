"""Line dedup: drop lines whose key stands in many documents.

Every document (a row) is split at ``\\n``.  A line's key is the line without blanks at
both ends, A-Z lower-cased.  Keys are hashed to 128 bits; a document names each of its
keys once, so a plain count per hash is the number of documents, and the count combines
on the map side.  Lines then travel as (document, position, hash) only: those whose hash
is frequent give the positions that each document loses, and the documents are
reassembled by position, in time linear in their lines.

Defined cases: a null or empty text is one empty line; empty keys (fewer than
``min_chars`` code points) never drop; a document that loses all lines keeps "";
rows that repeat a document count as documents of their own, and rows of one id with
different texts lose lines each by itself; other columns pass through unchanged; an empty
table gives an empty table.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sitemine.llm.common import BLANKS, ascii_lower, bounded_batches, fresh_name
from sitemine.session import broadcast_if_small, materialise

MIN_DOCS = 10
MIN_CHARS = 1
#: Documents, and positions in all, that a broadcast of what is dropped may hold; beyond it the texts are shuffled to them.
HIT_ROWS = 500_000
HIT_POSITIONS = 4_000_000


def lines_of(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def line_key(line: Column) -> Column:
    return ascii_lower(F.btrim(line, F.lit(BLANKS)))


def key_hash(key: Column) -> Column:
    """128 bits as two seeded 64-bit hashes, packed as one comparable struct."""
    return F.struct(F.xxhash64(key).alias("a"), F.xxhash64(F.lit(7), key).alias("b"))


def _hashes(text: Column, min_chars: int) -> Column:
    """The hash of each line's key, null for keys that never drop."""
    keys = F.transform(lines_of(text), line_key)
    return F.transform(keys, lambda k: F.when(F.char_length(k) >= min_chars, key_hash(k)))


def frequent_keys(docs: DataFrame, *, text: str = "text", min_docs: int = MIN_DOCS, min_chars: int = MIN_CHARS) -> DataFrame:
    """(key, n_docs): hashes of the keys found in at least ``min_docs`` documents."""
    each = docs.select(F.explode(F.array_distinct(_hashes(F.col(text), min_chars))).alias("key")).where(F.col("key").isNotNull())
    return each.groupBy("key").agg(F.count("*").alias("n_docs")).where(F.col("n_docs") >= min_docs)


def reassemble(joined: DataFrame, *, text: str, gone: str, n_lines: str, n_dropped: str) -> DataFrame:
    """``joined`` with ``text`` less the lines at the positions ``gone`` (null: none), and both counts in place of ``gone``."""
    kept = [c for c in joined.columns if c != gone]
    fields = [T.StructField(f.name, T.StringType()) if f.name == text else f for f in joined.schema if f.name != gone]
    schema = T.StructType([*fields, T.StructField(n_lines, T.LongType()), T.StructField(n_dropped, T.LongType())])
    at = kept.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, total, dropped = [], [], []
            for body, lost in zip(batch.column(at).to_pylist(), batch.column(len(kept)).to_pylist(), strict=True):
                body = body or ""
                if lost:
                    lines, lost = body.split("\n"), set(lost)
                    total.append(len(lines))
                    body = "\n".join(line for i, line in enumerate(lines) if i not in lost)
                else:
                    total.append(body.count("\n") + 1)
                dropped.append(len(lost or ()))
                texts.append(body)
            columns = [pa.array(texts, pa.string()) if i == at else batch.column(i) for i in range(len(kept))]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(total, pa.int64()), pa.array(dropped, pa.int64())], names=[*kept, n_lines, n_dropped])

    return joined.select(*kept, gone).mapInArrow(run, schema)


def drop_frequent_lines(
    docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", min_docs: int = MIN_DOCS, min_chars: int = MIN_CHARS
) -> DataFrame:
    """``docs`` with ``text`` reassembled, plus ``n_lines`` and ``n_dropped`` (renamed if taken)."""
    hit_id, mark, hit_mark = (fresh_name(docs, x) for x in ("hit_id", "mark", "hit_mark"))
    frequent = materialise(frequent_keys(docs, text=text, min_docs=min_docs, min_chars=min_chars).select("key"))
    lines = docs.select(F.col(id_col).alias(hit_id), F.xxhash64(F.col(text)).alias(hit_mark), F.posexplode(_hashes(F.col(text), min_chars)).alias("at", "key"))
    n_lines, n_dropped, gone = (fresh_name(docs, x) for x in ("n_lines", "n_dropped", "gone"))
    hits = materialise(lines.join(broadcast_if_small(frequent), "key", "left_semi").groupBy(hit_id, hit_mark).agg(F.collect_set("at").alias(gone)))
    rows, positions = hits.agg(F.count("*"), F.coalesce(F.sum(F.size(gone)), F.lit(0))).first()
    if rows <= HIT_ROWS and positions <= HIT_POSITIONS:
        hits = F.broadcast(hits)
    own = bounded_batches(docs).withColumn(mark, F.xxhash64(F.col(text)))
    joined = own.join(hits, F.col(id_col).eqNullSafe(F.col(hit_id)) & (F.col(mark) == F.col(hit_mark)), "left")
    return reassemble(joined.drop(hit_id, mark, hit_mark), text=text, gone=gone, n_lines=n_lines, n_dropped=n_dropped).select(*docs.columns, n_lines, n_dropped)


def op7_line_dedup(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out = drop_frequent_lines(docs)
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("text"), 256).alias("kept_sha256"))


ORACLE = """
with lines as (
  select doc_id, unnest(string_split(coalesce(text, ''), chr(10))) as line,
         generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) as pos
  from documents),
keyed as (
  select doc_id, pos, line,
         translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
                   'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as key
  from lines),
frequent as (
  select key from keyed where length(key) >= 1 group by key having count(distinct doc_id) >= 10)
select doc_id, count(*)::bigint as n_lines,
       count(*) filter (where f.key is not null)::bigint as n_dropped,
       sha256(coalesce(string_agg(line, chr(10) order by pos) filter (where f.key is null), '')) as kept_sha256
from keyed left join frequent f using (key)
group by doc_id
"""
