"""Small shared pieces of the corpus operators."""

from __future__ import annotations

import string

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: White space of the contracts: space, tab, line feed, vertical tab, form feed, carriage return.
BLANKS = " \t\n\x0b\x0c\r"
WORD = r"[^\x20\x09-\x0D]+"


def ascii_lower(c: Column) -> Column:
    """A-Z lower-cased, every other character as it is."""
    return F.translate(c, string.ascii_uppercase, string.ascii_lowercase)


def fresh_name(df: DataFrame, stem: str) -> str:
    """A column name that no column of ``df`` has in any case."""
    taken = {c.lower() for c in df.columns}
    while stem.lower() in taken:
        stem += "_"
    return stem


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))


#: Rows of one Arrow batch between Spark and Python: texts may be long, and a batch is held whole on both sides.
BATCH_ROWS = 1000


def bounded_batches(df: DataFrame) -> DataFrame:
    """``df``, its session held to batches of at most ``BATCH_ROWS`` rows (a setting that may change at run time)."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    conf = df.sparkSession.conf
    now = int(conf.get(name))
    if now <= 0 or now > BATCH_ROWS:
        conf.set(name, BATCH_ROWS)
    return df


_M1, _M2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9)


def mixed(*parts: np.ndarray | int) -> np.ndarray:
    """A 64-bit hash of numbers, the same wherever it is taken."""
    out = np.zeros(1, np.uint64)
    for part in parts:
        out = (out ^ np.asarray(part).astype(np.uint64)) * _M1
        out = (out ^ (out >> np.uint64(29))) * _M2
        out = out ^ (out >> np.uint64(32))
    return out


class HashTable:
    """Numbers by 64-bit hash in a worker: sorted hashes, and where each start of the hash begins."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        order = np.argsort(keys)
        self.keys, self.values = keys[order], values[order]
        bits = max(1, len(keys).bit_length())
        self.shift = np.uint64(64 - bits)
        self.first = np.searchsorted(self.keys >> self.shift, np.arange((1 << bits) + 1, dtype=np.uint64)).astype(np.int32)

    def find(self, asked: np.ndarray) -> np.ndarray:
        """The value of each hash, NaN where there is none."""
        start = (asked >> self.shift).astype(np.int64)
        at, end = self.first[start], self.first[start + 1]
        out = np.full(len(asked), np.nan)
        left = np.flatnonzero(at < end)
        at, end = at[left], end[left]
        while len(left):
            hit = self.keys[at] == asked[left]
            out[left[hit]] = self.values[at[hit]]
            at = at + 1
            more = ~hit & (at < end)
            left, at, end = left[more], at[more], end[more]
        return out
