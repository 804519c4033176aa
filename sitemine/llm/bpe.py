"""BPE encoding and decoding by tree concatenation.

A text is cut at the tokenizer's special strings, normalised as the tokenizer file says,
and split into words by its pattern; each word is encoded by its merges.  Results equal
``tokenizers.Tokenizer.encode(text, add_special_tokens=False)`` of the same file.

Long unsplit text is not encoded in one go.  Its halves (and their halves) are encoded
apart, then joined: a window of the last tokens of the left and the first of the right
is encoded again and grows until its first token is the left's and its last is the
right's.  Every neighbouring pair of the joined sequence then stands in a valid encoding,
and since each token of the vocabulary comes from one merge, the whole is the encoding.
This happens at two levels:

* inside one word (`Merges.join`), on its tokens;
* across a long document: texts over ``piece`` characters become rows of their own,
  pieces are encoded in parallel wherever they were cut, and one task per document joins
  neighbours pairwise, growing a window of words until the word boundaries and tokens on
  both sides agree (`join_pieces`).

Short words are looked up in a bounded cache, filled by the library in bulk.

Defined cases: null text is empty and has no tokens; special strings inside a text are
their own token, as in the library; characters outside the vocabulary cannot occur (all
bytes are in it); rows, repeated ids and extra columns are kept; an empty table gives an
empty table.
"""

from __future__ import annotations

import heapq
import json
import os
import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from tokenizers import Tokenizer, normalizers, pre_tokenizers

from sitemine.llm.common import bounded_batches, fresh_name

PIECE = 65_536
#: Symbols of a word that are merged in one go; longer words are joined from halves.
LEAF = 256
CACHE = 120_000
_SUFFIX = "</w>"

# Latin text needs no normalisation but lower case, and a plain pattern splits it.
_BEYOND = re.compile("[^\x00-ɏ]")
_LETTER, _NUMBER, _SPACE = "a-zA-ZªµºÀ-ÖØ-öø-ɏ", "0-9²³¹¼-¾", "\t-\r \x85\xa0"
_SHORT = "'s|'t|'re|'ve|'m|'ll|'d"
_LATIN = re.compile(f"{_SHORT}|[{_LETTER}]+|[{_NUMBER}]|[^{_SPACE}{_LETTER}{_NUMBER}]+")
_ANY = regex.compile(rf"{_SHORT}|\p{{L}}+|\p{{N}}|[^\p{{White_Space}}\p{{L}}\p{{N}}]+")


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def byte_symbols() -> list[str]:
    """The printable stand-in of each byte in byte-level vocabularies."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = iter(range(256, 512))
    return [chr(b) if b in own else chr(next(rest)) for b in range(256)]


class Merges:
    """Token ids of one word's symbols, whole or in parts."""

    def __init__(self, vocab: dict[str, int], merges: list):
        pairs = [tuple(m) if not isinstance(m, str) else tuple(m.split(" ")) for m in merges]
        self.rank = {(vocab[a], vocab[b]): (r, vocab[a + b]) for r, (a, b) in enumerate(pairs)}
        self.open = [vocab[s] for s in byte_symbols()]
        self.shut = [vocab[s + _SUFFIX] for s in byte_symbols()]
        self.close = dict(zip(self.open, self.shut, strict=True))
        self.reopen = dict(zip(self.shut, self.open, strict=True))
        self.parts: dict[int, tuple[int, int]] = {new: pair for pair, (_, new) in self.rank.items()}

    def symbols(self, ids: list[int]) -> list[int]:
        """The single symbols that made these tokens."""
        out, todo = [], list(reversed(ids))
        while todo:
            t = todo.pop()
            if pair := self.parts.get(t):
                todo += (pair[1], pair[0])
            else:
                out.append(t)
        return out

    def merge(self, ids: list[int]) -> list[int]:
        """All merges of a symbol sequence: lowest rank first, leftmost among equals."""
        ids = list(ids)
        after = [*range(1, len(ids)), -1]
        before = [*range(-1, len(ids) - 1)]
        heap = [(*self.rank[p], i, p) for i, p in enumerate(zip(ids, ids[1:])) if p in self.rank]
        heap = [(r, i, new, p) for r, new, i, p in heap]
        heapq.heapify(heap)
        while heap:
            _, i, new, pair = heapq.heappop(heap)
            j = after[i]
            if j < 0 or (ids[i], ids[j]) != pair:
                continue
            ids[i], ids[j] = new, -1
            after[i] = after[j]
            if after[j] >= 0:
                before[after[j]] = i
            for a in (before[i], i):
                if a >= 0 and after[a] >= 0 and (got := self.rank.get(p := (ids[a], ids[after[a]]))):
                    heapq.heappush(heap, (got[0], a, got[1], p))
        return [t for t in ids if t >= 0]

    def part(self, word: bytes) -> list[int]:
        """Tokens of a stretch inside a word, from its halves if it is long."""
        if len(word) <= LEAF:
            return self.merge([self.open[b] for b in word])
        half = len(word) // 2
        return self.join(self.part(word[:half]), self.part(word[half:]))

    def join(self, left: list[int], right: list[int]) -> list[int]:
        """Tokens of two neighbouring stretches, from the tokens of each."""
        width = 4
        while True:
            a, b = left[-width:], right[:width]
            window = self.merge(self.symbols(a + b))
            start, end = len(a) == len(left), len(b) == len(right)
            if (start or window[0] == a[0]) and (end or window[-1] == b[-1]):
                return left[: len(left) - len(a)] + window + right[len(b) :]
            width *= 2

    def finish(self, open_ids: list[int]) -> list[int]:
        """Tokens of the whole word from those of its stretch without the word's end."""
        width = 4
        while True:
            tail = self.symbols(open_ids[-width:])
            window = self.merge([*tail[:-1], self.close[tail[-1]]])
            if width >= len(open_ids) or window[0] == open_ids[-width]:
                return open_ids[: max(0, len(open_ids) - width)] + window
            width *= 2


@dataclass
class Piece:
    """A stretch of normalised text, its words [start, end), and the tokens of each."""

    text: str
    spans: list[tuple[int, int]]
    tokens: list  # of sequences of ids


class Bpe:
    """One tokenizer file, loaded once a worker."""

    def __init__(self, path: str):
        self.library = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.merges = Merges(spec["model"]["vocab"], spec["model"]["merges"])
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.specials = re.compile("|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) or "(?!)")
        self.names = [""] * self.library.get_vocab_size()
        for token, i in self.library.get_vocab().items():
            self.names[i] = token
        self.ends = np.array([n.endswith(_SUFFIX) for n in self.names])
        # words come to it split and normalised, so it need not do either
        self.bulk = Tokenizer.from_file(path)
        self.bulk.normalizer = normalizers.Sequence([])
        self.bulk.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        # ids of a word as the bytes of an int32 array: small, and quickly joined
        self.cache: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}

    def segments(self, text: str) -> Iterator[tuple[str, int]]:
        """(normalised text, -1) and ("", id of a special string), in order."""
        at = 0
        for m in self.specials.finditer(text) if "<|" in text or not self._barred else ():
            if m.start() > at:
                yield self.normal(text[at : m.start()]), -1
            yield "", self.special[m[0]]
            at = m.end()
        if at < len(text):
            yield self.normal(text[at:]), -1

    @property
    def _barred(self) -> bool:
        return all("<|" in s for s in self.special)

    def normal(self, text: str) -> str:
        return self.library.normalizer.normalize_str(text) if _BEYOND.search(text) else text.lower()

    @staticmethod
    def pattern(text: str):
        return _ANY if _BEYOND.search(text) else _LATIN

    def learn(self, words: set[str]) -> None:
        """Put the tokens of words into the cache; long words by halves, others in bulk."""
        known, short = self.old, []
        for w in words.difference(self.cache):
            if w in known:
                self.cache[w] = known[w]
            elif len(w) > LEAF:
                self.cache[w] = self.word(w)
            else:
                short.append(w)
        if short:
            ids = np.array(self.bulk.encode_batch_fast([" ".join(short)], add_special_tokens=False)[0].ids, np.int32)
            cuts = (np.flatnonzero(self.ends[ids]) + 1) * 4
            if len(cuts) == len(short):
                flat, at = ids.tobytes(), 0
                for w, cut in zip(short, cuts.tolist(), strict=True):
                    self.cache[w] = flat[at:cut]
                    at = cut
            else:
                self.cache |= {w: self.word(w) for w in short}

    def word(self, w: str) -> bytes:
        return np.array(self.merges.finish(self.merges.part(w.encode())), np.int32).tobytes()

    def trim(self) -> None:
        if len(self.cache) > CACHE:
            self.old, self.cache = self.cache, {}

    def encode_all(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of whole texts."""
        split = [[(self.pattern(t).findall(t), i) for t, i in self.segments(text)] for text in texts]
        self.learn(set().union(*(words for doc in split for words, _ in doc)))
        get = self.cache.__getitem__
        out = []
        for doc in split:
            parts = (i.to_bytes(4, "little") if i >= 0 else b"".join(map(get, words)) for words, i in doc)
            out.append(np.frombuffer(b"".join(parts), "<i4"))
        self.trim()
        return out

    def piece(self, text: str) -> Piece:
        spans = [m.span() for m in self.pattern(text).finditer(text)]
        words = [text[a:b] for a, b in spans]
        self.learn(set(words))
        out = Piece(text, spans, [tuple(np.frombuffer(self.cache[w], np.int32).tolist()) for w in words])
        self.trim()
        return out

    def join_pieces(self, left: Piece, right: Piece) -> Piece:
        """One piece from two neighbours, re-splitting ever more words around the join."""
        shift = len(left.text)
        width = 1
        while True:
            a, b = left.spans[-width:], right.spans[:width]
            start = 0 if len(a) == len(left.spans) else a[0][0]
            end = len(right.text) if len(b) == len(right.spans) else b[-1][1]
            window = left.text[start:] + right.text[:end]
            # the pattern reads letters alike in both forms, so the window may use its own
            spans = [(x + start, y + start) for x, y in (m.span() for m in self.pattern(window).finditer(window))]
            agree_left = len(a) == len(left.spans) or (spans and spans[0] == a[0])
            agree_right = len(b) == len(right.spans) or (spans and spans[-1] == (b[-1][0] + shift, b[-1][1] + shift))
            if agree_left and agree_right:
                break
            width *= 2
        text = left.text + right.text
        known = dict(zip(a, left.tokens[-width:], strict=False)) if a else {}
        known |= {(x + shift, y + shift): t for (x, y), t in zip(b, right.tokens[:width], strict=False)}
        tokens = []
        for span in spans:
            if span in known:
                tokens.append(known[span])
            elif a and b and span == (a[-1][0], b[0][1] + shift):  # one word, cut in two
                tokens.append(tuple(self.merges.join(self._reopen(left.tokens[-1]), list(right.tokens[0]))))
            else:
                tokens.append(tuple(self.merges.finish(self.merges.part(text[span[0] : span[1]].encode()))))
        keep = len(left.spans) - len(a)
        return Piece(
            text,
            left.spans[:keep] + spans + [(x + shift, y + shift) for x, y in right.spans[len(b) :]],
            left.tokens[:keep] + tokens + right.tokens[len(b) :],
        )

    def _opened(self, ids) -> list[int]:
        """Symbols of a finished word, its last one without the word's end."""
        symbols = self.merges.symbols(list(ids))
        return [*symbols[:-1], self.merges.reopen[symbols[-1]]]

    def _reopen(self, ids) -> list[int]:
        """Tokens of a finished word's stretch without the word's end: only its tail changes."""
        ids, width = list(ids), 4
        while True:
            window = self.merges.merge(self._opened(ids[-width:]))
            if width >= len(ids) or window[0] == ids[-width]:
                return ids[: max(0, len(ids) - width)] + window
            width *= 2

    def tree(self, pieces: list[Piece]) -> np.ndarray:
        while len(pieces) > 1:
            pieces = [self.join_pieces(*pieces[i : i + 2]) if i + 1 < len(pieces) else pieces[i] for i in range(0, len(pieces), 2)]
        return np.fromiter(chain.from_iterable(pieces[0].tokens), np.int32) if pieces else np.empty(0, np.int32)

    def decode(self, ids: list[int]) -> str:
        return " ".join(map(self.names.__getitem__, ids))


@lru_cache(2)
def load(path: str) -> Bpe:
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a worker has one core
    return Bpe(path)


def _lists(arrays: list[np.ndarray]) -> pa.ListArray:
    offsets = np.concatenate([[0], np.cumsum([len(a) for a in arrays])]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate([np.empty(0, np.int32), *arrays]), pa.int32()))


def _slices(batch: pa.RecordBatch, rows: int = 128) -> Iterator[pa.RecordBatch]:
    return (batch.slice(i, rows) for i in range(0, batch.num_rows, rows))


def _schema(df: DataFrame, more: str) -> str:
    return ", ".join([*(f"`{c}` {t}" for c, t in df.dtypes), more])


def encode(docs: DataFrame, *, text: str = "text", path: str | None = None, piece: int = PIECE) -> DataFrame:
    """``docs`` without ``text``, plus ``ids`` array<int> (renamed if taken)."""
    path = path or default_path()
    keep = bounded_batches(docs).drop(text)
    ids = fresh_name(keep, "ids")
    body = F.coalesce(F.col(text), F.lit(""))

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path)
        for batch in batches:
            for part in _slices(batch):
                made = bpe.encode_all(part.column(part.num_columns - 1).to_pylist())
                yield pa.RecordBatch.from_arrays([*part.columns[:-1], _lists(made)], names=[*part.schema.names[:-1], ids])

    made = _schema(keep, f"`{ids}` array<int>")
    short = docs.where(F.char_length(body) <= piece).select(*keep.columns, body.alias(fresh_name(keep, "whole_text"))).mapInArrow(whole, made)
    return short.unionByName(_encode_long(docs, text, ids, path, piece))


def _encode_long(docs: DataFrame, text: str, ids: str, path: str, piece: int) -> DataFrame:
    """The documents over ``piece`` characters, by pieces."""
    keep = docs.drop(text).columns
    rest = F.struct(F.lit(0).alias(fresh_name(docs, "spare")), *keep).alias("rest")
    rows = docs.where(F.char_length(text) > piece).select(F.monotonically_increasing_id().alias("rid"), rest, F.col(text).alias("text"))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Piece rows; the other columns travel with the first piece."""
        bpe = load(path)
        for batch in batches:
            for i in range(batch.num_rows):
                parts, part = [], 0
                for segment, special in bpe.segments(batch.column("text")[i].as_py()):
                    parts += [(part, "", special)] if special >= 0 else [(part, segment[j : j + piece], -1) for j in range(0, len(segment), piece)]
                    part += 1
                n = len(parts)
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column("rid").take(pa.array([i] * n)),
                        batch.column("rest").take(pa.array([i] + [None] * (n - 1), pa.int64())),
                        pa.array(range(n), pa.int32()),
                        *(pa.array([p[k] for p in parts], kind) for k, kind in enumerate((pa.int32(), pa.string(), pa.int32()))),
                    ],
                    names=["rid", "rest", "seq", "part", "piece", "special"],
                )

    def encode_pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path)
        for batch in batches:
            for row in _slices(batch, 1):
                made = bpe.piece(row.column("piece")[0].as_py())
                spans = np.array(made.spans, np.int32).reshape(-1, 2)
                tokens = np.fromiter(chain.from_iterable(made.tokens), np.int32)
                yield pa.RecordBatch.from_arrays(
                    [*row.columns, _lists([spans[:, 0]]), _lists([spans[:, 1]]), _lists([np.array([len(t) for t in made.tokens], np.int32)]), _lists([tokens])],
                    names=[*row.schema.names, "starts", "ends", "counts", "tokens"],
                )

    def stitch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path)
        for batch in batches:
            for row in _slices(batch, 1):
                out: list[np.ndarray] = []
                held: list[Piece] = []
                last = -1
                for p in row.column("pieces")[0].as_py():
                    if p["part"] != last and held:
                        out.append(bpe.tree(held))
                        held = []
                    last = p["part"]
                    if p["special"] >= 0:
                        out.append(np.array([p["special"]], np.int32))
                    else:
                        cuts = np.cumsum(p["counts"]).tolist()
                        tokens = [tuple(p["tokens"][a:b]) for a, b in zip([0, *cuts], cuts, strict=False)]
                        held.append(Piece(p["piece"], list(zip(p["starts"], p["ends"], strict=True)), tokens))
                if held:
                    out.append(bpe.tree(held))
                yield pa.RecordBatch.from_arrays([row.column("rest"), _lists([np.concatenate([np.empty(0, np.int32), *out])])], names=["rest", "ids"])

    other = dict(rows.dtypes)["rest"]
    shape = f"rid long, rest {other}, seq int, part int, piece string, special int"
    pieces = rows.mapInArrow(cut, shape).repartition("rid", "seq")
    encoded = pieces.mapInArrow(encode_pieces, shape + ", starts array<int>, ends array<int>, counts array<int>, tokens array<int>")
    fields = F.struct("seq", "part", "piece", "special", "starts", "ends", "counts", "tokens")
    gathered = encoded.groupBy("rid").agg(F.first("rest", ignorenulls=True).alias("rest"), F.sort_array(F.collect_list(fields)).alias("pieces"))
    joined = gathered.select("rest", "pieces").mapInArrow(stitch, f"rest {other}, ids array<int>")
    return joined.select(*[F.col("rest")[c].alias(c) for c in keep], F.col("ids").alias(ids))


def decode(encoded: DataFrame, *, ids: str = "ids", text: str = "decoded", path: str | None = None) -> DataFrame:
    """``encoded`` plus the library's decoding of ``ids``, special tokens included."""
    path = path or default_path()
    text = fresh_name(bounded_batches(encoded), text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path)
        names = np.array(bpe.names, object)
        for batch in batches:
            for part in _slices(batch):
                column = part.column(ids)
                flat, at = column.flatten().to_numpy(zero_copy_only=False), np.concatenate([[0], np.cumsum(column.value_lengths().fill_null(0).to_numpy())])
                made = [" ".join(names[flat[a:b]]) for a, b in zip(at[:-1], at[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(made, pa.string())], names=[*part.schema.names, text])

    return encoded.mapInArrow(run, _schema(encoded, f"`{text}` string"))


def op4_bpe(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out = decode(encode(docs))
    return out.select(
        "doc_id",
        F.size("ids").cast("long").alias("n_tokens"),
        F.sha2(F.array_join(F.col("ids").cast("array<string>"), " "), 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
    )
