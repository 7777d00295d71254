"""Substring dedup with one compressed FM-index per shard.

A word is removed if a window of ``WINDOW`` words that covers it also starts in a document with a smaller id.

1. Every window has an anchor, the smallest hash of its ``ANCHOR``-word runs; neighbouring windows with one anchor form a
   stretch. Equal windows have equal anchors, so shards by anchor see all occurrences of a window. Anchors of one document
   only can't matter and go.
2. Equal stretches (anchor and content) are one context with the smallest document id, whatever the number of copies.
3. Each shard indexes its contexts: words as symbols, Burrows-Wheeler transform, wavelet matrix with packed bits and sampled
   ranks, and the suffix classes that agree on ``WINDOW`` words. All contexts are streamed through backward search at once,
   right to left; a match that reaches the threshold is widened to its class (the capped matching statistic), which
   gives the smallest document id of that window.
4. Stretches take the intervals of their context; documents drop the words that an interval with a smaller id covers.

Null and empty texts have no words. Rows with a null doc_id lose nothing and take nothing away. Repeated rows have the
same id, so none is smaller. Ties of hashes inside a window don't matter: the anchor is a value, not a place. Extra columns
are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import batches_of, documents, mix, sha256_hex, table, window_hashes, word_hashes, words_of

WINDOW = 50
ANCHOR = 16
#: Words that a shard's index holds, about.
SHARD_WORDS = 700_000


# ---------------------------------------------------------------- the index
class WaveletMatrix:
    """Ranks of symbols in a sequence: one packed bit vector per bit of the symbols."""

    def __init__(self, symbols: np.ndarray, n_symbols: int):
        self.bits = max(1, int(n_symbols - 1).bit_length())
        self.levels = []
        now = symbols.astype(np.uint32)
        n = len(now)
        for level in range(self.bits - 1, -1, -1):
            one = ((now >> np.uint32(level)) & np.uint32(1)).astype(bool)
            packed = np.packbits(one, bitorder="little")
            words = np.zeros(n // 64 + 2, np.uint64)
            words.view(np.uint8)[: len(packed)] = packed
            before = np.zeros(len(words), np.int64)
            np.cumsum(np.bitwise_count(words)[:-1], out=before[1:])
            self.levels.append((words, before, n - int(one.sum())))
            now = np.concatenate([now[~one], now[one]])

    def walk(self, symbol: np.ndarray, *places: np.ndarray) -> list[np.ndarray]:
        """Where each place of the sequence comes to lie below all levels, on the way of its symbol."""
        places = list(places)
        for level, (words, before, zeros) in enumerate(self.levels):
            one = (symbol >> (self.bits - 1 - level)) & 1 == 1
            for k, at in enumerate(places):
                word = at >> 6
                mask = (np.uint64(1) << (at & 63).astype(np.uint64)) - np.uint64(1)
                ones = before[word] + np.bitwise_count(words[word] & mask)
                places[k] = np.where(one, zeros + ones, at - ones)
        return places


class FMIndex:
    """Backward search over many short texts, with matches capped at ``window`` symbols."""

    def __init__(self, texts: list[np.ndarray], window: int):
        """``texts``: symbols from 1; 0 closes each text."""
        self.window = window
        n = np.array([len(t) for t in texts], np.int64)
        full = np.zeros(int(n.sum()) + len(texts), np.int64)
        ends = np.cumsum(n + 1) - 1
        full[np.setdiff1d(np.arange(len(full)), ends, assume_unique=True)] = np.concatenate(texts) if texts else []
        self.text_of = np.repeat(np.arange(len(texts)), n + 1)
        order, self.class_of = self._sorted(full, window)
        bwt = full[order - 1]  # the symbol before each suffix; the first suffix has the last separator
        self.n_symbols = int(full.max()) + 1 if len(full) else 1
        self.less = np.concatenate([[0], np.cumsum(np.bincount(full, minlength=self.n_symbols))])
        self.matrix = WaveletMatrix(bwt, self.n_symbols)
        every = np.arange(self.n_symbols)
        self.base = self.less[:-1] - self.matrix.walk(every, np.zeros(self.n_symbols, np.int64))[0]
        self.class_start = np.flatnonzero(np.concatenate([[True], self.class_of[1:] != self.class_of[:-1]])) if len(full) else np.zeros(0, np.int64)
        self.class_of = np.repeat(np.arange(len(self.class_start)), np.diff(np.append(self.class_start, len(full))))
        self.class_end = np.append(self.class_start[1:], len(full))
        self.order = order

    @staticmethod
    def _sorted(full: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
        """Suffixes sorted by more than ``window`` symbols, and in that order the class of their first ``window``."""

        def paired(rank: np.ndarray, ahead: int) -> np.ndarray:
            second = np.zeros_like(rank)
            second[: len(rank) - ahead] = rank[ahead:] + 1
            return rank * (int(second.max(initial=0)) + 1) + second

        rank, depth, classes = full, 1, None
        while True:
            if depth <= window < 2 * depth:
                classes = paired(rank, window - depth) if window > depth else rank
            key = paired(rank, depth)
            depth *= 2
            if depth > window:
                order = np.argsort(key, kind="stable")
                return order, classes[order]
            rank = np.unique(key, return_inverse=True)[1]

    def least(self, value: np.ndarray) -> np.ndarray:
        """Smallest value of a text among the texts of each class."""
        return np.minimum.reduceat(value[self.text_of[self.order]], self.class_start) if len(self.class_start) else value[:0]

    def search(self, patterns: list[np.ndarray]) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """(start, pattern numbers, classes) of all windows, from the last start to the first.

        Patterns must be of symbols in the index; one that isn't found there is dropped where its match ends below a window.
        """
        if not patterns:
            return
        n = np.array([len(p) for p in patterns], np.int64)
        by = np.argsort(-n, kind="stable")  # longest first, so those still running are a prefix
        lengths = n[by]
        flat = np.concatenate([patterns[i] for i in by])
        last = np.cumsum(lengths) - 1
        lo = np.zeros(len(by), np.int64)
        hi = np.full(len(by), self.less[-1], np.int64)
        for step in range(int(lengths[0])):
            m = int(np.searchsorted(-lengths, -step, "left"))  # patterns longer than step
            symbol = flat[last[:m] - step]
            if step:
                a, b = self.matrix.walk(symbol, lo[:m], hi[:m])
                lo[:m], hi[:m] = a + self.base[symbol], b + self.base[symbol]
            else:
                lo[:m], hi[:m] = self.less[symbol], self.less[symbol + 1]
            if step + 1 >= self.window:
                found = lo[:m] < hi[:m]
                classes = self.class_of[lo[:m][found]]
                lo[:m][found], hi[:m][found] = self.class_start[classes], self.class_end[classes]
                yield step, by[:m][found], classes


def least_owners(contexts: list[list[bytes]], owner: np.ndarray, window: int = WINDOW) -> list[list[tuple[int, int, int]]]:
    """For each context the runs (first start, last start, smallest owner) of its windows."""
    symbol: dict[bytes, int] = {}
    texts = [np.array([symbol.setdefault(w, len(symbol) + 1) for w in c], np.int64) for c in contexts]
    index = FMIndex(texts, window)
    least = index.least(owner)
    out = [np.full(max(0, len(t) - window + 1), np.iinfo(np.int64).max) for t in texts]
    flat = np.concatenate(out) if out else np.zeros(0, np.int64)
    size = np.array([len(o) for o in out], np.int64)
    first = np.cumsum(size) - size
    length = np.array([len(t) for t in texts], np.int64)
    for step, number, classes in index.search(texts):
        flat[first[number] + length[number] - 1 - step] = least[classes]
    runs = []
    for f, s in zip(first.tolist(), size.tolist()):
        value = flat[f : f + s]
        cut = np.flatnonzero(np.diff(value)) + 1
        runs.append([(a, b - 1, int(value[a])) for a, b in zip([0, *cut.tolist()], [*cut.tolist(), s])] if s else [])
    return runs


# ---------------------------------------------------------------- stretches of windows with one anchor
_B = 0xD1342543DE82EF95
_POWERS: list[np.ndarray] = []


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _POWERS or len(_POWERS[0]) < n:
        size = max(1024, 1 << n.bit_length())
        with np.errstate(over="ignore"):
            _POWERS[:] = [np.cumprod(np.full(size, b, np.uint64)) for b in (_B, pow(_B, -1, 1 << 64))]
    return _POWERS[0], _POWERS[1]


def stretches(h: np.ndarray, window: int = WINDOW, anchor: int = ANCHOR) -> tuple[np.ndarray, ...]:
    """(anchor, content hash, first start, number of starts) of each stretch, from a document's word hashes."""
    n = len(h) - window + 1
    if n <= 0:
        return tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int32, np.int32))
    least, size, span = window_hashes(h, anchor), 1, window - anchor + 1
    while 2 * size <= span:
        least = np.minimum(least[: len(least) - size], least[size:])
        size *= 2
    if size < span:
        least = np.minimum(least[: len(least) - (span - size)], least[span - size :])
    first = np.flatnonzero(np.concatenate([[True], least[1:] != least[:-1]]))
    count = np.diff(np.append(first, n))
    up, down = _powers(len(h) + 1)
    with np.errstate(over="ignore"):
        total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(h * up[: len(h)])])
        content = mix((total[first + count + window - 1] - total[first]) * down[first] + count.astype(np.uint64))
    return least[first].view(np.int64), content.view(np.int64), first.astype(np.int32), count.astype(np.int32)


def _stretch_rows(docs: DataFrame) -> DataFrame:
    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches_of(it):
            parts, rows = [], []
            for i, text in enumerate(b.column("text").to_pylist()):
                found = stretches(word_hashes(words_of(text)))
                if len(found[0]):
                    parts.append(found)
                    rows.append(np.full(len(found[0]), i))
            if parts:
                at = pa.array(np.concatenate(rows))
                yield pa.RecordBatch.from_arrays([b.column("doc_id").take(at), b.column("t").take(at), *(pa.array(np.concatenate(x)) for x in zip(*parts))], names=["doc_id", "t", "a", "h", "s", "n"])

    return docs.filter("doc_id is not null").mapInArrow(run, "doc_id long, t long, a long, h long, s int, n int")


def _context_rows(docs_with_parts: DataFrame, shards: int) -> DataFrame:
    """Words of each context, taken from the document that shows it."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches_of(it):
            out = []
            for doc_id, text, parts in zip(b.column("doc_id").to_pylist(), b.column("text").to_pylist(), b.column("parts").to_pylist()):
                words = words_of(text)
                out += [(p["a"] % shards, p["a"], p["h"], doc_id, b" ".join(words[p["s"] : p["s"] + p["n"] + WINDOW - 1])) for p in parts]
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), (pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary()))], names=["shard", "a", "h", "doc_id", "words"])

    return docs_with_parts.mapInArrow(run, "shard int, a long, h long, doc_id long, words binary")


def _shard_intervals(rows: pd.DataFrame) -> pd.DataFrame:
    found = least_owners([w.split() for w in rows["words"]], rows["doc_id"].to_numpy(np.int64))
    return pd.DataFrame([(a, h, lo, hi, least) for a, h, runs in zip(rows["a"], rows["h"], found) for lo, hi, least in runs], columns=["a", "h", "lo", "hi", "least"])


def covered_intervals(docs: DataFrame) -> DataFrame:
    """(doc_id, t, parts): intervals of words (start, end exclusive) that windows with a smaller document cover."""
    runs = table(_stretch_rows(docs), "stretches")
    shared = runs.groupBy("a").agg(F.min("doc_id").alias("least"), F.max("doc_id").alias("most")).filter("least < most").select("a")
    hot = table(runs.join(shared, "a", "left_semi"), "shared-stretches")
    shown = table(hot.groupBy("a", "h").agg(F.min(F.struct("doc_id", "t", "s", "n")).alias("x")).select("a", "h", "x.*"), "contexts")
    words = shown.agg(F.coalesce(F.sum(F.col("n") + WINDOW - 1), F.lit(0))).first()[0]
    shards = int(words // SHARD_WORDS + 1)
    listed = shown.groupBy("doc_id", "t").agg(F.collect_list(F.struct("a", "h", "s", "n")).alias("parts"))
    contexts = _context_rows(docs.join(listed, ["doc_id", "t"]).select("doc_id", "text", "parts"), shards)
    owners = table(contexts.groupBy("shard").applyInPandas(_shard_intervals, "a long, h long, lo int, hi int, least long"), "owners")
    taken = hot.join(owners, ["a", "h"]).filter("least < doc_id").select("doc_id", "t", (F.col("s") + F.col("lo")).alias("start"), (F.col("s") + F.col("hi") + WINDOW).alias("end"))
    return taken.groupBy("doc_id", "t").agg(F.collect_list(F.struct("start", "end")).alias("parts"))


def _kept(docs: DataFrame, produce, schema) -> DataFrame:
    keyed = docs.withColumn("t", F.xxhash64("text"))
    intervals = covered_intervals(keyed.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), "t"))
    return keyed.join(intervals, ["doc_id", "t"], "left").select(*[keyed[c] for c in docs.columns], "parts").mapInArrow(produce, schema)


def _split(text: str | None, parts: list | None) -> tuple[list[bytes], list[bytes]]:
    words = words_of(text)
    if not parts:
        return words, words
    edge = np.zeros(len(words) + 1, np.int64)
    for p in parts:
        edge[p["start"]] += 1
        edge[p["end"]] -= 1
    return words, [w for w, c in zip(words, np.cumsum(edge[:-1]).tolist()) if not c]


def dedup_report(docs: DataFrame) -> DataFrame:
    """Words, removed words and digest of what is kept, of every document."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches_of(it):
            rows = [_split(t, p) for t, p in zip(b.column("text").to_pylist(), b.column("parts").to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([len(w) for w, _ in rows], pa.int64()), pa.array([len(w) - len(k) for w, k in rows], pa.int64()), pa.array([sha256_hex(b" ".join(k)) for _, k in rows])], names=["doc_id", "n_words", "n_removed", "kept_sha256"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return _kept(rows, run, "doc_id long, n_words long, n_removed long, kept_sha256 string")


def dedup_texts(docs: DataFrame) -> DataFrame:
    """Documents (doc_id, text) with the repeated words taken out of their texts."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches_of(it):
            texts = [t if not p else b" ".join(_split(t, p)[1]).decode("utf-8", "surrogatepass") for t, p in zip(b.column("text").to_pylist(), b.column("parts").to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(texts, pa.string())], names=["doc_id", "text"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return _kept(rows, run, "doc_id long, text string")


def op4_fm_index_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_report(documents(spark, sf_dir))
