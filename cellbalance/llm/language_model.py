"""Interpolated modified Kneser-Ney bigram model: counted in Spark, stored as sorted hash arrays, mapped by workers.

Counting. Each task reduces its words to distinct hashes with counts (NumPy) and sends one block per shard; a shard is a
range of word hashes. The task of a shard merges blocks into sorted arrays, writes them as ``.npy`` files into the shared
folder (under a temporary name first, so a repeated task does no harm) and passes on how many distinct words precede each
word; a second exchange gives those to the shard of that word. Nothing but a row of totals per shard reaches the driver.

    uni_key u64, uni_count i64       words and the end token
    ctx_key u32, ctx_stats i64[n,4]  of a preceding word: tokens, and followers seen once, twice, three times or more
    big_key u64, big_count i64       (32 bits of the preceding word's hash, 32 bits of the word's)
    cont_key u32, cont_count i64     distinct preceding words of a word

Scoring. Workers map the files and look a slice of documents up in sorted order, shard after shard: a merge of sorted
arrays. Model files are read through the page cache and are never loaded whole.

Discounts come from counts of counts; the lowest order is the continuation distribution, interpolated with the uniform one
over the known words and one unknown word. Null and empty texts have one token, the end. An empty training set gives each
token the uniform probability of one unknown word, 1. Repeated rows count as often as they occur.
"""

from __future__ import annotations

import functools
import os
from collections.abc import Iterator
from dataclasses import dataclass, field
from urllib.parse import urlparse

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import batches_of, documents, new_path, word_hashes, words_of

#: No word holds a space, so these hashes are of no word's bytes.
END, BEGIN = (np.uint64(xxhash.xxh3_64_intdigest(b)) for b in (b" end", b" begin"))
LOW32 = np.uint64(32)
FLUSH_KEYS = 600_000
BLOCK = "shard int, kind string, keys binary, counts binary"


@dataclass(frozen=True)
class Model:
    """Where a model lies and its totals."""

    path: str
    bits: int
    tokens: int = 0
    words: int = 0
    bigrams: int = 0
    discounts: tuple = (0.5, 1.0, 1.5)
    low_discounts: tuple = (0.5, 1.0, 1.5)
    low_classes: tuple = field(default=(0, 0, 0))  # words with one, two, three or more distinct preceding words


def discounts(n1: int, n2: int, n3: int, n4: int) -> tuple[float, float, float]:
    """The three discounts from counts of counts; fixed ones where a count is missing."""
    if min(n1, n2, n3, n4) <= 0:
        return 0.5, 1.0, 1.5
    y = n1 / (n1 + 2 * n2)
    found = 1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3
    return tuple(min(max(d, 0.05), k + 0.95) for k, d in enumerate(found))


def merged(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys, ascending, and the sums of their counts."""
    if not len(keys):
        return keys, counts
    order = np.argsort(keys, kind="stable")
    keys = keys[order]
    first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    return keys[first], np.add.reduceat(counts[order], first)


def tokens_of(texts: list, lower: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Token hashes of many texts, each closed by END, and the number of tokens of each."""
    words: list[bytes] = []
    n = np.zeros(len(texts), np.int64)
    ends = []
    for i, text in enumerate(texts):
        w = words_of(text, lower)
        words += w
        n[i] = len(w) + 1
        ends.append(len(words))
    return np.insert(word_hashes(words), ends, END), n


def before(tokens: np.ndarray, n: np.ndarray) -> np.ndarray:
    prev = np.empty_like(tokens)
    prev[1:] = tokens[:-1]
    prev[np.cumsum(n) - n] = BEGIN
    return prev


def pair_keys(prev: np.ndarray, tokens: np.ndarray) -> np.ndarray:
    return (prev >> LOW32 << LOW32) | (tokens >> LOW32)


# ---------------------------------------------------------------- counting
def _blocks(kind: str, keys: np.ndarray, counts: np.ndarray, bits: int, width: int = 64) -> Iterator[tuple]:
    """Sorted keys cut into one block per shard, the top ``bits`` of the key."""
    shard = (keys >> np.asarray(width - bits, keys.dtype)).astype(np.int64)
    cuts = np.flatnonzero(np.diff(shard)) + 1
    for lo, hi in zip([0, *cuts.tolist()], [*cuts.tolist(), len(keys)]):
        if lo < hi:
            c = counts[lo:hi]
            yield int(shard[lo]), kind, keys[lo:hi].tobytes(), (c.astype(np.uint8) if c.max() < 256 else c.astype(np.int64)).tobytes()


def _unblock(rows: pd.DataFrame, kind: str, dtype) -> tuple[np.ndarray, np.ndarray]:
    rows = rows[rows["kind"] == kind]
    keys = [np.frombuffer(k, dtype) for k in rows["keys"]]
    counts = [np.frombuffer(c, np.uint8 if len(c) == len(k) else np.int64).astype(np.int64) for k, c in zip(keys, rows["counts"])]
    return (np.concatenate(keys), np.concatenate(counts)) if keys else (np.zeros(0, dtype), np.zeros(0, np.int64))


def _save(folder: str, name: str, array: np.ndarray) -> None:
    temp = f"{folder}/.{name}.{os.getpid()}"
    with open(temp, "wb") as f:
        np.save(f, array)
    os.replace(temp, f"{folder}/{name}.npy")


def train(docs: DataFrame, name: str = "lm") -> Model:
    """Model of the column ``text`` of ``docs``."""
    spark = docs.sparkSession
    where = urlparse(new_path(spark, name))
    if where.scheme not in ("", "file"):
        raise RuntimeError("workers map model files: spark.checkpoint.dir must be a mounted folder")
    root = where.path
    bits = max(2, int(spark.conf.get("spark.sql.shuffle.partitions")) - 1).bit_length()

    def count(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, list] = {"uni": [], "big": []}
        size = 0

        def flush() -> pa.RecordBatch:
            rows = [r for kind, parts in held.items() for r in _blocks(kind, *merged(*(np.concatenate(x) for x in zip(*parts))), bits)]
            for parts in held.values():
                parts.clear()
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.string(), pa.binary(), pa.binary()))], names=["shard", "kind", "keys", "counts"])

        for b in batches_of(it):
            tokens, n = tokens_of(b.column("text").to_pylist())
            for kind, keys in (("uni", tokens), ("big", pair_keys(before(tokens, n), tokens))):
                held[kind].append(np.unique(keys, return_counts=True))
            size += len(held["big"][-1][0])
            if size > FLUSH_KEYS:
                yield flush()
                size = 0
        if size:
            yield flush()

    def write(key, rows: pd.DataFrame) -> pd.DataFrame:
        shard = int(key[0])
        folder = f"{root}/{shard:05d}"
        os.makedirs(folder, exist_ok=True)
        uni, uni_count = merged(*_unblock(rows, "uni", np.uint64))
        big, big_count = merged(*_unblock(rows, "big", np.uint64))
        context = (big >> LOW32).astype(np.uint32)
        first = np.flatnonzero(np.concatenate([[True], context[1:] != context[:-1]])) if len(big) else np.zeros(0, np.int64)
        stats = np.stack([np.add.reduceat(x.astype(np.int64), first) for x in (big_count, big_count == 1, big_count == 2, big_count >= 3)], 1) if len(big) else np.zeros((0, 4), np.int64)
        for n, x in (("uni_key", uni), ("uni_count", uni_count), ("big_key", big), ("big_count", big_count.astype(np.uint32)), ("ctx_key", context[first]), ("ctx_stats", stats)):
            _save(folder, n, x)
        out = [(s, "cont", k, c) for s, _, k, c in _blocks("cont", *np.unique((big & np.uint64(0xFFFFFFFF)).astype(np.uint32), return_counts=True), bits, 32)]
        total = np.array([uni_count.sum(), len(uni), len(big), *((big_count == k).sum() for k in (1, 2, 3, 4))], np.int64)
        return pd.DataFrame([*out, (shard, "total", total.tobytes(), b"")], columns=["shard", "kind", "keys", "counts"])

    def close(key, rows: pd.DataFrame) -> pd.DataFrame:
        folder = f"{root}/{int(key[0]):05d}"
        os.makedirs(folder, exist_ok=True)
        cont, count = merged(*_unblock(rows, "cont", np.uint32))
        _save(folder, "cont_key", cont)
        _save(folder, "cont_count", count)
        own = sum((np.frombuffer(k, np.int64) for k in rows["keys"][rows["kind"] == "total"]), np.zeros(7, np.int64))
        return pd.DataFrame([[*own.tolist(), *(int((count == k).sum()) for k in (1, 2, 3, 4)), int((count >= 3).sum())]], columns=list("abcdefghijkl"))

    totals = (
        docs.select(F.col("text").cast("string").alias("text"))
        .mapInArrow(count, BLOCK)
        .groupBy("shard")
        .applyInPandas(write, BLOCK)
        .groupBy("shard")
        .applyInPandas(close, ", ".join(f"{c} long" for c in "abcdefghijkl"))
        .agg(*(F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in "abcdefghijkl"))
        .first()
    )
    t = list(totals)
    return Model(root, bits, t[0], t[1], t[2], discounts(*t[3:7]), discounts(*t[7:11]), (t[7], t[8], t[11]))


# ---------------------------------------------------------------- scoring
class Reader:
    """Sorted-array lookups of one model."""

    def __init__(self, model: Model):
        self.model = model
        self._map = functools.lru_cache(maxsize=None)(self._open)

    def _open(self, shard: int, name: str) -> np.ndarray | None:
        path = f"{self.model.path}/{shard:05d}/{name}.npy"
        if not os.path.exists(path):
            return None
        try:
            return np.load(path, mmap_mode="r")
        except ValueError:  # an empty array can't be mapped
            return np.load(path)

    def find(self, name: str, keys: np.ndarray, value: str) -> np.ndarray:
        """Values of the keys, 0 where the model lacks them."""
        width = 8 * keys.dtype.itemsize
        order = np.argsort(keys, kind="stable")
        sorted_keys = keys[order]
        shard = (sorted_keys >> np.asarray(width - self.model.bits, keys.dtype)).astype(np.int64)
        cuts = np.flatnonzero(np.diff(shard)) + 1
        found = None
        for lo, hi in zip([0, *cuts.tolist()], [*cuts.tolist(), len(keys)]):
            if lo == hi:
                continue
            have = self._map(int(shard[lo]), name)
            if have is None or not len(have):
                continue
            values = self._map(int(shard[lo]), value)
            if found is None:
                found = np.zeros((len(keys), *values.shape[1:]), np.int64)
            at = np.minimum(np.searchsorted(have, sorted_keys[lo:hi]), len(have) - 1)
            hit = have[at] == sorted_keys[lo:hi]
            found[order[lo:hi][hit]] = values[at[hit]]
        return found if found is not None else np.zeros((len(keys), 4) if value == "ctx_stats" else len(keys), np.int64)

    def token_scores(self, tokens: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """log10 probabilities under the model and under the base, and which tokens are known."""
        m = self.model
        word, back = np.unique(tokens, return_inverse=True)
        count = self.find("uni_key", word, "uni_count")
        cont = self.find("cont_key", (word >> LOW32).astype(np.uint32), "cont_count")
        d1, d2, d3 = m.low_discounts
        if m.bigrams:
            rest = (d1 * m.low_classes[0] + d2 * m.low_classes[1] + d3 * m.low_classes[2]) / m.bigrams
            low = np.maximum(cont - np.choose(np.minimum(cont, 3), (0.0, d1, d2, d3)), 0) / m.bigrams + rest / (m.words + 1)
        else:
            low = np.full(len(word), 1 / (m.words + 1))
        prev = before(tokens, n)
        context, ctx_back = np.unique((prev >> LOW32).astype(np.uint32), return_inverse=True)
        stats = self.find("ctx_key", context, "ctx_stats").astype(np.float64)
        d = m.discounts
        seen = np.maximum(stats[:, 0], 1)
        gamma = np.where(stats[:, 0] > 0, (d[0] * stats[:, 1] + d[1] * stats[:, 2] + d[2] * stats[:, 3]) / seen, 1.0)
        pair, pair_back = np.unique(pair_keys(prev, tokens), return_inverse=True)
        c = self.find("big_key", pair, "big_count")
        top = np.maximum(c - np.choose(np.minimum(c, 3), (0.0, *d)), 0)[pair_back]
        p = top / seen[ctx_back] + gamma[ctx_back] * low[back]
        base = np.log10((count + 0.5) / (m.tokens + 0.5 * (m.words + 1)))
        return np.log10(p), base[back], (count > 0)[back]


@functools.lru_cache(maxsize=4)
def reader(model: Model) -> Reader:
    return Reader(model)


SCORED = {"n_tokens": "long", "n_known": "long", "base_score": "double", "score": "double"}


def score(docs: DataFrame, model: Model, keep_text: bool = False, prefix: str = "") -> DataFrame:
    """The columns of ``docs``, ``text`` only if asked for, and n_tokens, n_known, base_score, score of the text."""
    kept = [c for c in docs.columns if c != "text" or keep_text]
    added = [prefix + c for c in SCORED]
    types = {f.name: f.dataType.simpleString() for f in docs.schema}
    schema = ", ".join([*(f"`{c}` {types[c]}" for c in kept), *(f"`{c}` {t}" for c, t in zip(added, SCORED.values()))])

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lm = reader(model)
        for b in batches_of(it):
            tokens, n = tokens_of(b.column("text").to_pylist())
            full, base, known = lm.token_scores(tokens, n)
            at = np.cumsum(n) - n
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in kept), pa.array(n), pa.array(np.add.reduceat(known.astype(np.int64), at)), pa.array(np.add.reduceat(base, at)), pa.array(np.add.reduceat(full, at))], names=[*kept, *added])

    return docs.mapInArrow(run, schema)


def held_out() -> Column:
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 1


def op10_kneser_ney_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    model = train(docs.filter(~F.coalesce(held_out(), F.lit(False))))
    scored = score(docs, model)
    return scored.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "n_tokens", "n_known", F.lit(model.tokens).cast("long").alias("train_tokens"), "base_score", "score")
