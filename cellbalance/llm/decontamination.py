"""Benchmark decontamination with suffix arrays of the training text.

Each slice of training documents is a shard. Its words become ids of the benchmark's vocabulary (0: any other word), and
the suffixes that begin with the first two words of a benchmark window are put into a suffix array, sorted by their first
``WINDOW`` words; the other suffixes cannot match and are left out. Every benchmark window is looked up in it by binary
search, which gives the places of its verbatim matches; windows that follow each other in the text as they do in one item
give the longest verbatim match with an item and its places in both. Nothing is shuffled.

The benchmark reaches workers in blocks of at most ``BLOCK_WORDS`` words (or one item), one broadcast each, and a worker holds
one block at a time, so its memory is bounded for any size. Null and empty texts have no words and aren't contaminated; items
without words match nothing. Words of an item with a null id are hit like others, but it isn't counted or listed. Repeated items
count once per item_id, repeated documents are judged alike, texts of any length are searched whole, an empty table gives no rows,
of matches of one length the first counts, and extra columns stay in ``decontaminate``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import batches_of, documents, sha256_hex

WINDOW = 13
BLOCK_WORDS = 2_000_000
#: Letters, digits and all bytes from 0x80 are parts of words; A-Z are lowered; anything else is a space.
_TABLE = bytes(b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else b + 32 if 65 <= b <= 90 else 32 for b in range(256))


def item_words(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").translate(_TABLE).split() if text else []


class TestWindows:
    """Windows of a block of benchmark items, as ids of its own vocabulary."""

    __test__ = False

    def __init__(self, items: list[tuple], window: int = WINDOW):
        self.window, self.word = window, {}
        places: dict[tuple, list] = {}
        for number, (_, text) in enumerate(items):
            ids = [self.word.setdefault(w, len(self.word) + 1) for w in item_words(text)]
            for i in range(max(1, len(ids) - window + 1) if ids else 0):
                places.setdefault(tuple(ids[i : i + window]), []).append((number, i))
        keys = sorted(places)
        self.names = [item_id for item_id, _ in items]
        self.owners = [sorted({self.names[n] for n, _ in places[k]} - {None}) for k in keys]
        # where each window stands in the items: of window k, rows first[k] .. first[k + 1]
        self.first = np.cumsum([0, *(len(places[k]) for k in keys)])
        self.place = np.array([p for k in keys for p in places[k]], np.int64).reshape(-1, 2)
        self.length = np.array([len(k) for k in keys], np.int64)
        padded = np.zeros((len(keys), window), ">u4")
        ceiling = np.full((len(keys), window), 0xFFFFFFFF, ">u4")
        for row, k in enumerate(keys):
            padded[row, : len(k)] = ceiling[row, : len(k)] = k
        self.low, self.high = (np.ascontiguousarray(x).view(f"S{4 * window}").ravel() for x in (padded, ceiling))
        self.starts = np.unique([(k[0] << 32) | k[1] for k in keys if len(k) > 1]).astype(np.int64)
        self.single = np.unique([k[0] for k in keys if len(k) == 1]).astype(np.int64)

    def matches(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(position, window number) of every verbatim match in ``ids``; documents are set apart by zeros."""
        none = np.zeros(0, np.int64), np.zeros(0, np.int64)
        if not len(self.low) or not len(ids):
            return none
        follow = np.concatenate([ids[1:], [0]])
        start = np.isin((ids << 32) | follow, self.starts)
        if len(self.single):
            start |= np.isin(ids, self.single)
        at = np.flatnonzero(start)
        if not len(at):
            return none
        padded = np.concatenate([ids, np.zeros(self.window, np.int64)])
        suffix = np.ascontiguousarray(padded[at[:, None] + np.arange(self.window)].astype(">u4")).view(f"S{4 * self.window}").ravel()
        array = np.argsort(suffix, kind="stable")
        suffix, at = suffix[array], at[array]
        lo, hi = np.searchsorted(suffix, self.low, "left"), np.searchsorted(suffix, self.high, "right")
        n = hi - lo
        number = np.repeat(np.arange(len(n)), n)
        place = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(lo, n)
        return at[place], number


def longest_matches(block: TestWindows, at: np.ndarray, number: np.ndarray, doc: np.ndarray) -> dict[int, tuple]:
    """Of each document the longest verbatim match with one item: (words, place in the text, item number, place in the item)."""
    if not len(at):
        return {}
    times = block.first[number + 1] - block.first[number]
    row = np.repeat(block.first[number], times) + np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times)
    item, start = block.place[row].T
    at, doc, length = (np.repeat(x, times) for x in (at, doc, block.length[number]))
    order = np.lexsort((at, at - start, item, doc))
    item, start, at, doc, length = (x[order] for x in (item, start, at, doc, length))
    # windows of one item that follow each other in the text as they do in the item are one match
    new = np.ones(len(at), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (item[1:] != item[:-1]) | (at[1:] - start[1:] != at[:-1] - start[:-1]) | (at[1:] != at[:-1] + 1)
    head = np.flatnonzero(new)
    words = length[head] + np.diff(np.append(head, len(at))) - 1
    best = np.lexsort((start[head], item[head], at[head], -words, doc[head]))
    best = best[np.unique(doc[head][best], return_index=True)[1]]
    return {int(doc[head[i]]): (int(words[i]), int(at[head[i]]), int(item[head[i]]), int(start[head[i]])) for i in best}


def _one_by_one(blocks: list) -> Iterator[TestWindows]:
    """The blocks' contents. Of several, a worker holds one at a time."""
    for b in blocks:
        yield b.value
        if len(blocks) > 1:
            vars(b).pop("_value", None)  # read again from the worker's disk for the next slice


def _judged(texts: list, blocks) -> list[tuple]:
    """(n_words, n_hit, item ids, longest match) of each text; the match is (words, place in the text, item_id, place in the item)."""
    words = [item_words(t) for t in texts]
    n = np.array([len(w) for w in words], np.int64)
    first = np.cumsum(n + 1) - (n + 1)  # one zero behind each document
    total = int((n + 1).sum())
    edge = np.zeros(total + 1, np.int64)
    items: list[set] = [set() for _ in texts]
    longest: list[tuple] = [(0, None, None, None)] * len(texts)
    for block in blocks:
        ids, get = np.zeros(total, np.int64), block.word.get
        for w, f in zip(words, first.tolist()):
            ids[f : f + len(w)] = [get(x, 0) for x in w]
        at, number = block.matches(ids)
        np.add.at(edge, at, 1)
        np.add.at(edge, at + block.length[number], -1)
        doc = np.searchsorted(first, at, "right") - 1
        for d, k in set(zip(doc.tolist(), number.tolist())):
            items[d].update(block.owners[k])
        for d, (size, place, item, start) in longest_matches(block, at, number, doc).items():
            if size > longest[d][0]:
                longest[d] = (size, place - int(first[d]), block.names[item], start)
    hit = np.cumsum(edge[:-1]) > 0
    total_hits = np.concatenate([[0], np.cumsum(hit)])
    hits = total_hits[first + n] - total_hits[first]
    return list(zip(n.tolist(), hits.tolist(), items, longest))


def is_contaminated(n_words: int, n_hit: int) -> bool:
    return n_hit > 0 and 20 * n_hit >= n_words


def broadcast_blocks(benchmark: DataFrame, window: int = WINDOW) -> list:
    """One broadcast for each block of items; the driver holds one block at a time."""
    context = benchmark.sparkSession.sparkContext
    out, block, words = [], [], 0
    for item_id, text in benchmark.select(F.col("item_id").cast("string"), F.col("text").cast("string")).toLocalIterator():
        block.append((item_id, text))
        words += len(text or "") // 5 + 1
        if words > BLOCK_WORDS:
            out.append(context.broadcast(TestWindows(block, window)))
            block, words = [], 0
    return [*out, context.broadcast(TestWindows(block, window))] if block or not out else out


def _slice_bytes(blocks: list) -> int:
    """Larger slices where each of them loads several blocks."""
    return (2 if len(blocks) == 1 else 16) << 20


SCHEMA = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, longest_match long, match_start long, match_item string, item_start long"


def contamination(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """What each document shares with the benchmark."""
    blocks = broadcast_blocks(benchmark)

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [c.split()[0] for c in SCHEMA.split(", ")]
        types = [pa.int64()] * 3 + [pa.string(), pa.bool_(), pa.int64(), pa.int64(), pa.string(), pa.int64()]
        for b in batches_of(it, _slice_bytes(blocks)):
            found = _judged(b.column("text").to_pylist(), _one_by_one(blocks))
            columns = zip(*((w, h, len(i), sha256_hex(",".join(sorted(i)).encode()), is_contaminated(w, h), *match) for w, h, i, match in found))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), *(pa.array(c, t) for c, t in zip(columns, types))], names=names)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, SCHEMA)


def decontaminate(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The documents that aren't contaminated, with all their columns."""
    blocks = broadcast_blocks(benchmark)

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches_of(it, _slice_bytes(blocks)):
            yield b.filter(pa.array([not is_contaminated(w, h) for w, h, _, _ in _judged(b.column("text").to_pylist(), _one_by_one(blocks))]))

    return docs.mapInArrow(run, docs.schema)


def op5_suffix_array_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
