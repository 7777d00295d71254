"""Packing token ids into training windows by the online sum-of-squares rule.

A document is cut into whole windows and one remainder. Whole windows are sequences of their own; the remainder of
``s`` ids goes into the fill level ``h`` (0 = a new window) for which the sum of squares of the numbers of open windows
per level, kept in a level array, grows least. Each Spark task packs its own documents in one pass and holds only the open
windows; at its end the open ones are emptied, emptiest first, into the free space of the fullest, cutting freely, so
that one window of a task at most stays unfilled. Nothing is shuffled and a lost task packs the same windows again.

Null and empty texts have one id, the end id. Texts of any length are packed whole. Repeated rows are packed once each; an
empty table gives no rows. Extra columns are ignored.
"""

from __future__ import annotations

import base64
import functools
import json
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents

SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
_FIELDS = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
#: Chunks that a worker remembers before it starts anew.
CACHE_ENTRIES = 300_000


class FastIds:
    """Ids of the byte-level vocabulary as little-endian uint32 bytes, the same as those of ``tokenizers`` (tests compare both).

    Texts are split at the added tokens of the vocabulary's JSON file, which have ids of their own. What lies between is cut before each single space; such a cut is always a cut of the vocabulary's own splitting rule, unless a
    chunk is white space only, in which case the text is encoded as a whole. Chunks are remembered.
    """

    def __init__(self, ranks_path: str):
        import public_tokenizers
        import tiktoken

        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(ranks_path, "rb"))}
        self._encode = tiktoken.Encoding("bytes", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
        added = json.load(open(ranks_path.removesuffix(".tiktoken") + ".json", encoding="utf-8")).get("added_tokens", [])
        self._added = {t["content"]: np.asarray([t["id"]], dtype="<u4").tobytes() for t in added}
        # of tokens that start at the same place the longest counts
        self._split = re.compile("(" + "|".join(map(re.escape, sorted(self._added, key=len, reverse=True))) + ")").split if added else None
        self._known: dict[str, bytes | None] = {}

    def _parts(self, text: str, plain) -> bytes:
        if not any(token in text for token in self._added):
            return plain(text)
        parts = self._split(text)  # texts and tokens take turns
        return b"".join(self._added[p] if i % 2 else plain(p) for i, p in enumerate(parts) if p)

    def _whole(self, text: str) -> bytes:
        return self._parts(text, lambda t: np.asarray(self._encode(t), dtype="<u4").tobytes())

    def __call__(self, text: str) -> bytes:
        return self._parts(text, self._plain)

    def _plain(self, text: str) -> bytes:
        if len(self._known) > CACHE_ENTRIES:
            self._known.clear()
        known = self._known
        first, *rest = text.split(" ")
        found = [known.get(c) for c in rest]
        if None in found:
            for i, ids in enumerate(found):
                if ids is None:
                    chunk = rest[i]
                    if not chunk or chunk.isspace():
                        return self._whole(text)
                    found[i] = known[chunk] = self._whole(" " + chunk)
        if first:
            if first.isspace():
                return self._whole(text)
            found.insert(0, self._whole(first))
        elif rest and rest[0][:1].isspace():
            return self._whole(text)
        return b"".join(found)


@functools.lru_cache(maxsize=2)
def _ids(ranks_path: str) -> FastIds:
    return FastIds(ranks_path)


class LevelPacker:
    """Open windows by fill level. A window is a list of (document number, start, length)."""

    def __init__(self, size: int):
        self.size = size
        self.count = np.zeros(size + 1, np.int64)  # open windows at each level; level 0 and a full window count as none
        self.open: list[list[list]] = [[] for _ in range(size + 1)]

    def place(self, piece: tuple, length: int) -> list | None:
        """Put the piece in; returns the window if that fills it."""
        size, count = self.size, self.count
        # Change of the sum of squares for each level 0..size-length; only levels that have a window, or level 0.
        to = count[length : size + 1]
        grow = 2 * to + 1
        grow[size - length] = 0
        leave = count[: size - length + 1]
        delta = grow - 2 * leave + 1
        delta[0] = grow[0]
        delta[1:][leave[1:] == 0] = np.iinfo(np.int64).max
        # Ties go to the fuller window.
        level = size - length - int(np.argmin(delta[::-1]))
        window = self.open[level].pop() if level else []
        if level:
            count[level] -= 1
        window.append(piece)
        if level + length == size:
            return window
        self.open[level + length].append(window)
        count[level + length] += 1
        return None

    def rest(self) -> list[list]:
        """All open windows, fullest first."""
        return [w for level in range(self.size, 0, -1) for w in self.open[level]]


def _drain(windows: list[list], size: int) -> Iterator[list]:
    """Fill the fullest windows with what the emptiest hold, cutting pieces where needed."""
    lo, hi = 0, len(windows) - 1
    fill = [sum(p[2] for p in w) for w in windows]
    while lo <= hi:
        while lo < hi and fill[lo] < size:
            doc, start, length = windows[hi].pop()
            take = min(length, size - fill[lo])
            windows[lo].append((doc, start + length - take, take))
            fill[lo] += take
            fill[hi] -= take
            if take < length:
                windows[hi].append((doc, start, length - take))
            if not windows[hi]:
                hi -= 1
        yield windows[lo]
        lo += 1


def pack_texts(rows: Iterator[tuple], ids_of, size: int, first_sequence: int) -> Iterator[tuple]:
    """(doc_id, text) rows to piece rows; ``ids_of`` gives a text's ids as bytes."""
    packer, sequence = LevelPacker(size), first_sequence
    held: dict[int, list] = {}  # of documents with a piece in an open window: doc_id, ids, tokens, open pieces

    def emit(window: list) -> Iterator[tuple]:
        nonlocal sequence
        offset = 0
        for doc, start, length in window:
            doc_id, ids, base, tokens = held[doc][:4]
            yield doc_id, start, length, zlib.crc32(ids[4 * (start - base) : 4 * (start - base + length)]), tokens, sequence, offset
            offset += length
        sequence += 1

    for number, (doc_id, text) in enumerate(rows):
        ids = (ids_of(text) if text else b"") + b"\0\0\0\0"
        tokens = len(ids) // 4
        whole = tokens // size * size
        for start in range(0, whole, size):
            yield doc_id, start, size, zlib.crc32(ids[4 * start : 4 * (start + size)]), tokens, sequence, 0
            sequence += 1
        if whole < tokens:
            held[number] = [doc_id, ids[4 * whole :], whole, tokens]
            full = packer.place((number, whole, tokens - whole), tokens - whole)
            if full:
                yield from emit(full)
                for doc, _, _ in full:
                    del held[doc]
    for window in _drain(packer.rest(), size):
        yield from emit(window)


def pack(docs: DataFrame, ranks_path: str | None = None, size: int = 1024) -> DataFrame:
    """Pieces of all documents in sequences of at most ``size`` ids. ``docs`` has doc_id and text."""
    if ranks_path is None:
        import public_tokenizers

        ranks_path = public_tokenizers.path("byte_bpe_50k.tiktoken")

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        task = TaskContext.get()
        rows = ((i, t) for b in it for i, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist()))
        out: list[tuple] = []

        def batch() -> pa.RecordBatch:
            columns = list(zip(*out))
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=_FIELDS)

        for piece in pack_texts(rows, _ids(ranks_path), size, task.partitionId() << 40):
            out.append(piece)
            if len(out) >= 20_000:
                yield batch()
                out.clear()
        if out:
            yield batch()

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, SCHEMA)


def op9_sum_of_squares_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(documents(spark, sf_dir))
