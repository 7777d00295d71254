"""Helpers shared by the training-data operators: words, hashes, shared tables and connected components."""

from __future__ import annotations

import ctypes
import hashlib
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space that separates words (fixed values).
SPACES = " \t\n\x0b\f\r"
SPACE_CLASS = r"[\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

_MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)
_MIX = np.uint64(0xBF58476D1CE4E5B9)


# ---------------------------------------------------------------- tables that every executor can reach
def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder (``spark.checkpoint.dir``); a temporary one only for local masters where it is unset."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if where:
        return where.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise RuntimeError("spark.checkpoint.dir is unset: name a folder that all executors share")
    where = "file://" + tempfile.mkdtemp(prefix="shared-")
    spark.conf.set("spark.checkpoint.dir", where)
    return where


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def table(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` into the shared folder and read it back: lineage is cut, and a lost executor loses nothing."""
    spark = df.sparkSession
    path = new_path(spark, name)
    held = spark.conf.get(_CLEANUP, None)
    spark.conf.set(_CLEANUP, "true")  # this write's shuffle files aren't needed once the table stands
    try:
        df.write.option("compression", "zstd").parquet(path)
    finally:
        spark.conf.unset(_CLEANUP) if held is None else spark.conf.set(_CLEANUP, held)
    out = spark.read.schema(df.schema).parquet(path)
    out.shared_path = path
    return out


def discard(*tables: DataFrame) -> None:
    """Delete written tables that nothing reads any more. What is returned to the caller must not be built on them."""
    for t in tables:
        context = t.sparkSession.sparkContext
        where = context._jvm.org.apache.hadoop.fs.Path(t.shared_path)
        where.getFileSystem(context._jsc.hadoopConfiguration()).delete(where, True)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


#: Most labelled documents that a classifier is fitted on; their ids are broadcast.
MAX_TRUSTED = 50_000


def bounded_sample(labelled: DataFrame, most: int = MAX_TRUSTED) -> DataFrame:
    """At most ``most`` distinct doc_ids, those of the smallest hashes: the same ones however the table is laid out."""
    ids = labelled.select(F.col("doc_id").cast("long").alias("doc_id")).filter("doc_id is not null").distinct()
    return ids.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)


def empty(spark: SparkSession, schema: str) -> DataFrame:
    return spark.createDataFrame([], schema)


# ---------------------------------------------------------------- columns
def word_array(text: Column) -> Column:
    """Words of a text, ``[^\\x20\\x09-\\x0D]+``; null has none."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), SPACE_CLASS), lambda w: w != "")


def let(value: Column, body) -> Column:
    """Evaluate ``value`` once and use it in ``body``: a lambda variable is never computed again."""
    return F.transform(F.array(value), body)[0]


# ---------------------------------------------------------------- words in Python workers
def words_of(text: str | None, lower: bool = False) -> list[bytes]:
    """The same words as UTF-8 bytes. ``bytes.split`` knows just the six ASCII spaces, ``bytes.lower`` just A-Z."""
    if not text:
        return []
    raw = text.encode("utf-8", "surrogatepass")
    return (raw.lower() if lower else raw).split()


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), dtype=np.uint64, count=len(words))


def mix(h: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        h = h ^ (h >> np.uint64(29))
        h = h * _MIX
        return h ^ (h >> np.uint64(32))


def window_hashes(h: np.ndarray, k: int) -> np.ndarray:
    """Hash of every run of ``k`` word hashes, by doubling: O(log k) passes."""
    m = len(h) - k + 1
    if m <= 0:
        return np.zeros(0, np.uint64)
    with np.errstate(over="ignore"):
        level, size, done, out = mix(h * _MULTIPLIER), 1, 0, None
        while True:
            if k & size:
                part = level[done : done + m]
                out = part if out is None else mix(out * _MULTIPLIER + part)
                done += size
            if done == k:
                return out
            level = mix(level[: len(level) - size] * _MULTIPLIER + level[size:])
            size *= 2


def batches_of(it: Iterator[pa.RecordBatch], limit: int = 2 << 20) -> Iterator[pa.RecordBatch]:
    """Slices with about ``limit`` bytes of text (column ``text``), one row at least: memory stays bounded for any batch."""
    for b in it:
        if not b.num_rows:
            continue
        sizes = np.asarray(pc.binary_length(b.column("text")).fill_null(0)).astype(np.int64) + 64
        group = np.cumsum(sizes) // limit
        cuts = np.flatnonzero(np.diff(group)) + 1
        for lo, hi in zip([0, *cuts.tolist()], [*cuts.tolist(), b.num_rows]):
            yield b.slice(lo, hi - lo)
    trim_memory()


def trim_memory() -> None:
    """Give freed memory back, so that a reused worker doesn't hold what an earlier task needed."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def sha256_hex(data: bytes) -> str:
    return hashlib.sha256(data).hexdigest()


# ---------------------------------------------------------------- connected components
def components(edges: DataFrame) -> DataFrame:
    """(id, component) for every id in ``edges(a, b)``; component = smallest id reachable.

    Rounds of large stars and small stars, on DataFrames only: each node hands its larger neighbours, then the others, to
    the smallest of its neighbourhood, until every group is a star. Rounds grow with the logarithm of a group's size. Edges
    stay distributed and each round's table is written to the shared folder. Ids without edges aren't returned.
    """
    pairs = edges.select(F.greatest(F.col("a").cast("long"), F.col("b").cast("long")).alias("a"), F.least(F.col("a").cast("long"), F.col("b").cast("long")).alias("b"))
    star = table(pairs.filter("a <> b").distinct(), "cc-0")  # a > b
    mark = lambda df: tuple(df.agg(F.count("*"), F.coalesce(F.bit_xor(F.xxhash64("a", "b")), F.lit(0)), F.coalesce(F.sum(F.xxhash64("b", "a").bitwiseAND(0xFFFFFFFF)), F.lit(0))).first())
    seen, r = mark(star), 0
    while True:
        r += 1
        both = star.unionByName(star.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = table(both.filter("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").distinct(), f"cc-{r}-large")
        # every edge now hangs from its larger end
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        moved = large.join(least, "a").select(F.explode(F.array(F.struct("a", F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("e")).select("e.a", "e.b")
        star = table(moved.filter("a <> b").distinct(), f"cc-{r}")
        now = mark(star)
        if now == seen:
            break
        seen = now
    roots = star.select(F.col("b").alias("id")).distinct().withColumn("component", F.col("id"))
    return star.select(F.col("a").alias("id"), F.col("b").alias("component")).unionByName(roots)


# ---------------------------------------------------------------- joins with hot keys
#: A key counts as hot above this share of all rows, so there are at most 1 / HOT of them.
HOT = 1 / 4096


def join_hot(left: DataFrame, right: DataFrame, key: str, n: str) -> DataFrame:
    """``left`` inner-joined to ``right``, which has one row a key and the number ``n`` of left rows with it.

    Hot keys, fewer than 1 / HOT, are broadcast; rows of other keys are shuffled. ``n`` isn't returned.
    """
    total = right.agg(F.coalesce(F.sum(n), F.lit(0))).first()[0]
    is_hot = F.col(n) > F.lit(max(1000, int(total * HOT)))
    hot, cold = right.filter(is_hot).drop(n), right.filter(~is_hot).drop(n)
    return left.join(F.broadcast(hot), key).unionByName(left.join(F.broadcast(hot.select(key)), key, "left_anti").join(cold, key))
