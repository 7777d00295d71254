"""Sharding by Karmarkar-Karp differencing: near-equal bytes for indivisible groups of equal texts.

1. Documents are summed by text hash (map-side first), so a group of any number of copies is one row; a hash collision
   only keeps two texts together.
2. Items for differencing are bounded for any input: a group above 1/HEAVY of all bytes (there are fewer than HEAVY) is an
   item of its own, the light groups are folded by hash into at most BUNDLES items.
3. One task differences the items: the two partial partitions of largest spread are combined again and again, the heaviest
   part of one with the lightest of the other. The items' shards, of a proven size, are broadcast to the documents.
4. Slots are gapless by counting (shard, cell) pairs and adding offsets, never by one window over a shard.

Null texts count as empty, texts of any length by all their bytes. Equal sizes are taken in the order of hash and bundle number.
Repeated rows are rows of their own. An empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import documents, table

BUNDLES = 1 << 15
HEAVY = 1 << 12
SLOT_CELLS = 256


def difference(sizes: list[int], shards: int) -> list[int]:
    """The shard of each item."""
    heap = [(-size, n, [0] * (shards - 1) + [size], [[]] * (shards - 1) + [[n]]) for n, size in enumerate(sizes)]
    heapq.heapify(heap)
    number = len(heap)
    while len(heap) > 1:
        _, _, a, in_a = heapq.heappop(heap)
        _, _, b, in_b = heapq.heappop(heap)
        order = sorted(range(shards), key=lambda i: (a[i] + b[-1 - i], i))
        joined, members = [a[i] + b[-1 - i] for i in order], []
        for i in order:
            x, y = in_a[i], in_b[-1 - i]
            if x and y:
                x, y = (x, y) if len(x) >= len(y) else (y, x)
                x.extend(y)  # into the longer list, so an item moves O(log n) times
            members.append(x or y)
        heapq.heappush(heap, (joined[0] - joined[-1], number, joined, members))
        number += 1
    out = [0] * len(sizes)
    for shard, members in enumerate(heap[0][3] if heap else []):
        for n in members:
            out[n] = shard
    return out


def shard_documents(docs: DataFrame, shards: int = 16, bundles: int | None = BUNDLES) -> DataFrame:
    """Every document's shard, by near-equal bytes, and its gapless slot there. With ``bundles=None`` each group is an item of its own: the
    exact method, for tables whose groups fit into one task."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.xxhash64(text).alias("g"))
    groups = table(rows.groupBy("g").agg(F.sum("size").alias("size")), "kk-groups")
    total = groups.agg(F.coalesce(F.sum("size"), F.lit(0))).first()[0]
    bundle = F.col("g") if bundles is None else F.pmod(F.shiftright("g", 3), F.lit(bundles)).cast("long")
    heavy = F.col("size") * HEAVY > F.lit(total)
    # item: a heavy group by its hash, a bundle by its number
    items = groups.groupBy(heavy.alias("heavy"), F.when(heavy, F.col("g")).otherwise(bundle).alias("item")).agg(F.sum("size").alias("size"))

    def place(it: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        frames = [f for f in it if len(f)]
        if frames:
            all_items = pd.concat(frames).sort_values(["size", "heavy", "item"], ascending=False)
            yield all_items.assign(shard=difference(all_items["size"].tolist(), shards))[["heavy", "item", "shard"]]

    # fewer than HEAVY + BUNDLES rows meet in this task, whatever the input
    placed = table(items.coalesce(1).mapInPandas(place, "heavy boolean, item long, shard int"), "kk-items")
    hot = placed.filter("heavy").select(F.col("item").alias("g"), F.col("shard").alias("hot_shard"))
    cold = placed.filter("not heavy").select(F.col("item").alias("bundle"), F.col("shard").alias("cold_shard"))
    sharded = (
        rows.withColumn("bundle", bundle)
        .join(F.broadcast(hot), "g", "left")
        .join(cold if bundles is None else F.broadcast(cold), "bundle", "left")
        .select("doc_id", "size", "text_crc32", F.coalesce("hot_shard", "cold_shard").alias("shard"), F.pmod(F.xxhash64("doc_id"), F.lit(SLOT_CELLS)).cast("int").alias("cell"))
    )
    sharded = table(sharded, "kk-sharded")
    counts = sharded.groupBy("shard", "cell").agg(F.count("*").alias("n"))  # at most shards * SLOT_CELLS rows
    before = counts.select("shard", "cell", (F.sum("n").over(Window.partitionBy("shard").orderBy("cell")) - F.col("n")).alias("before"))
    inside = F.row_number().over(Window.partitionBy("shard", "cell").orderBy("doc_id", "text_crc32", "size"))
    return (
        sharded.withColumn("inside", inside)
        .join(F.broadcast(before), ["shard", "cell"])
        .select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), F.col("shard").cast("int").alias("shard"), (F.col("before") + F.col("inside") - 1).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
    )


def op2_karmarkar_karp_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_documents(documents(spark, sf_dir))
