"""Prefix sums of weights along the line.

``scan_single_site`` sorts everything in one task, as the single-site balancer does; it is refused above a number of cells.
``scan_blocks`` cuts the line into blocks by arithmetic on the position (so a repeated task sees the same block), scans each
on its own, scans the block totals and adds them back by broadcast: two levels, or three if the totals are many.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

MAX_SINGLE_SITE_CELLS = 50_000_000
BLOCK = 65_536
#: Block totals above this number are themselves scanned by blocks.
MAX_TOTALS = 100_000

_UP_TO_HERE = (Window.unboundedPreceding, Window.currentRow)


def scan_single_site(weights: DataFrame) -> DataFrame:
    """(pos, weight, s_prev, s, total, n), all in one task."""
    if weights.limit(MAX_SINGLE_SITE_CELLS + 1).count() > MAX_SINGLE_SITE_CELLS:
        raise ValueError(f"more than {MAX_SINGLE_SITE_CELLS} cells for one site: use scan_blocks")
    line = Window.orderBy("pos")
    everything = line.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    s = F.sum("weight").over(line.rowsBetween(*_UP_TO_HERE))
    return weights.select("pos", "weight", (s - F.col("weight")).alias("s_prev"), s.alias("s"), F.sum("weight").over(everything).alias("total"), F.count("*").over(everything).alias("n"))


def block_totals(weights: DataFrame, block: int) -> DataFrame:
    """(block, block_sum, block_n): one row a block."""
    return weights.groupBy(F.expr(f"(pos - 1) div {block}").alias("block")).agg(F.sum("weight").alias("block_sum"), F.count("*").alias("block_n"))


def line_totals(weights: DataFrame, block: int = BLOCK) -> DataFrame:
    """One row: n, total (0 for an empty line), from the block totals that the scan shuffles anyway: that exchange is used again."""
    return block_totals(weights, block).agg(F.coalesce(F.sum("block_n"), F.lit(0)).alias("n"), F.coalesce(F.sum("block_sum"), F.lit(0)).alias("total"))


def block_offsets(totals: DataFrame, levels: int = 1, block: int = BLOCK) -> DataFrame:
    """(block, before, total, n): exclusive scan of the block totals, in one small task or again by blocks."""
    if levels > 1:
        scanned = scan_blocks(totals.select((F.col("block") + 1).alias("pos"), F.col("block_sum").alias("weight")), block, levels - 1)
        # n counts blocks there; the number of cells is a sum of its own
        n = totals.agg(F.sum("block_n").alias("n")).scalar()
        return scanned.select((F.col("pos") - 1).alias("block"), F.col("s_prev").alias("before"), "total", n.alias("n"))
    line = Window.orderBy("block")
    everything = line.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    before = F.sum("block_sum").over(line.rowsBetween(*_UP_TO_HERE)) - F.col("block_sum")
    return totals.select("block", before.alias("before"), F.sum("block_sum").over(everything).alias("total"), F.sum("block_n").over(everything).alias("n"))


def scan_blocks(weights: DataFrame, block: int = BLOCK, levels: int = 1) -> DataFrame:
    """(pos, weight, s_prev, s, total, n) without a task that sees all cells.

    The offsets (one row a block) are broadcast: size them with ``block`` and ``levels`` (see ``scan_settings``).
    """
    offsets = block_offsets(block_totals(weights, block), levels, block)
    blocked = weights.withColumn("block", F.expr(f"(pos - 1) div {block}"))
    local = F.sum("weight").over(Window.partitionBy("block").orderBy("pos").rowsBetween(*_UP_TO_HERE))
    scanned = blocked.select("pos", "weight", "block", local.alias("s_local"))
    s = F.col("s_local") + F.col("before")
    return scanned.join(F.broadcast(offsets), "block").select("pos", "weight", (s - F.col("weight")).alias("s_prev"), s.alias("s"), "total", "n")


def scan_settings(n_cells: int, block: int = BLOCK) -> tuple[int, int]:
    """(block, levels) so that at most MAX_TOTALS rows are broadcast and no last-level task gets more than that."""
    while n_cells // block > MAX_TOTALS:
        block *= 2
    return block, 2 if n_cells // block > BLOCK else 1


def owner_offsets(weights: DataFrame, cell_map: DataFrame) -> DataFrame:
    """(slot, load, before): load of each slot and of all slots before it; one row a slot."""
    loads = weights.join(cell_map, "pos").groupBy("slot").agg(F.sum("weight").alias("load"))
    before = F.sum("load").over(Window.orderBy("slot").rowsBetween(Window.unboundedPreceding, -1))
    return loads.select("slot", "load", F.coalesce(before, F.lit(0)).alias("before"))
