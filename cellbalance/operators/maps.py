"""Cell maps (pos, slot) and their compact form, the cut vector."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def intervals(cuts: DataFrame) -> DataFrame:
    """(slot, first_pos, last_pos) of the slots that hold cells; P rows."""
    nxt = F.lead("b").over(Window.orderBy("k"))
    return cuts.select(F.col("k").alias("slot"), (F.col("b") + 1).alias("first_pos"), nxt.alias("last_pos")).filter("last_pos >= first_pos")


def cuts_to_map(cells: DataFrame, cuts: DataFrame, block: int = 4096) -> DataFrame:
    """Slot of every cell: the range lookup as an equi-join on the block of positions, P + blocks rows on one side."""
    spans = intervals(cuts).withColumn("block", F.explode(F.expr(f"sequence((first_pos - 1) div {block}, (last_pos - 1) div {block})")))
    keyed = cells.withColumn("block", F.expr(f"(pos - 1) div {block}"))
    joined = keyed.join(spans, "block").filter("pos between first_pos and last_pos")
    return joined.select(*cells.columns, F.col("slot").cast("int").alias("slot"))


def map_to_cuts(cell_map: DataFrame, p: int) -> DataFrame:
    """Cut vector of a contiguous map: cells of the slots before each, from one count per slot."""
    per_slot = cell_map.groupBy(F.col("slot").alias("k")).agg(F.count("*").alias("c"))
    slots = cell_map.sparkSession.range(0, p + 1, 1, 1).select(F.col("id").cast("int").alias("k")).join(F.broadcast(per_slot), "k", "left")
    before = F.sum(F.coalesce("c", F.lit(0))).over(Window.orderBy("k").rowsBetween(Window.unboundedPreceding, -1))
    return slots.select("k", F.coalesce(before, F.lit(0)).cast("long").alias("b"))


def check_map(cell_map: DataFrame, p: int, cap: int | None = None) -> DataFrame:
    """One row: contiguous, covers (positions 1..n once each), in_range, within_cap."""
    per_slot = cell_map.groupBy("slot").agg(F.count("*").alias("c"), F.min("pos").alias("lo"), F.max("pos").alias("hi"))
    ordered = per_slot.withColumn("prev_hi", F.coalesce(F.lag("hi").over(Window.orderBy("slot")), F.lit(0)))  # one row a slot
    return ordered.agg(
        F.min(F.col("hi") - F.col("lo") + 1 == F.col("c")).alias("contiguous"),
        F.min(F.col("lo") == F.col("prev_hi") + 1).alias("covers"),
        F.min((F.col("slot") >= 0) & (F.col("slot") < p)).alias("in_range"),
        (F.max("c") <= (cap if cap is not None else 2**62)).alias("within_cap"),
    )
