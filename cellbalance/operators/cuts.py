"""Cut vectors: b[0..P], slot k holds positions b[k]+1 .. b[k+1]. All are P+1 rows (k, b).

Targets k*T/P are never divided: comparisons are cross-multiplied in longs (P*T below 2**62; beyond, ANSI mode raises).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def _slots(spark: SparkSession, p: int, first: int = 0) -> DataFrame:
    return spark.range(first, p + 1, 1, 1).select(F.col("id").cast("int").alias("k"))


def _total(scan: DataFrame) -> DataFrame:
    """One row: n, total (0 for an empty line)."""
    return scan.agg(F.coalesce(F.max("n"), F.lit(0)).alias("n"), F.coalesce(F.max("total"), F.lit(0)).alias("total"))


def cuts_uniform(cells: DataFrame, p: int) -> DataFrame:
    """Equal numbers of cells: b[k] = k*n div P."""
    n = cells.agg(F.count("*").alias("n")).scalar()
    return _slots(cells.sparkSession, p).select("k", n.alias("n")).select("k", F.expr(f"(k * n) div {p}").cast("long").alias("b"))


def _or_uniform(cuts: DataFrame, p: int) -> DataFrame:
    """A line without any weight is cut uniformly. ``cuts``: k, b, n, total."""
    return cuts.select("k", F.when(F.col("total") > 0, F.col("b")).otherwise(F.expr(f"(k * n) div {p}")).cast("long").alias("b"))


def cuts_nearest(scan: DataFrame, p: int, whole: DataFrame | None = None) -> DataFrame:
    """Nearest cuts: after the first cell whose sum exceeds k*T/P, or before it if that is strictly nearer.

    Each cell generates the cuts whose target it reaches, so the n rows are passed once and never joined. ``whole`` is one
    row, n and total, where the caller has it (``line_totals``); without it the scan is passed again.
    """
    lo = F.expr(f"greatest(1, (s_prev * {p} + total - 1) div nullif(total, 0))")
    hi = F.expr(f"least({p - 1}, (s * {p} + total - 1) div nullif(total, 0) - 1)")
    reached = scan.select("pos", "s_prev", "s", "total", lo.alias("lo"), hi.alias("hi")).filter("total > 0 and lo <= hi")
    inner = reached.select(F.explode(F.sequence("lo", "hi")).alias("k"), "pos", "s_prev", "s", "total")
    inner = inner.select(F.col("k").cast("int").alias("k"), F.when(2 * F.col("k") * F.col("total") < p * (F.col("s_prev") + F.col("s")), F.col("pos") - 1).otherwise(F.col("pos")).alias("cut"))
    ends = _slots(scan.sparkSession, p).join(F.broadcast(inner), "k", "left")
    filled = ends.join(F.broadcast(whole if whole is not None else _total(scan)), F.lit(True), "left")
    b = F.when(F.col("k") == 0, F.lit(0)).when(F.col("k") == p, F.col("n")).otherwise(F.col("cut"))
    return _or_uniform(filled.select("k", b.alias("b"), "n", "total"), p)


def _quotient(s: str, p: int, unit: int) -> Column:
    return F.expr(f"case when total > 0 then case when {s} < {unit} then 0 else least({p - 1}, (({s} - {unit}) * {p}) div total) end end").cast("int")


def quotient_slots(scan: DataFrame, p: int, unit: int = 1) -> DataFrame:
    """(pos, slot, n, total): a cell's prefix sum less one unit, over the mean load, floored and clamped."""
    return scan.select("pos", _quotient("s", p, unit).alias("slot"), "n", "total")


def first_of_scan(scan: DataFrame, p: int, unit: int = 1) -> DataFrame:
    """(slot, first_pos) of the quotient map, straight from the scan.

    The left neighbour's prefix sum is a cell's own less its weight, so its slot is known without looking at its row: a
    filter over the scan, with no window, and nothing travels between blocks. ``first_cells`` does it for any map.
    """
    both = scan.filter("total > 0").select("pos", _quotient("s", p, unit).alias("slot"), _quotient("s_prev", p, unit).alias("before"))
    return both.filter("pos = 1 or slot <> before").select("slot", F.col("pos").alias("first_pos"))


def first_cells(mapped: DataFrame, block: int = 65_536) -> DataFrame:
    """(slot, first_pos): where the slot differs from the left neighbour's.

    Inside a block the neighbour is the row before; for its first row it is the last slot of the block before, the only
    thing that travels between blocks.
    """
    blocked = mapped.withColumn("block", F.expr(f"(pos - 1) div {block}"))
    last = blocked.groupBy("block").agg(F.max_by("slot", "pos").alias("last_slot"))
    left = last.select("block", F.lag("last_slot").over(Window.orderBy("block")).alias("left_slot"))  # one row a block
    inside = blocked.select("pos", "slot", "block", F.lag("slot").over(Window.partitionBy("block").orderBy("pos")).alias("before"))
    joined = inside.join(F.broadcast(left), "block").withColumn("before", F.coalesce("before", "left_slot"))
    return joined.filter(F.col("before").isNull() | (F.col("slot") != F.col("before"))).select(F.col("slot").cast("int").alias("slot"), F.col("pos").alias("first_pos"))


def close_gaps(first: DataFrame, p: int, whole: DataFrame) -> DataFrame:
    """Cut vector from first cells. A slot that no cell was given is empty: it begins where the next one does.

    ``whole`` is one row: n, total.
    """
    slots = _slots(first.sparkSession, p).join(F.broadcast(first.withColumnRenamed("slot", "k")), "k", "left").join(F.broadcast(whole), F.lit(True), "left")
    following = Window.orderBy("k").rowsBetween(Window.currentRow, Window.unboundedFollowing)
    begin = F.coalesce(F.first("first_pos", ignorenulls=True).over(following), F.col("n") + 1)
    b = F.when(F.col("k") == 0, F.lit(0)).otherwise(begin - 1)
    return _or_uniform(slots.select("k", b.alias("b"), "n", "total"), p)


def apply_cap(cuts: DataFrame, cap: int, strict: bool = False) -> DataFrame:
    """At most ``cap`` cells a slot, the surplus going right: b'[k] = k*cap + min over j<=k of (b[j] - j*cap).

    The last slot takes what is left and may exceed the cap; with ``strict`` slots are filled from the right, too, and a
    line that can't fit raises when the plan runs.
    """
    p = F.max("k").over(Window.orderBy("k").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    n = F.max("b").over(Window.orderBy("k").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    upto = Window.orderBy("k").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    moved = F.col("k") * F.lit(cap).cast("long") + F.min(F.col("b") - F.col("k") * F.lit(cap).cast("long")).over(upto)
    out = cuts.select("k", "b", moved.alias("moved"), p.alias("p"), n.alias("n"))
    b = F.when(F.col("k") == F.col("p"), F.col("n")).otherwise(F.col("moved"))
    if strict:
        fits = F.col("n") <= F.col("p") * F.lit(cap).cast("long")
        b = F.when(fits, F.greatest(b, F.col("n") - (F.col("p") - F.col("k")) * F.lit(cap).cast("long"))).otherwise(F.raise_error(F.lit(f"more cells than slots times the cap {cap}")).cast("long"))
    return out.select("k", b.cast("long").alias("b"))
