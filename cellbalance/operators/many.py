"""The balancers on many lines at once: every line has its own key, number of slots and weights, and all share one plan.

``cells`` is (line, p, pos, weight): ``line`` any struct or value that names the line, p its slots. Windows are over blocks of a
line, or over the at most p + 1 rows of its cut vector.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .balance import repair_in_one_place
from .scan import BLOCK

_UP_TO_HERE = (Window.unboundedPreceding, Window.currentRow)


def scan_many(cells: DataFrame, block: int = BLOCK) -> DataFrame:
    """(line, p, pos, weight, s_prev, s, total, n)."""
    blocked = cells.withColumn("block", F.expr(f"(pos - 1) div {block}"))
    totals = blocked.groupBy("line", "block").agg(F.sum("weight").alias("block_sum"), F.count("*").alias("block_n"))
    upto = Window.partitionBy("line").orderBy("block").rowsBetween(*_UP_TO_HERE)
    whole = Window.partitionBy("line")
    offsets = totals.select("line", "block", (F.sum("block_sum").over(upto) - F.col("block_sum")).alias("before"), F.sum("block_sum").over(whole).alias("total"), F.sum("block_n").over(whole).alias("n"))
    local = F.sum("weight").over(Window.partitionBy("line", "block").orderBy("pos").rowsBetween(*_UP_TO_HERE)) + F.col("before")
    return blocked.join(offsets, ["line", "block"]).withColumn("s", local).select("line", "p", "pos", "weight", (F.col("s") - F.col("weight")).alias("s_prev"), "s", "total", "n")


def lines_of(scan: DataFrame) -> DataFrame:
    """(line, p, n, total): one row a line."""
    return scan.groupBy("line").agg(F.first("p").alias("p"), F.first("n").alias("n"), F.first("total").alias("total"))


def _slots(lines: DataFrame) -> DataFrame:
    return lines.select("*", F.explode(F.sequence(F.lit(0), F.col("p"))).alias("k"))


def _finished(slots: DataFrame, cap: int | None) -> DataFrame:
    """(line, p, k, b) with uniform cuts where nothing weighs anything, the surplus over the cap going right."""
    cuts = slots.withColumn("b", F.when(F.col("total") > 0, F.col("b")).otherwise(F.expr("(k * n) div p")).cast("long"))
    if cap is not None:
        room = F.col("k") * F.lit(cap).cast("long")
        moved = room + F.min(F.col("b") - room).over(Window.partitionBy("line").orderBy("k").rowsBetween(*_UP_TO_HERE))
        cuts = cuts.withColumn("b", F.when(F.col("k") == F.col("p"), F.col("n")).otherwise(moved))
    return cuts.select("line", "p", "k", F.col("b").cast("long").alias("b"))


def uniform_many(lines: DataFrame) -> DataFrame:
    """Equal numbers of cells; ``lines`` is (line, p, n)."""
    return _slots(lines).select("line", "p", "k", F.expr("(k * n) div p").cast("long").alias("b"))


def single_site_many(scan: DataFrame, cap: int | None = None) -> DataFrame:
    """Nearest cuts of every line."""
    lo, hi = F.expr("greatest(1, (s_prev * p + total - 1) div nullif(total, 0))"), F.expr("least(p - 1, (s * p + total - 1) div nullif(total, 0) - 1)")
    reached = scan.withColumns({"lo": lo, "hi": hi}).filter("total > 0 and lo <= hi").withColumn("k", F.explode(F.sequence("lo", "hi")))
    cut = F.when(2 * F.col("k") * F.col("total") < F.col("p") * (F.col("s_prev") + F.col("s")), F.col("pos") - 1).otherwise(F.col("pos"))
    inner = reached.select("line", F.col("k").cast("int").alias("k"), cut.alias("cut"))
    b = F.when(F.col("k") == 0, F.lit(0)).when(F.col("k") == F.col("p"), F.col("n")).otherwise(F.col("cut"))
    return _finished(_slots(lines_of(scan)).join(inner, ["line", "k"], "left").withColumn("b", b), cap)


def _first_cells(scan: DataFrame) -> DataFrame:
    """(line, slot, first_pos) of the quotient maps."""
    quotient = lambda s: F.expr(f"case when {s} < 1 then 0 else least(p - 1, (({s} - 1) * p) div total) end").cast("int")
    both = scan.filter("total > 0").select("line", "pos", quotient("s").alias("slot"), quotient("s_prev").alias("before"))
    return both.filter("pos = 1 or slot <> before").select("line", "slot", F.col("pos").alias("first_pos"))


def peer_many(scan: DataFrame, cap: int | None = None) -> DataFrame:
    """Quotient maps, their gaps closed by a window over the slots of each line."""
    slots = _slots(lines_of(scan)).join(_first_cells(scan).withColumnRenamed("slot", "k"), ["line", "k"], "left")
    following = Window.partitionBy("line").orderBy("k").rowsBetween(Window.currentRow, Window.unboundedFollowing)
    begin = F.coalesce(F.first("first_pos", ignorenulls=True).over(following), F.col("n") + 1)
    return _finished(slots.withColumn("b", F.when(F.col("k") == 0, F.lit(0)).otherwise(begin - 1)), cap)


def hybrid_many(scan: DataFrame, cap: int | None = None) -> DataFrame:
    """The same cuts; the at most p pairs of a line are repaired in one place each, not on the driver."""
    pairs = lines_of(scan).join(_first_cells(scan).groupBy("line").agg(F.collect_list("slot").alias("slots"), F.collect_list("first_pos").alias("firsts")), "line", "left")

    @F.pandas_udf("array<bigint>")
    def repaired(p: pd.Series, n: pd.Series, total: pd.Series, slots: pd.Series, firsts: pd.Series) -> pd.Series:
        out = []
        for p_, n_, t, s, f in zip(p, n, total, slots, firsts):
            # without any weight the line is cut uniformly
            found = list(zip(map(int, s), map(int, f))) if t > 0 else [(k, k * int(n_) // int(p_) + 1) for k in range(int(p_))]
            out.append(repair_in_one_place(found, int(p_), int(n_), cap, False))
        return pd.Series(out)

    return pairs.select("line", "p", F.posexplode(repaired("p", "n", "total", "slots", "firsts")).alias("k", "b"))


METHODS = {"single_site": single_site_many, "peer": peer_many, "hybrid": hybrid_many}


def loads_many(cells: DataFrame, cuts: DataFrame, by: tuple[str, ...] = (), block: int = 64) -> DataFrame:
    """(line, *by, slot, cells, load) of the slots that hold cells; columns ``by`` tell several cut vectors of a line apart."""
    spans = cuts.select("line", *by, F.col("k").alias("slot"), (F.col("b") + 1).alias("lo"), F.lead("b").over(Window.partitionBy("line", *by).orderBy("k")).alias("hi")).filter("hi >= lo")
    keyed = spans.withColumn("block", F.explode(F.expr(f"sequence((lo - 1) div {block}, (hi - 1) div {block})")))
    placed = cells.withColumn("block", F.expr(f"(pos - 1) div {block}")).join(keyed, ["line", "block"]).filter("pos between lo and hi")
    return placed.groupBy("line", *by, "slot").agg(F.count("*").alias("cells"), F.sum("weight").alias("load"))


def stays_many(old: DataFrame, new: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(line, *by, stays): cells that keep their slot, from two cut vectors a line; no cell is read."""
    span = lambda cuts, c: cuts.select("line", *by, "k", F.col("b").alias(f"{c}_lo"), F.lead("b").over(Window.partitionBy("line", *by).orderBy("k")).alias(f"{c}_hi"))
    shared = F.greatest(F.lit(0), F.least("o_hi", "n_hi") - F.greatest("o_lo", "n_lo"))
    return span(old, "o").join(span(new, "n"), ["line", *by, "k"]).filter("o_hi is not null").groupBy("line", *by).agg(F.sum(shared).cast("long").alias("stays"))
