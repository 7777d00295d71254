"""The balancers: weights in, cut vector out.

Single-site and peer differ in who knows the prefix sums; peer and hybrid give the same map and differ in how it travels:
the peer plan keeps first cells, gaps and cap as relations inside the plan, the hybrid one collects at most P pairs in one
place, repairs them there and hands out a literal cut vector.
"""

from __future__ import annotations

import bisect

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import cuts as c
from . import scan as s
from .maps import cuts_to_map


def _capped(cuts: DataFrame, cap: int | None, strict: bool) -> DataFrame:
    return cuts if cap is None else c.apply_cap(cuts, cap, strict)


def balance_uniform(weights: DataFrame, p: int, cap: int | None = None, strict: bool = False) -> DataFrame:
    """The baseline: equal counts whatever the weights."""
    return _capped(c.cuts_uniform(weights, p), cap, strict)


def _scanned(weights: DataFrame, cells: int | None, block: int) -> tuple[DataFrame, DataFrame]:
    """The scan, and one row with n and total. ``cells``: about how many there are, to size blocks and levels by."""
    block, levels = (block, 1) if cells is None else s.scan_settings(cells, block)
    return s.scan_blocks(weights, block, levels), s.line_totals(weights, block)


def balance_single_site(weights: DataFrame, p: int, cap: int | None = None, strict: bool = False, scan: str = "blocks", block: int = s.BLOCK, cells: int | None = None) -> DataFrame:
    """Nearest cuts. ``scan='single'`` sorts all cells in one task as the method is described; 'blocks' gives the same cuts."""
    if scan == "single":
        return _capped(c.cuts_nearest(s.scan_single_site(weights), p), cap, strict)
    scanned, whole = _scanned(weights, cells, block)
    return _capped(c.cuts_nearest(scanned, p, whole), cap, strict)


def peer_map(weights: DataFrame, p: int, unit: int = 1, block: int = s.BLOCK) -> DataFrame:
    """(pos, slot, n, total) before any cap."""
    return c.quotient_slots(s.scan_blocks(weights, block), p, unit)


def balance_peer(weights: DataFrame, p: int, cap: int | None = None, strict: bool = False, unit: int = 1, block: int = s.BLOCK, cells: int | None = None) -> DataFrame:
    scanned, whole = _scanned(weights, cells, block)
    return _capped(c.close_gaps(c.first_of_scan(scanned, p, unit), p, whole), cap, strict)


def repair_in_one_place(pairs: list[tuple[int, int]], p: int, n: int, cap: int | None, strict: bool) -> list[int]:
    """Cut vector from (slot, first cell) pairs: gaps closed from the right, then the cap from left to right."""
    begin = {slot: first - 1 for slot, first in pairs if slot is not None}
    b = [0] * (p + 1)
    b[p] = n
    for k in range(p - 1, 0, -1):
        b[k] = begin.get(k, b[k + 1])
    if cap is not None:
        if strict and n > p * cap:
            raise ValueError(f"more cells than slots times the cap {cap}")
        for k in range(1, p):
            b[k] = min(b[k], b[k - 1] + cap)
        if strict:
            for k in range(p - 1, 0, -1):
                b[k] = max(b[k], b[k + 1] - cap)
    return b


def balance_hybrid(weights: DataFrame, p: int, cap: int | None = None, strict: bool = False, unit: int = 1, block: int = s.BLOCK, cells: int | None = None) -> DataFrame:
    scanned, whole = _scanned(weights, cells, block)
    first = c.first_of_scan(scanned, p, unit)
    # one job brings the pairs, at most one a slot, and the totals
    tagged = first.select("slot", F.col("first_pos").alias("x")).unionByName(whole.select(F.expr("case when total > 0 then -1 else -2 end").alias("slot"), F.col("n").alias("x")))
    rows = [(r[0], r[1]) for r in tagged.collect()]
    mark, n = next((s_, x) for s_, x in rows if s_ is not None and s_ < 0)
    if mark == -2:
        b = [k * n // p for k in range(p + 1)]
        b = b if cap is None else repair_in_one_place([(k, b[k] + 1) for k in range(p)], p, n, cap, strict)
    else:
        b = repair_in_one_place([r for r in rows if r[0] is not None and r[0] >= 0], p, n, cap, strict)
    return weights.sparkSession.createDataFrame(list(enumerate(b)), "k int, b long")


def share_full_map(weights: DataFrame, p: int, unit: int = 1) -> DataFrame:
    """The rejected alternative: the map of every cell travels, not the cuts. It is shuffled to the cells, as a copy at each site grows with them."""
    mapped = peer_map(weights, p, unit).select("pos", "slot")
    return weights.join(mapped, "pos").select("pos", "weight", "slot")


METHODS = {"uniform": balance_uniform, "single_site": balance_single_site, "peer": balance_peer, "hybrid": balance_hybrid}


def rebalance(weights: DataFrame, p: int, method: str, **options) -> DataFrame:
    """(pos, weight, slot) under fresh cuts; the map in force before doesn't matter."""
    return cuts_to_map(weights, METHODS[method](weights, p, **options))


def initial_balance(weights: DataFrame, p: int, method: str = "single_site", **options) -> DataFrame:
    """The mandatory balance before the first step: version 0 of the cuts."""
    return METHODS[method](weights, p, **options).withColumn("version", F.lit(0))


def cuts_optimal(weights: DataFrame, p: int, max_cells: int = 1_000_000) -> DataFrame:
    """Yardstick: the contiguous split with the smallest possible slowest slot, for lines of bounded length."""
    rows = s.scan_blocks(weights).select("pos", "s").limit(max_cells + 1).collect()
    if len(rows) > max_cells:
        raise ValueError(f"more than {max_cells} cells")
    sums = [0, *(x for _, x in sorted((r[0], r[1]) for r in rows))]
    n = len(sums) - 1

    def greedy(most: int) -> list[int]:
        b = [0]
        for _ in range(p):
            b.append(bisect.bisect_right(sums, sums[b[-1]] + most) - 1)
        return b

    lo, hi = max((y - x for x, y in zip(sums, sums[1:])), default=0), sums[-1]
    while lo < hi:
        mid = (lo + hi) // 2
        lo, hi = (lo, mid) if greedy(mid)[-1] == n else (mid + 1, hi)
    b = greedy(lo)
    b[-1] = n
    return weights.sparkSession.createDataFrame(list(enumerate(b)), "k int, b long")
