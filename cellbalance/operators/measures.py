"""What the experiments report: loads, step times, speed-ups, overheads and the data that rebalancing moves."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .maps import cuts_to_map


def slot_loads(weights: DataFrame, cuts: DataFrame) -> DataFrame:
    """(slot, cells, load) of all slots, empty ones too."""
    loads = cuts_to_map(weights, cuts).groupBy("slot").agg(F.count("*").alias("cells"), F.sum("weight").alias("load"))
    slots = cuts.filter(F.col("k") < cuts.agg(F.max("k")).scalar()).select(F.col("k").alias("slot"))
    return slots.join(loads, "slot", "left").select("slot", F.coalesce("cells", F.lit(0)).cast("long").alias("cells"), F.coalesce("load", F.lit(0)).cast("long").alias("load"))


def imbalance(loads: DataFrame) -> DataFrame:
    """One row: step (the slowest slot, which all others wait for), mean, imbalance = step / mean, least and most cells."""
    return loads.agg(F.max("load").alias("step"), F.avg("load").alias("mean_load"), F.min("cells").alias("least_cells"), F.max("cells").alias("most_cells")).withColumn("imbalance", F.round(F.col("step") / F.col("mean_load"), 9)).select("step", F.round("mean_load", 9).alias("mean_load"), "imbalance", "least_cells", "most_cells")


def average_step(trace: DataFrame, first: int | None = None, last: int | None = None) -> DataFrame:
    """(run_id, avg_secs) over all steps or a window of them."""
    rows = trace if first is None else trace.filter(F.col("step") >= first)
    rows = rows if last is None else rows.filter(F.col("step") <= last)
    return rows.groupBy("run_id").agg(F.avg("secs").alias("avg_secs"))


def speedup(original: float, balanced: float) -> float:
    return original / balanced


def improvement(fixed: float, adaptive: float) -> float:
    """Per cent."""
    return 100 * (fixed - adaptive) / fixed


def overhead_steps(overhead_secs: float, step_secs: float) -> float:
    """One rebalancing in time steps."""
    return overhead_secs / step_secs


def non_empty(weights_counts: DataFrame) -> DataFrame:
    """Share of cells with particles and mean particles of a cell. ``weights_counts``: cnt."""
    return weights_counts.agg(F.round(F.avg((F.col("cnt") > 0).cast("double")), 9).alias("share"), F.round(F.avg("cnt"), 9).alias("mean_particles"))


def amortised_total(trace: DataFrame, decisions: DataFrame, lb_cost: float) -> DataFrame:
    """(run_id, step_secs, lb_secs, total, share): time with the rebalancings paid."""
    fired = decisions.groupBy("run_id").agg((F.count("*") * lb_cost).alias("lb_secs"))
    steps = trace.groupBy("run_id").agg(F.sum("secs").alias("step_secs"))
    joined = steps.join(fired, "run_id", "left").withColumn("lb_secs", F.coalesce("lb_secs", F.lit(0.0)))
    total = F.col("step_secs") + F.col("lb_secs")
    return joined.select("run_id", "step_secs", "lb_secs", total.alias("total"), (F.col("lb_secs") / total).alias("share"))


@dataclass(frozen=True)
class Words:
    """Pairs that one rebalancing sends: into one place, out of one place to everyone, and among neighbours; rounds of messages."""

    gathered: int
    handed_out: int
    neighbours: int
    rounds: int
    critical: float


def words_moved(method: str, n: int, p: int) -> Words:
    log = max(1, math.ceil(math.log2(max(2, p))))
    if method == "single_site":
        return Words(n, (p + 1) * p, 0, 2 * log, n * math.log2(max(2, n)))
    if method == "peer":
        return Words(0, p * p, p - 1, 2 * log + 1, n / p + p)
    if method == "hybrid":
        return Words(p, (p + 1) * p, p - 1, 3 * log + 1, n / p + p)
    if method == "full_map":
        return Words(0, n * p, p - 1, 2 * log, n / p + n)
    raise ValueError(method)


#: alpha: a round of messages, beta: a word into the busiest node, gamma: a unit of work on the critical path, all_to_all: a
#: message of an all-to-all exchange. Presets that keep the orders found on the two machines.
PRESETS = {
    "slow_network": {"alpha": 2e-5, "beta": 1e-7, "gamma": 2e-8, "all_to_all": 4e-6},
    "fast_network": {"alpha": 4e-5, "beta": 1e-7, "gamma": 4e-8, "all_to_all": 1e-7},
}


def overhead_model(method: str, n: int, p: int, alpha: float, beta: float, gamma: float, all_to_all: float) -> float:
    """Seconds of the remapping part of one rebalancing."""
    w = words_moved(method, n, p)
    if method == "single_site":
        return alpha * w.rounds + beta * 2 * (w.gathered + p) + gamma * w.critical
    if method == "peer":
        return alpha * w.rounds + all_to_all * p + gamma * w.critical
    if method == "hybrid":
        return alpha * w.rounds + beta * 2 * (w.gathered + p) + gamma * (w.critical + p)
    return alpha * w.rounds + all_to_all * n + gamma * w.critical
