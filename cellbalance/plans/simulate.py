"""The whole loop: steps, trigger, balancer, migration; and the motion of the fan on the table bindings."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.balance import METHODS
from ..operators.maps import cuts_to_map
from ..sources.bindings import BAND_DAYS, DAY_ZERO, DAYS, ship_day
from ..sources.tables import table
from .trigger import Rule, StepState, transition


def fan_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(day): one row for each particle of the fan, its cell before any step."""
    rows = table(spark, sf_dir, "lineitem").select("l_shipdate").filter(F.col("l_shipdate") < F.expr(f"timestamp_ntz '{DAY_ZERO} 00:00:00' + interval {BAND_DAYS} days"))
    return rows.select(ship_day().alias("day"))


def fan_weights(days: DataFrame, step: int, stretch: float = 2.0, base: int = 3) -> DataFrame:
    """(pos, weight) after a number of steps, each of which stretches all positions by a factor."""
    return fan_weights_of(days, [step], stretch, base).select("pos", "weight")


def fan_weights_of(days: DataFrame, steps: list[int], stretch: float = 2.0, base: int = 3) -> DataFrame:
    """(step, pos, weight) of many steps in one plan: each particle is repeated for each step before it is counted."""
    each = F.explode(F.array(*(F.struct(F.lit(s).alias("step"), F.lit(float(stretch) ** s).alias("factor")) for s in steps))).alias("m")
    at = days.select("day", each).select(F.col("m.step").alias("step"), F.least(F.lit(DAYS - 1), F.floor((F.col("day") + 0.5) * F.col("m.factor"))).cast("long").alias("cell"))
    counts = at.groupBy("step", "cell").agg(F.count("*").alias("cnt"))
    cells = days.sparkSession.range(DAYS).select(F.explode(F.array(*map(F.lit, steps))).alias("step"), F.col("id").alias("cell"))
    return cells.join(counts, ["step", "cell"], "left").select("step", (F.col("cell") + 1).alias("pos"), (F.coalesce("cnt", F.lit(0)) + base).cast("long").alias("weight"))


def step_loads(weights: DataFrame, cuts: DataFrame) -> DataFrame:
    """(step, load): slowest slot of each step of ``weights`` (step, pos, weight) under one cut vector."""
    return cuts_to_map(weights, cuts).groupBy("step", "slot").agg(F.sum("weight").alias("load")).groupBy("step").agg(F.max("load").alias("load"))


@dataclass
class Run:
    """What a closed loop did."""

    steps: list[tuple[int, float]]
    firings: list[tuple]

    def average(self, lb_cost: float = 0.0) -> float:
        return (sum(s for _, s in self.steps) + lb_cost * len(self.firings)) / len(self.steps)


def closed_loop(moved: Callable[[list[int]], DataFrame], p: int, method: str, rule: Rule | None, steps: int, chunk: int = 20, unit_secs: float = 1.0, fixed: int | None = None, **options) -> Run:
    """Simulate with a balancer and a trigger; the first balance comes before the first step.

    ``moved(steps)`` gives (step, pos, weight) of the steps. One job computes the step times of a whole chunk under the cuts in force; the
    driver walks through them, and only a firing costs another balance: jobs follow firings and chunks, not steps.
    """
    # P + 1 rows: the cuts in force are a literal from here on
    def literal(df: DataFrame) -> DataFrame:
        return df.sparkSession.createDataFrame([tuple(r) for r in df.collect()], "k int, b long")

    cuts = literal(METHODS[method](moved([0]).drop("step"), p, **options))
    state, trace, fired, step = StepState(), [], [], 1
    while step <= steps:
        ahead = list(range(step, min(steps, step + chunk - 1) + 1))
        loads = dict((r[0], r[1]) for r in step_loads(moved(ahead), cuts).collect())
        for s in ahead:
            secs = loads[s] * unit_secs
            trace.append((s, secs))
            step = s + 1
            hit = None
            if rule is not None:
                state, hit = transition(state, s, secs, rule)
            elif fixed and s % fixed == 0:
                hit = ("fixed", None, fixed)
            if hit:
                fired.append((s, *hit))
                cuts = literal(METHODS[method](moved([s]).drop("step"), p, **options))
                break
    return Run(trace, fired)
