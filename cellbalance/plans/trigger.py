"""When to rebalance: every k steps, or by the measured step times.

``transition`` is the whole adaptive rule, one step at a time. It is pure, so a batch replay, a stream and a closed loop run
the same code.
"""

from __future__ import annotations

import math
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, replace

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Rule:
    """Parameters of the adaptive rule."""

    lb_cost: float
    threshold: float = 0.05
    eval_len: int = 100
    use_interval: bool = True
    use_loss: bool = True
    phase_offset: int = 1


@dataclass(frozen=True)
class StepState:
    """Between two steps of one run."""

    last: int = 0  # step of the last rebalancing
    once: bool = False  # whether one has been triggered yet
    phase_sum: float = 0.0
    phase_n: int = 0
    recent: tuple[float, ...] = ()
    epoch: float = 0.0  # length of the epoch before the last rebalancing
    tau: float = math.inf
    loss: float = 0.0


def median_of_recent(recent: tuple[float, ...]) -> float:
    """Median of the last three step times, or of as many as there are."""
    r = sorted(recent)
    m = len(r) // 2
    return r[m] if len(r) % 2 else (r[m - 1] + r[m]) / 2


def transition(state: StepState, step: int, secs: float, rule: Rule) -> tuple[StepState, tuple | None]:
    """The next state, and (reason, tau, epoch_len) if this step ends with a rebalancing.

    On the first step after a rebalancing the ideal interval is computed before the new evaluation phase opens, so it uses
    the old phase's mean. Without degradation the interval is infinite and only the loss counts, which may be negative.
    """
    recent = (*state.recent, secs)[-3:]
    now = median_of_recent(recent)
    before = state.phase_sum / state.phase_n if state.phase_n else 0.0
    since = step - state.last
    s = replace(state, recent=recent)
    if s.once and since == 1:
        tau = math.sqrt(2 * s.epoch * rule.lb_cost / (now - before)) if now > before else math.inf
        s = replace(s, tau=tau, phase_sum=0.0, phase_n=0)
    if rule.phase_offset <= since < rule.phase_offset + rule.eval_len:
        return replace(s, phase_sum=s.phase_sum + secs, phase_n=s.phase_n + 1), None
    if since < rule.phase_offset:
        return s, None
    if not s.once:
        if before > 0 and (now - before) / before > rule.threshold:
            epoch = step - (s.last + rule.eval_len // 2)
            return replace(s, last=step, once=True, epoch=float(epoch)), ("degrade", None, epoch)
        return s, None
    loss = s.loss + (now - before)
    due, costly = rule.use_interval and since >= s.tau, rule.use_loss and loss > rule.lb_cost
    if due or costly:
        return replace(s, last=step, epoch=float(since), loss=0.0), ("interval" if due else "loss", None if math.isinf(s.tau) else s.tau, since)
    return replace(s, loss=loss), None


def replay(rows: Iterable[tuple[int, float]], rule: Rule, state: StepState | None = None) -> Iterator[tuple]:
    """(step, reason, tau, epoch_len) of each firing."""
    state = state or StepState()
    for step, secs in rows:
        state, fired = transition(state, step, secs, rule)
        if fired:
            yield step, *fired


def replay_states(rows: Iterable[tuple[int, float]], rule: Rule, state: StepState) -> tuple[StepState, list[tuple]]:
    """The state after the rows, and the firings."""
    found = []
    for step, secs in rows:
        state, fired = transition(state, step, secs, rule)
        if fired:
            found.append((step, *fired))
    return state, found


DECISIONS = "run_id string, step long, reason string, tau double, epoch_len long"


def adaptive_triggers(trace: DataFrame, rule: Rule) -> DataFrame:
    """Decisions of every run of ``trace`` (run_id, step, secs). One shuffle on the run; constant state inside it."""

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("step")
        rows = [(key[0], *x) for x in replay(zip(pdf["step"].tolist(), pdf["secs"].tolist()), rule)]
        out = pd.DataFrame(rows, columns=["run_id", "step", "reason", "tau", "epoch_len"])
        return out.astype({"tau": "float64"})

    return trace.select("run_id", "step", "secs").groupBy("run_id").applyInPandas(run, DECISIONS)


def numbered(events: DataFrame, run: str | Column) -> DataFrame:
    """(run_id, step, secs): the events of a run in order of time are its steps, their value the time of a step."""
    key = F.col(run).cast("string") if isinstance(run, str) else run
    step = F.row_number().over(Window.partitionBy(key).orderBy("ts", "event_id"))
    return events.select(key.alias("run_id"), step.cast("long").alias("step"), F.col("value").alias("secs"))


def recent_median(trace: DataFrame) -> DataFrame:
    """(run_id, step, t2): median of the last three step times by comparisons alone."""
    w = Window.partitionBy("run_id").orderBy("step")
    a, b, c = F.col("secs"), F.lag("secs", 1).over(w), F.lag("secs", 2).over(w)
    three = F.greatest(F.least(a, b), F.least(F.greatest(a, b), c))
    return trace.select("run_id", "step", F.when(b.isNull(), a).when(c.isNull(), (a + b) / 2).otherwise(three).alias("t2"))


def phase_mean(trace: DataFrame, eval_len: int = 100) -> DataFrame:
    """(run_id, t1, midpoint) of the first evaluation phase."""
    return trace.filter(F.col("step") <= eval_len).groupBy("run_id").agg(F.avg("secs").alias("t1"), F.lit(eval_len // 2).cast("long").alias("midpoint"))


def phase_means(trace: DataFrame, firings: DataFrame, eval_len: int = 100) -> DataFrame:
    """(run_id, epoch_start, t1, midpoint) of the evaluation phase of every epoch: the ``eval_len`` steps after the run's start (0) and after
    each step of ``firings`` (run_id, step). One sort by run: the last firing before a step is carried forward."""
    marks = firings.select("run_id", "step", F.lit(None).cast("double").alias("secs"), F.col("step").alias("fired"))
    rows = trace.select("run_id", "step", "secs", F.lit(None).cast("long").alias("fired")).unionByName(marks)
    # a step that fires still belongs to the epoch before it
    last = F.last("fired", ignorenulls=True).over(Window.partitionBy("run_id").orderBy("step", F.col("fired").isNotNull()))
    phase = rows.withColumn("epoch_start", F.coalesce(last, F.lit(0))).filter("secs is not null").filter(F.col("step") - F.col("epoch_start") <= eval_len)
    return phase.groupBy("run_id", "epoch_start").agg(F.avg("secs").alias("t1")).withColumn("midpoint", F.col("epoch_start") + eval_len // 2)


def ideal_interval(lb_cost: float, slope: float) -> float:
    """Interval with the least sum of rebalancing cost and degradation per step."""
    return math.sqrt(2 * lb_cost / slope) if slope > 0 else math.inf


def ideal_interval_of(lb_cost: float, slope: Column) -> Column:
    """The same as a column; null where nothing degrades."""
    return F.when(slope > 0, F.sqrt(2 * F.lit(lb_cost) / slope))


def suggest_k(trace: DataFrame, lb_cost: float) -> DataFrame:
    """(run_id, k): fixed interval from a run without rebalancing, by the slope of its step times."""
    slope = F.regr_slope("secs", "step")
    return trace.groupBy("run_id").agg(ideal_interval_of(lb_cost, slope).alias("k"))


def policy_never(trace: DataFrame) -> DataFrame:
    return trace.filter(F.lit(False)).select("run_id", "step")


def policy_once(trace: DataFrame) -> DataFrame:
    """Only the mandatory balance before the first step, shown as step 0."""
    return trace.select("run_id").distinct().select("run_id", F.lit(0).cast("long").alias("step"))


def policy_fixed(trace: DataFrame, k: int) -> DataFrame:
    return trace.filter(F.col("step") % k == 0).select("run_id", "step")


def threshold_sweep(trace: DataFrame, grid: list[float], rule: Rule) -> DataFrame:
    """(threshold, run_id, firings, first_step) for each threshold: one group per run and threshold."""

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("step")
        found = list(replay(zip(pdf["step"].tolist(), pdf["secs"].tolist()), replace(rule, threshold=key[1])))
        return pd.DataFrame([(key[1], key[0], len(found), found[0][0] if found else None)], columns=["threshold", "run_id", "firings", "first_step"]).astype({"first_step": "Int64"})

    thresholds = F.explode(F.array(*(F.lit(float(x)) for x in grid))).alias("threshold")
    return trace.select("run_id", "step", "secs", thresholds).groupBy("run_id", "threshold").applyInPandas(run, "threshold double, run_id string, firings long, first_step long")


# ---------------------------------------------------------------- closed loops with a given degradation
def drift_loop(rule: Rule, slope: float, steps: int, base: float = 1.0, policy: str = "adaptive", k: int = 500, flat: int = 0) -> tuple[list[float], list[tuple]]:
    """Step times base + slope * (step - last rebalancing), flat for the first steps; the times and the firings."""
    state, last, secs, fired = StepState(), 0, [], []
    for step in range(1, steps + 1):
        t = base + slope * max(0, step - max(last, flat))
        secs.append(t)
        if policy == "adaptive":
            state, hit = transition(state, step, t, rule)
            if hit:
                fired.append((step, *hit))
                last = step
        elif policy == "fixed" and step % k == 0:
            fired.append((step, "fixed", None, k))
            last = step
    return secs, fired


def drift_runs(slopes: DataFrame, rule: Rule, steps: int) -> DataFrame:
    """Decisions of a closed loop for every run of ``slopes`` (run_id, slope)."""

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        rows = [(key[0], *x) for x in drift_loop(rule, float(pdf["slope"].iloc[0]), steps)[1]]
        return pd.DataFrame(rows, columns=["run_id", "step", "reason", "tau", "epoch_len"]).astype({"tau": "float64"})

    return slopes.groupBy("run_id").applyInPandas(run, DECISIONS)
