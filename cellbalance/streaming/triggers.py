"""The adaptive rule on a stream of step times, and windowed summaries of the stream."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..plans.trigger import DECISIONS, Rule, StepState, replay_states
from ..sources.tables import event_stream

_STATE = "step long, last long, once boolean, phase_sum double, phase_n long, recent array<double>, epoch double, tau double, loss double"


def adaptive_stream(events: DataFrame, rule: Rule, run: str = "event_type") -> DataFrame:
    """Decisions as they fall. State per run is constant in size; the events of a micro-batch are sorted by (ts, event_id)."""

    def update(key: tuple, frames: Iterator[pd.DataFrame], held: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        if held.exists:
            step, last, once, total, n, recent, epoch, tau, loss = held.get
            state = StepState(last, once, total, n, tuple(recent), epoch, tau, loss)
        else:
            step, state = 0, StepState()
        numbered = zip(range(step + 1, step + 1 + len(rows)), rows["value"].tolist())
        state, fired = replay_states(numbered, rule, state)
        held.update((step + len(rows), state.last, state.once, state.phase_sum, state.phase_n, list(state.recent), state.epoch, state.tau, state.loss))
        out = pd.DataFrame([(key[0], *f) for f in fired], columns=["run_id", "step", "reason", "tau", "epoch_len"])
        yield out.astype({"tau": "float64"})

    keyed = events.select(F.col(run).cast("string").alias("run_id"), "ts", "event_id", "value")
    return keyed.groupBy("run_id").applyInPandasWithState(update, DECISIONS, _STATE, "append", GroupStateTimeout.NoTimeout)


def shared_path(spark: SparkSession) -> str:
    """A new path in the cluster's shared folder; in a temporary one for local sessions without it."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if where is None and not spark.sparkContext.master.startswith("local["):
        raise RuntimeError("spark.checkpoint.dir is unset: name a folder that all executors share")
    return f"{where or tempfile.mkdtemp(prefix='stream-')}/stream-{uuid.uuid4().hex}"


def drained(stream: DataFrame) -> DataFrame:
    """All that a finite stream yields, as a table in the shared folder: nothing passes through the driver, and the query's own
    checkpoint beside it lets a restarted one go on where it stopped."""
    where = shared_path(stream.sparkSession)
    query = stream.writeStream.format("parquet").option("checkpointLocation", f"{where}/state").trigger(availableNow=True).start(f"{where}/rows")
    query.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(f"{where}/rows")


def adaptive_events(spark: SparkSession, sf_dir: str, rule: Rule) -> DataFrame:
    return drained(adaptive_stream(event_stream(spark, sf_dir), rule))


def tumbling(events: DataFrame, size: str = "1 day", late: str = "1 hour") -> DataFrame:
    """(start, event_type, n, mean_secs) of closed windows; the last window stays open in append mode."""
    w = F.window("ts", size)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.avg("value").alias("mean_secs")).select(F.col("w.start").alias("start"), "event_type", "n", "mean_secs")


def sliding(events: DataFrame, size: str = "2 days", step: str = "1 day", late: str = "1 hour") -> DataFrame:
    w = F.window("ts", size, step)
    return events.withWatermark("ts", late).groupBy(w.alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "12 hours", late: str = "1 hour") -> DataFrame:
    w = F.session_window("ts", gap)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def without_repeats(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each event once, within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
