"""Logical tables of the engine: names, types and the check on entry."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T

L, I, D, S = T.LongType(), T.IntegerType(), T.DoubleType(), T.StringType()


def _schema(**fields: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(n, t) for n, t in fields.items()])


SCHEMAS = {
    "weights": _schema(pos=L, weight=L),
    "scan": _schema(pos=L, weight=L, s_prev=L, s=L, total=L, n=L),
    "cuts": _schema(k=I, b=L),
    "cell_map": _schema(pos=L, slot=I),
    "first_cells": _schema(slot=I, first_pos=L),
    "transfer_plan": _schema(pos=L, src=I, dst=I),
    "particles": _schema(particle_id=L, cell_id=L, x=D, y=D, z=D, vx=D, vy=D, vz=D, mass=D),
    "conserved": _schema(mass=T.ArrayType(D), energy=T.ArrayType(D), mx=T.ArrayType(D), my=T.ArrayType(D), mz=T.ArrayType(D)),
    "trace": _schema(run_id=S, step=L, secs=D),
    "decisions": _schema(run_id=S, step=L, reason=S, tau=D, epoch_len=L),
    "events": _schema(event_id=L, ts=T.TimestampNTZType(), user_id=L, event_type=S, value=D, props=S),
}


def conform(df: DataFrame, name: str) -> DataFrame:
    """The columns of the logical table, in order and with its types; a missing column is an error."""
    schema = SCHEMAS[name]
    missing = [f.name for f in schema if f.name not in df.columns]
    if missing:
        raise ValueError(f"{name} lacks {missing}")
    return df.select(*(df[f.name].cast(f.dataType).alias(f.name) for f in schema))
