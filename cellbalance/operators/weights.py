"""What a cell costs: the particles in it plus a constant for the fluid work."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def particle_counts(particles: DataFrame, key: str) -> DataFrame:
    """(cell_id, cnt). Partial counts are taken before the shuffle, so a hot cell is one row per task."""
    return particles.groupBy(F.col(key).cast("long").alias("cell_id")).agg(F.count("*").alias("cnt"))


def cell_weights(cells: DataFrame, counts: DataFrame, base_cost: int = 3, unit: int = 1) -> DataFrame:
    """(pos, weight) of all cells; empty ones keep the base. ``cells`` has cell_id and pos; ``base_cost`` is in units."""
    joined = cells.select("cell_id", "pos").join(counts, "cell_id", "left")
    return joined.select(F.col("pos").cast("long").alias("pos"), (F.coalesce("cnt", F.lit(0)) * unit + base_cost).cast("long").alias("weight"))


def calibrate_base_cost(samples: DataFrame) -> DataFrame:
    """One row, base_cost: mean time of a cell over mean time of a particle. ``samples``: kind ('cell', 'particle'), secs."""
    mean = lambda kind: F.avg(F.when(F.col("kind") == kind, F.col("secs")))
    return samples.agg((mean("cell") / mean("particle")).alias("base_cost"))


def fluid_cost(n: Column | int) -> Column:
    """Relative fluid work of a cell with n grid points per axis: n to the fourth."""
    return F.pow(n if isinstance(n, Column) else F.lit(n), F.lit(4))


def total_weight(weights: DataFrame) -> DataFrame:
    return weights.agg(F.coalesce(F.sum("weight"), F.lit(0)).cast("long").alias("total"))


def total_from_counts(counts: DataFrame, n_cells: DataFrame, base_cost: int) -> DataFrame:
    """The same total without weights: particles + base * cells. ``n_cells`` is one row, n."""
    particles = counts.agg(F.coalesce(F.sum("cnt"), F.lit(0)).alias("m"))
    return particles.select("m", n_cells.select("n").scalar().alias("n")).select((F.col("m") + F.col("n") * base_cost).cast("long").alias("total"))


def front_weights(cells: DataFrame, counts: DataFrame, base_cost: int, t: float) -> DataFrame:
    """Weights while a front moves in: cells whose left edge ``x_left`` lies ahead of exp(t/2) have no fluid work yet."""
    base = F.when(F.col("x_left") <= F.exp(F.lit(t / 2)), F.lit(base_cost)).otherwise(F.lit(0))
    return cells.select("cell_id", "pos", "x_left").join(counts, "cell_id", "left").select("pos", (F.coalesce("cnt", F.lit(0)) + base).cast("long").alias("weight"))
