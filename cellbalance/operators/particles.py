"""One time step of the particles: interpolate, push, find the new cell, hand over between slots."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.interpolation import interpolated


@dataclass(frozen=True)
class Box:
    """A rectangular domain; the default is the prism of the expansion test."""

    x0: float = -2.208
    x1: float = 6.0
    y0: float = 0.0
    y1: float = 0.0802
    z0: float = 0.0
    z1: float = 0.0802


CURTAIN = Box(0.0, 10.0, 0.0, 1.0, 0.0, 1.0)
#: Where the particles of the expansion test start, in x.
INITIAL_BAND = (-1.0, -0.5)


def lattice_cell(box: Box, shape: tuple[int, int, int]) -> Column:
    """Cell number (x slowest, z fastest) of a location; locations outside belong to the nearest cell."""
    nx, ny, nz = shape

    def index(c: str, lo: float, hi: float, n: int) -> Column:
        return F.greatest(F.lit(0), F.least(F.lit(n - 1), F.floor((F.col(c) - lo) / (hi - lo) * n))).cast("long")

    return (index("x", box.x0, box.x1, nx) * ny + index("y", box.y0, box.y1, ny)) * nz + index("z", box.z0, box.z1, nz)


def interpolate(particles: DataFrame, fields: DataFrame, n: int, out: str = "u") -> DataFrame:
    """Fluid property at each particle, from the grid points of its own cell only.

    ``particles`` has cell_id and the place inside the cell (rx, ry, rz in [-1, 1]); ``fields`` has cell_id and field.
    """
    return particles.join(fields.select("cell_id", "field"), "cell_id").withColumn(out, interpolated("field", "rx", "ry", "rz", n)).drop("field")


def drag_factor(dt: float, tau: float) -> float:
    """What three-stage third-order stepping leaves of the velocity gap after one step of linear drag."""
    z = dt / tau
    return 1 - z + z**2 / 2 - z**3 / 6


def advance_drag(particles: DataFrame, dt: float, tau: float, gas: str = "u") -> DataFrame:
    """Velocity and position after one three-stage, third-order, total-variation-diminishing step of linear drag.

    Each stage is an Euler step averaged with the start, by the weights (0, 1), (3/4, 1/4) and (1/3, 2/3) (fixed values).
    """
    v0, x0, u = F.col("vx"), F.col("x"), F.col(gas)
    v1, x1 = v0 + dt * (u - v0) / tau, x0 + dt * v0
    v2 = 0.75 * v0 + 0.25 * (v1 + dt * (u - v1) / tau)
    x2 = 0.75 * x0 + 0.25 * (x1 + dt * v1)
    v3 = v0 / 3 + 2 / 3 * (v2 + dt * (u - v2) / tau)
    x3 = x0 / 3 + 2 / 3 * (x2 + dt * v2)
    return particles.withColumns({"vx": v3, "x": x3})


def advance_euler(particles: DataFrame, dt: float, columns: tuple[str, ...] = ("x",)) -> DataFrame:
    """Forward Euler with the imposed velocity x/3: each step stretches the cloud by 1 + dt/3, in one or more dimensions."""
    return particles.withColumns({c: F.col(c) + dt * F.col(c) / 3 for c in columns})


def relocate(particles: DataFrame, cell: Column, cell_map: DataFrame) -> DataFrame:
    """New cell and slot of each particle. ``particles`` has pos (its old cell); ``cell`` gives the new position on the line."""
    old = cell_map.select("pos", F.col("slot").alias("src"))
    new = cell_map.select(F.col("pos").alias("new_pos"), F.col("slot").alias("dst"))
    return particles.withColumn("new_pos", cell).join(old, "pos").join(new, "new_pos")


def handover_matrix(relocated: DataFrame) -> DataFrame:
    """(src, dst, particles) of those that change slot."""
    return relocated.filter("src <> dst").groupBy("src", "dst").agg(F.count("*").alias("particles"))


def fan_velocity(x: Column, t: float, diaphragm: float = 0.5, rho: float = 1.0, pressure: float = 1000.0, gamma: float = 1.4) -> Column:
    """Gas velocity inside an expansion fan running left from a diaphragm into gas at rest (textbook self-similar solution)."""
    sound = (gamma * pressure / rho) ** 0.5
    inside = 2 / (gamma + 1) * (sound + (x - diaphragm) / t)
    return F.when((x - diaphragm) / t <= -sound, F.lit(0.0)).otherwise(F.least(inside, F.lit(2 * sound / (gamma - 1))))


def front_velocity(x: Column, t: float) -> Column:
    """Gas velocity behind a front at exp(t/2): 1, ahead of it 0."""
    return F.when(x <= F.exp(F.lit(t / 2)), F.lit(1.0)).otherwise(F.lit(0.0))
