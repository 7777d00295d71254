"""Cells and particles read from the given tables: each binding gives (pos, weight), and the same as SQL."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.ordering import dense_pos, key_order
from ..operators.weights import cell_weights, particle_counts
from .tables import table

DAYS = 2_500
BAND_DAYS = 152  # 6.1 % of the line
DAY_ZERO = "1995-01-01"


def _dense_key(cells: str, cell_key: str, particles: str, particle_key: str, base: int = 3):
    def build(spark: SparkSession, d: str) -> DataFrame:
        return cell_weights(key_order(table(spark, d, cells), cell_key), particle_counts(table(spark, d, particles), particle_key), base)

    sql = f"select cast({cell_key} + 1 as bigint) as pos, cast(coalesce(c, 0) + {base} as bigint) as weight from {cells} left join (select {particle_key} as pk, count(*) as c from {particles} group by 1) on pk = {cell_key}"
    return build, sql


def ship_day() -> F.Column:
    return F.datediff(F.col("l_shipdate").cast("date"), F.lit(DAY_ZERO).cast("date"))


def _day(band: int | None):
    def build(spark: SparkSession, d: str) -> DataFrame:
        rows = table(spark, d, "lineitem").select("l_shipdate")
        if band is not None:  # on the stored column, so the scan gets it
            rows = rows.filter(F.col("l_shipdate") < F.expr(f"timestamp_ntz '{DAY_ZERO} 00:00:00' + interval {band} days"))
        counts = rows.groupBy(ship_day().cast("long").alias("cell_id")).agg(F.count("*").alias("cnt"))
        days = spark.range(DAYS).select(F.col("id").alias("cell_id"), (F.col("id") + 1).alias("pos"))
        return cell_weights(days, counts)

    where = "" if band is None else f" where date_diff('day', timestamp '{DAY_ZERO}', l_shipdate) < {band}"
    sql = f"select cast(d + 1 as bigint) as pos, cast(coalesce(c, 0) + 3 as bigint) as weight from (select unnest(range(0, {DAYS})) as d) left join (select date_diff('day', timestamp '{DAY_ZERO}', l_shipdate) as day, count(*) as c from lineitem{where} group by 1) on day = d"
    return build, sql


def _sized(cells: str, key: str, size: str, plus: int):
    """One row a cell, its weight a number in it."""

    def build(spark: SparkSession, d: str) -> DataFrame:
        t = table(spark, d, cells).select(F.col(key).alias("cell_id"), (F.expr(size) + plus).cast("long").alias("weight"))
        return dense_pos(t, "cell_id", carry=("weight",)).select("pos", "weight")

    return build, f"select row_number() over (order by {key}) as pos, cast({size} + {plus} as bigint) as weight from {cells}"


def _counted(rows: str, key: str, plus: int):
    """A cell for each distinct key, its weight the number of rows plus a constant."""

    def build(spark: SparkSession, d: str) -> DataFrame:
        t = table(spark, d, rows).groupBy(F.col(key).alias("cell_id")).agg((F.count("*") + plus).cast("long").alias("weight"))
        return dense_pos(t, "cell_id", carry=("weight",)).select("pos", "weight")

    return build, f"select row_number() over (order by {key}) as pos, cast(c + {plus} as bigint) as weight from (select {key}, count(*) as c from {rows} group by 1)"


@dataclass(frozen=True)
class Binding:
    name: str
    p: int
    weights: Callable[[SparkSession, str], DataFrame]
    sql: str


BINDINGS = {
    name: Binding(name, p, *made)
    for name, p, made in (
        ("orders", 16, _dense_key("orders", "o_orderkey", "lineitem", "l_orderkey")),
        ("part", 16, _dense_key("part", "p_partkey", "lineitem", "l_partkey")),
        ("customer", 16, _dense_key("customer", "c_custkey", "orders", "o_custkey")),
        ("supplier", 128, _dense_key("supplier", "s_suppkey", "lineitem", "l_suppkey")),
        ("day", 16, _day(None)),
        ("fan", 16, _day(BAND_DAYS)),
        ("documents", 16, _sized("documents", "doc_id", "n_chars", 100)),
        ("pages", 16, _sized("pages", "page_id", "length(html)", 0)),
        ("conversations", 16, _counted("conversations", "conv_id", 1)),
        ("users", 16, _counted("events", "user_id", 3)),
    )
}
