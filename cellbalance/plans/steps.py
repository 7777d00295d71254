"""The whole time step on tables: interpolate, push, find the new cell, hand over, time the slots, decide, balance, ship.

Particles stay distributed, partition = slot. Each step's particles are written once (reliable checkpoint), so that lineage
doesn't grow and a lost executor costs a step at most. What reaches the driver in a step is one row a slot, and P + 1 cuts in
a rebalancing. The physics reads nothing of the slots, so a balanced run ends with the same particles as an unbalanced one.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.interpolation import lobatto_nodes
from ..operators import maps, migrate, particles, weights
from ..operators.balance import METHODS
from ..operators.ordering import checkpointer
from ..sources.bindings import BAND_DAYS, DAY_ZERO, DAYS, ship_day
from ..sources.tables import table
from . import oracle as sql
from .trigger import Rule, StepState, transition


@dataclass(frozen=True)
class Physics:
    """Linear drag towards a gas velocity that is given on ``nodes`` points a direction of each cell (of unit length)."""

    dt: float = 1.03
    tau: float = 1.1
    nodes: int = 2


@dataclass
class Loop:
    """Particles after the last step; (step, slowest slot, particles that changed slot); what each rebalancing did and took."""

    particles: DataFrame
    trace: list[tuple[int, int, int]] = field(default_factory=list)
    firings: list[tuple[int, str, int, float, float, float]] = field(default_factory=list)


def line_field(cells: DataFrame, nodes: int = 2) -> DataFrame:
    """(pos, field): gas velocity x / 3 on the nodes of cells of unit length, x running fastest."""
    inside = [(float(v) + 1) / 2 for v in lobatto_nodes(nodes)]
    return cells.select("pos", F.array(*((F.col("pos") - 1 + v) / 3 for _ in range(nodes * nodes) for v in inside)).alias("field"))


def advance(moving: DataFrame, fields: DataFrame, n_cells: int, physics: Physics) -> DataFrame:
    """Columns x, vx and pos of ``moving`` one step later."""
    inside = moving.withColumns({"cell_id": F.col("pos"), "rx": 2 * (F.col("x") - (F.col("pos") - 1)) - 1, "ry": F.lit(0.0), "rz": F.lit(0.0)})
    pushed = particles.advance_drag(particles.interpolate(inside, fields.withColumnRenamed("pos", "cell_id"), physics.nodes), physics.dt, physics.tau)
    # those that leave the line stay in its last cell
    return pushed.select(*[c for c in moving.columns if c != "pos"], cell_of("x", n_cells).alias("pos"))


def cell_of(x: str, n_cells: int):
    return F.greatest(F.lit(1), F.least(F.lit(n_cells), F.floor(x) + 1)).cast("long")


def run_steps(start: DataFrame, cells: DataFrame, fields: DataFrame, n_cells: int, p: int, steps: int, method: str = "uniform", every: int | None = None, rule: Rule | None = None, physics: Physics = Physics(), base: int = 3, unit_secs: float = 1.0, **options) -> Loop:
    """``start`` has pos, x, vx and whatever names a particle. The first balance comes before the first step.

    ``every`` rebalances after every so many steps, ``rule`` adaptively by the slowest slot's load times ``unit_secs``.
    """
    spark, save = start.sparkSession, checkpointer(start.sparkSession)

    def cuts_for(now: DataFrame) -> list[tuple[int, int]]:
        w = weights.cell_weights(cells.withColumn("cell_id", F.col("pos")), now.groupBy(F.col("pos").alias("cell_id")).agg(F.count("*").alias("cnt")), base)
        return sorted(tuple(r) for r in METHODS[method](w, p, **options).collect())  # P + 1 rows

    def map_of(b: list[tuple[int, int]]) -> DataFrame:
        return maps.cuts_to_map(cells.select("pos"), spark.createDataFrame(b, "k int, b long")).select("pos", "slot")

    cuts, now = cuts_for(start), start
    placed = map_of(cuts)
    out, state = Loop(start), StepState()
    for step in range(1, steps + 1):
        names = now.columns
        moved = advance(now.withColumnRenamed("pos", "old").withColumn("pos", F.col("old")), fields, n_cells, physics)
        handed = moved.join(placed.select(F.col("pos").alias("old"), F.col("slot").alias("src")), "old").join(placed.withColumnRenamed("slot", "dst"), "pos")
        stepped = save(handed.repartitionById(p, F.col("dst")))
        size = {k: cuts[k + 1][1] - cuts[k][1] for k in range(p)}
        seen = {r[0]: (r[1], r[2]) for r in stepped.groupBy("dst").agg(F.count("*"), F.count_if(F.col("src") != F.col("dst"))).collect()}
        load = max(base * size[k] + seen.get(k, (0, 0))[0] for k in range(p))
        out.trace.append((step, load, sum(h for _, h in seen.values())))
        now = stepped.select(*names)
        reason = None
        if rule is not None:
            state, hit = transition(state, step, load * unit_secs, rule)
            reason = hit and hit[0]
        elif every and step % every == 0:
            reason = "fixed"
        if reason:
            began = time.perf_counter()
            cuts = cuts_for(now)
            remapped = time.perf_counter()
            new = map_of(cuts)
            plan = migrate.transfer_plan(placed, new)
            n_moved = plan.count()
            # the particles of moving cells travel packed, the others stay where they are
            buffers = migrate.pack(migrate.particles_to_move(plan, now), [c for c in names if c != "pos"])
            arrived = migrate.unpack(buffers).select(*names)
            now = save(now.join(plan.select("pos"), "pos", "left_anti").select(*names).unionByName(arrived).join(new, "pos").repartitionById(p, F.col("slot")).select(*names))
            shipped = time.perf_counter()
            placed = new
            # static data never travel: each site reads those of its new cells again
            migrate.reattach_static(migrate.migrate(cells.select("pos"), new, p), fields, "pos").write.format("noop").mode("overwrite").save()
            out.firings.append((step, reason, n_moved, remapped - began, shipped - remapped, time.perf_counter() - shipped))
    out.particles = now
    return out


# ---------------------------------------------------------------- the fan, pushed
def fan_particles(spark: SparkSession, d: str) -> DataFrame:
    """Lineitems of the first days, at rest in the middle of their day's cell."""
    rows = table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_shipdate").filter(F.col("l_shipdate") < F.expr(f"timestamp_ntz '{DAY_ZERO} 00:00:00' + interval {BAND_DAYS} days"))
    at = rows.select("l_orderkey", "l_linenumber", (ship_day() + 0.5).cast("double").alias("x"), F.lit(0.0).alias("vx"))
    return at.withColumn("pos", cell_of("x", DAYS))


def fan_loop(spark: SparkSession, d: str, p: int, steps: int, **how) -> Loop:
    cells = spark.range(1, DAYS + 1).select(F.col("id").alias("pos"))
    return run_steps(fan_particles(spark, d), cells, line_field(cells), DAYS, p, steps, **how)


def fan_factors(steps: int, physics: Physics = Physics()) -> list[tuple[float, float]]:
    """(position, velocity) after 0, 1 .. steps, of a particle that starts at 1 at rest: the whole step is linear in them.

    From the step's exact polynomial in z = dt / tau, and not from its stages.
    """
    z, dt = physics.dt / physics.tau, physics.dt
    out = [(1.0, 0.0)]
    for _ in range(steps):
        x, v = out[-1]
        gap = x / 3 - v
        # the stages' positions see the velocity gap of the first and second order terms only
        out.append((x + dt * (v + gap * (z / 2 - z * z / 6)), v + gap * (z - z * z / 2 + z**3 / 6)))
    return out


P, LOOP_STEPS, LOOP_EVERY = 16, 6, 2


def whole_loop(spark: SparkSession, d: str) -> DataFrame:
    """(step, load, handed, moved): hybrid balancer, rebalanced after every second step; moved are the cells it ships."""
    done = fan_loop(spark, d, P, LOOP_STEPS, method="hybrid", every=LOOP_EVERY)
    moved = {f[0]: f[2] for f in done.firings}
    return spark.createDataFrame([(s, load, handed, moved.get(s, 0)) for s, load, handed in done.trace], "step long, load long, handed long, moved long")


_DAY = f"date_diff('day', timestamp '{DAY_ZERO}', l_shipdate)"


def _cell_sql(factor: float) -> str:
    return f"least({DAYS - 1}, cast(floor(({_DAY} + 0.5) * {factor!r}) as bigint)) + 1"


def whole_loop_sql() -> str:
    at = [f for f, _ in fan_factors(LOOP_STEPS)]

    def line(s: int) -> str:
        return f"select cast(p as bigint) as pos, cast(coalesce(c, 0) + 3 as bigint) as weight from (select unnest(range(1, {DAYS + 1})) as p) left join (select {_cell_sql(at[s])} as cell, count(*) as c from lineitem where {_DAY} < {BAND_DAYS} group by 1) on cell = p"

    rows = []
    for s in range(1, LOOP_STEPS + 1):
        force = sql.cuts("hybrid", line((s - 1) // LOOP_EVERY * LOOP_EVERY), P)
        held = sql.intervals(force)
        handed = f"""select count(*) from (select {_cell_sql(at[s - 1])} as x, {_cell_sql(at[s])} as y from lineitem where {_DAY} < {BAND_DAYS})
            join ({held}) o on x between o.first_pos and o.last_pos join ({held}) n on y between n.first_pos and n.last_pos where o.slot <> n.slot"""
        moved = f"select count(*) from ({sql.transfer_plan(line(s), force, sql.cuts('hybrid', line(s), P))})" if s % LOOP_EVERY == 0 else "select 0"
        rows.append(f"select cast({s} as bigint) as step, (select max(load) from ({sql.loads(line(s), force)})) as load, cast(({handed}) as bigint) as handed, cast(({moved}) as bigint) as moved")
    return " union all ".join(rows)


def same_physics(spark: SparkSession, d: str) -> DataFrame:
    """Particles of a balanced run beside those of an unbalanced one: sums, and rows that only one of them has."""
    ends = [fan_loop(spark, d, P, LOOP_STEPS, **how).particles.select("l_orderkey", "l_linenumber", F.round("x", 9).alias("x"), F.round("vx", 9).alias("vx")) for how in ({"method": "peer", "every": LOOP_EVERY}, {"method": "uniform"})]
    differ = migrate.check_migration(*ends)
    sums = ends[0].agg(F.count("*").alias("particles"), F.round(F.sum("x"), 3).alias("x"), F.round(F.sum("vx"), 3).alias("vx"))
    return differ.select("*", *(sums.select(c).scalar().alias(c) for c in sums.columns))


def same_physics_sql() -> str:
    x, v = fan_factors(LOOP_STEPS)[-1]
    return f"select cast(0 as bigint) as lost, cast(0 as bigint) as gained, count(*) as particles, round(sum(cast({_DAY} + 0.5 as double) * {x!r}), 3) as x, round(sum(cast({_DAY} + 0.5 as double) * {v!r}), 3) as vx from lineitem where {_DAY} < {BAND_DAYS}"


def overhead_stages(spark: SparkSession, d: str) -> DataFrame:
    """(method, step, remap_secs, ship_secs, reinit_secs): what one rebalancing takes, by stage: new map; pack, send, unpack; static data."""
    rows = [(m, f[0], *map(float, f[3:])) for m in ("single_site", "peer", "hybrid") for f in fan_loop(spark, d, P, 2, method=m, every=2).firings]
    return spark.createDataFrame(rows, "method string, step long, remap_secs double, ship_secs double, reinit_secs double")
