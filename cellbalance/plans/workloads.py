"""The experiments on the given tables, and their SQL."""

from __future__ import annotations

import time
from collections.abc import Iterable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import balance as bal
from ..operators import cuts as cut
from ..operators import many, maps, measures, migrate, ordering, particles, weights
from ..sources.bindings import BAND_DAYS, BINDINGS, DAY_ZERO, DAYS
from ..sources.tables import table
from . import oracle as sql
from . import simulate
from .trigger import Rule

P = 16
FAN_STEPS = (0, 1, 2, 3, 4)


def union(frames: Iterable[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def slowest(w: DataFrame, cuts: DataFrame, name: str = "step") -> DataFrame:
    return measures.slot_loads(w, cuts).agg(F.max("load").alias(name))


# ---------------------------------------------------------------- worked example (fixed values)
EXAMPLE_PARTICLES = (1, 2, 1, 2, 5, 8, 7, 3, 2, 2, 2, 1)
_EXAMPLE = "select pos, c + 3 as weight from (values " + ", ".join(f"(cast({i + 1} as bigint), cast({c} as bigint))" for i, c in enumerate(EXAMPLE_PARTICLES)) + ") as t(pos, c)"


def example_weights(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(i + 1, c + 3) for i, c in enumerate(EXAMPLE_PARTICLES)], "pos long, weight long")


_PRICED = "least(12, cast(floor(l_extendedprice / 8000) as bigint) + 1)"
_PRICES = f"select pos, cast(coalesce(c, 0) + 3 as bigint) as weight from (select unnest(range(1, 13)) as pos) left join (select {_PRICED} as cell, count(*) as c from lineitem group by 1) on cell = pos"


def price_weights(spark: SparkSession, d: str) -> DataFrame:
    """A line as long as the worked example's: lines of orders in 12 cells by price, the last one open."""
    cell = F.least(F.lit(12), F.floor(F.col("l_extendedprice") / 8000) + 1).cast("long")
    counts = table(spark, d, "lineitem").groupBy(cell.alias("cell_id")).agg(F.count("*").alias("cnt"))
    return weights.cell_weights(spark.range(1, 13).select(F.col("id").alias("cell_id"), F.col("id").alias("pos")), counts)


def example_map(spark: SparkSession, method: str, w: DataFrame | None = None) -> DataFrame:
    w = example_weights(spark) if w is None else w
    return maps.cuts_to_map(w, bal.METHODS[method](w, 3))


def example_sql(method: str, line: str = _EXAMPLE) -> str:
    return sql.cell_map(line, sql.cuts(method, line, 3))


def example_transfer(spark: SparkSession, w: DataFrame | None = None) -> DataFrame:
    w = example_weights(spark) if w is None else w
    plan = migrate.transfer_plan(maps.cuts_to_map(w, cut.cuts_uniform(w, 3)), example_map(spark, "single_site", w))
    return plan.join(w, "pos").select("pos", "src", "dst", (F.col("weight") - 3).alias("particles"))


def example_transfer_sql(line: str = _EXAMPLE) -> str:
    return f"select pos, src, dst, weight - 3 as particles from ({sql.transfer_plan(line, sql.cuts('uniform', line, 3), sql.cuts('single_site', line, 3))}) join ({line}) using (pos)"


# ---------------------------------------------------------------- the fan in motion
def fan_sql(step: int) -> str:
    day = f"date_diff('day', timestamp '{DAY_ZERO}', l_shipdate)"
    return f"""select cast(d + 1 as bigint) as pos, cast(coalesce(c, 0) + 3 as bigint) as weight from (select unnest(range(0, {DAYS})) as d) left join
        (select least({DAYS - 1}, cast(floor(({day} + 0.5) * {2**step}) as bigint)) as cell, count(*) as c from lineitem where {day} < {BAND_DAYS} group by 1) on cell = d"""


def _fan(spark: SparkSession, d: str, step: int) -> DataFrame:
    return simulate.fan_weights(simulate.fan_days(spark, d), step)


def _traced(spark: SparkSession, d: str, balancer, steps=FAN_STEPS) -> DataFrame:
    """(s, step): slowest slot of each step; ``balancer(w)`` gives the cuts of each step's own weights."""
    days = simulate.fan_days(spark, d)
    return union(simulate.step_loads(simulate.fan_weights_of(days, [s]), balancer(simulate.fan_weights(days, s))).select(F.col("step").alias("s"), F.col("load").alias("step")) for s in steps)


def fan_trace(spark: SparkSession, d: str) -> DataFrame:
    """(s, method, step): slowest slot of each step with fresh cuts."""
    return union(_traced(spark, d, lambda w, m=m: bal.METHODS[m](w, P)).select("s", F.lit(m).alias("method"), "step") for m in ("uniform", "single_site", "peer"))


def fan_trace_sql() -> str:
    return " union all ".join(f"select {s} as s, '{m}' as method, max(load) as step from ({sql.loads(fan_sql(s), sql.cuts(m, fan_sql(s), P))})" for s in FAN_STEPS for m in ("uniform", "single_site", "peer"))


def fan_stale_vs_fresh(spark: SparkSession, d: str) -> DataFrame:
    """(s, fresh, stale, moved): the map of step 0 degrades, a fresh one restores; cells that the fresh one moves."""
    start = _fan(spark, d, 0)
    first = bal.balance_single_site(start, P)
    old = maps.cuts_to_map(start, first).select("pos", "slot")
    rows = []
    for s in FAN_STEPS:
        w = _fan(spark, d, s)
        fresh = bal.balance_single_site(w, P)
        moved = migrate.transfer_plan(old, maps.cuts_to_map(w, fresh).select("pos", "slot")).agg(F.count("*").alias("moved"))
        rows.append(slowest(w, fresh, "fresh").select(F.lit(s).alias("s"), "fresh", slowest(w, first, "stale").scalar().alias("stale"), moved.scalar().alias("moved")))
    return union(rows)


def fan_stale_sql() -> str:
    first = sql.cuts("single_site", fan_sql(0), P)
    return " union all ".join(
        f"select {s} as s, (select max(load) from ({sql.loads(fan_sql(s), sql.cuts('single_site', fan_sql(s), P))})) as fresh, (select max(load) from ({sql.loads(fan_sql(s), first)})) as stale, (select count(*) from ({sql.transfer_plan(fan_sql(s), first, sql.cuts('single_site', fan_sql(s), P))})) as moved" for s in FAN_STEPS
    )


def fan_fixed_k(spark: SparkSession, d: str, k: int) -> DataFrame:
    """(s, step): rebalanced every k steps, so step s runs on the cuts of step floor(s/k)*k."""
    return union(slowest(_fan(spark, d, s), bal.balance_peer(_fan(spark, d, s // k * k), P)).select(F.lit(s).alias("s"), "step") for s in FAN_STEPS)


def fan_fixed_sql(k: int) -> str:
    return " union all ".join(f"select {s} as s, max(load) as step from ({sql.loads(fan_sql(s), sql.cuts('peer', fan_sql(s // k * k), P))})" for s in FAN_STEPS)


def _ratio(original: DataFrame, balanced: DataFrame, **more) -> DataFrame:
    o, b = (f.agg(F.avg("step").alias("a")) for f in (original, balanced))
    extra = [F.lit(v).alias(n) for n, v in more.items()]
    return o.select(*extra, F.round("a", 6).alias("original"), F.round(b.scalar(), 6).alias("balanced"), F.round(F.col("a") / b.scalar(), 6).alias("speedup"))


def _ratio_sql(original: str, balanced: str, more: str = "") -> str:
    return f"select {more} round(o, 6) as original, round(b, 6) as balanced, round(o / b, 6) as speedup from (select (select avg(step) from ({original})) as o, (select avg(step) from ({balanced})) as b)"


def speedup_fan(spark: SparkSession, d: str) -> DataFrame:
    w = _fan(spark, d, 0)
    return union(_ratio(slowest(w, cut.cuts_uniform(w, P)), slowest(w, bal.METHODS[m](w, P)), method=m) for m in ("single_site", "peer", "hybrid"))


def speedup_sql() -> str:
    worst = lambda m: f"select max(load) as step from ({sql.loads(fan_sql(0), sql.cuts(m, fan_sql(0), P))})"
    return " union all ".join(_ratio_sql(worst("uniform"), worst(m), f"'{m}' as method,") for m in ("single_site", "peer", "hybrid"))


#: Cells a slot may hold, in multiples of the mean: as in the two long runs, and one that binds.
XEON_CAP, BGQ_CAP, TIGHT_CAP = (9, 1), (10, 1), (5, 4)


def cap_of(times: tuple[int, int]) -> int:
    return -(-DAYS * times[0] // (P * times[1]))


def fan_speedup_hybrid(spark: SparkSession, d: str) -> DataFrame:
    """Hybrid, rebalanced at each step, under the loose and the tight cap, against the uniform split."""
    uniform = simulate.step_loads(simulate.fan_weights_of(simulate.fan_days(spark, d), list(FAN_STEPS)), cut.cuts_uniform(spark.range(DAYS), P)).select(F.col("load").alias("step"))
    return union(_ratio(uniform, _traced(spark, d, lambda w, c=c: bal.balance_hybrid(w, P, cap=c)), cap=c) for c in map(cap_of, (XEON_CAP, TIGHT_CAP)))


def _uniform_sql() -> str:
    return " union all ".join(f"select max(load) as step from ({sql.loads(fan_sql(s), sql.cuts('uniform', fan_sql(s), P))})" for s in FAN_STEPS)


def fan_speedup_hybrid_sql() -> str:
    return " union all ".join(_ratio_sql(_uniform_sql(), " union all ".join(f"select max(load) as step from ({sql.loads(fan_sql(s), sql.cuts('hybrid', fan_sql(s), P, c))})" for s in FAN_STEPS), f"{c} as cap,") for c in map(cap_of, (XEON_CAP, TIGHT_CAP)))


def fan_speedup_peer(spark: SparkSession, d: str) -> DataFrame:
    """Peer, balanced once before the first step, against the uniform split."""
    c = cap_of(BGQ_CAP)
    once = bal.balance_peer(_fan(spark, d, 0), P, cap=c)
    # the cuts of step 0 are P + 1 numbers, the same for all steps: one plan for the whole trace
    moving = simulate.fan_weights_of(simulate.fan_days(spark, d), list(FAN_STEPS))
    trace = lambda cuts: simulate.step_loads(moving, cuts).select(F.col("load").alias("step"))
    return _ratio(trace(cut.cuts_uniform(spark.range(DAYS), P)), trace(once), cap=c)


def fan_speedup_peer_sql() -> str:
    c = cap_of(BGQ_CAP)
    return _ratio_sql(_uniform_sql(), " union all ".join(f"select max(load) as step from ({sql.loads(fan_sql(s), sql.cuts('peer', fan_sql(0), P, c))})" for s in FAN_STEPS), f"{c} as cap,")


def fan_closed_loop(spark: SparkSession, d: str) -> DataFrame:
    """(policy, avg_step, firings): the adaptive loop against no balancing, the cloud growing one per cent a step."""
    days = simulate.fan_days(spark, d).cache()
    moved = lambda steps: simulate.fan_weights_of(days, steps, 1.02)
    rule = Rule(lb_cost=500.0, eval_len=10)
    runs = {"original": simulate.closed_loop(moved, P, "uniform", None, 40), "once": simulate.closed_loop(moved, P, "hybrid", None, 40), "adaptive": simulate.closed_loop(moved, P, "hybrid", rule, 40), "fixed": simulate.closed_loop(moved, P, "hybrid", None, 40, fixed=10)}
    days.unpersist()
    return spark.createDataFrame([(n, r.average(), len(r.firings)) for n, r in runs.items()], "policy string, avg_step double, firings long")


# ---------------------------------------------------------------- weak scaling and overhead
SCALES = (4, 16, 64, 256, 1024)


#: A hundred steps, balanced every ten: the cloud moves one cell to the right a step, around the slice's end.
EVERY, REBALANCINGS = 10, 10


def weak_scaling(spark: SparkSession, d: str, per_slot: int, cap: int) -> DataFrame:
    """(p, n, method, step, stale, fresh, most_cells, moved): slices of the orders line with a fixed number of cells per slot.

    Each of the ten rebalancings starts from the cuts of the one before, the first from uniform ones. All scales,
    rebalancings and methods are one plan, and cells meet all cut vectors in one join. Scales whose slice the table can't fill are left out.
    """
    line = BINDINGS["orders"].weights(spark, d).filter(F.col("pos") <= per_slot * max(SCALES))
    p, r = F.explode(F.array(*map(F.lit, SCALES))), F.explode(F.sequence(F.lit(1), F.lit(REBALANCINGS)))
    cells_there = table(spark, d, "orders").agg(F.count("*")).scalar()
    each = line.withColumn("p", p).filter((F.col("pos") <= per_slot * F.col("p")) & (per_slot * F.col("p") <= cells_there)).withColumn("r", r)
    shifted = ((F.col("pos") - 1 + EVERY * F.col("r")) % (per_slot * F.col("p")) + 1).cast("long")
    cells = each.select(F.struct("p", "r").alias("line"), "p", shifted.alias("pos"), "weight")
    scan = many.scan_many(cells)
    by = ("method",)
    # a cut vector has p + 1 rows and is read four times below: it is written once, so that no scan runs again
    fresh = ordering.checkpointer(spark)(union(cut_all(scan, cap).withColumn("method", F.lit(m)) for m, cut_all in many.METHODS.items()))
    first = many.uniform_many(spark.createDataFrame([((q, 1), q, per_slot * q) for q in SCALES], "line struct<p: int, r: int>, p int, n long").filter(F.col("n") <= cells_there))
    later = fresh.filter(F.col("line.r") < REBALANCINGS).withColumn("line", F.struct(F.col("line.p").alias("p"), (F.col("line.r") + 1).alias("r")))
    old = later.unionByName(first.withColumn("method", F.explode(F.array(*map(F.lit, many.METHODS)))))
    loads = many.loads_many(cells, union(c.withColumn("age", F.lit(a)) for a, c in (("fresh", fresh), ("stale", old))), ("method", "age"))
    of = lambda column, age: F.when(F.col("age") == age, F.col(column))
    worst = loads.groupBy("line", *by).agg(F.max(of("load", "stale")).alias("stale"), F.max(of("load", "fresh")).alias("fresh"), F.max(of("cells", "fresh")).alias("most_cells"), F.sum(of("cells", "fresh")).cast("long").alias("n"))
    joined = worst.join(many.stays_many(old, fresh, by), ["line", *by])
    return joined.select(F.col("line.p").alias("p"), "n", "method", (F.col("line.r") * EVERY).alias("step"), "stale", "fresh", "most_cells", (F.col("n") - F.col("stays")).alias("moved"))


def weak_scaling_sql(per_slot: int, cap: int) -> str:
    return f"""with recursive base as materialized (select * from ({BINDINGS['orders'].sql}) where pos <= {per_slot * max(SCALES)}),
        w as materialized (select p, r, (pos - 1 + {EVERY} * r) % ({per_slot} * p) + 1 as pos, weight from base, (select unnest({list(SCALES)}) as p), (select unnest(range(1, {REBALANCINGS + 1})) as r) where pos <= {per_slot} * p and {per_slot} * p <= (select count(*) from orders)),
        sc as materialized (select *, sum(weight) over (partition by p, r order by pos) as s, sum(weight) over (partition by p, r) as t, count(*) over (partition by p, r) as n from w),
        slots as (select p, r, n, t, unnest(range(0, p + 1)) as k from (select distinct p, r, n, t from sc)),
        hit as (select p, r, k, min(pos) as pos from slots join sc using (p, r) where sc.s * p > k * sc.t and k between 1 and p - 1 group by p, r, k),
        nearest as (select p, r, k, case when 2 * k * t < p * (2 * s - weight) then pos - 1 else pos end as b from hit join sc using (p, r, pos) union all select p, r, k, case when k = 0 then 0 else n end from slots where k = 0 or k = p),
        quotient as (select p, r, k, case when k = 0 then 0 when k = p then max(sc.n) else count(*) filter (where s * p < k * sc.t + p) end as b from slots join sc using (p, r) group by p, r, k),
        plain as materialized (select 'single_site' as method, * from nearest union all select m, quotient.* from quotient, (select unnest(['peer', 'hybrid']) as m)),
        capped(method, p, r, k, b) as (select method, p, r, k, cast(b as bigint) from plain where k = 0 union all
            select c.method, c.p, c.r, c.k, least(cast(c.b as bigint), x.b + case when c.k = c.p then cast(4611686018427387904 as bigint) else {cap} end) from capped x join plain c on c.method = x.method and c.p = x.p and c.r = x.r and c.k = x.k + 1),
        force as (select method, p, r, k, b, 'fresh' as age from capped union all select method, p, r + 1, k, b, 'stale' from capped where r < {REBALANCINGS} union all
            select m, p, r, k, (k * n) // p, 'stale' from slots, (select unnest(['single_site', 'peer', 'hybrid']) as m) where r = 1),
        span as (select *, lead(b) over (partition by age, method, p, r order by k) as e from force),
        placed as materialized (select age, method, p, r, k, pos, weight from span join w using (p, r) where pos > b and pos <= e),
        loads as (select age, method, p, r, k, sum(weight) as load, count(*) as cells from placed group by all),
        moved as (select x.method, x.p, x.r, count(*) filter (where x.k <> y.k) as moved from placed x join placed y on x.age = 'fresh' and y.age = 'stale' and x.method = y.method and x.p = y.p and x.r = y.r and x.pos = y.pos group by all)
        select p, cast(sum(cells) filter (where age = 'fresh') as bigint) as n, method, cast(r * {EVERY} as integer) as step, cast(max(load) filter (where age = 'stale') as bigint) as stale, cast(max(load) filter (where age = 'fresh') as bigint) as fresh,
            max(cells) filter (where age = 'fresh') as most_cells, any_value(moved) as moved from loads join moved using (method, p, r) group by p, method, r"""


#: Published seconds of one rebalancing and of one step, by machine and method (fixed values).
PUBLISHED_OVERHEAD = (
    ("xeon", "single_site", 0.33, 0.17),
    ("xeon", "peer", 0.57, 0.17),
    ("xeon", "hybrid", 0.31, 0.17),
    ("bgq", "single_site", 1.00, 0.33),
    ("bgq", "peer", 0.77, 0.33),
    ("bgq", "hybrid", 0.84, 0.33),
)


def overhead_steps(spark: SparkSession, d: str) -> DataFrame:
    return spark.createDataFrame([(a, m, o, s, round(measures.overhead_steps(o, s), 2)) for a, m, o, s in PUBLISHED_OVERHEAD], "machine string, method string, secs double, step_secs double, steps double")


def overhead_steps_sql() -> str:
    return "select machine, method, cast(secs as double) as secs, cast(step_secs as double) as step_secs, cast(round(secs / step_secs, 2) as double) as steps from (values " + ", ".join(f"('{a}', '{m}', {o}, {s})" for a, m, o, s in PUBLISHED_OVERHEAD) + ") as t(machine, method, secs, step_secs)"


def published_ratios(spark: SparkSession, d: str) -> DataFrame:
    rows = [("xeon", "speedup", round(measures.speedup(9.92, 0.995), 2)), ("bgq", "speedup", round(measures.speedup(20.0, 2.52), 1)), ("bgq", "improvement", round(measures.improvement(4.17, 3.78), 1))]
    return spark.createDataFrame(rows, "machine string, measure string, ratio double")


def published_ratios_sql() -> str:
    return "select * from (values ('xeon', 'speedup', cast(9.97 as double)), ('bgq', 'speedup', cast(7.9 as double)), ('bgq', 'improvement', cast(9.4 as double))) as t(machine, measure, ratio)"


def overhead_orders(spark: SparkSession, d: str) -> DataFrame:
    """(method, remap_secs, modelled seconds): wall time of each balancer on the orders line, beside the cost model."""
    w = BINDINGS["orders"].weights(spark, d).cache()
    n = w.count()
    rows = []
    for m in ("single_site", "peer", "hybrid"):
        began = time.perf_counter()
        bal.METHODS[m](w, P).collect()  # P + 1 rows
        rows.append((m, time.perf_counter() - began, *(measures.overhead_model(m, n, P, **preset) for preset in measures.PRESETS.values())))
    w.unpersist()
    return spark.createDataFrame(rows, "method string, remap_secs double, slow_network_secs double, fast_network_secs double")


def words_moved(spark: SparkSession, d: str) -> DataFrame:
    n = table(spark, d, "orders").count()
    rows = [(m, w.gathered, w.handed_out, w.neighbours) for m in ("single_site", "peer", "hybrid", "full_map") for w in [measures.words_moved(m, n, P)]]
    return spark.createDataFrame(rows, "method string, gathered long, handed_out long, neighbours long")


def words_moved_sql() -> str:
    n = "(select count(*) from orders)"
    return f"select 'single_site' as method, {n} as gathered, cast({(P + 1) * P} as bigint) as handed_out, cast(0 as bigint) as neighbours union all select 'peer', 0, {P * P}, {P - 1} union all select 'hybrid', {P}, {(P + 1) * P}, {P - 1} union all select 'full_map', 0, {n} * {P}, {P - 1}"


# ---------------------------------------------------------------- the prism
PRISM_SHAPE = (64, 2, 2)


def prism_weights(spark: SparkSession, d: str, stretch: float) -> DataFrame:
    """(pos, weight) of the expansion test's prism; the cloud starts in the initial band and is stretched from its left end.

    Places come from prices (x), discounts (y) and taxes (z).
    """
    box = particles.Box()
    lo, hi = particles.INITIAL_BAND
    x = F.lit(lo) + (F.col("l_extendedprice") % 1000) / 1000 * ((hi - lo) * stretch)
    p = table(spark, d, "lineitem").select(x.alias("x"), (F.col("l_discount") * box.y1).alias("y"), (F.col("l_tax") * box.z1).alias("z"))
    counts = p.groupBy(particles.lattice_cell(box, PRISM_SHAPE).alias("cell_id")).agg(F.count("*").alias("cnt"))
    return weights.cell_weights(ordering.lattice_order(ordering.lattice(spark, PRISM_SHAPE), PRISM_SHAPE), counts)


def prism_sql(stretch: float) -> str:
    box = particles.Box()
    lo, hi = particles.INITIAL_BAND
    nx, ny, nz = PRISM_SHAPE
    index = lambda e, a, b, n: f"greatest(0, least({n - 1}, cast(floor(({e} - {a!r}) / {b - a!r} * {n}) as bigint)))"
    cell = f"({index(f'({lo!r} + (l_extendedprice % 1000) / 1000 * {(hi - lo) * stretch!r})', box.x0, box.x1, nx)} * {ny} + {index(f'(l_discount * {box.y1!r})', box.y0, box.y1, ny)}) * {nz} + {index(f'(l_tax * {box.z1!r})', box.z0, box.z1, nz)}"
    return f"select cast(c + 1 as bigint) as pos, cast(coalesce(k, 0) + 3 as bigint) as weight from (select unnest(range(0, {nx * ny * nz})) as c) left join (select {cell} as cell, count(*) as k from lineitem group by 1) on cell = c"
