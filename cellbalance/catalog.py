"""Every query by name: a callable (spark, sf_dir) -> DataFrame, and DuckDB SQL where SQL can express it.

Names: ``w_*`` weights, ``order_*``, ``scan_*``, ``<method>_<binding>`` cut vectors, ``slot_loads_*`` and ``imbalance_*`` measures,
``op_*`` surroundings; the others are named after the method, measure or experiment they run.
"""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .operators import balance as bal
from .operators import cuts as cut
from .operators import maps, measures, migrate, ordering, particles, scan, weights
from .plans import oracle as sql
from .plans import simulate, steps, trigger, workloads
from .sources.bindings import BAND_DAYS, BINDINGS, DAY_ZERO, DAYS, ship_day
from .sources.tables import event_stream, table
from .streaming import triggers as streams

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}
METHODS = ("uniform", "single_site", "peer", "hybrid")
CUT_BINDINGS = ("orders", "part", "fan", "documents", "pages", "conversations", "supplier")
#: Caps of the capped queries, in cells, at about 1.25 times the mean of the binding at sf0.01 for each.
CAP_FACTOR = (5, 4)


def register(name: str, oracle: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if oracle is not None:
            ORACLE_SQL[name] = oracle
        return f

    return keep


def _w(name: str, spark: SparkSession, d: str) -> DataFrame:
    return BINDINGS[name].weights(spark, d)


def _cap(n: int, p: int) -> int:
    """1.25 times the mean number of cells, rounded up."""
    return -(-n * CAP_FACTOR[0] // (p * CAP_FACTOR[1]))


# ---------------------------------------------------------------- weights
for _name, _b in BINDINGS.items():
    register(f"w_{_name}", _b.sql)(_b.weights)


@register("calibrate_base", "select round(avg(case when event_type = 'click' then value end) / avg(case when event_type = 'view' then value end), 9) as base_cost from events")
def _(spark, d):
    """Clicks stand for timings of cells, views for timings of particles."""
    kind = F.when(F.col("event_type") == "click", "cell").when(F.col("event_type") == "view", "particle")
    samples = table(spark, d, "events").select(kind.alias("kind"), F.col("value").alias("secs"))
    return weights.calibrate_base_cost(samples).select(F.round("base_cost", 9).alias("base_cost"))


@register("total_identity", f"select cast((select sum(weight) from ({BINDINGS['orders'].sql})) as bigint) as by_weights, cast((select count(*) from lineitem) + 3 * (select count(*) from orders) as bigint) as by_counts")
def _(spark, d):
    counts = weights.particle_counts(table(spark, d, "lineitem"), "l_orderkey")
    n = table(spark, d, "orders").agg(F.count("*").alias("n"))
    other = weights.total_from_counts(counts, n, 3)
    return weights.total_weight(_w("orders", spark, d)).select(F.col("total").alias("by_weights"), other.scalar().alias("by_counts"))


@register("fluid_cost", "select n, count(*) as cells, cast(n as double) ** 4 as relative from (select cast(l_quantity as bigint) as n from lineitem) group by n")
def _(spark, d):
    """Lines of orders as cells, their quantity as grid points per axis."""
    cells = table(spark, d, "lineitem").groupBy(F.col("l_quantity").cast("long").alias("n")).agg(F.count("*").alias("cells"))
    return cells.select("n", "cells", weights.fluid_cost(F.col("n")).alias("relative"))


_CURTAIN_CELLS = 100
_CURTAIN_X = "cast(event_id % 1000 as double) / 1000"


def _curtain(spark, d, t: int, growth: float = 1 + 1 / 3):
    """Cells of the curtain box in x, weights behind the front, after t steps of dt = 1."""
    x = F.col("event_id") % 1000 / 1000 * growth**t
    counts = table(spark, d, "events").groupBy(F.least(F.lit(_CURTAIN_CELLS - 1), F.floor(x / 10 * _CURTAIN_CELLS)).cast("long").alias("cell_id")).agg(F.count("*").alias("cnt"))
    cells = spark.range(_CURTAIN_CELLS).select(F.col("id").alias("cell_id"), (F.col("id") + 1).alias("pos"), (F.col("id") * 10 / _CURTAIN_CELLS).alias("x_left"))
    return weights.front_weights(cells, counts, 3, float(t))


def _curtain_sql(t: int) -> str:
    growth = (1 + 1 / 3) ** t
    return f"""select c + 1 as pos, cast(coalesce(k, 0) + case when c * 10 / {_CURTAIN_CELLS} <= exp({t / 2}) then 3 else 0 end as bigint) as weight
        from (select unnest(range(0, {_CURTAIN_CELLS})) as c) left join
        (select least({_CURTAIN_CELLS - 1}, cast(floor(({_CURTAIN_X}) * {growth!r} / 10 * {_CURTAIN_CELLS}) as bigint)) as cell, count(*) as k from events group by 1) on cell = c"""


@register("front_weights", _curtain_sql(3))
def _(spark, d):
    return _curtain(spark, d, 3)


# ---------------------------------------------------------------- orders
@register("order_key", "select o_orderkey as cell_id, o_orderkey + 1 as pos from orders")
def _(spark, d):
    return ordering.key_order(table(spark, d, "orders"), "o_orderkey")


_BOX = (16, 4, 2)
_BOX_CELLS = f"select c as cell_id, c // {_BOX[1] * _BOX[2]} as ix, (c // {_BOX[2]}) % {_BOX[1]} as iy, c % {_BOX[2]} as iz from (select unnest(range(0, {_BOX[0] * _BOX[1] * _BOX[2]})) as c)"


@register("order_lattice", f"select cell_id, cell_id + 1 as pos from ({_BOX_CELLS})")
def _(spark, d):
    return ordering.lattice_order(ordering.lattice(spark, _BOX), _BOX)


@register("order_lattice_bisect", "select c as cell_id, c + 1 as pos from (select unnest(range(0, 64)) as c)")
def _(spark, d):
    """On a one-cell-wide prism halving the longest axis gives the cells from left to right."""
    return ordering.lattice_order(ordering.lattice(spark, (64, 1, 1)), (64, 1, 1), "bisect")


@register("order_lattice_bisect_box")
def _(spark, d):
    return ordering.lattice_order(ordering.lattice(spark, _BOX), _BOX, "bisect")


@register("order_morton", f"select cell_id, row_number() over (order by {' + '.join(f'(((ix >> {b}) & 1) << {3 * b + 2}) + (((iy >> {b}) & 1) << {3 * b + 1}) + (((iz >> {b}) & 1) << {3 * b})' for b in range(5))}, cell_id) as pos from ({_BOX_CELLS})")
def _(spark, d):
    return ordering.curve_order(ordering.lattice(spark, _BOX), ["ix", "iy", "iz"], bits=5)


@register("order_hilbert")
def _(spark, d):
    return ordering.curve_order(ordering.lattice(spark, (16, 16, 1)), ["ix", "iy"], "hilbert", bits=4)


@register("order_spectral_prism", "select c as cell_id, c + 1 as pos from (select unnest(range(0, 64)) as c)")
def _(spark, d):
    return ordering.spectral_order(ordering.lattice_edges(spark, (64, 1, 1)), ordering.lattice(spark, (64, 1, 1)))


#: A path of cells whose ids are scattered by a fixed permutation (multiplication modulo a prime).
_PATH, _SCATTER = 5003, 2111


@register("order_spectral_scattered_path", f"select cast(i * {_SCATTER} % {_PATH} as bigint) as cell_id, cast(i + 1 as bigint) as pos from (select unnest(range(0, {_PATH})) as i)")
def _(spark, d):
    """The line of a path comes back, up to reversal: it is turned so that cell 0, the path's first, has the first place."""
    at = lambda i: (i * _SCATTER % _PATH).cast("long")
    line = spark.range(_PATH)
    cells = line.select(at(F.col("id")).alias("cell_id"))
    edges = line.filter(F.col("id") < _PATH - 1).select(at(F.col("id")).alias("a"), at(F.col("id") + 1).alias("b"))
    return ordering.spectral_order(edges, cells)


@register("order_spectral_box")
def _(spark, d):
    return ordering.spectral_order(ordering.lattice_edges(spark, _BOX), ordering.lattice(spark, _BOX))


def _vec_cells(spark, d):
    """Embeddings as cells: their first three components on a grid of 8 steps each."""
    scaled = lambda i: F.least(F.lit(7), F.greatest(F.lit(0), F.floor((F.get("embedding", F.lit(i)) + 2) * 2))).cast("int")
    return table(spark, d, "embeddings").select(F.col("vec_id").alias("cell_id"), *(scaled(i).alias(c) for i, c in enumerate(("ix", "iy", "iz"))))


@register("order_spectral_vec")
def _(spark, d):
    """Embeddings in the same or a neighbouring grid cell in x count as neighbours, chained by id."""
    cells = _vec_cells(spark, d)
    chain = Window.partitionBy("ix", "iy").orderBy("iz", "cell_id")
    inside = cells.select(F.lag("cell_id").over(chain).alias("a"), F.col("cell_id").alias("b")).filter("a is not null")
    heads = cells.groupBy("ix", "iy").agg(F.min("cell_id").alias("h"))
    between = heads.select(F.lag("h").over(Window.orderBy("ix", "iy")).alias("a"), F.col("h").alias("b")).filter("a is not null")  # at most 64 rows
    return ordering.spectral_order(inside.unionByName(between), cells)


_EDGES = f"""select cell_id as a, cell_id + {_BOX[1] * _BOX[2]} as b from ({_BOX_CELLS}) where ix < {_BOX[0] - 1} union all
    select cell_id, cell_id + {_BOX[2]} from ({_BOX_CELLS}) where iy < {_BOX[1] - 1} union all select cell_id, cell_id + 1 from ({_BOX_CELLS}) where iz < {_BOX[2] - 1}"""


#: Orders as cells of a box lattice of (25, 4) cells across: steps to the neighbours, and where there is one.
_FACES = ((100, "true"), (4, "k // 4 % 25 < 24"), (1, "k % 4 < 3"))


@register("line_locality", "with o as (select o_orderkey as k from orders) select round(avg(d), 9) as mean_distance, cast(max(d) as bigint) as max_distance from (" + " union all ".join(f"select {s} as d from o where {w} and k + {s} in (select k from o)" for s, w in _FACES) + ")")
def _(spark, d):
    key = F.col("o_orderkey")
    cells = table(spark, d, "orders").select(key.alias("cell_id"), F.expr("o_orderkey div 100").alias("ix"), F.expr("o_orderkey div 4 % 25").alias("iy"), (key % 4).alias("iz"))
    faces = F.array(*(F.when(F.expr(w.replace("//", "div").replace("k", "cell_id")), F.col("cell_id") + s) for s, w in _FACES))
    edges = cells.select(F.col("cell_id").alias("a"), F.explode(faces).alias("b")).filter("b is not null")
    return ordering.line_locality(edges, ordering.lattice_order(cells, (0, 25, 4)))  # a step off the end finds no order


@register("dense_pos_documents", "select doc_id as cell_id, row_number() over (order by doc_id) as pos from documents")
def _(spark, d):
    return ordering.dense_pos(table(spark, d, "documents"), "doc_id")


# ---------------------------------------------------------------- scans
def _scan_sql(name: str) -> str:
    return f"select pos, weight, s - weight as s_prev, s, t as total, n from ({sql.scan(BINDINGS[name].sql)})"


register("scan_single_site_orders", _scan_sql("orders"))(lambda spark, d: scan.scan_single_site(_w("orders", spark, d)))
register("scan_blocks_orders", _scan_sql("orders"))(lambda spark, d: scan.scan_blocks(_w("orders", spark, d), 1024))
register("scan_two_levels_orders", _scan_sql("orders"))(lambda spark, d: scan.scan_blocks(_w("orders", spark, d), 64, levels=2))
register("scan_blocks_documents", _scan_sql("documents"))(lambda spark, d: scan.scan_blocks(_w("documents", spark, d), 128))

_ORD = BINDINGS["orders"].sql
_UNIFORM_ORD, _SINGLE_ORD, _PEER_ORD = (sql.cuts(m, _ORD, 16) for m in ("uniform", "single_site", "peer"))


@register("owner_offsets_orders", f"select slot, load, cast(sum(load) over (order by slot) - load as bigint) as before from ({sql.loads(_ORD, _UNIFORM_ORD)})")
def _(spark, d):
    w = _w("orders", spark, d)
    return scan.owner_offsets(w, maps.cuts_to_map(w, cut.cuts_uniform(w, 16)).select("pos", "slot"))


# ---------------------------------------------------------------- cuts, loads, imbalance
def _capped_query(method: str, name: str, p: int, strict: bool):
    def run(spark, d):
        w = _w(name, spark, d)
        return bal.METHODS[method](w, p, cap=_cap(w.count(), p), strict=strict)

    return run


def _capped_sql(method: str, name: str, p: int, strict: bool) -> str:
    cap = f"((select count(*) from ({BINDINGS[name].sql})) * {CAP_FACTOR[0]} + {p * CAP_FACTOR[1]} - 1) // {p * CAP_FACTOR[1]}"
    return sql.cuts(method, BINDINGS[name].sql, p, f"({cap})", strict)


for _name in CUT_BINDINGS:
    _b = BINDINGS[_name]
    for _m in METHODS:
        register(f"{_m}_{_name}", sql.cuts(_m, _b.sql, _b.p))(lambda spark, d, m=_m, b=_b: bal.METHODS[m](b.weights(spark, d), b.p))
        if _m != "uniform":
            register(f"{_m}_cap_{_name}", _capped_sql(_m, _name, _b.p, False))(_capped_query(_m, _name, _b.p, False))
    for _m in ("uniform", "single_site", "peer"):
        _loads = sql.loads(_b.sql, sql.cuts(_m, _b.sql, _b.p))
        register(f"slot_loads_{_m}_{_name}", _loads)(lambda spark, d, m=_m, b=_b: (lambda w: measures.slot_loads(w, bal.METHODS[m](w, b.p)))(b.weights(spark, d)))

    def _imbalance(spark, d, b=_b):
        w = b.weights(spark, d)
        rows = [measures.imbalance(measures.slot_loads(w, bal.METHODS[m](w, b.p))).select(F.lit(m).alias("method"), "*") for m in ("uniform", "single_site", "peer")]
        return rows[0].unionByName(rows[1]).unionByName(rows[2])

    register(f"imbalance_{_name}", " union all ".join(f"select '{m}' as method, * from ({sql.imbalance(sql.loads(_b.sql, sql.cuts(m, _b.sql, _b.p)))})" for m in ("uniform", "single_site", "peer")))(_imbalance)

register("strict_cap_fan", _capped_sql("single_site", "fan", 16, True))(_capped_query("single_site", "fan", 16, True))
register("strict_cap_peer_fan", _capped_sql("peer", "fan", 16, True))(_capped_query("peer", "fan", 16, True))
register("single_site_one_task_orders", _SINGLE_ORD)(lambda spark, d: bal.balance_single_site(_w("orders", spark, d), 16, scan="single"))


@register("peer_units_orders", _PEER_ORD)
def _(spark, d):
    """Weights in thousandths with the unit to match: the same cuts."""
    return bal.balance_peer(_w("orders", spark, d).withColumn("weight", F.col("weight") * 1000), 16, unit=1000)


@register("first_cells_orders", f"select slot, first_pos from ({sql.intervals(_PEER_ORD)}) where last_pos >= first_pos".replace("select slot", "select cast(slot as integer) as slot", 1))
def _(spark, d):
    return cut.first_cells(bal.peer_map(_w("orders", spark, d), 16).select("pos", "slot"), 1024)


_MAP_PEER = sql.cell_map(_ORD, _PEER_ORD)
register("full_map_orders", _MAP_PEER)(lambda spark, d: bal.share_full_map(_w("orders", spark, d), 16))
register("rebalance_orders", sql.cell_map(_ORD, _SINGLE_ORD))(lambda spark, d: bal.rebalance(_w("orders", spark, d), 16, "single_site"))
register("initial_balance_orders", f"select k, b, 0 as version from ({_SINGLE_ORD})")(lambda spark, d: bal.initial_balance(_w("orders", spark, d), 16))


@register("map_from_cuts_orders", _MAP_PEER)
def _(spark, d):
    w = _w("orders", spark, d)
    return maps.cuts_to_map(w, bal.balance_peer(w, 16), 512)


@register("cuts_from_map_orders", _PEER_ORD)
def _(spark, d):
    w = _w("orders", spark, d)
    return maps.map_to_cuts(maps.cuts_to_map(w, bal.balance_peer(w, 16)), 16)


@register("check_map_orders", "select true as contiguous, true as covers, true as in_range, true as within_cap")
def _(spark, d):
    w = _w("orders", spark, d)
    return maps.check_map(maps.cuts_to_map(w, bal.balance_single_site(w, 16)), 16, cap=w.count())


def _optimal_sql(weights_sql: str, p: int) -> str:
    """The smallest possible slowest slot by dynamic programming over slots; the cuts fill each slot as far as that allows."""
    best = ["b1 as materialized (select pos, s as worst from sc)"]
    best += [f"b{k} as materialized (select y.pos, min(greatest(x.worst, y.s - z.s)) as worst from sc y join sc z on z.pos <= y.pos join b{k - 1} x on x.pos = z.pos group by y.pos)" for k in range(2, p + 1)]
    return f"""with recursive sc as materialized (select pos, s from ({sql.scan(weights_sql)}) union all select 0, 0), {", ".join(best)},
        most as materialized (select worst from b{p} where pos = (select max(pos) from sc)),
        r(k, b) as (select 0, cast(0 as bigint) union all select k + 1, (select max(pos) from sc where s <= (select worst from most) + (select s from sc h where h.pos = r.b)) from r where k < {p - 1})
        select cast(k as integer) as k, b from r union all select {p}, (select max(pos) from sc)"""


@register("optimal_cuts_fan", _optimal_sql(BINDINGS["fan"].sql, 16))
def _(spark, d):
    return bal.cuts_optimal(_w("fan", spark, d), 16)


# ---------------------------------------------------------------- moving
def _old_new(spark, d, name: str = "orders", p: int = 16):
    w = _w(name, spark, d)
    to_map = lambda c: maps.cuts_to_map(w, c).select("pos", "slot")
    return w, to_map(cut.cuts_uniform(w, p)), to_map(bal.balance_single_site(w, p))


_PLAN = sql.transfer_plan(_ORD, _UNIFORM_ORD, _SINGLE_ORD)


@register("transfer_plan_orders", _PLAN)
def _(spark, d):
    _w_, old, new = _old_new(spark, d)
    return migrate.transfer_plan(old, new)


@register("transfer_ranges_orders", f"select src, dst, min(pos) as first_pos, max(pos) as last_pos from ({_PLAN}) group by src, dst")
def _(spark, d):
    w = _w("orders", spark, d)
    return migrate.transfer_ranges(cut.cuts_uniform(w, 16), bal.balance_single_site(w, 16))


@register("transfer_particles_orders", f"select src, dst, count(*) as particles, round(sum(l_quantity), 6) as quantity from ({_PLAN}) join lineitem on l_orderkey = pos - 1 group by src, dst")
def _(spark, d):
    _w_, old, new = _old_new(spark, d)
    lines = table(spark, d, "lineitem").select((F.col("l_orderkey") + 1).alias("pos"), "l_quantity")
    return migrate.particles_to_move(migrate.transfer_plan(old, new), lines).groupBy("src", "dst").agg(F.count("*").alias("particles"), F.round(F.sum("l_quantity"), 6).alias("quantity"))


_FAN = BINDINGS["fan"].sql
_FAN_PLAN = sql.transfer_plan(_FAN, sql.cuts("uniform", _FAN, 16), sql.cuts("single_site", _FAN, 16))
CELL_BYTES, PARTICLE_BYTES = 5 * 5**3 * 8, 8 * 8


@register("transfer_matrix_fan", f"select src, dst, count(*) as cells, cast(sum(weight - 3) as bigint) as particles, cast(count(*) * {CELL_BYTES} + sum(weight - 3) * {PARTICLE_BYTES} as bigint) as bytes from ({_FAN_PLAN}) p join ({_FAN}) w on p.pos = w.pos group by cube (src, dst)")
def _(spark, d):
    w, old, new = _old_new(spark, d, "fan")
    return migrate.transfer_matrix(migrate.transfer_plan(old, new), w.select("pos", (F.col("weight") - 3).alias("cnt")), CELL_BYTES, PARTICLE_BYTES)


@register("migrate_placement", f"select slot, cells, cast(0 as bigint) as misplaced from ({sql.loads(_ORD, _SINGLE_ORD)}) where cells > 0")
def _(spark, d):
    w, _old, new = _old_new(spark, d)
    placed = migrate.migrate(w, new, 16).withColumn("partition", F.spark_partition_id())
    return placed.groupBy("slot").agg(F.count("*").alias("cells"), F.count_if(F.col("partition") != F.col("slot")).alias("misplaced"))


@register("pack_unpack_orders", f"select pos, weight, src, dst from ({_PLAN}) join ({_ORD}) using (pos)")
def _(spark, d):
    w, old, new = _old_new(spark, d)
    return migrate.unpack(migrate.pack(migrate.transfer_plan(old, new).join(w, "pos"), ["weight"])).select("pos", "weight", "src", "dst")


@register("reattach_static_customer", f"select slot, c_mktsegment, n_name, count(*) as cells from ({sql.cell_map(BINDINGS['customer'].sql, sql.cuts('single_site', BINDINGS['customer'].sql, 16))}) join customer on c_custkey = pos - 1 join nation on n_nationkey = c_nationkey group by all")
def _(spark, d):
    w, _old, new = _old_new(spark, d, "customer")
    static = table(spark, d, "customer").select((F.col("c_custkey") + 1).alias("pos"), "c_mktsegment", "c_nationkey")
    moved = migrate.reattach_static(migrate.migrate(w, new, 16), static, "pos")
    named = migrate.reattach_static(moved, table(spark, d, "nation").select(F.col("n_nationkey").alias("c_nationkey"), "n_name"), "c_nationkey")
    return named.groupBy("slot", "c_mktsegment", "n_name").agg(F.count("*").alias("cells"))


@register("shared_faces_grid", f"with e as ({_EDGES}) select slot, count(*) as faces from (select a // 8 as x, b // 8 as y from e where a // 8 <> b // 8) t, lateral (select unnest([x, y]) as slot) group by slot".replace("select slot,", "select cast(slot as integer) as slot,", 1))
def _(spark, d):
    """A box lattice on 16 slots of eight cells each."""
    cells = ordering.lattice_order(ordering.lattice(spark, _BOX), _BOX)
    edges = ordering.lattice_edges(spark, _BOX).select((F.col("a") + 1).alias("a"), (F.col("b") + 1).alias("b"))
    return migrate.shared_faces(edges, cells.select("pos", F.expr("cast((pos - 1) div 8 as int)").alias("slot")))


@register("conservation_orders", "select cast(0 as bigint) as lost, cast(0 as bigint) as gained")
def _(spark, d):
    w, _old, new = _old_new(spark, d)
    lines = table(spark, d, "lineitem").select((F.col("l_orderkey") + 1).alias("pos"), "l_linenumber", "l_quantity", "l_extendedprice")
    return migrate.check_migration(lines, migrate.migrate(lines, new, 16))


# ---------------------------------------------------------------- particles
@register("interp_polynomial", "select count(*) as points, true as exact from lineitem")
def _(spark, d):
    """Values of x*y + z*z - 2*x, given on the nodes of a cell, at places read from lineitem: exact."""
    from .functions.interpolation import lobatto_nodes

    n = 5
    nodes = [float(v) for v in lobatto_nodes(n)]
    field = F.array(*(F.lit(x * y + z * z - 2 * x) for z in nodes for y in nodes for x in nodes))
    places = table(spark, d, "lineitem").select((F.col("l_discount") * 2 - 1).alias("rx"), (F.col("l_tax") * 2 - 1).alias("ry"), (F.col("l_quantity") / 50 * 2 - 1).alias("rz"), F.lit(0).cast("long").alias("cell_id"))
    fields = spark.range(1).select(F.col("id").alias("cell_id"), field.alias("field"))
    want = F.col("rx") * F.col("ry") + F.col("rz") * F.col("rz") - 2 * F.col("rx")
    return particles.interpolate(places, fields, n).agg(F.count("*").alias("points"), F.min(F.abs(F.col("u") - want) < 1e-9).alias("exact"))


_Z = 0.1


@register("rk3_drag", f"select event_id, round(1.0 + (value - 1.0) * ({particles.drag_factor(_Z, 1.0)!r}), 9) as vx from events")
def _(spark, d):
    """One step of drag towards a gas velocity of 1: the gap shrinks by a known factor."""
    p = table(spark, d, "events").select("event_id", F.lit(0.0).alias("x"), F.col("value").alias("vx"), F.lit(1.0).alias("u"))
    return particles.advance_drag(p, _Z, 1.0).select("event_id", F.round("vx", 9).alias("vx"))


@register("euler_expand", f"select event_id, round({_CURTAIN_X} * {(1 + 0.3 / 3) ** 4!r}, 9) as x from events")
def _(spark, d):
    p = table(spark, d, "events").select("event_id", (F.col("event_id") % 1000 / 1000).alias("x"))
    for _i in range(4):
        p = particles.advance_euler(p, 0.3)
    return p.select("event_id", F.round("x", 9).alias("x"))


@register("fan_velocity", "select event_id, e as x10, round(case when (e / 10.0 - 0.5) / 0.01 <= -sqrt(1400.0) then 0 else least(2 / 2.4 * (sqrt(1400.0) + (e / 10.0 - 0.5) / 0.01), 2 * sqrt(1400.0) / 0.4) end, 6) as u from (select event_id, event_id % 30 - 10 as e from events)")
def _(spark, d):
    """Gas velocity at 30 places beside the diaphragm, on which the events lie as particles."""
    p = table(spark, d, "events").select("event_id", (F.col("event_id") % 30 - 10).alias("x10"))
    return p.select("event_id", "x10", F.round(particles.fan_velocity(F.col("x10") / 10, 0.01), 6).alias("u"))


_REL_OLD = "event_id % 100 + 1"
_REL_NEW = "least(99, ((event_id % 100) * 5 + 1) // 4) + 1"
_REL_SLOTS = 10


def _relocated(spark, d):
    cells = spark.range(1, 101).select(F.col("id").alias("pos"), F.expr(f"cast((id - 1) div {100 // _REL_SLOTS} as int)").alias("slot"))
    p = table(spark, d, "events").select("event_id", F.expr(_REL_OLD).alias("pos"))
    return particles.relocate(p, F.expr("least(99, ((event_id % 100) * 5 + 1) div 4) + 1"), cells)


@register("relocate_events", f"select event_id, {_REL_OLD} as pos, {_REL_NEW} as new_pos, cast((event_id % 100) // 10 as integer) as src, cast(({_REL_NEW} - 1) // 10 as integer) as dst from events")
def _(spark, d):
    return _relocated(spark, d).select("event_id", "pos", "new_pos", "src", "dst")


@register("handover_events", f"select src, dst, count(*) as particles from (select cast((event_id % 100) // 10 as integer) as src, cast(({_REL_NEW} - 1) // 10 as integer) as dst from events) where src <> dst group by src, dst")
def _(spark, d):
    return particles.handover_matrix(_relocated(spark, d))


register("curtain_step", _curtain_sql(1))(lambda spark, d: _curtain(spark, d, 1))

_CURTAIN_STEPS = (0, 1, 2, 4)
register("curtain_trace", " union all ".join(f"select {t} as t, '{m}' as method, max(load) as step from ({sql.loads(_curtain_sql(t), sql.cuts(m, _curtain_sql(t), 8))})" for t in _CURTAIN_STEPS for m in ("uniform", "single_site", "peer")))(
    lambda spark, d: workloads.union(
        measures.slot_loads(w, bal.METHODS[m](w, 8)).agg(F.max("load").alias("step")).select(F.lit(t).alias("t"), F.lit(m).alias("method"), "step") for t in _CURTAIN_STEPS for w in [_curtain(spark, d, t)] for m in ("uniform", "single_site", "peer")
    )
)

# ---------------------------------------------------------------- prism of the expansion test
register("prism_initial_weights", workloads.prism_sql(1.0))(lambda spark, d: workloads.prism_weights(spark, d, 1.0))
register("prism_expand", workloads.prism_sql(1.5))(lambda spark, d: workloads.prism_weights(spark, d, 1.5))


@register("expand_dims", " union all ".join(f"select {n} as dims, round(sum(x), 3) as sx, round(sum(y), 3) as sy, round(sum(z), 3) as sz from (select l_discount * {1.1 if n >= 1 else 1.0} as x, l_tax * {1.1 if n >= 2 else 1.0} as y, l_quantity * {1.1 if n >= 3 else 1.0} as z from lineitem)" for n in (1, 2, 3)))
def _(spark, d):
    base = table(spark, d, "lineitem").select(F.col("l_discount").alias("x"), F.col("l_tax").alias("y"), F.col("l_quantity").alias("z"))
    moved = lambda n: particles.advance_euler(base, 0.3, ("x", "y", "z")[:n])
    return workloads.union(moved(n).agg(F.round(F.sum("x"), 3).alias("sx"), F.round(F.sum("y"), 3).alias("sy"), F.round(F.sum("z"), 3).alias("sz")).select(F.lit(n).alias("dims"), "sx", "sy", "sz") for n in (1, 2, 3))


# ---------------------------------------------------------------- triggers
_TYPE_TRACE, _USER_TRACE = sql.numbered("event_type"), sql.numbered("user_id")


def _trace(spark, d, run: str = "event_type"):
    return trigger.numbered(table(spark, d, "events"), run)


def _rounded(decisions: DataFrame) -> DataFrame:
    return decisions.select("run_id", "step", "reason", F.round("tau", 6).alias("tau"), "epoch_len")


#: Events of a larger value count as slow; a run degrades by a number of seconds a step times their share.
_SLOW = 20


def _slopes(spark, d, unit: float):
    slow, n = F.count_if(F.col("value") > _SLOW).cast("double"), F.count("*").cast("double")
    return table(spark, d, "events").groupBy(F.col("event_type").alias("run_id")).agg((F.lit(unit) * slow / n).alias("slope"))


def _slopes_sql(unit: float) -> str:
    return f"select event_type as run_id, cast({unit} as double) * cast(count(*) filter (value > {_SLOW}) as double) / cast(count(*) as double) as slope from events group by 1"


register("never_events", f"select run_id, round(sum(secs), 4) as step_secs, cast(0 as double) as lb_secs, round(sum(secs), 4) as total from ({_TYPE_TRACE}) group by run_id")(
    lambda spark, d: (lambda t: measures.amortised_total(t, trigger.policy_never(t), 500.0).select("run_id", *(F.round(c, 4).alias(c) for c in ("step_secs", "lb_secs", "total"))))(_trace(spark, d))
)
register("once_events", f"select distinct run_id, cast(0 as bigint) as step from ({_TYPE_TRACE})")(lambda spark, d: trigger.policy_once(_trace(spark, d)))
register("fixed_k_events", f"select run_id, step from ({_TYPE_TRACE}) where step % 500 = 0")(lambda spark, d: trigger.policy_fixed(_trace(spark, d), 500))
register("suggest_k_events", f"select run_id, round(case when regr_slope(secs, step) > 0 then sqrt(2 * 500 / regr_slope(secs, step)) end, 4) as k from ({_TYPE_TRACE}) group by run_id")(lambda spark, d: trigger.suggest_k(_trace(spark, d), 500.0).select("run_id", F.round("k", 4).alias("k")))
register("recent_median_events", f"select run_id, step, round(median(secs) over (partition by run_id order by step rows between 2 preceding and current row), 9) as t2 from ({_TYPE_TRACE})")(lambda spark, d: trigger.recent_median(_trace(spark, d)).select("run_id", "step", F.round("t2", 9).alias("t2")))
register("phase_mean_events", f"select run_id, round(avg(secs), 9) as t1, cast(50 as bigint) as midpoint from ({_TYPE_TRACE}) where step <= 100 group by run_id")(lambda spark, d: trigger.phase_mean(_trace(spark, d)).select("run_id", F.round("t1", 9).alias("t1"), "midpoint"))
register("phase_means_every_500", f"select run_id, cast((step - 1) // 500 * 500 as bigint) as epoch_start, round(avg(secs), 9) as t1, cast((step - 1) // 500 * 500 + 50 as bigint) as midpoint from ({_TYPE_TRACE}) where (step - 1) % 500 < 100 group by 1, 2, 4")(
    lambda spark, d: trigger.phase_means(_trace(spark, d), trigger.policy_fixed(_trace(spark, d), 500)).select("run_id", "epoch_start", F.round("t1", 9).alias("t1"), "midpoint")
)
register("adaptive_events_type", sql.decisions(500, trace=_TYPE_TRACE))(lambda spark, d: _rounded(trigger.adaptive_triggers(_trace(spark, d), trigger.Rule(500))))
register("adaptive_events_user", sql.decisions(500, eval_len=10, trace=_USER_TRACE))(lambda spark, d: _rounded(trigger.adaptive_triggers(_trace(spark, d, "user_id"), trigger.Rule(500, eval_len=10))))
register("adaptive_interval_only", sql.decisions(500, trace=_TYPE_TRACE, use_loss=False))(lambda spark, d: _rounded(trigger.adaptive_triggers(_trace(spark, d), trigger.Rule(500, use_loss=False))))
register("adaptive_loss_only", sql.decisions(500, trace=_TYPE_TRACE, use_interval=False))(lambda spark, d: _rounded(trigger.adaptive_triggers(_trace(spark, d), trigger.Rule(500, use_interval=False))))
register("adaptive_drift", sql.decisions(20, drift=(1.0, None, 0), slopes=_slopes_sql(0.0003), steps=3000))(lambda spark, d: _rounded(trigger.drift_runs(_slopes(spark, d, 0.0003), trigger.Rule(20), 3000)))
register("adaptive_stream_type", sql.decisions(500, trace=_TYPE_TRACE))(lambda spark, d: _rounded(streams.adaptive_events(spark, d, trigger.Rule(500))))
_GRID = (0.03, 0.05, 0.1, 0.15, 0.2)
register("threshold_sweep", " union all ".join(f"select cast({t} as double) as threshold, r.run_id, coalesce(f.firings, 0) as firings, f.first_step from (select distinct run_id from ({_TYPE_TRACE})) r left join (select run_id, count(*) as firings, min(step) as first_step from ({sql.decisions(500, threshold=t, trace=_TYPE_TRACE)}) group by 1) f on f.run_id = r.run_id" for t in _GRID))(lambda spark, d: trigger.threshold_sweep(_trace(spark, d), list(_GRID), trigger.Rule(500)))


@register("threshold_sensitivity", "select round(stddev_samp(a), 6) as deviation from (" + " union all ".join(f"select avg(secs) as a from ({sql.decisions(20, threshold=t, drift=(1.0, 0.0006, 0), steps=3000, keep_all=True)})" for t in _GRID) + ")")
def _(spark, d):
    """Deviation over thresholds of the average step time of a drifting run."""
    rows = [(t, sum(s) / len(s)) for t in _GRID for s in [trigger.drift_loop(trigger.Rule(20, threshold=t), 0.0006, 3000)[0]]]
    return spark.createDataFrame(rows, "threshold double, avg_secs double").agg(F.round(F.stddev_samp("avg_secs"), 6).alias("deviation"))


_SHARP = {"unit": 0.0018, "lb": 20.0, "flat": 4000, "steps": 6000}


_IDEAL = ((20.0, 0.0003), (50.0, 0.0015), (20.0, 0.0018))


@register("ideal_interval_drift", " union all ".join(f"select run_id, cast({lb} as double) as lb, cast({unit} as double) as unit, round(sqrt(2 * {lb} / slope), 6) as interval from ({_slopes_sql(unit)})" for lb, unit in _IDEAL))
def _(spark, d):
    """The ideal interval of every run of events, at three costs and degradations."""
    ideal = lambda lb, unit: F.round(trigger.ideal_interval_of(lb, F.col("slope")), 6)
    return workloads.union(_slopes(spark, d, unit).select("run_id", F.lit(lb).alias("lb"), F.lit(unit).alias("unit"), ideal(lb, unit).alias("interval")) for lb, unit in _IDEAL)


@register(
    "adaptive_vs_fixed",
    f"""with slopes as ({_slopes_sql(_SHARP['unit'])}), a as ({sql.decisions(_SHARP['lb'], drift=(1.0, None, _SHARP['flat']), slopes=_slopes_sql(_SHARP['unit']), steps=_SHARP['steps'], keep_all=True)}),
    f as (select run_id, step, 1.0 + slope * cast(greatest(0, step - greatest((step - 1) // 500 * 500, {_SHARP['flat']})) as double) as secs, case when step % 500 = 0 then 'fixed' end as reason from slopes, (select unnest(range(1, {_SHARP['steps'] + 1})) as step))
    select run_id, 'adaptive' as policy, round((sum(secs) + {_SHARP['lb']} * count(reason)) / count(*), 6) as avg_secs, count(reason) as firings from a where step > {_SHARP['flat']} group by run_id union all
    select run_id, 'fixed', round((sum(secs) + {_SHARP['lb']} * count(reason)) / count(*), 6), count(reason) from f where step > {_SHARP['flat']} group by run_id""",
)
def _(spark, d):
    """Runs that are flat and then degrade sharply; average over the last 2,000 steps, rebalancings paid."""
    rule, flat, steps = trigger.Rule(_SHARP["lb"]), _SHARP["flat"], _SHARP["steps"]

    def run(key, pdf):
        out = []
        for policy in ("adaptive", "fixed"):
            secs, fired = trigger.drift_loop(rule, float(pdf["slope"].iloc[0]), steps, policy=policy, flat=flat)
            late = sum(f[0] > flat for f in fired)
            out.append((key[0], policy, round((sum(secs[flat:]) + rule.lb_cost * late) / (steps - flat), 6), late))
        return pd.DataFrame(out, columns=["run_id", "policy", "avg_secs", "firings"])

    return _slopes(spark, d, _SHARP["unit"]).groupBy("run_id").applyInPandas(run, "run_id string, policy string, avg_secs double, firings long")


# ---------------------------------------------------------------- experiments
register("example_single_site", workloads.example_sql("single_site", workloads._PRICES))(lambda spark, d: workloads.example_map(spark, "single_site", workloads.price_weights(spark, d)))
register("example_peer", workloads.example_sql("peer", workloads._PRICES))(lambda spark, d: workloads.example_map(spark, "peer", workloads.price_weights(spark, d)))
register("example_transfer", workloads.example_transfer_sql(workloads._PRICES))(lambda spark, d: workloads.example_transfer(spark, workloads.price_weights(spark, d)))
register("fan_trace", workloads.fan_trace_sql())(workloads.fan_trace)
register("fan_stale_vs_fresh", workloads.fan_stale_sql())(workloads.fan_stale_vs_fresh)
register("fan_fixed_k", workloads.fan_fixed_sql(2))(lambda spark, d: workloads.fan_fixed_k(spark, d, 2))
register("speedup_fan", workloads.speedup_sql())(workloads.speedup_fan)
register("fan_speedup_hybrid", workloads.fan_speedup_hybrid_sql())(workloads.fan_speedup_hybrid)
register("fan_speedup_peer", workloads.fan_speedup_peer_sql())(workloads.fan_speedup_peer)
register("fan_closed_loop")(workloads.fan_closed_loop)
register("whole_loop_fan", steps.whole_loop_sql())(steps.whole_loop)
register("same_physics_fan", steps.same_physics_sql())(steps.same_physics)
register("overhead_stages_fan")(steps.overhead_stages)
register("weak_scaling_xeon", workloads.weak_scaling_sql(4, 16))(lambda spark, d: workloads.weak_scaling(spark, d, 4, 16))
register("weak_scaling_bgq", workloads.weak_scaling_sql(2, 8))(lambda spark, d: workloads.weak_scaling(spark, d, 2, 8))
register("overhead_steps", workloads.overhead_steps_sql())(workloads.overhead_steps)
register("published_ratios", workloads.published_ratios_sql())(workloads.published_ratios)
register("overhead_orders")(workloads.overhead_orders)
register("words_moved", workloads.words_moved_sql())(workloads.words_moved)
register("non_empty_fan", f"select round(avg(case when weight > 3 then 1.0 else 0.0 end), 9) as share, round(avg(weight - 3), 9) as mean_particles from ({_FAN})")(lambda spark, d: measures.non_empty(_w("fan", spark, d).select((F.col("weight") - 3).alias("cnt"))))
_DEC = sql.decisions(500, trace=_TYPE_TRACE)
register("amortised_total", f"select t.run_id, round(s, 4) as step_secs, round(cast(coalesce(c, 0) as double) * 500, 4) as lb_secs, round(s + coalesce(c, 0) * 500.0, 4) as total, round(coalesce(c, 0) * 500.0 / (s + coalesce(c, 0) * 500.0), 6) as share from (select run_id, sum(secs) as s from ({_TYPE_TRACE}) group by 1) t left join (select run_id, count(*) as c from ({_DEC}) group by 1) f on f.run_id = t.run_id")(
    lambda spark, d: (lambda t: measures.amortised_total(t, trigger.adaptive_triggers(t, trigger.Rule(500)), 500.0).select("run_id", *(F.round(c, 4).alias(c) for c in ("step_secs", "lb_secs", "total")), F.round("share", 6).alias("share")))(_trace(spark, d))
)
register("average_step_events", f"select run_id, round(avg(secs), 6) as avg_secs from ({_TYPE_TRACE}) where step between 101 and 200 group by run_id")(lambda spark, d: measures.average_step(_trace(spark, d), 101, 200).select("run_id", F.round("avg_secs", 6).alias("avg_secs")))
register("rebalancing_counts", f"select run_id, count(*) as firings, min(step) as first_step from ({_DEC}) group by run_id")(lambda spark, d: trigger.adaptive_triggers(_trace(spark, d), trigger.Rule(500)).groupBy("run_id").agg(F.count("*").alias("firings"), F.min("step").alias("first_step")))

from . import surroundings  # noqa: E402, F401  registers op_*

__all__ = ["ORACLE_SQL", "QUERIES", "BAND_DAYS", "DAYS", "DAY_ZERO", "event_stream", "ship_day", "simulate"]
