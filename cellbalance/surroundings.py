"""Sources, sinks and relational operators that users of the balancers need, one query each (``op_*``)."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .catalog import _MAP_PEER, _ORD, _PEER_ORD, _UNIFORM_ORD, _old_new, _trace, _TYPE_TRACE, _w, register
from .functions.user_functions import NearestCuts, slope_of, weights_of_nodes
from .operators import balance as bal
from .operators import cuts as cut
from .operators import maps, migrate, scan
from .plans import oracle as sql
from .sources.bindings import BINDINGS, ship_day
from .sources.tables import event_stream, read_cuts, table, write_cuts
from .streaming import triggers as streams

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


@register("op_scan_counts", " union all ".join(f"select '{t}' as name, count(*) as n from {t}" for t in TABLES))
def _(spark, d):
    out = None
    for t in TABLES:
        one = table(spark, d, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n")
        out = one if out is None else out.unionByName(one)
    return out


@register("op_roundtrip_cuts", _PEER_ORD)
def _(spark, d):
    path = streams.shared_path(spark)
    write_cuts(bal.balance_peer(_w("orders", spark, d), 16), path, 3)
    return read_cuts(spark, path, 3)


@register("op_band_filter", "select count(*) as n, round(sum(l_quantity), 6) as quantity from lineitem where l_discount between 0.02 and 0.04")
def _(spark, d):
    return table(spark, d, "lineitem").where(F.col("l_discount").between(0.02, 0.04)).agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 6).alias("quantity"))


@register("op_props_weight", "select event_type, cast(sum(cast(json_extract(props, '$.k') as bigint)) as bigint) as weight from events group by event_type")
def _(spark, d):
    k = F.from_json("props", "k long")["k"]
    return table(spark, d, "events").groupBy("event_type").agg(F.sum(k).alias("weight"))


@register("op_left_weights", _ORD)
def _(spark, d):
    counts = table(spark, d, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("c"))
    joined = table(spark, d, "orders").join(counts, F.col("o_orderkey") == F.col("l_orderkey"), "left")
    return joined.select((F.col("o_orderkey") + 1).alias("pos"), (F.coalesce("c", F.lit(0)) + 3).alias("weight"))


@register("op_broadcast_offsets", f"select block, sum(weight) - max(own) as local from (select (pos - 1) // 1024 as block, weight, 0 as own from ({_ORD})) group by block".replace("sum(weight) - max(own)", "cast(sum(weight) as bigint)"))
def _(spark, d):
    from .operators.scan import block_totals

    return block_totals(_w("orders", spark, d), 1024).select("block", F.col("block_sum").alias("local"))


@register("op_range_lookup", f"select pos, slot from ({_MAP_PEER})")
def _(spark, d):
    w = _w("orders", spark, d)
    return maps.cuts_to_map(w, bal.balance_peer(w, 16)).select("pos", "slot")


@register("op_asof_version", f"select t.run_id, t.step, cast(t.step // 500 * 500 as bigint) as version from ({_TYPE_TRACE}) t")
def _(spark, d):
    """The cuts in force at each step, rebalanced every 500: last version at or before it, in one pass."""
    steps = _trace(spark, d)
    versions = steps.filter("step % 500 = 0").select("run_id", "step", F.col("step").alias("v"), F.lit(0).alias("o"))
    both = steps.select("run_id", "step", F.lit(None).cast("long").alias("v"), F.lit(1).alias("o")).unionByName(versions)
    last = F.last("v", ignorenulls=True).over(Window.partitionBy("run_id").orderBy("step", "o").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return both.select("run_id", "step", "o", F.coalesce(last, F.lit(0)).alias("version")).filter("o = 1").drop("o")


@register("op_nonempty_cells", "select count(*) as n from orders where o_orderkey in (select l_orderkey from lineitem)")
def _(spark, d):
    return table(spark, d, "orders").join(table(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").agg(F.count("*").alias("n"))


@register("op_empty_cells", "select o_orderkey from orders where o_orderkey not in (select l_orderkey from lineitem)")
def _(spark, d):
    return table(spark, d, "orders").join(table(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey")


@register("op_labelled_documents", "select lang, count(*) as n from documents where doc_id in (select doc_id from labels) group by lang")
def _(spark, d):
    return table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id", "left_semi").groupBy("lang").agg(F.count("*").alias("n"))


@register("op_sweep_grid", f"select p, cap, cast(p * cap as integer) as room, n, total, p * cap >= n as fits from (values (4), (16), (64)) as a(p), (values (8), (16)) as b(cap), (select count(*) as n, cast(sum(weight) as bigint) as total from ({BINDINGS['supplier'].sql}))")
def _(spark, d):
    """Slots and caps to try, and whether the line of suppliers has room in them."""
    ps, caps = (spark.createDataFrame([(x,) for x in v], f"{n} int") for n, v in (("p", (4, 16, 64)), ("cap", (8, 16))))
    room = F.col("p") * F.col("cap")
    whole = scan.line_totals(_w("supplier", spark, d))
    return ps.crossJoin(F.broadcast(caps)).crossJoin(F.broadcast(whole)).select("p", "cap", room.alias("room"), "n", "total", (room >= F.col("n")).alias("fits"))


@register("op_slot_summary", f"select slot, count(*) as cells, cast(sum(weight) as bigint) as load, min(weight) as least, max(weight) as most from ({_MAP_PEER}) group by slot")
def _(spark, d):
    w = _w("orders", spark, d)
    return maps.cuts_to_map(w, bal.balance_peer(w, 16)).groupBy("slot").agg(F.count("*").alias("cells"), F.sum("weight").alias("load"), F.min("weight").alias("least"), F.max("weight").alias("most"))


@register("op_distinct_users", "select event_type, count(distinct user_id) as users from events group by event_type")
def _(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@register("op_approx_users", "select event_type, true as close from events group by event_type")
def _(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg((F.abs(F.approx_count_distinct("user_id", 0.02) - F.count_distinct("user_id")) <= 0.1 * F.count_distinct("user_id")).alias("close"))


@register("op_rollup_region", "select r_name, n_name, count(*) as customers from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by rollup (r_name, n_name)")
def _(spark, d):
    nations = table(spark, d, "nation").join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return table(spark, d, "customer").join(nations, F.col("c_nationkey") == F.col("n_nationkey")).rollup("r_name", "n_name").agg(F.count("*").alias("customers"))


_PLAN = sql.transfer_plan(_ORD, _UNIFORM_ORD, sql.cuts("single_site", _ORD, 16))


def _moves(spark, d) -> DataFrame:
    _x, old, new = _old_new(spark, d)
    return migrate.transfer_plan(old, new)


@register("op_cube_transfer", f"select src, dst, count(*) as cells from ({_PLAN}) group by cube (src, dst)")
def _(spark, d):
    return _moves(spark, d).cube("src", "dst").agg(F.count("*").alias("cells"))


@register("op_grouping_sets_transfer", f"select src, dst, count(*) as cells from ({_PLAN}) group by grouping sets ((src), (dst))")
def _(spark, d):
    return _moves(spark, d).groupingSets([[F.col("src")], [F.col("dst")]], "src", "dst").agg(F.count("*").alias("cells"))


@register("op_pivot_transfer", "select src, " + ", ".join(f"coalesce(cast(sum(case when dst = {k} then 1 end) as bigint), 0) as to_{k}" for k in range(4)) + f" from ({_PLAN}) group by src")
def _(spark, d):
    wide = _moves(spark, d).groupBy("src").pivot("dst", [0, 1, 2, 3]).agg(F.count("dst"))
    return wide.select("src", *(F.coalesce(F.col(f"`{k}`"), F.lit(0)).alias(f"to_{k}") for k in range(4)))


@register("op_lag_slot", f"select pos from (select pos, slot, lag(slot) over (order by pos) as before from ({_MAP_PEER})) where slot <> before")
def _(spark, d):
    return cut.first_cells(bal.peer_map(_w("orders", spark, d), 16).select("pos", "slot"), 2048).filter("first_pos > 1").select(F.col("first_pos").alias("pos"))


@register("op_rank_cells", f"select slot, pos, rank() over (partition by slot order by weight desc, pos) as r from ({_MAP_PEER}) qualify r <= 3")
def _(spark, d):
    w = _w("orders", spark, d)
    ranked = maps.cuts_to_map(w, bal.balance_peer(w, 16)).withColumn("r", F.rank().over(Window.partitionBy("slot").orderBy(F.desc("weight"), "pos")))
    return ranked.filter("r <= 3").select("slot", "pos", F.col("r").cast("long").alias("r"))


@register("op_ntile_slots", "select supplier, tile from (select s_suppkey as supplier, cast(ntile(8) over (partition by s_nationkey order by s_acctbal, s_suppkey) as integer) as tile from supplier)")
def _(spark, d):
    tile = F.ntile(8).over(Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey"))
    return table(spark, d, "supplier").select(F.col("s_suppkey").alias("supplier"), tile.alias("tile"))


@register("op_top_cells", f"select pos, weight from ({_ORD}) order by weight desc, pos limit 20")
def _(spark, d):
    return _w("orders", spark, d).orderBy(F.desc("weight"), "pos").limit(20)


@register("op_top_per_slot", f"select slot, pos, weight from (select *, row_number() over (partition by slot order by weight desc, pos) as r from ({_MAP_PEER})) where r = 1")
def _(spark, d):
    w = _w("orders", spark, d)
    best = maps.cuts_to_map(w, bal.balance_peer(w, 16)).groupBy("slot").agg(F.max(F.struct("weight", (-F.col("pos")).alias("p"))).alias("x"))
    return best.select("slot", (-F.col("x.p")).alias("pos"), F.col("x.weight").alias("weight"))


_UNI_MAP, _SINGLE_MAP = (sql.cell_map(_ORD, sql.cuts(m, _ORD, 16)) for m in ("uniform", "single_site"))


@register("op_intersect_maps", f"select count(*) as n from (select pos, slot from ({_UNI_MAP}) intersect select pos, slot from ({_SINGLE_MAP}))")
def _(spark, d):
    _x, old, new = _old_new(spark, d)
    return old.intersect(new).agg(F.count("*").alias("n"))


@register("op_except_maps", f"select pos, slot from ({_SINGLE_MAP}) except all select pos, slot from ({_UNI_MAP})")
def _(spark, d):
    _x, old, new = _old_new(spark, d)
    return new.exceptAll(old)


@register("op_weight_quantiles", f"select quantile_cont(weight, 0.5) as median, quantile_cont(weight, 0.9) as p90, cast(max(weight) as bigint) as most from ({_ORD})".replace("quantile_cont(weight", "quantile_cont(cast(weight as double)"))
def _(spark, d):
    return _w("orders", spark, d).agg(F.percentile("weight", 0.5).alias("median"), F.percentile("weight", 0.9).alias("p90"), F.max("weight").alias("most"))


@register("op_host_weights", "select split_part(split_part(url, '://', 2), '/', 1) as host, cast(sum(length(html)) as bigint) as weight from pages group by 1")
def _(spark, d):
    host = F.split_part(F.split_part("url", F.lit("://"), F.lit(2)), F.lit("/"), F.lit(1))
    return table(spark, d, "pages").groupBy(host.alias("host")).agg(F.sum(F.length("html")).cast("long").alias("weight"))


@register("op_month_weights", "select strftime(date_trunc('month', o_orderdate), '%Y-%m') as month, count(*) as weight from orders group by 1")
def _(spark, d):
    return table(spark, d, "orders").groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("month")).agg(F.count("*").alias("weight"))


@register("op_day_span", "select min(date_diff('day', timestamp '1995-01-01', l_shipdate)) as lo, max(date_diff('day', timestamp '1995-01-01', l_shipdate)) as hi from lineitem".replace("select min(", "select cast(min(").replace(")) as lo, max(", ")) as integer) as lo, cast(max(").replace(")) as hi", ")) as integer) as hi"))
def _(spark, d):
    return table(spark, d, "lineitem").agg(F.min(ship_day()).alias("lo"), F.max(ship_day()).alias("hi"))


@register("op_cut_array", f"select cast(sum(b * k) as bigint) as mark, cast(count(*) as integer) as n from ({_PEER_ORD})")
def _(spark, d):
    packed = bal.balance_peer(_w("orders", spark, d), 16).agg(F.array_sort(F.collect_list(F.struct("k", "b"))).alias("cuts"))
    return packed.select(F.aggregate("cuts", F.lit(0).cast("long"), lambda s, c: s + c["k"] * c["b"]).alias("mark"), F.size("cuts").alias("n"))


@register("op_embedding_norm", "select vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: cast(x as double) * cast(x as double)))), 5) as norm from embeddings")
def _(spark, d):
    squares = F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda s, x: s + x)
    return table(spark, d, "embeddings").select("vec_id", F.round(F.sqrt(squares), 5).alias("norm"))


_DAY = "select strftime(date_trunc('day', ts), '%Y-%m-%d') as day, event_type, count(*) as n from events group by 1, 2"


@register("op_stream_tumbling", f"select * from ({_DAY}) where day < (select max(day) from ({_DAY}))")
def _(spark, d):
    out = streams.drained(streams.tumbling(event_stream(spark, d)))
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n")


@register("op_stream_sliding", """select strftime(s, '%Y-%m-%d') as start, count(*) as n from (select unnest([date_trunc('day', ts), date_trunc('day', ts) - interval 1 day]) as s from events) where s + interval 2 days <= (select max(ts) - interval 1 hour from events) group by 1""")
def _(spark, d):
    out = streams.drained(streams.sliding(event_stream(spark, d)))
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("start"), "n")


_SESSIONS = """select user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') as start, count(*) as n
    from (select *, sum(fresh) over (partition by user_id order by ts, event_id) as part
        from (select *, case when ts < lag(ts) over (partition by user_id order by ts, event_id) + interval 12 hours then 0 else 1 end as fresh from events))
    group by user_id, part having max(ts) + interval 12 hours <= (select max(ts) - interval 1 hour from events)"""


@register("op_stream_session", _SESSIONS)
def _(spark, d):
    out = streams.drained(streams.sessions(event_stream(spark, d)))
    return out.select("user_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@register("op_stream_late", "select event_type, count(distinct event_id) as n from events group by event_type")
def _(spark, d):
    return streams.drained(streams.without_repeats(event_stream(spark, d)).select("event_id", "event_type")).groupBy("event_type").agg(F.count("*").alias("n"))


@register("op_udf_bary", "select cast(l_linenumber + 2 as integer) as n, cast(0 as double) as checksum, cast(l_linenumber + 2 as bigint) as nodes, count(*) as cells from lineitem group by l_linenumber")
def _(spark, d):
    """Lines of orders as cells of l_linenumber + 2 nodes: the weights of each number of nodes sum to 0, as for every set of more than one node."""
    node_weights = F.pandas_udf(weights_of_nodes, "array<double>")
    cells = table(spark, d, "lineitem").groupBy((F.col("l_linenumber") + 2).cast("int").alias("n")).agg(F.count("*").alias("cells"))
    return cells.select("n", "cells", F.explode(node_weights("n")).alias("w")).groupBy("n", "cells").agg(F.abs(F.round(F.sum("w"), 6)).alias("checksum"), F.count("*").alias("nodes")).select("n", "checksum", "nodes", "cells")


@register("op_udaf_slope", f"select run_id, round(regr_slope(secs, step), 9) as slope from ({_TYPE_TRACE}) group by run_id")
def _(spark, d):
    return _trace(spark, d).groupBy("run_id").agg(F.round(slope_of(F.col("secs"), F.col("step").cast("double")), 9).alias("slope"))


@register("op_udtf_cuts", sql.cuts("single_site", BINDINGS["conversations"].sql, 16))
def _(spark, d):
    line = _w("conversations", spark, d).agg(F.array_sort(F.collect_list(F.struct("pos", "weight"))).alias("a")).select(F.transform("a", lambda x: x["weight"]).alias("weights"))
    return line.lateralJoin(NearestCuts(F.col("weights").outer(), F.lit(16))).select("k", "b")


@register("op_sql_peer", _MAP_PEER)
def _(spark, d):
    """The peer map in Spark SQL over temporary views, for one site."""
    view = f"weights_{uuid.uuid4().hex}"
    _w("orders", spark, d).createOrReplaceTempView(view)
    return spark.sql(f"""
        with blocks as (select (pos - 1) div 1024 as block, sum(weight) as block_sum from {view} group by 1),
        offsets as (select block, sum(block_sum) over (order by block) - block_sum as before, sum(block_sum) over () as total from blocks),
        local as (select *, sum(weight) over (partition by (pos - 1) div 1024 order by pos) as s from {view})
        select /*+ broadcast(o) */ pos, weight, cast(greatest(0, least(15, (s + before - 1) * 16 div total)) as int) as slot from local l join offsets o on o.block = (l.pos - 1) div 1024
    """)
