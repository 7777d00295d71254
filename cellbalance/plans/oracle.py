"""SQL for DuckDB, written from the definitions and not from the Spark plans: inequality joins, cascades by recursion."""

from __future__ import annotations


def scan(weights: str) -> str:
    return f"select pos, weight, cast(sum(weight) over (order by pos) as bigint) as s, cast(sum(weight) over () as bigint) as t, count(*) over () as n from ({weights})"


def cuts(method: str, weights: str, p: int, cap: int | None = None, strict: bool = False) -> str:
    """(k, b) of one method."""
    slots = f"(select unnest(range(0, {p + 1})) as k)"
    if method == "uniform":
        plain = f"select k, (k * (select count(*) from ({weights}))) // {p} as b from {slots}"
    elif method == "single_site":
        plain = f"""with sc as ({scan(weights)}), hit as (select k, min(pos) as p from {slots} join sc on s * {p} > k * t where k between 1 and {p - 1} group by k)
            select k, case when 2 * k * t < {p} * (2 * s - weight) then p - 1 else p end as b from hit join sc on pos = p
            union all select 0, 0 union all select {p}, (select count(*) from sc)"""
    else:  # peer and hybrid
        plain = f"""with sc as ({scan(weights)}) select k, case when k = 0 then 0 when k = {p} then (select count(*) from sc) else (select count(*) from sc where s * {p} < k * t + {p}) end as b from {slots}"""
    if cap is not None:
        plain = f"""with recursive c as ({plain}), r(k, b) as (select cast(0 as bigint), cast(0 as bigint) union all select r.k + 1, least(cast(c.b as bigint), r.b + {cap}) from r join c on c.k = r.k + 1 where r.k + 1 < {p}),
            m as (select b as n from c where k = {p})
            select k, {f"greatest(b, (select n from m) - ({p} - k) * {cap})" if strict else "b"} as b from r union all select {p}, n from m"""
    return f"select cast(k as integer) as k, cast(b as bigint) as b from ({plain})"


def intervals(cut_sql: str) -> str:
    return f"select k as slot, b + 1 as first_pos, lead(b) over (order by k) as last_pos from ({cut_sql})"


def cell_map(weights: str, cut_sql: str) -> str:
    return f"select w.pos, w.weight, cast(i.slot as integer) as slot from ({weights}) w join ({intervals(cut_sql)}) i on w.pos between i.first_pos and i.last_pos"


def loads(weights: str, cut_sql: str) -> str:
    return f"""select cast(i.slot as integer) as slot, cast(count(w.pos) as bigint) as cells, cast(coalesce(sum(w.weight), 0) as bigint) as load
        from ({intervals(cut_sql)}) i left join ({weights}) w on w.pos between i.first_pos and i.last_pos where i.last_pos is not null group by i.slot"""


def imbalance(load_sql: str) -> str:
    return f"select max(load) as step, round(avg(load), 9) as mean_load, round(max(load) / avg(load), 9) as imbalance, min(cells) as least_cells, max(cells) as most_cells from ({load_sql})"


def transfer_plan(weights: str, old: str, new: str) -> str:
    return f"select o.pos, o.slot as src, n.slot as dst from ({cell_map(weights, old)}) o join ({cell_map(weights, new)}) n on o.pos = n.pos where o.slot <> n.slot"


def numbered(run: str) -> str:
    return f"select cast({run} as varchar) as run_id, row_number() over (partition by {run} order by ts, event_id) as step, value as secs from events"


def decisions(lb_cost: float, threshold: float = 0.05, eval_len: int = 100, trace: str | None = None, drift: tuple | None = None, slopes: str | None = None, steps: int = 0, use_interval: bool = True, use_loss: bool = True, keep_all: bool = False) -> str:
    """The adaptive rule by recursion over steps, on a trace or on a closed-form drift (base, slope, flat), its slope
    that of each run where ``slopes`` (run_id, slope) is given."""
    if trace is None:
        base, slope, flat = drift
        first = "select 'drift' as run_id"
        joined = f"(select st.*, st.step + 1 as now_step, {base} + {slope} * cast(greatest(0, st.step + 1 - greatest(st.last, {flat})) as double) as secs from st where st.step < {steps})"
        if slopes is not None:
            first = "select run_id from sl"
            joined = f"(select st.*, st.step + 1 as now_step, {base} + sl.slope * cast(greatest(0, st.step + 1 - greatest(st.last, {flat})) as double) as secs from st join sl on sl.run_id = st.run_id where st.step < {steps})"
    else:
        first = f"select distinct run_id from ({trace})"
        joined = "(select st.*, tr.step as now_step, tr.secs from st join tr on tr.run_id = st.run_id and tr.step = st.step + 1)"
    with_trace = f"tr as materialized ({trace}), " if trace is not None else f"sl as materialized ({slopes}), " if slopes is not None else ""
    due = "since >= tau2" if use_interval else "false"
    costly = f"loss + (t2 - mean) > {lb_cost}" if use_loss else "false"
    body = f"""
        select run_id, now_step as step, case when fire then now_step else last end as last, once or fire as once,
               case when in_phase then psum2 + secs else psum2 end as psum, case when in_phase then pn2 + 1 else pn2 end as pn,
               case when fire then cast(len as double) else epoch end as epoch, tau2 as tau,
               case when fire then 0.0 when once and not in_phase then loss + (t2 - mean) else loss end as loss,
               secs as s1, s1 as s2,
               case when not fire then null when not once then 'degrade' when {due} then 'interval' else 'loss' end as reason,
               case when fire and once and not isinf(tau2) then tau2 end as ftau, case when fire then len end as flen, secs as secs_now
        from (
            select *, (not in_phase) and (case when once then ({due}) or ({costly}) else mean > 0 and (t2 - mean) / mean > {threshold} end) as fire,
                   cast(case when once then since else now_step - (last + {eval_len // 2}) end as bigint) as len
            from (
                select *, case when once and since = 1 then case when t2 > mean then sqrt(2 * epoch * {lb_cost} / (t2 - mean)) else cast('infinity' as double) end else tau end as tau2,
                       case when once and since = 1 then 0.0 else psum end as psum2, case when once and since = 1 then 0 else pn end as pn2,
                       since between 1 and {eval_len} as in_phase
                from (
                    select *, now_step - last as since, case when pn > 0 then psum / pn else 0.0 end as mean,
                           case when s1 is null then secs when s2 is null then (secs + s1) / 2 else greatest(least(secs, s1), least(greatest(secs, s1), s2)) end as t2
                    from {joined}
                )
            )
        )"""
    return f"""with recursive {with_trace}st as (
        select run_id, cast(0 as bigint) as step, cast(0 as bigint) as last, false as once, cast(0.0 as double) as psum, cast(0 as bigint) as pn,
               cast(0.0 as double) as epoch, cast('infinity' as double) as tau, cast(0.0 as double) as loss, cast(null as double) as s1, cast(null as double) as s2,
               cast(null as varchar) as reason, cast(null as double) as ftau, cast(null as bigint) as flen, cast(null as double) as secs_now from ({first})
        union all {body})
        select run_id, step, {"reason, secs_now as secs" if keep_all else "reason, round(ftau, 6) as tau, flen as epoch_len"} from st where {"step > 0" if keep_all else "reason is not null"}"""
