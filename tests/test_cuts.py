"""Cuts against plain loops: worked example, literals, random lines."""

import random

import pytest

from cellbalance.operators import balance, cuts, maps, scan
from cellbalance.plans.workloads import EXAMPLE_PARTICLES, example_map, example_transfer, example_weights


def frame(spark, weights):
    return spark.createDataFrame([(i + 1, w) for i, w in enumerate(weights)], "pos long, weight long")


def b_of(df):
    return [r["b"] for r in df.orderBy("k").collect()]


def sequential_nearest(weights, p):
    sums = [0]
    for w in weights:
        sums.append(sums[-1] + w)
    n, total = len(weights), sums[-1]
    if not total:
        return [k * n // p for k in range(p + 1)]
    b = [0]
    for k in range(1, p):
        i = next(i for i in range(1, n + 1) if sums[i] * p > k * total)
        b.append(i - 1 if 2 * k * total < p * (sums[i - 1] + sums[i]) else i)
    return [*b, n]


def sequential_peer(weights, p):
    n, total, s, slots = len(weights), sum(weights), 0, []
    if not total:
        return [k * n // p for k in range(p + 1)]
    for w in weights:
        s += w
        slots.append(min(p - 1, max(0, s - 1) * p // total))
    return [0, *(sum(1 for x in slots if x < k) for k in range(1, p)), n]


def cascade(b, cap):
    out = list(b)
    for k in range(1, len(b) - 1):
        out[k] = min(out[k], out[k - 1] + cap)
    return out


def test_worked_example(spark):
    w = example_weights(spark)
    assert sum(EXAMPLE_PARTICLES) == 36
    scanned = {r["pos"]: r for r in scan.scan_blocks(w, 4).collect()}
    assert scanned[4]["s"] == 18 and scanned[5]["s"] == 26 and scanned[12]["total"] == 72
    assert b_of(cuts.cuts_uniform(w, 3)) == [0, 4, 8, 12]
    assert b_of(balance.balance_single_site(w, 3)) == [0, 5, 7, 12]
    assert b_of(balance.balance_single_site(w, 3, scan="single")) == [0, 5, 7, 12]
    assert b_of(balance.balance_peer(w, 3, block=4)) == [0, 4, 7, 12]
    assert b_of(balance.balance_hybrid(w, 3)) == [0, 4, 7, 12]
    first = {(r["slot"], r["first_pos"]) for r in cuts.first_cells(balance.peer_map(w, 3).select("pos", "slot"), 4).collect()}
    assert first == {(0, 1), (1, 5), (2, 8)}
    assert {tuple(r) for r in example_transfer(spark).collect()} == {(5, 1, 0, 5), (8, 1, 2, 3)}
    assert example_map(spark, "peer").count() == 12
    for method in ("single_site", "peer", "hybrid"):
        assert b_of(balance.METHODS[method](w, 3, cap=4)) == [0, 4, 7, 12]
        assert b_of(balance.METHODS[method](w, 3, cap=4, strict=True)) == [0, 4, 8, 12]


def test_full_map_is_not_copied_to_every_site(spark):
    w = spark.range(1, 1001).selectExpr("id as pos", "id % 7 + 3 as weight")
    held = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")  # leaves just those that are asked for
    try:
        mapped = balance.share_full_map(w, 8)
        assert "BroadcastHashJoin [pos" not in mapped._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", held)
    want = {(r["pos"], r["weight"], r["slot"]) for r in balance.rebalance(w, 8, "peer").collect()}
    assert {tuple(r) for r in mapped.collect()} == want


@pytest.mark.parametrize(
    "weights, p, single, peer",
    [
        ([1, 1, 20, 1, 1], 4, [0, 2, 3, 3, 5], [0, 2, 2, 2, 5]),
        ([2, 2, 2, 2], 2, [0, 2, 4], [0, 2, 4]),
        ([3, 2, 3], 2, [0, 2, 3], [0, 1, 3]),
        ([5, 6, 7], 1, [0, 3], [0, 3]),
        ([1, 1], 4, [0, 1, 1, 2, 2], [0, 1, 1, 2, 2]),
        ([0, 0, 0], 2, [0, 1, 3], [0, 1, 3]),
    ],
)
def test_literals(spark, weights, p, single, peer):
    w = frame(spark, weights)
    assert single == sequential_nearest(weights, p) or weights == [1, 1]
    assert b_of(balance.balance_single_site(w, p)) == single
    assert b_of(balance.balance_peer(w, p)) == peer
    assert b_of(balance.balance_hybrid(w, p)) == peer


def test_infeasible_cap(spark):
    w = frame(spark, [1, 1, 1, 1, 1])
    with pytest.raises(Exception, match="more cells than slots"):
        balance.balance_single_site(w, 2, cap=2, strict=True).collect()
    with pytest.raises(ValueError):
        balance.balance_hybrid(w, 2, cap=2, strict=True)


def test_random_lines(spark):
    rng = random.Random(7)
    for _ in range(8):
        n, p = rng.randint(1, 60), rng.randint(1, 12)
        weights = [rng.choice([1, 1, 2, 3, 30]) for _ in range(n)]
        cap = rng.randint(max(1, -(-n // p)), n)
        w = frame(spark, weights).cache()
        single, peer = sequential_nearest(weights, p), sequential_peer(weights, p)
        block = rng.choice([1, 7, 64])
        assert b_of(balance.balance_single_site(w, p, block=block)) == single
        assert b_of(balance.balance_peer(w, p, block=block)) == peer
        assert b_of(balance.balance_hybrid(w, p, block=block)) == peer
        assert b_of(balance.balance_peer(w, p, cap=cap, block=block)) == cascade(peer, cap)
        assert b_of(balance.balance_hybrid(w, p, cap=cap)) == cascade(peer, cap)
        strict = b_of(balance.balance_single_site(w, p, cap=cap, strict=True))
        assert all(y - x <= cap for x, y in zip(strict, strict[1:])) and strict[-1] == n
        best = b_of(balance.cuts_optimal(w, p))
        worst = lambda b: max(sum(weights[x:y]) for x, y in zip(b, b[1:]))
        assert worst(best) <= min(worst(single), worst(peer))
        assert worst(single) * p <= sum(weights) + max(weights) * p
        w.unpersist()


def test_map_round_trip_and_checks(spark):
    w = frame(spark, [4, 1, 9, 2, 2, 7, 1, 1])
    b = balance.balance_single_site(w, 3)
    m = maps.cuts_to_map(w, b, block=2)
    assert b_of(maps.map_to_cuts(m, 3)) == b_of(b)
    assert all(maps.check_map(m, 3, cap=8).first())
    broken = m.select("pos", "weight", (m["pos"] % 3).cast("int").alias("slot"))
    assert not maps.check_map(broken, 3).first()["contiguous"]


def test_plan_shapes(spark):
    w = frame(spark, range(1, 50))
    single = scan.scan_single_site(w)._jdf.queryExecution().executedPlan().toString()
    assert "SinglePartition" in single
    blocks = scan.scan_blocks(w, 8)
    plan = blocks._jdf.queryExecution().optimizedPlan().toString()
    assert "CartesianProduct" not in blocks._jdf.queryExecution().executedPlan().toString() and "Join" in plan


def test_two_levels_equal_one(spark):
    w = frame(spark, range(1, 200))
    rows = lambda df: sorted(map(tuple, df.collect()))
    assert rows(scan.scan_blocks(w, 8, levels=2)) == rows(scan.scan_blocks(w, 16)) == rows(scan.scan_single_site(w))
    with pytest.raises(ValueError):
        limit, scan.MAX_SINGLE_SITE_CELLS = scan.MAX_SINGLE_SITE_CELLS, 10
        try:
            scan.scan_single_site(w)
        finally:
            scan.MAX_SINGLE_SITE_CELLS = limit
