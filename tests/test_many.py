"""Many lines in one plan against one line at a time; the step loop against its closed form."""

import random

import pytest
from pyspark.sql import functions as F

from cellbalance.operators import balance, cuts, many, maps
from cellbalance.plans import steps

LINES = {"a": (3, [1, 9, 2, 2, 7, 1, 1, 4]), "b": (5, [0, 0, 0, 0, 0, 0, 0]), "c": (4, [1, 1]), "d": (1, [5, 5, 5]), "e": (6, [random.Random(4).randrange(30) for _ in range(90)])}


@pytest.mark.parametrize("method", ["single_site", "peer", "hybrid"])
@pytest.mark.parametrize("cap", [None, 20])
def test_many_lines(spark, method, cap):
    cells = spark.createDataFrame([(name, p, i + 1, w) for name, (p, line) in LINES.items() for i, w in enumerate(line)], "line string, p int, pos long, weight long")
    got = {}
    for r in many.METHODS[method](many.scan_many(cells, 16), cap).collect():
        got.setdefault(r["line"], {})[r["k"]] = r["b"]
    for name, (p, line) in LINES.items():
        w = spark.createDataFrame([(i + 1, x) for i, x in enumerate(line)], "pos long, weight long")
        assert got[name] == {r["k"]: r["b"] for r in balance.METHODS[method](w, p, cap=cap, block=16).collect()}, name


def test_stays_and_loads(spark):
    w = spark.range(1, 101).selectExpr("id as pos", "id % 7 + 1 as weight")
    old, new = cuts.cuts_uniform(w, 6), balance.balance_peer(w, 6)
    tag = lambda c: c.withColumn("line", F.lit(1))
    both = maps.cuts_to_map(w, old).select("pos", F.col("slot").alias("o")).join(maps.cuts_to_map(w, new), "pos")
    assert many.stays_many(tag(old), tag(new)).first()["stays"] == both.filter("o = slot").count()
    loads = {(r["slot"], r["cells"], r["load"]) for r in many.loads_many(tag(w), tag(new), block=8).collect()}
    assert loads == {(r["slot"], r["c"], r["l"]) for r in both.groupBy("slot").agg(F.count("*").alias("c"), F.sum("weight").alias("l")).collect()}


def test_first_of_scan(spark):
    from cellbalance.operators import scan

    w = spark.createDataFrame([(i + 1, x) for i, x in enumerate(LINES["e"][1])], "pos long, weight long")
    scanned = scan.scan_blocks(w, 16)
    want = {tuple(r) for r in cuts.first_cells(cuts.quotient_slots(scanned, 6), 16).collect()}
    assert {tuple(r) for r in cuts.first_of_scan(scanned, 6).collect()} == want


def test_step_loop(spark):
    n, count = 40, 3
    cells = spark.range(1, n + 1).selectExpr("id as pos")
    start = spark.createDataFrame([(i, (i % 8) + 0.5, 0.0, i % 8 + 1) for i in range(200)], "particle_id long, x double, vx double, pos long")
    done = steps.run_steps(start, cells, steps.line_field(cells), n, 4, count, method="peer", every=2)
    x, v = steps.fan_factors(count)[-1]
    rows = {r["particle_id"]: r for r in done.particles.collect()}
    assert len(rows) == 200 and [f[:2] for f in done.firings] == [(2, "fixed")]
    for i, r in rows.items():
        assert r["x"] == pytest.approx((i % 8 + 0.5) * x) and r["vx"] == pytest.approx((i % 8 + 0.5) * v)
        assert r["pos"] == min(n, int(r["x"]) + 1)
