"""Interpolation, stepping, orders, migration."""

import numpy as np
import pytest

from cellbalance.functions.interpolation import barycentric_weights, cardinal_values, interpolate_points, lobatto_nodes
from cellbalance.operators import balance, cuts, maps, migrate, ordering, particles


def test_lobatto_and_barycentric():
    assert lobatto_nodes(3).tolist() == pytest.approx([-1, 0, 1])
    assert lobatto_nodes(5)[1] == pytest.approx(-np.sqrt(3 / 7))
    assert barycentric_weights(5).sum() == pytest.approx(0, abs=1e-9)
    on = cardinal_values(lobatto_nodes(5), 5)
    assert np.array_equal(on, np.eye(5))


@pytest.mark.parametrize("n", [2, 4, 5, 7])
def test_polynomials_are_exact(n):
    rng = np.random.default_rng(n)
    nodes = lobatto_nodes(n)
    z, y, x = np.meshgrid(nodes, nodes, nodes, indexing="ij")
    f = lambda x, y, z: x ** (n - 1) + y * z ** (n - 1) - 2
    p = rng.uniform(-1, 1, (3, 20))
    got = interpolate_points(np.tile(f(x, y, z).ravel(), (20, 1)), *p, n)
    assert got == pytest.approx(f(*p), abs=1e-9)


def test_drag_and_euler(spark):
    p = spark.createDataFrame([(1, 0.5, 3.0, 1.0)], "particle_id long, x double, vx double, u double")
    assert particles.advance_drag(p, 0.1, 1.0).first()["vx"] == pytest.approx(1 + 2 * particles.drag_factor(0.1, 1.0))
    q = p
    for _ in range(3):
        q = particles.advance_euler(q, 0.3)
    assert q.first()["x"] == pytest.approx(0.5 * 1.1**3)


def test_orders(spark):
    shape = (64, 1, 1)
    cells, edges = ordering.lattice(spark, shape), ordering.lattice_edges(spark, shape)
    assert ordering.spectral_order(edges, cells).filter("pos <> cell_id + 1").count() == 0
    assert ordering.lattice_order(cells, shape, "bisect").filter("pos <> cell_id + 1").count() == 0
    for shape in ((16, 2, 1), (8, 3, 2)):
        cells, edges = ordering.lattice(spark, shape), ordering.lattice_edges(spark, shape)
        half = shape[0] * shape[1] * shape[2] // 2
        split = ordering.spectral_order(edges, cells).join(cells, "cell_id")
        assert split.filter(f"(pos <= {half}) <> (ix < {shape[0] // 2})").count() == 0
        for kind in ("axis", "bisect"):
            order = ordering.lattice_order(cells, shape, kind)
            assert sorted(r["pos"] for r in order.collect()) == list(range(1, 2 * half + 1))
    shape = (32, 4, 2)
    got = ordering.line_locality(ordering.lattice_edges(spark, shape), ordering.lattice_order(ordering.lattice(spark, shape), shape)).first()
    assert round(got["mean_distance"], 2) == 4.39


def test_spectral_levels_as_joins(spark):
    shape = (24, 1, 1)
    order = ordering.spectral_order(ordering.lattice_edges(spark, shape), ordering.lattice(spark, shape), leaf=12, iterations=10)
    assert sorted(r["pos"] for r in order.collect()) == list(range(1, 25))


def test_spectral_order_of_thousands_of_cells_in_one_task(spark):
    saves, n = [], 3001
    line = spark.range(n)
    edges = line.filter(f"id < {n - 1}").selectExpr(f"id * 977 % {n} as a", f"(id + 1) * 977 % {n} as b")
    cells = line.selectExpr(f"id * 977 % {n} as cell_id")
    order = ordering.spectral_order(edges, cells, checkpoint=lambda df: saves.append(df) or df)
    assert order.filter(f"(pos - 1) * 977 % {n} <> cell_id").count() == 0 and order.count() == n
    assert len(saves) == 1  # no step of it is a job of its own
    assert ordering.spectral_order(edges.limit(0), cells, checkpoint=lambda df: df).select("pos").distinct().count() == n


def test_migration(spark):
    w = spark.range(1, 41).selectExpr("id as pos", "id % 7 + 1 as weight")
    old = maps.cuts_to_map(w, cuts.cuts_uniform(w, 4)).select("pos", "slot")
    b = balance.balance_single_site(w, 4)
    new = maps.cuts_to_map(w, b).select("pos", "slot")
    from pyspark.sql import functions as F

    placed = migrate.migrate(w, new, 4)
    assert placed.withColumn("at", F.spark_partition_id()).filter("at <> slot").count() == 0
    assert tuple(migrate.check_migration(w, placed).first()) == (0, 0)
    plan = migrate.transfer_plan(old, new)
    ranges = migrate.transfer_ranges(cuts.cuts_uniform(w, 4), b)
    spelled = ranges.select("src", "dst", F.explode(F.sequence("first_pos", "last_pos")).alias("pos")).select("pos", "src", "dst")
    assert spelled.exceptAll(plan).count() == plan.exceptAll(spelled).count() == 0
