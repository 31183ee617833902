"""Layouts, overlays, costs, gains and solvers: analytic anchors, properties, independent figures, edge cases."""

from __future__ import annotations

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from relayout.operators import measures
from relayout.plans import assign, cost, graph
from relayout.plans.layout import Layout, Splits
from relayout.plans.overlay import axis_overlay, factored_parcels, grid_overlay, grid_parcels, layout_parcels, parcel_lines, parcels
from relayout.plans.relabel import find_matrix_relabeling, find_relabeling, gains
from relayout.sources import tables

BC = Layout.block_cyclic


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_hand_example(spark):
    lb, la = BC(4, 4, 2, 2, 2, 2), BC(4, 4, 2, 2, 2, 2, "col")
    p = find_matrix_relabeling(spark, la, lb, elem_bytes=1)
    assert (p.before, p.after, p.messages, p.reduction) == (8, 0, 2, 100.0) and p.sigma == [0, 2, 1, 3]
    kept = find_matrix_relabeling(spark, la, lb, elem_bytes=1, beta=1, a_home="original")
    assert kept.after == kept.before == 8
    assert find_matrix_relabeling(spark, la, lb, op="transpose", elem_bytes=1).before == 0


@pytest.mark.parametrize(
    ("la", "lb", "op", "want"),
    [
        (BC(100_000, 100_000, 10_000, 10_000, 10, 10, "col"), BC(100_000, 100_000, 9999, 9999, 10, 10), "identity", (9_001_099_615, 10_996_975)),
        (BC(100_000, 100_000, 10_000, 10_000, 10, 10, "col"), BC(100_000, 100_000, 1, 1, 10, 10), "identity", (9_900_000_000, 9_900_000_000)),
        (BC(4096, 4096, 128, 128, 16, 16), BC(4096, 4096, 32, 32, 16, 16), "identity", (16_711_680, 15_728_640)),
        (BC(2048, 2048, 128, 128, 16, 16), BC(2048, 2048, 32, 32, 16, 16), "transpose", (4_177_920, 3_932_160)),
        (BC(500, 64, 16, 16, 4, 4, "col"), BC(500, 64, 8, 8, 4, 4), "identity", (30_016, 23_936)),
        (Layout.contiguous(500, 64, 4, 2), BC(500, 64, 4, 4, 2, 4), "identity", (28_000, 27_936)),
    ],
)
def test_independent_figures(spark, la, lb, op, want):
    p = find_matrix_relabeling(spark, la, lb, op=op, elem_bytes=1)
    assert (p.before, p.after) == want


def test_overlay_covers_each_index_once(spark):
    a, b = (Splits(100, 7), 3, 90), (Splits(95, bounds=(0, 10, 24, 50, 95)), 5, 90)
    got = axis_overlay(spark, a, b).orderBy("lo").collect()
    assert [r.k for r in got] == list(range(len(got)))
    assert got[0].lo == 0 and got[-1].hi == 90 and all(x.hi == y.lo for x, y in zip(got, got[1:], strict=False))
    for r in got:
        for i in range(r.lo, r.hi):
            assert r.ka == (i + 3) // 7 and a[0].count > r.ka
            assert (0, 10, 24, 50, 95)[r.kb] <= i + 5 < (0, 10, 24, 50, 95)[r.kb + 1]


def test_factored_is_the_counted_form(spark):
    for la, lb in ((BC(37, 23, 5, 4, 2, 3), BC(37, 23, 3, 7, 3, 2, "col")), (BC(37, 23, 5, 4, 2, 3).transposed(), BC(23, 37, 3, 7, 3, 2)), (BC(50, 40, 5, 4, 2, 3).window(3, 31, 7, 40), BC(28, 33, 4, 4, 3, 2, r_src=1, c_src=1))):
        one, two = (x.select("src", "dst", "n_pieces", "vol") for x in (parcels(grid_overlay(spark, la, lb)), factored_parcels(spark, la, lb)))
        assert rows(one) == rows(two)
        assert sum(r[3] for r in rows(one)) == la.m * la.n * 8


def random_parcels(spark, n, seed):
    draw = random.Random(seed)
    return spark.createDataFrame([(s, d, draw.randint(1, 4), draw.randint(1, 50)) for s in range(n) for d in range(n) if draw.random() < 0.7], "src int, dst int, n_pieces long, vol long")


@pytest.mark.parametrize("seed", range(3))
def test_solvers_and_gain_identity(spark, seed):
    n = 5
    p = random_parcels(spark, n, seed)
    gain = gains(p, None, n)
    best = assign.gain_of(gain, assign.solve_bruteforce(gain))
    sigma, (u, v) = assign.solve_exact(gain)
    assert assign.gain_of(gain, sigma) == best == assign.gain_of(gain, assign.solve_flow(gain))
    assert abs(u.sum() + v.sum() - best) < 1e-6 and (u[:, None] + v[None, :] >= gain - 1e-6).all()
    for order in ("gain", "retained"):
        assert 0 <= assign.gain_of(gain, assign.solve_greedy(gain, order)) <= best
    assert 0 <= assign.gain_of(gain, assign.solve_random_swap(gain, seed)) <= best
    assert np.allclose(gains(p, cost.FnCost(lambda s, d, vol, k: F.when(s != d, vol).otherwise(0)), n), gain)
    links = cost.LinkCost(cost.region_links(spark))
    plan = find_relabeling(p, links, n=n)
    delta = gains(p, links, n)
    before, after = (graph.total_cost(graph.comm_graph(x, links)).first()[0] for x in (p, graph.relabel_graph(p, plan.sigma_frame())))
    assert abs(before - after - assign.gain_of(delta, plan.sigma)) < 1e-6 and after <= before


def test_exact_solver_against_brute_force():
    draw = np.random.default_rng(3)
    for n in (1, 2, 4, 6):
        for _ in range(10):
            gain = draw.integers(-50, 50, (n, n)).astype(float)
            best = assign.gain_of(gain, assign.solve_bruteforce(gain))
            assert assign.gain_of(gain, assign.solve_exact(gain)[0]) == best == assign.gain_of(gain, assign.solve_flow(gain))


def test_rounds_are_sequential_greedy(spark):
    p = random_parcels(spark, 6, 11)
    home = np.zeros(6)
    for r in p.filter("src = dst").collect():
        home[r.src] = r.vol
    one = assign.solve_greedy(gains(p, None, 6), "retained", floor_identity=False, home=home)
    many = {r.role: r.site for r in assign.solve_dominant_rounds(p.select(F.col("dst").alias("role"), F.col("src").alias("site"), "vol"), 6).collect()}
    kept = lambda s: sum(r.vol for r in p.collect() if s[r.dst] == r.src)
    assert sorted(many.values()) == list(range(6)) and kept(many) == kept(one)


def test_greedy_trap(spark):
    p = spark.createDataFrame([(0, 0, 1, 3), (1, 0, 1, 4), (1, 1, 1, 3)], "src int, dst int, n_pieces long, vol long")
    gain = gains(p, None, 2)
    assert assign.solve_greedy(gain, floor_identity=False) == [1, 0] and assign.gain_of(gain, [1, 0]) == -2
    assert find_relabeling(p, solver="greedy", n=2).after == find_relabeling(p, n=2).after == 4


def test_blind_transform_cost_cannot_steer(spark):
    p = random_parcels(spark, 4, 5)
    assert np.allclose(gains(p, cost.TransformCost(2.0), 4), 0)


def test_swapped_ends_give_the_inverse(spark):
    p = random_parcels(spark, 5, 7)
    turned = p.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "n_pieces", "vol")
    assert find_relabeling(p, n=5).after == find_relabeling(turned, n=5).after


def test_edges(spark):
    one = BC(9, 5, 2, 2, 1, 1)
    assert find_matrix_relabeling(spark, one, BC(9, 5, 4, 3, 1, 1)).before == 0
    assert layout_parcels(spark, BC(9, 5, 2, 2, 2, 2).window(3, 3, 0, 5), BC(9, 5, 3, 3, 2, 2).window(3, 3, 0, 5)).count() == 0
    assert Layout.from_json(BC(9, 5, 2, 2, 2, 2).relabel([1, 0, 3, 2]).to_json()) == BC(9, 5, 2, 2, 2, 2).relabel([1, 0, 3, 2])
    for bad in (lambda: BC(9, 5, 2, 2, 2, 2).relabel([0, 0, 1, 2]), lambda: Splits(5), lambda: Splits(5, bounds=(0, 3, 3, 5)), lambda: BC(9, 5, 2, 2, 2, 2).window(0, 10, 0, 5), lambda: Layout.grid_of((0, 2), (0, 2), [[4]], 2), lambda: BC(4, 4, 2, 2, 1, 1, "diagonal")):
        with pytest.raises(ValueError):
            bad()
    assert find_relabeling(spark.createDataFrame([], "src int, dst int, n_pieces long, vol long"), n=3).sigma == [0, 1, 2]


def test_driver_counts_are_the_spark_counts(spark):
    pairs = [
        (BC(37, 23, 5, 4, 2, 3), BC(37, 23, 3, 7, 3, 2, "col")), (BC(37, 23, 5, 4, 2, 3).transposed(), BC(23, 37, 3, 7, 3, 2)), (BC(400, 90, 2, 3, 2, 2), BC(400, 90, 3, 2, 2, 2)),
        (BC(50, 40, 5, 4, 2, 3).window(3, 31, 7, 40), BC(28, 33, 4, 4, 3, 2, r_src=1, c_src=1)), (BC(900, 40, 4, 4, 2, 2).window(2, 802, 0, 40).relabel([2, 0, 3, 1]), BC(800, 40, 6, 5, 2, 2)), (BC(9, 5, 2, 2, 2, 2).window(3, 3, 0, 5), BC(9, 5, 3, 3, 2, 2).window(3, 3, 0, 5)),
    ]
    for la, lb in pairs:
        got = grid_parcels(la, lb)
        want = rows(factored_parcels(spark, la, lb).select("src", "dst", "n_pieces", "vol"))
        assert sorted(x for x in zip(*(c.tolist() for c in got), strict=True)) == want


def test_long_constants_are_one_literal(spark):
    n = 5000
    sigma = list(range(n))[::-1]
    layout = BC(n, 1, 1, 1, n, 1).relabel(sigma)
    df = spark.range(n).select(layout.owner_of(F.col("id"), F.lit(0).cast("long")).alias("site"))
    assert [r.site for r in df.collect()] == sigma
    assert len(df._jdf.queryExecution().analyzed().toString()) < 60_000


def greedy_by_gain(gain):
    """One pair after the other: the largest gain left, ties by role, then site."""
    n, sigma, taken = len(gain), {}, set()
    for _, x, y in sorted((-gain[x][y], x, y) for x in range(n) for y in range(n)):
        if x not in sigma and y not in taken:
            sigma[x] = y
            taken.add(y)
    return [sigma[x] for x in range(n)]


@pytest.mark.parametrize("seed", range(3))
def test_costs_hold_beyond_the_limit(spark, monkeypatch, seed):
    p, links = random_parcels(spark, 5, seed), cost.LinkCost(cost.region_links(spark))
    for model in (links, links + 0.5 * cost.ItemCost()):
        delta = gains(p, model, 5)
        want = greedy_by_gain(delta.tolist())
        want = want if assign.gain_of(delta, want) >= 0 else list(range(5))
        with monkeypatch.context() as m:
            m.setattr(assign, "EXACT_LIMIT", 2)
            plan = find_relabeling(p, model, n=5)
        assert plan.solver == "rounds" and plan.sigma == want
        assert abs(plan.cost_before - plan.cost_after - assign.gain_of(delta, want)) < 1e-6
    with monkeypatch.context() as m:
        m.setattr(assign, "EXACT_LIMIT", 2)
        for solver in ("exact", "greedy", "swap", "flow"):
            with pytest.raises(ValueError):
                find_relabeling(p, links, solver, n=5)


def test_each_term_has_its_own_links(spark):
    p = spark.createDataFrame([(0, 1, 1, 10), (1, 0, 1, 7)], "src int, dst int, n_pieces long, vol long")
    one = cost.LinkCost(spark.createDataFrame([(0, 1, 3000.0, 0.0), (1, 0, 1.0, 0.0)], "src int, dst int, lat double, bw double"))
    two = cost.LinkCost(spark.createDataFrame([(0, 1, 1.0, 2.0), (1, 0, 5.0, 1.0)], "src int, dst int, lat double, bw double"))
    price = lambda c: {r.src: r.weight for r in graph.comm_graph(p, c).collect()}
    assert price(one) == {0: 3000.0, 1: 1.0} and price(two) == {0: 21.0, 1: 12.0}
    assert price(one + two) == {0: 3021.0, 1: 13.0} and price(2 * (one + 3 * two) + cost.VolumeCost()) == {0: 6136.0, 1: 81.0}
    with pytest.raises(ValueError):
        (one + two).of(F.lit(0), F.lit(1), F.lit(1), F.lit(1), F.lit(0.0), F.lit(0.0))


def test_costs_read_lines_and_needs(spark):
    la, lb = BC(8, 8, 4, 4, 2, 1), BC(8, 8, 8, 4, 1, 2)
    by_row, by_col = (parcel_lines(grid_overlay(spark, la, lb), o) for o in ("row", "col"))
    assert {r.n_lines for r in by_row.collect()} == {4} and {r.vol for r in by_row.collect()} == {128}
    locality = lambda p: {r.weight for r in graph.comm_graph(p, cost.LocalityCost(2.0, 64, True, "n_lines")).filter("src <> dst").collect()}
    assert locality(by_row) == locality(by_col) == {4 * 64 * 2.0}
    p = spark.createDataFrame([(0, 1, 1, 10, 4), (1, 0, 1, 7, 0)], "src int, dst int, n_pieces long, vol long, turned long")
    assert [r.weight for r in cost.TransformCost(0.5, needs="turned").weight(p).collect()] == [2.0, 0.0]


def test_solver_cost_grows_with_sites():
    assert 0 < measures.solver_seconds(16) < 5 and measures.solver_seconds(64, "greedy") > 0


def test_files_and_descriptors(spark, tmp_path):
    layout = BC(9, 5, 2, 2, 2, 2).window(1, 8, 0, 5).relabel([1, 0, 3, 2])
    tables.save_layout(spark, layout, f"{tmp_path}/layout")
    assert tables.load_layout(spark, f"{tmp_path}/layout") == layout
    df = spark.range(20).select("id", (F.col("id") % 3).alias("site"))
    tables.write(df, f"{tmp_path}/sites", by=["site"])
    assert sorted(p.name for p in (tmp_path / "sites").iterdir() if p.is_dir()) == ["site=0", "site=1", "site=2"]
    assert rows(tables.read(spark, f"{tmp_path}/sites").select("id", F.col("site").cast("long"))) == rows(df)
    tables.write(df, f"{tmp_path}/c", fmt="csv")
    assert rows(tables.read(spark, f"{tmp_path}/c", "csv", "id long, site long")) == rows(df)
    with pytest.raises(ValueError):
        tables.write(df, f"{tmp_path}/b", buckets=4)
