"""The routine: values, edge cases, and what crosses an exchange."""

from __future__ import annotations

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from relayout.operators import measures, product, routine, tiles
from relayout.plans.layout import Layout, Splits
from relayout.sources import tables

BC = Layout.block_cyclic
LB, LA, LT = BC(12, 9, 2, 2, 2, 2), BC(12, 9, 5, 4, 2, 2, "col"), BC(9, 12, 4, 5, 2, 2)


@pytest.fixture(scope="module")
def b(spark):
    return spark.range(12 * 9).select((F.col("id") / 9).cast("long").alias("i"), (F.col("id") % 9).alias("j"), (F.col("id") * 7 % 31).cast("double").alias("v"))


def cells(df):
    return {(r.i, r.j): r.v for r in df.collect()}


@pytest.mark.parametrize("relabel", ["optimal", "greedy", "retained", "none"])
@pytest.mark.parametrize("transform", ["receive", "send"])
def test_transpose_scale_accumulate(spark, b, relabel, transform):
    a = b.select(F.col("j").alias("i"), F.col("i").alias("j"), (F.col("v") + 1).alias("v")).filter("i <> 3")
    out, layout, plan = routine.shuffle_transpose(a, LT, b, LB, 2, 0.5, "transpose", relabel=relabel, transform=transform)
    old = cells(a)
    want = {(j, i): 2 * v + 0.5 * old.get((j, i), 0) for (i, j), v in cells(b).items()}
    assert cells(out) == want and plan.after <= plan.before
    assert out.select("pid", layout.owner_of(F.col("i"), F.col("j")).alias("o")).filter("pid <> o").count() == 0


def test_there_and_back_and_twice(spark, b):
    out, la, _ = routine.shuffle_transpose(None, LA, b, LB)
    back, _, _ = routine.shuffle_transpose(None, LB, out.select("i", "j", "v"), la)
    assert cells(back) == cells(b)
    once, lt, _ = routine.shuffle_transpose(None, LT, b, LB, op="transpose")
    twice, _, _ = routine.shuffle_transpose(None, LA, once.select("i", "j", "v"), lt, op="transpose")
    assert cells(twice) == cells(b)


def test_beta_zero_never_reads_a(spark, b):
    nan = b.withColumn("v", F.lit(float("nan")))
    out, _, _ = routine.shuffle_transpose(nan, LA, b, LB, beta=0)
    assert not any(math.isnan(v) for v in cells(out).values())
    assert set(cells(routine.shuffle_transpose(None, LA, b, LB, alpha=0)[0]).values()) == {0.0}


def test_only_what_moves_is_exchanged(spark, b):
    out, _, plan = routine.shuffle_transpose(None, LA, b, LB, bypass_local=True)
    text = out._jdf.queryExecution().executedPlan().toString()
    assert text.count("Exchange") == 1 and "Python" not in text and "Pandas" not in text
    whole = routine.shuffle_transpose(None, LA, b, LB, bypass_local=False)[0]
    assert cells(whole) == cells(out)
    moved = routine.rows_of(routine.Task(None, LA, b, LB), plan.sigma, False).filter("src <> pid").count()
    assert moved * 8 == plan.after


def test_batch_is_the_single_form(spark, b):
    tasks = [routine.Task(None, LA, b.withColumn("v", F.col("v") + k), LB, alpha=k + 1) for k in range(3)]
    for sigma in ("shared", "per_pair"):
        out, _ = routine.shuffle_transpose_batch(tasks, sigma=sigma)
        for k in range(3):
            assert cells(out.filter(F.col("mat") == k)) == {c: (v + k) * (k + 1) for c, v in cells(b).items()}


def test_batch_with_beta_and_ops(spark, b):
    a = b.select("i", "j", (F.col("v") * 3).alias("v")).filter("j <> 2")
    turned = a.select(F.col("j").alias("i"), F.col("i").alias("j"), "v")
    tasks = [routine.Task(a, LA, b, LB, 2, 0.5), routine.Task(turned, LT, b, LB, 1, 4, "transpose"), routine.Task(None, LA, b, LB, 5)]
    out, plans = routine.shuffle_transpose_batch(tasks)
    assert len(plans) == 3
    for k, t in enumerate(tasks):
        alone = routine.shuffle_transpose(t.a, t.la, t.b, t.lb, t.alpha, t.beta, t.op)[0]
        assert cells(out.filter(F.col("mat") == k)) == cells(alone)
    one = routine.shuffle_transpose_batch(tasks[2:] * 3)[0]._jdf.queryExecution().executedPlan().toString()
    assert one.count("Exchange") == 1


def test_content_of_a_moves_with_its_role(spark, b):
    a = b.select("i", "j", (F.col("v") + 7).alias("v")).filter("i <> 1")
    for home in ("relabelled", "original"):
        out, layout, plan = routine.shuffle_transpose(a, LA, b, LB, 2, 3, a_home=home)
        old = cells(a)
        assert cells(out) == {c: 2 * v + 3 * old.get(c, 0) for c, v in cells(b).items()}
        assert out.select("pid", layout.owner_of(F.col("i"), F.col("j")).alias("o")).filter("pid <> o").count() == 0
    turned = [1, 0, 3, 2]
    moved = routine.rows_of(routine.Task(a, LA, b, LB, 1, 1), turned, False, "original").filter("kind = 1")
    assert moved.filter("src = pid").count() == 0 and routine.rows_of(routine.Task(a, LA, b, LB, 1, 1), turned, False).filter("kind = 1 AND src <> pid").count() == 0


@pytest.mark.parametrize("op", ["identity", "transpose"])
@pytest.mark.parametrize("transform", ["receive", "send"])
def test_tiles_through_the_routine(spark, b, op, transform):
    la = LT if op == "transpose" else LA
    a = b.select("i", "j", (F.col("v") + 1).alias("v")) if op == "identity" else b.select(F.col("j").alias("i"), F.col("i").alias("j"), (F.col("v") + 1).alias("v"))
    for order, pad, to, to_pad in (("row", 0, "col", 0), ("col", 2, "row", 3)):
        t = tiles.to_tiles(b, LB, order=order, pad=pad)
        out, layout, plan = tiles.shuffle_tiles(t, LB, la, 2, 0.5, tiles.to_tiles(a, la, order=to, pad=1), op, to, to_pad, transform=transform)
        want = routine.shuffle_transpose(a, la, b, LB, 2, 0.5, op)[0]
        assert cells(tiles.from_tiles(out)) == cells(want)
        assert {(r.ord, r.ld - (r.nc if to == "row" else r.nr)) for r in out.collect()} == {(to, to_pad)}
        assert out.select("pid", layout.owner_of_block(F.col("bi"), F.col("bj")).alias("o")).filter("pid <> o").count() == 0 and plan.after <= plan.before


def test_tiles_of_windows_and_general_grids(spark, b):
    inside = routine.submatrix(b, (3, 11, 1, 9))
    whole = tiles.to_tiles(inside, LB.window(3, 11, 1, 9))
    target = Layout.grid_of((0, 3, 8), (0, 5, 8), [[0, 1], [2, 0]], 3)
    assert cells(tiles.from_tiles(tiles.shuffle_tiles(whole, LB.window(3, 11, 1, 9), target)[0])) == cells(inside)
    for bad in (lambda: tiles.shuffle_tiles(whole, LB, LA, op="conj"), lambda: tiles.shuffle_tiles(whole, LB, LA, beta=1)):
        with pytest.raises(ValueError):
            bad()


def test_tiles_shuffle_fewer_bytes_than_cells(spark):
    n = 256
    lb, la = BC(n, n, 32, 32, 4, 4), BC(n, n, 64, 64, 4, 4)
    x = tables.square(spark, n)
    t = tiles.to_tiles(x, lb).persist()
    t.count()
    run = lambda df: df.write.format("noop").mode("overwrite").save()
    packed, _ = measures.shuffled(spark, lambda: run(tiles.shuffle_tiles(t, lb, la)[0]))
    single, records = measures.shuffled(spark, lambda: run(routine.shuffle_transpose(None, la, x, lb, bypass_local=False)[0]))
    assert 0 < packed < single and records == n * n


def test_tensors_are_laid_out_anew(spark):
    shape, perm = (6, 5, 4), [2, 0, 1]
    b = spark.range(120).select(F.array((F.col("id") / 20).cast("long"), F.pmod((F.col("id") / 4).cast("long"), F.lit(5)), F.col("id") % 4).alias("idx"), F.col("id").alias("v"))
    lb = [(Splits(6, 2), 2), (Splits(5, 2), 3), (Splits(4, 1), 2)]
    la = [(Splits(4, 2), 2), (Splits(6, 1), 3), (Splits(5, 3), 2)]
    out, plan = routine.reshuffle_tensor(b, perm, la, lb, alpha=2)
    got = {tuple(r.idx): (r.v, r.pid) for r in out.collect()}
    held, own = [[0] * 12 for _ in range(12)], {}
    for r in b.collect():
        x = tuple(r.idx)
        y = tuple(x[p] for p in perm)
        src = ((x[0] // 2 % 2) * 3 + x[1] // 2 % 3) * 2 + x[2] % 2
        dst = ((y[0] // 2 % 2) * 3 + y[1] % 3) * 2 + y[2] // 3 % 2
        held[src][dst] += 8
        own[y] = (2 * r.v, plan.sigma[dst])
    assert got == own and len(got) == 6 * 5 * 4 and shape == (6, 5, 4)
    assert plan.before == sum(held[s][t] for s in range(12) for t in range(12) if s != t)
    assert plan.after == sum(held[s][t] for s in range(12) for t in range(12) if s != plan.sigma[t]) <= plan.before
    with pytest.raises(ValueError):
        routine.reshuffle_tensor(b, [0, 1, 2], la, lb)


def test_products_on_slabs(spark):
    draw = np.random.default_rng(2)
    for m, nx, ny, share in ((40, 7, 5, 1.0), (33, 1100, 3, 0.2), (10, 4, 4, 0.0)):
        x, y = draw.integers(-50, 50, (m, nx)), draw.integers(-50, 50, (m, ny))
        there = [draw.random(z.shape) <= share for z in (x, y)]
        frames = [spark.createDataFrame([(int(i), int(j), int(z[i, j])) for i, j in zip(*np.nonzero(t), strict=True)], "i long, j long, v long") for z, t in zip((x, y), there, strict=True)]
        got = {(r.i, r.j): r.v for r in product.gram(*frames, BC(m, nx, 3, 3, 2, 2), BC(m, ny, 4, 2, 2, 2), BC(nx, ny, 4, 4, 2, 2), 3)[0].collect()}
        want, some = (x * there[0]).T @ (y * there[1]), there[0].astype(int).T @ there[1].astype(int) > 0
        assert got == {(int(i), int(j)): int(want[i, j]) for i, j in zip(*np.nonzero(some), strict=True)}
    x = spark.createDataFrame([(0, 0, 2**31), (1, 0, 2**30)], "i long, j long, v long")
    assert product.gram(x, x, BC(2, 1, 1, 1, 2, 1), BC(2, 1, 1, 1, 2, 1), BC(1, 1, 1, 1, 1, 1), 1)[0].first().v == 2**62 + 2**60
    plan = product.gram(x, x, BC(2, 1, 1, 1, 2, 1), BC(2, 1, 1, 1, 2, 1), BC(1, 1, 1, 1, 1, 1), 1)[0]._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") <= 4


def test_tiles_keep_cells(spark, b):
    for order in ("row", "col"):
        for pad in (0, 2):
            t = tiles.to_tiles(b, LA, order=order, pad=pad)
            assert cells(tiles.from_tiles(t)) == cells(b)
            assert cells(tiles.from_tiles(tiles.transpose_tiles(t))) == {(j, i): v for (i, j), v in cells(b).items()}


def test_wrong_arguments(spark, b):
    for bad in (lambda: routine.shuffle_transpose(None, LT, b, LB), lambda: routine.shuffle_transpose(None, LA, b, LB, op="turn"), lambda: routine.shuffle_transpose(None, LA, b, LB, beta=1), lambda: routine.block_cyclic_reshuffle(b, Layout.grid_of((0, 12), (0, 9), [[0]], 4), LA)):
        with pytest.raises(ValueError):
            bad()
