"""Queries read whole tables: more embeddings than 500, at one go against numpy."""

from __future__ import annotations

import numpy as np
import pytest

from relayout.queries import load

QUERIES, _ = load()
M, N = 530, 64


@pytest.fixture(scope="module")
def wide(spark, tmp_path_factory):
    d = str(tmp_path_factory.mktemp("wide"))
    x = np.random.default_rng(3).integers(-40, 40, (M, N))
    rows = [(k, [float(v) for v in row]) for k, row in enumerate(x)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").write.parquet(f"{d}/embeddings.parquet")
    return d, x * 1000


@pytest.mark.parametrize("name", ["scan_entries_emb", "reshuffle_emb", "w1_reshuffle", "subset_sites", "tiles_roundtrip", "base_reshuffle", "base_all_to_all"])
def test_all_embeddings_are_moved(spark, wide, name):
    d, x = wide
    got = {(r.i, r.j): r.v for r in QUERIES[name](spark, d).collect()}
    assert got == {(i, j): int(x[i, j]) for i in range(M) for j in range(N)}


@pytest.mark.parametrize("name", ["transpose_emb", "w2_transpose", "base_transpose"])
def test_all_embeddings_are_transposed(spark, wide, name):
    d, x = wide
    got = {(r.i, r.j): r.v for r in QUERIES[name](spark, d).collect()}
    assert got == {(j, i): int(x[i, j]) for i in range(M) for j in range(N)}


@pytest.mark.parametrize("name", ["w5_gram", "gram_emb", "base_gram_entries", "base_gram_tiles"])
def test_products_are_of_all_embeddings(spark, wide, name):
    d, x = wide
    want = x.T @ x
    assert {(r.i, r.j): r.v for r in QUERIES[name](spark, d).collect()} == {(i, j): int(want[i, j]) for i in range(N) for j in range(N)}


def test_complex_embeddings(spark, wide):
    d, x = wide
    got = {(r.i, r.j): (r.re, r.im) for r in QUERIES["conj_transpose_emb"](spark, d).collect()}
    x = x / 1000
    assert got == {(k, i): (2 * x[i, 2 * k], -2 * x[i, 2 * k + 1]) for i in range(M) for k in range(N // 2)}


@pytest.mark.parametrize(("name", "rows"), [("w3_batched3", 3 * M * N), ("batched_emb", 3 * M * N), ("base_unbatched", 3 * M * N), ("axpby_emb", M * N), ("axpby_transpose", M * N), ("wrap_transpose", M * N), ("owner_of_cell", M * N), ("udf_owner", M * N)])
def test_no_cell_is_left_out(spark, wide, name, rows):
    assert QUERIES[name](spark, wide[0]).count() == rows


@pytest.mark.parametrize("how", ["inner", "left", "right", "full"])
def test_joins_read_both_tables_whole(spark, tmp_path, how):
    orders, customers = [(k, k % 7) for k in range(1, 30)], [(k, k % 3) for k in range(2, 12)]
    spark.createDataFrame(orders, "o_orderkey long, o_custkey long").write.parquet(f"{tmp_path}/orders.parquet")
    spark.createDataFrame(customers, "c_custkey long, c_nationkey int").write.parquet(f"{tmp_path}/customer.parquet")
    nation = dict(customers)
    want = [(o, c, nation[c]) for o, c in orders if c in nation]
    if how in ("left", "full"):
        want += [(o, None, None) for o, c in orders if c not in nation]
    if how in ("right", "full"):
        want += [(None, c, n) for c, n in customers if c not in {c for _, c in orders}]
    got = [tuple(r) for r in QUERIES[f"join_{how}"](spark, str(tmp_path)).collect()]
    assert sorted(got, key=str) == sorted(want, key=str)
