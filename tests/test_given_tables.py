"""Layouts, overlays and joins over whole given tables, against plain Python, on small tables with gaps and nulls."""

from __future__ import annotations

from collections import Counter
from datetime import datetime, timedelta

import numpy as np
import pytest

from relayout.queries import load

QUERIES, _ = load()


@pytest.fixture(scope="module")
def tables(spark, tmp_path_factory):
    """A folder of tables, and their rows. The last keys occur once; some have no key or no date."""
    d, rng = str(tmp_path_factory.mktemp("given")), np.random.default_rng(5)
    when = lambda: datetime(1999, 1, 1) + timedelta(minutes=int(rng.integers(0, 525_600)))
    some = lambda k: int(rng.integers(0, k))
    orders = [(k, some(61), when()) for k in range(90)] + [(90, 83, when()), (91, None, when()), (92, 5, None), (93, None, None)]
    lines = [(some(43), some(51), when(), float(some(51)), some(8)) for _ in range(150)] + [(70, 77, when(), 50.0, 7), (None, 3, when(), 51.0, 1), (3, None, when(), None, 2), (4, 5, None, 9.0, None), (1, 1, when(), float("nan"), 1), (2, 2, when(), 3.0, 8)]
    events = [(k, some(110), datetime(1999, 1, 1) + timedelta(minutes=k * 7 + some(7))) for k in range(900)] + [(2100, 160, datetime(1999, 1, 9)), (None, 4, datetime(1999, 1, 10)), (901, None, datetime(1999, 1, 11)), (902, 7, None)]
    customers = [(k, some(7)) for k in range(2, 60)] + [(90, 8), (91, None), (None, 9)]
    parts = [(k, 1 + some(5)) for k in range(3, 70)] + [(88, 9), (None, 9)]
    for name, rows, schema in (
        ("orders", orders, "o_orderkey long, o_custkey long, o_orderdate timestamp_ntz"), ("lineitem", lines, "l_suppkey long, l_partkey long, l_shipdate timestamp_ntz, l_quantity double, l_linenumber int"),
        ("events", events, "event_id long, user_id long, ts timestamp_ntz"), ("customer", customers, "c_custkey long, c_nationkey int"), ("part", parts, "p_partkey long, p_size int"),
    ):
        spark.createDataFrame(rows, schema).write.parquet(f"{d}/{name}.parquet")
    return d, {"orders": orders, "lineitem": lines, "events": events, "customer": customers, "part": parts}


def whole(pairs):
    """Of (i, j) those with both."""
    return [(i, j) for i, j in pairs if i is not None and j is not None]


def customer_months(rows):
    return whole((c, t and t.month - 1) for _, c, t in rows["orders"])


def supplier_months(rows):
    return whole((s, t and t.month - 1) for s, _, t, *_ in rows["lineitem"])


def supplier_parts(rows):
    return whole((s, p) for s, p, *_ in rows["lineitem"])


def user_hours(rows):
    return whole((u, t and t.hour) for _, u, t in rows["events"])


def got(spark, d, name):
    df = QUERIES[name](spark, d)
    return sorted(tuple(r) for r in df.collect())


def grid(cells, m, n, mb, nb, site):
    """Blocks of m x n cells, their site, and how many of cells each holds."""
    held = Counter((i // mb, j // nb) for i, j in cells)
    return sorted((x, y, x * mb, min(m, x * mb + mb), y * nb, min(n, y * nb + nb), site(x, y), held[x, y]) for x in range(-(-m // mb)) for y in range(-(-n // nb)))


def test_layout_block_cyclic_holds_every_order(spark, tables):
    d, rows = tables
    assert got(spark, d, "layout_block_cyclic") == grid(customer_months(rows), 84, 12, 7, 5, lambda x, y: y % 4 * 3 + x % 3)


def test_layout_blocks_holds_every_line(spark, tables):
    d, rows = tables
    cells = whole((q, k) for *_, q, k in rows["lineitem"])
    blocks = [(0, 0, 0, 7, 0, 4, 0), (0, 1, 0, 7, 4, 8, 1), (1, 0, 7, 10, 0, 4, 2), (1, 1, 7, 10, 4, 8, 0), (2, 0, 10, 51, 0, 4, 1), (2, 1, 10, 51, 4, 8, 2)]
    assert got(spark, d, "layout_blocks") == [(*b, sum(b[2] <= i < b[3] and b[4] <= j < b[5] for i, j in cells)) for b in blocks]


def test_layout_contiguous_holds_every_line(spark, tables):
    d, rows = tables
    assert got(spark, d, "layout_contiguous") == grid(supplier_parts(rows), 71, 78, 18, 39, lambda x, y: x * 2 + y)


def test_layout_contiguous_without_lines(spark, tmp_path):
    spark.createDataFrame([(None, 1)], "l_suppkey long, l_partkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    assert got(spark, str(tmp_path), "layout_contiguous") == []


def test_layout_relabelled_holds_every_event(spark, tables):
    d, rows = tables
    want = grid(user_hours(rows), 161, 24, 50, 16, lambda x, y: [3, 1, 0, 2][x % 2 * 2 + y % 2])
    assert got(spark, d, "layout_relabelled") == [(b[0], b[1], b[6], b[7]) for b in want]


def test_layout_transposed_holds_every_line(spark, tables):
    d, rows = tables
    want = grid(supplier_months(rows), 71, 12, 7, 5, lambda x, y: x % 3 * 4 + y % 4)
    assert got(spark, d, "layout_transposed") == sorted((y, x, c, ce, r, re, site, n) for x, y, r, re, c, ce, site, n in want)


def test_axis_overlay_holds_every_order(spark, tables):
    d, rows = tables
    keys = [c for _, c, _ in rows["orders"] if c is not None]
    starts = sorted({*range(0, 84, 7), *range(0, 84, 12)})
    assert got(spark, d, "axis_overlay") == [(k, lo, hi, lo // 7, lo // 12, sum(lo <= c < hi for c in keys)) for k, (lo, hi) in enumerate(zip(starts, [*starts[1:], 84], strict=True))]


def test_grid_overlay_holds_every_event(spark, tables):
    d, rows = tables
    held, pieces = Counter((t.minute, t.hour) for *_, t in rows["events"] if t), {}
    for i in range(60):
        for j in range(24):
            pieces.setdefault((i // 7, j // 5, i // 4, j // 6), []).append((i, j))
    want = []
    for (ra, ca, rb, cb), at in pieces.items():
        i, j = zip(*at, strict=True)
        want.append((min(i), max(i) + 1, min(j), max(j) + 1, rb % 3 * 2 + cb % 2, ca % 3 * 2 + ra % 2, sum(held[x] for x in at)))
    assert got(spark, d, "grid_overlay") == sorted(want)


def moved(cells, b, a):
    """Pairs of sites between which cells go; b, a: block, on 4 x 4 sites, and the order of sites."""
    site = lambda i, j, k, order: (i // k % 4 * 4 + j // k % 4) if order == "row" else (j // k % 4 * 4 + i // k % 4)
    return {(site(i, j, *b), site(i, j, *a)) for i, j in cells}


def test_batch_messages_are_of_all_tables(spark, tables):
    d, rows = tables
    each = [{(s, t) for s, t in moved(f(rows), (2, "row"), (8, "row")) if s != t} for f in (customer_months, supplier_months, user_hours)]
    assert got(spark, d, "batch_messages") == [(len(set().union(*each)), sum(map(len, each)))]


def test_graph_neighbours_are_those_of_the_lines(spark, tables):
    d, rows = tables
    pairs = moved(supplier_parts(rows), (8, "row"), (16, "col"))
    text = lambda xs: ",".join(sorted(map(str, xs)))
    sites = {s for s, _ in pairs} & {t for _, t in pairs}
    assert got(spark, d, "graph_neighbours") == sorted((x, text(s for s, t in pairs if t == x), text(t for s, t in pairs if s == x)) for x in sites)


def span(pairs):
    """(k, lo, hi) of (k, x); a group without x has no bounds."""
    groups = {}
    for k, x in pairs:
        groups.setdefault(k, []).extend([] if x is None else [x])
    return [(k, min(xs, default=None), max(xs) + 1 if xs else None) for k, xs in groups.items()]


def test_join_cross_is_of_all_orders_and_lines(spark, tables):
    d, rows = tables
    a, b = span((t and t.month, c) for _, c, t in rows["orders"]), span((k, p) for _, p, _, _, k in rows["lineitem"])
    area = lambda x, y: None if None in (x[1], y[1]) else (x[2] - x[1]) * (y[2] - y[1])
    assert sorted(map(tuple, QUERIES["join_cross"](spark, d).collect()), key=str) == sorted(((x[0], y[0], area(x, y)) for x in a for y in b), key=str)


def test_join_interval_is_of_all_events(spark, tables):
    d, rows = tables
    days = span((t and (t - datetime(1970, 1, 1)).days, k) for k, _, t in rows["events"])
    want = [(k, b) for k, lo, hi in days if lo is not None for b in range(-(-2101 // 700)) if lo < min(2101, b * 700 + 700) and b * 700 < hi]
    assert sorted(map(tuple, QUERIES["join_interval"](spark, d).collect()), key=str) == sorted(want, key=str)
