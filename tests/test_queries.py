"""Every registered query of the library against its SQL in DuckDB, at the smallest scale."""

from __future__ import annotations

import glob
import math
import os
from decimal import Decimal

import duckdb
import pytest

from relayout.queries import load

SF = "/root/testdata/sf0.01"
QUERIES, ORACLES = load()
#: Slow ones; the driver compares them too.
SLOW = {"w4_reduction", "w4_volume_sweep", "relabel_auction_region"}


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(t)[:-8]} AS SELECT * FROM '{t}'")
    return con


def plain(x):
    if isinstance(x, Decimal):
        x = float(x)
    return ("nan" if math.isnan(x) else round(x, 9)) if isinstance(x, float) else x


@pytest.mark.parametrize("name", sorted(set(ORACLES) - SLOW))
def test_against_sql(spark, duck, name):
    df = QUERIES[name](spark, SF)
    got = df.collect()
    found = duck.execute(ORACLES[name])
    names = [c[0] for c in found.description]
    assert sorted(names) == sorted(df.columns)
    want = found.fetchall()
    key = sorted(df.columns)
    assert sorted([tuple(plain(r[c]) for c in key) for r in got], key=str) == sorted([tuple(plain(r[names.index(c)]) for c in key) for r in want], key=str)


def test_entry(spark):
    import __spark_entry__

    row = __spark_entry__.entry(spark).first()
    assert (row.before, row.after) == (124_251, 119_130)
