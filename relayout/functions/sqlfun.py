"""Functions under SQL names: owners and costs as expressions, the total gain as an aggregate, overlay and assignment as
table functions. Native expressions come first; Python runs only where SQL has no form for it, on data of a plan's size."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relayout.plans import assign
from relayout.plans.graph import gain_matrix_volume


def register(spark: SparkSession) -> None:
    """owner_cyclic, remote_cost (SQL functions), total_gain (aggregate), overlay_axis, solve_assignment (table functions)."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION owner_cyclic(i BIGINT, j BIGINT, mb INT, nb INT, pr INT, pc INT) RETURNS INT RETURN CAST(pmod(i div mb, pr) * pc + pmod(j div nb, pc) AS INT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION remote_cost(src INT, dst INT, vol BIGINT) RETURNS BIGINT RETURN CASE WHEN src <> dst THEN vol ELSE 0 END")
    spark.udtf.register("overlay_axis", OverlayAxis)
    spark.udtf.register("solve_assignment", SolveAssignment)

    @F.pandas_udf("long")
    def total_gain(gain: pd.Series) -> int:
        return int(gain.sum())

    spark.udf.register("total_gain", total_gain)


@F.udtf(returnType="lo bigint, hi bigint, ka bigint, kb bigint")
class OverlayAxis:
    """The pieces of two equal splits of an axis."""

    def eval(self, extent: int, a: int, b: int) -> Iterator[tuple[int, int, int, int]]:
        lo = 0
        while lo < extent:
            hi = min((lo // a + 1) * a, (lo // b + 1) * b, extent)
            yield lo, hi, lo // a, lo // b
            lo = hi


@F.udtf(returnType="role int, site int")
class SolveAssignment:
    """The best relabeling of a table of parcels (src, dst, vol); all rows in one partition, as many as sites squared."""

    def __init__(self) -> None:
        self.rows: list[tuple[int, int, int]] = []

    def eval(self, row) -> None:  # noqa: ANN001
        self.rows.append((row["src"], row["dst"], row["vol"]))

    def terminate(self) -> Iterator[tuple[int, int]]:
        import numpy as np

        n = 1 + max((max(s, d) for s, d, _ in self.rows), default=-1)
        held = np.zeros((n, n))
        for s, d, v in self.rows:
            held[d, s] += v
        sigma, _ = assign.solve_exact(held - np.diag(held)[:, None])
        yield from enumerate(sigma)


def owner_by_name(spark: SparkSession, entries: DataFrame) -> DataFrame:
    register(spark)
    entries.createOrReplaceTempView("relayout_entries")
    return spark.sql("SELECT i, j, owner_cyclic(i, j, 8, 8, 4, 4) AS site FROM relayout_entries")


def gain_by_udaf(spark: SparkSession, parcels: DataFrame, sigma: list[int]) -> DataFrame:
    register(spark)
    line = F.array(*(F.lit(s) for s in sigma))
    gain_matrix_volume(parcels).filter(F.col("site") == F.element_at(line, F.col("role") + 1)).createOrReplaceTempView("relayout_gain")
    return spark.sql("SELECT total_gain(gain) AS total_gain FROM relayout_gain")


def overlay_by_name(spark: SparkSession, extent: int, a: int, b: int) -> DataFrame:
    register(spark)
    return spark.sql(f"SELECT * FROM overlay_axis({extent}, {a}, {b})")


def assignment_by_name(spark: SparkSession, parcels: DataFrame) -> DataFrame:
    """(before, after) of the relabeling that the table function finds."""
    register(spark)
    parcels.select("src", "dst", "vol").createOrReplaceTempView("relayout_trade")
    return spark.sql(
        "WITH best AS (SELECT * FROM solve_assignment(TABLE(SELECT src, dst, vol FROM relayout_trade) WITH SINGLE PARTITION)) "
        "SELECT sum(CASE WHEN src <> dst THEN vol ELSE 0 END) AS before, sum(CASE WHEN src <> site THEN vol ELSE 0 END) AS after FROM relayout_trade JOIN best ON dst = role"
    )
