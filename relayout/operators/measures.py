"""What a plan moves: bytes, messages, load, and how well a solver did."""

from __future__ import annotations

import time
from collections.abc import Callable
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from relayout.plans.layout import Layout, Splits
from relayout.plans.overlay import axis_overlay, grid_overlay, piece_start
from relayout.plans.relabel import _solve, sigma_expr


def volume_remote(parcels: DataFrame, sigma: list[int] | None = None) -> DataFrame:
    dst: Column = F.col("dst") if sigma is None else sigma_expr(sigma, F.col("dst"))
    return parcels.agg(F.coalesce(F.sum(F.when(F.col("src") != dst, F.col("vol"))), F.lit(0)).cast("long").alias("remote"))


def reduction_pct(parcels: DataFrame, sigma: list[int]) -> DataFrame:
    """(before, after, reduction): per cent less, null if nothing was remote."""
    both = volume_remote(parcels).toDF("before").crossJoin(volume_remote(parcels, sigma).toDF("after"))
    return both.withColumn("reduction", F.when(F.col("before") > 0, F.round((F.col("before") - F.col("after")) * 100.0 / F.col("before"), 4)))


def message_count(parcels: DataFrame) -> DataFrame:
    """(packed, unpacked): remote parcels, and remote pieces."""
    far = parcels.filter("src <> dst")
    return far.agg(F.count(F.lit(1)).alias("packed"), F.coalesce(F.sum("n_pieces"), F.lit(0)).cast("long").alias("unpacked"))


def batch_messages(batch: list[DataFrame]) -> DataFrame:
    """(batched, apart): remote parcels where several matrices move at once, a parcel for each pair of sites, and where
    each moves by itself."""
    pairs = reduce(DataFrame.union, (p.select("src", "dst") for p in batch)).filter("src <> dst").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))
    return pairs.agg(F.count(F.lit(1)).alias("batched"), F.coalesce(F.sum("n"), F.lit(0)).alias("apart"))


def site_load(parcels: DataFrame) -> DataFrame:
    """(site, sent, received): remote bytes."""
    far = parcels.filter("src <> dst")
    sent = far.groupBy(F.col("src").alias("site")).agg(F.sum("vol").alias("sent"))
    got = far.groupBy(F.col("dst").alias("site")).agg(F.sum("vol").alias("received"))
    return sent.join(got, "site", "full").select("site", F.coalesce("sent", F.lit(0)).alias("sent"), F.coalesce("received", F.lit(0)).alias("received"))


def block_load(layout: Layout, cells: DataFrame) -> DataFrame:
    """(bi, bj, r_lo, r_hi, c_lo, c_hi, site, n_rows): all blocks of a layout, and how many rows of cells (i, j) lie in
    each. Rows outside the matrix lie in none. With a column n_rows, a row of cells stands for that many."""
    bi, bj = layout.blocks_of(F.col("i"), F.col("j"))
    inside = cells.filter(F.col("i").between(0, layout.m - 1) & F.col("j").between(0, layout.n - 1))
    held = inside.groupBy(bi.alias("x"), bj.alias("y")).agg(F.sum(F.col("n_rows") if "n_rows" in cells.columns else F.lit(1)).alias("n_rows"))
    # null-safe, though no key is null: from a plain one the blocks' own conditions are inferred for every row of cells
    same = F.col("bi").eqNullSafe(F.col("x")) & F.col("bj").eqNullSafe(F.col("y"))
    return layout.blocks(cells.sparkSession).join(held, same, "left").drop("x", "y").withColumn("n_rows", F.coalesce("n_rows", F.lit(0)))


def axis_load(a: tuple[Splits, int, int], b: tuple[Splits, int, int], cells: DataFrame) -> DataFrame:
    """axis_overlay() and n_rows: how many rows of cells (i) lie in each piece."""
    held = cells.groupBy(piece_start(a, b, F.col("i")).alias("lo")).agg(F.count(F.lit(1)).alias("n_rows"))
    return axis_overlay(cells.sparkSession, a, b).join(held, "lo", "left").withColumn("n_rows", F.coalesce("n_rows", F.lit(0)))


def grid_load(la: Layout, lb: Layout, cells: DataFrame) -> DataFrame:
    """grid_overlay() and n_rows: how many rows of cells (i, j, n_rows) lie in each piece."""
    r, c = (piece_start(la.axis(k), lb.axis(k), F.col("ij"[k])).alias(("r_lo", "c_lo")[k]) for k in (0, 1))
    held = cells.groupBy(r, c).agg(F.sum("n_rows").alias("n_rows"))
    return grid_overlay(cells.sparkSession, la, lb).join(held, ["r_lo", "c_lo"], "left").withColumn("n_rows", F.coalesce("n_rows", F.lit(0)))


def shuffled(spark: SparkSession, action: Callable[[], object]) -> tuple[int, int]:
    """Bytes and records that an action's stages write to exchanges: what physically moves, beside the logical volume."""
    store = spark.sparkContext._jsc.sc().statusStore()

    def stages() -> dict[tuple[int, int], tuple[int, int]]:
        found = store.stageList(spark.sparkContext._jvm.java.util.ArrayList(), False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), spark.sparkContext._jvm.java.util.ArrayList())
        return {(x.stageId(), x.attemptId()): (x.shuffleWriteBytes(), x.shuffleWriteRecords()) for x in (found.apply(k) for k in range(found.size()))}

    before = set(stages())
    action()
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
    new = [v for k, v in stages().items() if k not in before]
    return sum(b for b, _ in new), sum(r for _, r in new)


def solver_seconds(n: int, solver: str = "exact", seed: int = 0) -> float:
    """Seconds to assign n roles to n sites for random volumes; planning cost against n."""
    volumes = np.random.default_rng(seed).integers(0, 1000, (n, n))
    began = time.perf_counter()
    _solve(volumes, solver)
    return time.perf_counter() - began


def max_residual(a: DataFrame, b: DataFrame) -> DataFrame:
    """(residual): the largest absolute difference of two matrices' cells."""
    both = a.select("i", "j", F.col("v").alias("x")).join(b.select("i", "j", F.col("v").alias("y")), ["i", "j"], "full")
    return both.agg(F.max(F.abs(F.coalesce("x", F.lit(0)) - F.coalesce("y", F.lit(0)))).alias("residual"))


def gain_bound(parcels: DataFrame) -> DataFrame:
    """(bound): no relabeling can win more: for each role its largest parcel less what it has at home."""
    v = parcels.groupBy("dst").agg(F.max("vol").alias("top"), F.coalesce(F.sum(F.when(F.col("src") == F.col("dst"), F.col("vol"))), F.lit(0)).alias("own"))
    return v.agg(F.sum(F.greatest(F.col("top") - F.col("own"), F.lit(0))).cast("long").alias("bound"))
