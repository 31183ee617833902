"""Products that need their operands in another layout: C = A' B over row slabs, reduced and laid out as C is wanted."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relayout.operators.routine import Task, rows_of
from relayout.plans.layout import Layout
from relayout.plans.relabel import Plan, find_matrix_relabeling, find_shared_relabeling, sigma_expr

#: Columns of a block of C, and cells of a stretch of rows that one kernel call holds.
WIDTH, CELLS = 1024, 2_000_000


def gram(a: DataFrame, b: DataFrame, la: Layout, lb: Layout, lc: Layout, p: int) -> tuple[DataFrame, list[Plan]]:
    """C = A' B (i, j, v, pid) in layout lc, of whole numbers. A and B go to p row slabs, the product's native layout, one
    exchange each; a slab's rows are multiplied where they lie, a stretch of rows by a block of columns at a time, and
    only the sums leave it: combined before they move, reduced by cell, and sent to C's site.

    A cell of C is there if some row has both factors, as in a join of cells; sums are exact up to 64 bits."""
    spark = a.sparkSession
    ends = [(Layout.slabs(x.m, x.n, p), x, "identity") for x in (la, lb)]
    plan = find_shared_relabeling(spark, ends)  # a slab of A and that of B lie at one site
    plan_c = find_matrix_relabeling(spark, lc, Layout.slabs(lc.m, lc.n, p))
    c = slab_product(_on_slabs(a, la, p, plan), _on_slabs(b, lb, p, plan), la.n, lb.n)
    n = max(lc.n_sites, p)
    pid = sigma_expr(plan_c.sigma, lc.owner_of(F.col("i"), F.col("j")))
    return c.withColumn("pid", pid).repartitionById(n, "pid"), [plan, plan, plan_c]


def _on_slabs(x: DataFrame, layout: Layout, p: int, plan: Plan) -> DataFrame:
    """(i, j, v, pid): cells with the slab that they go to; the product's own exchange carries them."""
    return rows_of(Task(None, Layout.slabs(layout.m, layout.n, p), x, layout), plan.sigma, False).select("i", "j", "v", "pid")


def slab_product(xs: DataFrame, ys: DataFrame, nx: int, ny: int) -> DataFrame:
    """(i, j, v) of X' Y from cells (i, j, v, pid): a numpy product for each stretch of rows of a slab and pair of column
    blocks, then one sum. Stretches bound what a task holds, whatever a slab's size."""
    blocks_x, blocks_y = -(-nx // WIDTH), -(-ny // WIDTH)
    tall = max(1, CELLS // max(1, min(max(nx, ny), WIDTH)))

    def side(df: DataFrame, others: int, names: tuple[str, str]) -> DataFrame:
        row = F.col("i").cast("long")
        block = ((F.col("j") - F.pmod("j", F.lit(WIDTH))) / WIDTH).cast("int")
        other = F.lit(0) if others <= 1 else F.explode(F.sequence(F.lit(0), F.lit(others - 1)))
        out = df.select("pid", ((row - F.pmod(row, F.lit(tall))) / tall).cast("long").alias("stretch"), F.pmod(row, F.lit(tall)).cast("int").alias("i"), F.pmod("j", F.lit(WIDTH)).cast("int").alias("j"), F.col("v").cast("long").alias("v"), block.alias(names[0]))
        return out.withColumn(names[1], other)

    def run(x: pa.Table, y: pa.Table) -> pa.Table:
        schema = pa.schema([("i", pa.int64()), ("j", pa.int64()), ("v", pa.int64())])
        if not x.num_rows or not y.num_rows:
            return schema.empty_table()
        at = lambda t, c: t.column(c).to_numpy()
        rows = int(max(at(x, "i").max(), at(y, "i").max())) + 1
        dense, there = [], []
        for t in (x, y):
            shape = (rows, int(at(t, "j").max()) + 1)
            v, held = np.zeros(shape, np.int64), np.zeros(shape, bool)
            v[at(t, "i"), at(t, "j")], held[at(t, "i"), at(t, "j")] = at(t, "v"), True
            dense.append(v)
            there.append(held)
        top = int(np.abs(dense[0]).max()) * int(np.abs(dense[1]).max()) * rows
        product = np.rint(dense[0].astype(float).T @ dense[1].astype(float)).astype(np.int64) if top < 2**53 else dense[0].T @ dense[1]
        if there[0].all() and there[1].all():
            some = np.ones(product.shape, bool)
        else:
            some = there[0].astype(np.float32).T @ there[1].astype(np.float32) > 0
        i, j = np.nonzero(some)
        left, right = x.column("bx")[0].as_py() * WIDTH, y.column("by")[0].as_py() * WIDTH
        return pa.table([pa.array(i + left), pa.array(j + right), pa.array(product[i, j])], schema=schema)

    keys = ["pid", "stretch", "bx", "by"]
    x, y = side(xs, blocks_y, ("bx", "by")), side(ys, blocks_x, ("by", "bx")).toDF("pid", "stretch", "i", "j", "v", "by", "bx")
    return x.groupBy(*keys).cogroup(y.groupBy(*keys)).applyInArrow(run, "i long, j long, v long").groupBy("i", "j").agg(F.sum("v").alias("v"))


def entry_product(a: DataFrame, b: DataFrame) -> DataFrame:
    """(i, j, v) of A' B by a join of cells on the common row and a sum: map-side combined, one exchange of partial sums."""
    x = a.select(F.col("i").alias("k"), F.col("j").alias("i"), F.col("v").alias("x"))
    y = b.select(F.col("i").alias("k"), "j", F.col("v").alias("y"))
    return x.join(y, "k").groupBy("i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("v"))
