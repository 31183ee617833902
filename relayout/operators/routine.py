"""A <- alpha * op(B) + beta * A from one layout into another, with as few remote bytes as possible.

Rows at rest carry the site that holds them and lie in the partition of that number. The relabeling is planned from the
descriptors; only rows whose site changes cross an exchange (the local bypass), once, to the partition of their new
site; scaling and conjugation happen on receipt. What stays is folded with beta * A where it lies, and one join on the
site's own partitions adds what arrives. Each cell stands at most once in B and in A.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce
from math import prod

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from relayout.plans.cost import Cost
from relayout.plans.layout import Layout, Splits
from relayout.plans.overlay import parcels_from_rows, tensor_parcels
from relayout.plans.relabel import Plan, find_matrix_relabeling, find_relabeling, find_shared_relabeling, op_layout, sigma_expr

OPS = ("identity", "transpose", "conj_transpose", "conj")


@dataclass
class Task:
    """One instance of a batch: (A, LA, B, LB, alpha, beta, op)."""

    a: DataFrame | None
    la: Layout
    b: DataFrame
    lb: Layout
    alpha: float | int = 1
    beta: float | int = 0
    op: str | Callable[[Column], Column] = "identity"


def is_complex(df: DataFrame) -> bool:
    return dict(df.dtypes)["v"].startswith("struct")


def _apply(v: Column, factor: float | int, op: object, complex_: bool) -> Column:
    """factor * op(v), on receipt."""
    if callable(op):
        v = op(v)
    if complex_:
        im = -v["im"] if op in ("conj", "conj_transpose") else v["im"]
        return F.struct((v["re"] * factor).alias("re"), (im * factor).alias("im"))
    return v if factor == 1 else v * F.lit(factor)


def _plus(x: Column, y: Column, complex_: bool) -> Column:
    if complex_:
        both = F.struct((x["re"] + y["re"]).alias("re"), (x["im"] + y["im"]).alias("im"))
    else:
        both = x + y
    return F.when(x.isNull(), y).when(y.isNull(), x).otherwise(both)


def _shape(t: Task) -> tuple[int, int]:
    return (t.lb.n, t.lb.m) if t.op in ("transpose", "conj_transpose") else (t.lb.m, t.lb.n)


def _checked(t: Task) -> None:
    if not callable(t.op) and t.op not in OPS:
        raise ValueError(f"op is one of {OPS} or a function of a Column")
    if _shape(t) != (t.la.m, t.la.n):
        raise ValueError(f"op(B) is {_shape(t)}, A is {(t.la.m, t.la.n)}")
    if t.beta and t.a is None:
        raise ValueError("beta needs A")


def rows_of(t: Task, sigma: list[int], send: bool, a_home: str = "relabelled") -> DataFrame:
    """(i, j, v, src, pid, kind): B's cells at their place in A, and A's cells (kind 1) where A lies: at the relabelled
    site, or with a_home 'original' at the site of the layout as it was, so that a moved role moves A's content too."""
    complex_ = is_complex(t.b)
    turn = t.op in ("transpose", "conj_transpose")
    i, j = (F.col("j"), F.col("i")) if turn else (F.col("i"), F.col("j"))
    v = _apply(F.col("v"), t.alpha, t.op, complex_) if send else F.col("v")
    b = t.b.select(i.alias("i"), j.alias("j"), v.alias("v"), t.lb.owner_of(F.col("i"), F.col("j")).alias("src"), F.lit(0).alias("kind"))
    role = t.la.owner_of(F.col("i"), F.col("j"))
    target = sigma_expr(sigma, role)
    rows = b.withColumn("pid", target)
    if t.beta:
        home = role if a_home == "original" else target
        rows = rows.unionByName(t.a.select("i", "j", "v", home.alias("src"), F.lit(1).alias("kind"), target.alias("pid")))
    return rows


def assemble(tasks: list[Task], rows: DataFrame, n: int, send: bool, bypass: bool = True) -> DataFrame:
    """(mat, i, j, v, pid): the targets' cells in the partition of their site. rows: those of all tasks, with mat their number;
    all that moves, of all tasks, crosses one exchange, and is transformed on receipt."""
    complex_ = is_complex(tasks[0].b)

    def received(v: Column) -> Column:
        return v if send else _of_task(tasks, lambda t: _apply(v, t.alpha, t.op, complex_))

    moving = F.col("src") != F.col("pid") if bypass else F.lit(True)
    if not any(t.beta for t in tasks):
        moved = rows.filter(moving).repartitionById(n, "pid") if bypass else rows.repartitionById(n, "pid")
        both = rows.filter(~moving).unionByName(moved) if bypass else moved
        return both.select("mat", "i", "j", received(F.col("v")).alias("v"), "pid")
    # rows at rest lie in their site's partition: what stays is folded there, and meets what arrives by (mat, cell)
    keys = ["mat", "pid", "i", "j"]
    one = F.first if complex_ else F.max
    some = {"ignorenulls": True} if complex_ else {}
    pick = lambda kind, name: one(F.when(F.col("kind") == kind, F.col("v")), **some).alias(name)
    stay = rows.filter(~moving) if bypass else rows.filter("kind = 1")
    came = rows.filter(moving) if bypass else rows.filter("kind = 0")
    local = stay.repartitionById(n, "src").groupBy(*keys).agg(pick(1, "old"), pick(0, "here"))
    moved = came.repartitionById(n, "pid").groupBy(*keys).agg(pick(1, "old_came"), pick(0, "came"))
    both = local.join(moved, keys, "full")
    arrived, old = F.coalesce("here", "came"), F.coalesce("old", "old_came")
    new = F.when(arrived.isNotNull(), received(arrived))
    kept = F.when(old.isNotNull(), _of_task(tasks, lambda t: _apply(old, t.beta, None, complex_)))
    return both.select("mat", "i", "j", _plus(new, kept, complex_).alias("v"), "pid")


def _of_task(tasks: list[Task], value: Callable[[Task], Column]) -> Column:
    """value of the row's own task; one expression where all tasks agree."""
    if len({(t.alpha, t.beta, t.op) for t in tasks}) == 1:
        return value(tasks[0])
    out = F.when(F.col("mat") == 0, value(tasks[0]))
    for k, t in enumerate(tasks[1:], 1):
        out = out.when(F.col("mat") == k, value(t))
    return out


def worth_bypassing(before: int, plan: Plan, beta: bool) -> bool:
    """Keeping rows that stay out of the exchange takes a second look at B: worth it where a tenth of the bytes stays."""
    return beta or (before > 0 and plan.after <= 0.9 * before)


def shuffle_transpose(
    a: DataFrame | None, la: Layout, b: DataFrame, lb: Layout, alpha: float | int = 1, beta: float | int = 0, op: str | Callable[[Column], Column] = "identity",
    cost: Cost | None = None, relabel: str = "optimal", transform: str = "receive", bypass_local: bool | None = None, a_home: str = "relabelled",
) -> tuple[DataFrame, Layout, Plan]:
    """The target's cells (i, j, v, pid), its layout (relabelled), and the plan.

    b, a: (i, j, v), each cell at most once; absent cells are 0. Values: whole, float, decimal, or STRUCT<re, im>. beta 0
    never reads A, so NaN there does no harm. relabel: optimal, greedy, retained, or none; transform: receive or send.
    bypass_local: rows that stay are kept out of the exchange, at the price of a second look at B; by default where that
    is a tenth of the bytes or more.
    """
    t = Task(a, la, b, lb, alpha, beta, op)
    _checked(t)
    n = max(la.n_sites, lb.n_sites)
    solver = {"optimal": "auto"}.get(relabel, relabel)
    plan = find_matrix_relabeling(b.sparkSession, la, lb, cost, op, solver, a_home=a_home, beta=beta)
    send = transform == "send"
    if bypass_local is None:
        bypass_local = worth_bypassing(la.m * la.n * 8, plan, bool(beta))
    out = assemble([t], rows_of(t, plan.sigma, send, a_home).withColumn("mat", F.lit(0)), n, send, bypass_local).drop("mat")
    return out, la.widened(n).relabel(plan.sigma), plan


def shuffle_transpose_batch(tasks: list[Task], cost: Cost | None = None, relabel: str = "optimal", sigma: str = "shared", transform: str = "receive") -> tuple[DataFrame, list[Plan]]:
    """(mat, i, j, v, pid) of several instances in one exchange, transformed on receipt, each with its own alpha, beta and op.
    sigma: one relabeling on the summed volumes, or per_pair. Equal pairs of layouts are planned once: their volumes
    only add up to a multiple, which has the same best relabeling."""
    n = max(max(t.la.n_sites, t.lb.n_sites) for t in tasks)
    spark, solver = tasks[0].b.sparkSession, {"optimal": "auto"}.get(relabel, relabel)
    for t in tasks:
        _checked(t)
    if len({is_complex(t.b) for t in tasks}) > 1:
        raise ValueError("a batch is complex or real, not both")
    if sigma == "per_pair" or len({(t.la, op_layout(t.lb, t.op)) for t in tasks}) == 1:
        plans = [find_matrix_relabeling(spark, t.la, t.lb, cost, t.op, solver) for t in tasks]
    else:
        plans = [find_shared_relabeling(spark, [(t.la, t.lb, t.op) for t in tasks], cost, solver)] * len(tasks)
    send = transform == "send"
    rows = reduce(DataFrame.unionByName, [rows_of(t, p.sigma, send).withColumn("mat", F.lit(k)) for k, (t, p) in enumerate(zip(tasks, plans, strict=True))])
    bypass = any(worth_bypassing(t.la.m * t.la.n * 8, p, bool(t.beta)) for t, p in zip(tasks, plans, strict=True))
    return assemble(tasks, rows, n, send, bypass), plans


def redistribute(b: DataFrame, spec_from: dict, spec_to: dict, window: tuple[int, int, int, int] | None = None) -> tuple[DataFrame, Layout, Plan]:
    """Block-cyclic arguments only; window: rows and columns of B to take, counted from 0 in the result."""
    la, lb = Layout.block_cyclic(**spec_to), Layout.block_cyclic(**spec_from)
    if window:
        b, lb = submatrix(b, window), lb.window(*window)
    return shuffle_transpose(None, la, b, lb)


def transpose_add(alpha: float | int, b: DataFrame, spec_b: dict, beta: float | int, a: DataFrame, spec_a: dict) -> tuple[DataFrame, Layout, Plan]:
    return shuffle_transpose(a, Layout.block_cyclic(**spec_a), b, Layout.block_cyclic(**spec_b), alpha, beta, "transpose")


def submatrix(b: DataFrame, window: tuple[int, int, int, int]) -> DataFrame:
    r0, r1, c0, c1 = window
    inside = (F.col("i") >= r0) & (F.col("i") < r1) & (F.col("j") >= c0) & (F.col("j") < c1)
    return b.filter(inside).select((F.col("i") - r0).alias("i"), (F.col("j") - c0).alias("j"), "v")


def relabel_repartition(df: DataFrame, src: Column, dst: Column, n: int, vol: Column | None = None) -> tuple[DataFrame, Plan]:
    """A table's rows at the partition that plays their bucket's role, chosen to move little: df with pid."""
    plan = find_relabeling(parcels_from_rows(df, src, dst, vol), n=n)
    rows = df.withColumns({"_src": src.cast("int"), "pid": sigma_expr(plan.sigma, dst)})
    moving = F.col("_src") != F.col("pid")
    return rows.filter(~moving).unionByName(rows.filter(moving).repartitionById(n, "pid")).drop("_src"), plan


def tensor_owner(axes: list[tuple[Splits, int]], idx: list[Column]) -> Column:
    """The site of a cell of a tensor: blocks of each axis are dealt in turn to its sites, the last axis fastest."""
    site = F.lit(0)
    for (splits, p), x in zip(axes, idx, strict=True):
        site = site * F.lit(p) + F.pmod(splits.block_of(x), F.lit(p))
    return site.cast("int")


def reshuffle_tensor(b: DataFrame, perm: list[int], la: list[tuple[Splits, int]], lb: list[tuple[Splits, int]], alpha: float | int = 1, relabel: str = "optimal") -> tuple[DataFrame, Plan]:
    """(idx, v, pid) with the axes permuted (axis k of the result is axis perm[k] of b) and laid out as la says, relabelled so
    that little moves; only cells whose site changes cross the exchange. b: (idx, v), each cell at most once; la, lb: of
    each axis the splits and the number of sites along it."""
    if sorted(perm) != list(range(len(lb))) or [s.extent for s, _ in la] != [lb[p][0].extent for p in perm]:
        raise ValueError("A's axes are B's, permuted")
    sites = [prod(p for _, p in x) for x in (la, lb)]
    plan = find_relabeling(tensor_parcels(b.sparkSession, la, lb, perm=perm), None, {"optimal": "auto"}.get(relabel, relabel), max(sites))
    at = lambda k: F.element_at("idx", k + 1)
    rows = b.select(F.array(*(at(p) for p in perm)).alias("idx"), "v", tensor_owner(lb, [at(k) for k in range(len(lb))]).alias("src"), sigma_expr(plan.sigma, tensor_owner(la, [at(p) for p in perm])).alias("pid"))
    moving = F.col("src") != F.col("pid")
    out = rows.filter(~moving).unionByName(rows.filter(moving).repartitionById(max(sites), "pid"))
    return out.select("idx", _apply(F.col("v"), alpha, None, False).alias("v"), "pid"), plan


# ---- baselines ----------------------------------------------------------------------------------


def block_cyclic_reshuffle(b: DataFrame, lb: Layout, la: Layout, transpose: bool = False) -> DataFrame:
    """What libraries for block-cyclic layouts do: every cell through a hash exchange and a full sort, no relabeling."""
    if la.grid is None or lb.grid is None:
        raise ValueError("block-cyclic layouts only")
    rows = b.select(F.col("j").alias("i"), F.col("i").alias("j"), "v") if transpose else b
    rows = rows.withColumn("pid", la.owner_of(F.col("i"), F.col("j")))
    return rows.repartition(la.n_sites, "pid").sortWithinPartitions("pid", "i", "j").select("i", "j", "v", "pid")


def exchange_all(b: DataFrame, la: Layout) -> DataFrame:
    """A plain all-to-all: local cells are sent too."""
    return b.withColumn("pid", la.owner_of(F.col("i"), F.col("j"))).repartition(la.n_sites, "pid")
