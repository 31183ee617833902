"""From parcels, or two layouts, to a relabeling of the target's sites and what it saves."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from relayout.plans import assign
from relayout.plans.cost import Cost, VolumeCost
from relayout.plans.graph import comm_graph, gain_matrix, gain_matrix_volume, relabel_graph, total_cost
from relayout.plans.layout import Layout, numbers
from relayout.plans.overlay import grid_parcels, layout_parcels


#: Assignments by the volumes between sites, so that instances of one shape are solved once.
_PLANS: dict = {}


@dataclass
class Plan:
    """before and after: remote bytes; cost_before and cost_after: the same under the cost that the plan is for."""

    make_parcels: Callable[[], DataFrame]
    sigma: list[int]
    before: int
    after: int
    messages: int
    pieces: int
    solver: str
    certificate: tuple[np.ndarray, np.ndarray] | None = None
    cost_before: float | None = None
    cost_after: float | None = None

    def __post_init__(self) -> None:
        if self.cost_before is None:
            self.cost_before, self.cost_after = float(self.before), float(self.after)

    @property
    def parcels(self) -> DataFrame:
        return self.make_parcels()

    @property
    def reduction(self) -> float | None:
        return None if not self.before else 100.0 * (self.before - self.after) / self.before

    def sigma_frame(self) -> DataFrame:
        return self.parcels.sparkSession.createDataFrame(list(enumerate(self.sigma)), "role int, site int")

    def explain_plan(self) -> str:
        cut = "nothing to move" if self.reduction is None else f"{self.reduction:.4f} % less"
        return f"{self.solver}: {self.before} -> {self.after} remote bytes ({cut}), {self.messages} messages, {self.pieces} pieces, sigma {self.sigma[:16]}"


def remote_volume(parcels: DataFrame, sigma: list[int] | None = None) -> int:
    dst = F.col("dst") if sigma is None else sigma_expr(sigma, F.col("dst"))
    return int(parcels.agg(F.coalesce(F.sum(F.when(F.col("src") != dst, F.col("vol"))), F.lit(0))).first()[0])


def _diagonal(parcels: DataFrame, n: int) -> np.ndarray:
    out = np.zeros(n)
    for row in parcels.filter("src = dst").groupBy("src").agg(F.sum("vol").alias("v")).collect():  # n rows
        out[row["src"]] = row["v"]
    return out


def gains(parcels: DataFrame, cost: Cost | None, n: int) -> np.ndarray:
    """gain[role, site] on the driver, for n up to EXACT_LIMIT."""
    if cost is None or isinstance(cost, VolumeCost):
        return assign.dense(gain_matrix_volume(parcels), n, _diagonal(parcels, n))
    return assign.dense(gain_matrix(parcels, cost, n), n)


def _cost_of(parcels: DataFrame, cost: Cost, sigma: list[int] | None = None) -> float:
    """W of the graph, or of the one with receivers relabelled."""
    if sigma is not None:
        parcels = parcels.withColumn("dst", sigma_expr(sigma, F.col("dst")))
    return float(total_cost(comm_graph(parcels, cost)).first()[0])


def _solve(held: np.ndarray, solver: str) -> tuple[list[int], tuple[np.ndarray, np.ndarray] | None]:
    """For the volume cost, from the volumes between all sites: the relabeling, and the exact solver's certificate."""
    home = np.diag(held).astype(float)
    gain = held.T - home[:, None]
    if solver == "exact":
        return assign.solve_exact(gain)
    return _DRIVER[solver](gain, home), None


_DRIVER: dict[str, Callable[[np.ndarray, np.ndarray | None], list[int]]] = {
    "flow": lambda g, home: assign.solve_flow(g),
    "brute": lambda g, home: assign.solve_bruteforce(g),
    "swap": lambda g, home: assign.solve_random_swap(g),
    "greedy": lambda g, home: assign.solve_greedy(g),
    "retained": lambda g, home: assign.solve_greedy(g, "retained", home=home),
}


def _volume_plan(make: Callable[[], DataFrame], src: np.ndarray, dst: np.ndarray, n_pieces: np.ndarray, vol: np.ndarray, n: int, solver: str) -> Plan:
    """A plan for the volume cost from parcels on the driver: no job at all."""
    held, far = np.zeros((n, n), np.int64), src != dst
    held[src, dst] = vol
    messages, pieces, before = int((far & (n_pieces > 0)).sum()), int(n_pieces[far].sum()), int(held.sum() - np.trace(held))
    sigma, certificate, own = list(range(n)), None, list(range(n))
    if solver != "none" and before:
        sigma, certificate = _solve(held, solver)
    else:
        solver = "none"
    return Plan(make, sigma, before, int(held.sum() - held[sigma, own].sum()), messages, pieces, solver, certificate)


def find_relabeling(parcels: DataFrame, cost: Cost | None = None, solver: str = "auto", n: int | None = None) -> Plan:
    """The relabeling with the largest gain under the cost: solver exact, flow, greedy, retained, swap, brute, rounds, auction,
    none, or auto (exact for up to EXACT_LIMIT sites, else distributed greedy rounds). Rounds order pairs by retained
    volume for the volume cost, and by gain for any other; both equal greedy one by one. Solvers with an n x n array refuse
    more than EXACT_LIMIT sites. A relabeling that loses is dropped for the identity."""
    n = n if n is not None else int(parcels.agg(F.greatest(F.max("src"), F.max("dst"))).first()[0] or 0) + 1
    volume = cost is None or isinstance(cost, VolumeCost)
    if solver == "auto":
        solver = "exact" if n <= assign.EXACT_LIMIT else "rounds"
    if volume and n <= assign.EXACT_LIMIT and solver in ("exact", "none", *_DRIVER):
        # all parcels between so few sites fit the driver: one job, and no other
        found = parcels.groupBy("src", "dst").agg(F.sum("n_pieces").alias("n_pieces"), F.sum("vol").alias("vol")).toPandas()
        return _volume_plan(lambda: parcels, *(found[c].to_numpy(np.int64) for c in ("src", "dst", "n_pieces", "vol")), n, solver)
    certificate, own = None, list(range(n))
    far = parcels.filter("src <> dst").agg(F.count(F.lit(1)).alias("m"), F.coalesce(F.sum("n_pieces"), F.lit(0)).alias("p"), F.coalesce(F.sum("vol"), F.lit(0)).alias("v")).first()
    messages, pieces, before = int(far["m"]), int(far["p"]), int(far["v"])
    cost_before = float(before) if volume else _cost_of(parcels, cost)
    if solver == "none" or (volume and not before):
        sigma, solver = own, "none"
    elif solver == "rounds":
        if volume:
            pairs = parcels.groupBy(F.col("dst").alias("role"), F.col("src").alias("site")).agg(F.sum("vol").alias("vol"))
            best = assign.solve_dominant_rounds(pairs, n)
        else:
            best = assign.solve_dominant_rounds(gain_matrix(parcels, cost, n), n, "gain")
        sigma = [r["site"] for r in best.orderBy("role").collect()]  # n rows
    elif solver == "auction":
        sigma = assign.solve_auction(gain_matrix(parcels, cost or VolumeCost(), n), n)
    else:
        gain = gains(parcels, cost, n)
        if solver == "exact":
            sigma, certificate = assign.solve_exact(gain)
        else:
            sigma = _DRIVER[solver](gain, _diagonal(parcels, n) if volume else None)
    cost_after = float(remote_volume(parcels, sigma)) if volume else _cost_of(parcels, cost, sigma)
    if cost_after > cost_before:
        sigma, cost_after = own, cost_before
    after = int(cost_after) if volume else remote_volume(parcels, sigma)
    return Plan(lambda: parcels, sigma, before, after, messages, pieces, solver, certificate, cost_before, cost_after)


def op_layout(lb: Layout, op: object) -> Layout:
    return lb.transposed() if op in ("transpose", "conj_transpose") else lb


def find_matrix_relabeling(spark: SparkSession, la: Layout, lb: Layout, cost: Cost | None = None, op: object = "identity", solver: str = "auto", elem_bytes: int = 8, a_home: str = "relabelled", beta: float = 0) -> Plan:
    """Parcels of A <- op(B) from the two descriptors alone, then find_relabeling. With a_home 'original' and a beta, what
    A holds counts as parcels from each role to itself: moving the role would move A's old content."""
    n = max(la.n_sites, lb.n_sites)
    lb = op_layout(lb, op)
    held = beta and a_home == "original"
    volume = cost is None or isinstance(cost, VolumeCost)
    wanted = "exact" if solver == "auto" and n <= assign.EXACT_LIMIT else solver
    if volume and not held and n <= assign.EXACT_LIMIT and wanted in ("exact", "none", *_DRIVER):
        found = grid_parcels(la, lb, elem_bytes)
        if found is not None:  # two site grids: counted on the driver, without a job
            key = (tuple(x.tobytes() for x in found), n, wanted)
            make = lambda: layout_parcels(spark, la, lb, elem_bytes)
            if key not in _PLANS:
                if len(_PLANS) >= 256:
                    _PLANS.pop(next(iter(_PLANS)))
                _PLANS[key] = _volume_plan(make, *found, n, wanted)
            return replace(_PLANS[key], make_parcels=make)
    found = layout_parcels(spark, la, lb, elem_bytes)
    if held:
        own = la.blocks(spark).groupBy("site").agg(F.count(F.lit(1)).alias("n_pieces"), F.sum((F.col("r_hi") - F.col("r_lo")) * (F.col("c_hi") - F.col("c_lo")) * elem_bytes).alias("vol"))
        own = own.select(F.col("site").alias("src"), F.col("site").alias("dst"), "n_pieces", "vol")
        found = found.unionByName(own).groupBy("src", "dst").agg(F.sum("n_pieces").alias("n_pieces"), F.sum("vol").alias("vol"))
    return find_relabeling(found, cost, solver, n)


def find_shared_relabeling(spark: SparkSession, pairs: list[tuple[Layout, Layout, object]], cost: Cost | None = None, solver: str = "auto", elem_bytes: int = 8) -> Plan:
    """One relabeling of the target's sites for several instances (LA, LB, op) at once: on the sum of their parcels."""
    n = max(max(la.n_sites, lb.n_sites) for la, lb, _ in pairs)
    ends = [(la, op_layout(lb, op)) for la, lb, op in pairs]
    make = lambda: reduce(DataFrame.unionByName, [layout_parcels(spark, la, lb, elem_bytes).select("src", "dst", "n_pieces", "vol") for la, lb in ends]).groupBy("src", "dst").agg(F.sum("n_pieces").alias("n_pieces"), F.sum("vol").alias("vol"))
    wanted = "exact" if solver == "auto" and n <= assign.EXACT_LIMIT else solver
    if (cost is None or isinstance(cost, VolumeCost)) and n <= assign.EXACT_LIMIT and wanted in ("exact", "none", *_DRIVER):
        found = [grid_parcels(la, lb, elem_bytes) for la, lb in ends]
        if all(f is not None for f in found):
            src, dst, n_pieces, vol = (np.concatenate(x) for x in zip(*found, strict=True))
            key, at = np.unique(src * n + dst, return_inverse=True)
            sums = [np.zeros(len(key), np.int64) for _ in range(2)]
            np.add.at(sums[0], at, n_pieces)
            np.add.at(sums[1], at, vol)
            return _volume_plan(make, key // n, key % n, *sums, n, wanted)
    return find_relabeling(make(), cost, solver, n)


def sigma_expr(sigma: list[int], role: Column) -> Column:
    return F.element_at(numbers(sigma), role.cast("int") + 1)


__all__ = ["Plan", "comm_graph", "find_matrix_relabeling", "find_relabeling", "find_shared_relabeling", "gains", "op_layout", "relabel_graph", "remote_volume", "sigma_expr"]
