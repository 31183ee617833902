"""Assignment solvers: which site plays which role, for the largest total gain.

Small problems (up to a few thousand sites) are solved on the driver over an n x n array. Large ones stay distributed:
greedy by locally dominant rounds over the sparse gains, or an auction whose bids are aggregated on the executors.
"""

from __future__ import annotations

import itertools
import random

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from relayout.sources.durable import drop, durable

EXACT_LIMIT, BRUTE_LIMIT = 4000, 8


def dense(delta: DataFrame, n: int, diagonal: np.ndarray | None = None) -> np.ndarray:
    """gain[role, site]; pairs that delta lacks gain minus diagonal[role] (the volume kept at home)."""
    if n > EXACT_LIMIT:
        raise ValueError(f"{n} sites need an array of {n} x {n}; beyond {EXACT_LIMIT} use the solvers rounds or auction")
    out = np.zeros((n, n)) if diagonal is None else np.repeat(-diagonal[:, None].astype(float), n, axis=1)
    found = delta.select("role", "site", F.col("gain").cast("double").alias("gain")).toPandas()  # at most n * n rows
    out[found["role"].to_numpy(int), found["site"].to_numpy(int)] = found["gain"].to_numpy()
    return out


def gain_of(gain: np.ndarray, sigma: list[int]) -> float:
    return float(sum(gain[x, y] for x, y in enumerate(sigma)))


def solve_exact(gain: np.ndarray) -> tuple[list[int], tuple[np.ndarray, np.ndarray]]:
    """Largest total gain, and prices (u, v) that prove it: u[x] + v[y] >= gain[x, y], equal on the assignment.

    Prices start at each role's best gain, and roles take a free site of that gain, their own before others. The others
    enter one at a time; each grows a tree of tight pairs (shortest augmenting path) until it meets a free site."""
    n = len(gain)
    cost = -np.asarray(gain, float)
    price_role, price_site = np.zeros(n + 1), np.zeros(n + 1)
    role_at = np.full(n + 1, n)
    waiting = []
    if n:
        price_role[:n] = cost.min(axis=1)
        for x in sorted(range(n), key=lambda x: cost[x, x] != price_role[x]):
            tight = np.flatnonzero((cost[x] == price_role[x]) & (role_at[:n] == n))
            if len(tight):
                role_at[x if role_at[x] == n and cost[x, x] == price_role[x] else tight[0]] = x
            else:
                waiting.append(x)
    for x in waiting:
        role_at[n] = x
        slack, came, done = np.full(n + 1, np.inf), np.full(n + 1, n), np.zeros(n + 1, bool)
        at = n
        while True:
            done[at] = True
            role = role_at[at]
            reduced = cost[role] - price_role[role] - price_site[:n]
            closer = ~done[:n] & (reduced < slack[:n])
            slack[:n][closer], came[:n][closer] = reduced[closer], at
            open_ = np.where(done[:n], np.inf, slack[:n])
            nxt = int(open_.argmin())
            step = open_[nxt]
            held = role_at[done]
            price_role[held] += step
            price_site[done] -= step
            slack[:n][~done[:n]] -= step
            at = nxt
            if role_at[at] == n:
                break
        while at != n:
            back = came[at]
            role_at[at] = role_at[back]
            at = back
    sigma = [0] * n
    for y in range(n):
        sigma[role_at[y]] = y
    return sigma, (-price_role[:n], -price_site[:n])


def solve_flow(gain: np.ndarray) -> list[int]:
    """The same optimum as a flow: n units from a source through roles and sites, one augmenting path of least cost at a
    time, found by relaxing arcs of the residual network (costs may be negative, so without potentials)."""
    n = len(gain)
    cost = -np.asarray(gain, float)
    of_site, of_role = [-1] * n, [-1] * n
    for _ in range(n):
        to_role = np.array([0.0 if of_role[x] < 0 else np.inf for x in range(n)])
        to_site, via = np.full(n, np.inf), np.full(n, -1)
        changed = True
        while changed:
            changed = False
            reach = to_role[:, None] + cost
            for x in range(n):
                if of_role[x] >= 0:
                    reach[x, of_role[x]] = np.inf
            best = reach.min(axis=0)
            better = best < to_site - 1e-9
            if better.any():
                changed = True
                via[better], to_site[better] = reach.argmin(axis=0)[better], best[better]
            for y in range(n):
                x = of_site[y]
                if x >= 0 and to_site[y] - cost[x, y] < to_role[x] - 1e-9:
                    to_role[x] = to_site[y] - cost[x, y]
                    changed = True
        y = min((y for y in range(n) if of_site[y] < 0), key=lambda y: to_site[y])
        while y >= 0:
            x = int(via[y])
            of_site[y], of_role[x], y = x, y, of_role[x]
    return of_role


def solve_bruteforce(gain: np.ndarray) -> list[int]:
    n = len(gain)
    if n > BRUTE_LIMIT:
        raise ValueError(f"brute force is for {BRUTE_LIMIT} sites at most")
    return list(max(itertools.permutations(range(n)), key=lambda s: gain_of(gain, s)))


def solve_greedy(gain: np.ndarray, order: str = "gain", floor_identity: bool = True, home: np.ndarray | None = None) -> list[int]:
    """Pairs by gain, or by retained volume (gain plus what the role has at home), ties by role, then site. With
    floor_identity, a relabeling that loses is dropped for the identity. home: each role's volume at its own site; without
    it, the least gain of a role counts as retaining nothing."""
    n = len(gain)
    value = gain if order == "gain" else gain - gain.min(axis=1, keepdims=True) if home is None else gain + home[:, None]
    role, site = np.divmod(np.lexsort((np.tile(np.arange(n), n), np.repeat(np.arange(n), n), -value.ravel())), n)
    sigma, taken = [-1] * n, [False] * n
    for x, y in zip(role.tolist(), site.tolist(), strict=True):
        if sigma[x] < 0 and not taken[y]:
            sigma[x], taken[y] = y, True
    return list(range(n)) if floor_identity and gain_of(gain, sigma) < 0 else sigma


def solve_random_swap(gain: np.ndarray, seed: int = 0, rounds: int = 2000) -> list[int]:
    """A random start, then swaps of two roles' sites that don't lose; never below the identity."""
    draw, n = random.Random(seed), len(gain)
    sigma = list(range(n))
    draw.shuffle(sigma)
    for _ in range(rounds if n > 1 else 0):
        a, b = draw.sample(range(n), 2)
        if gain[a, sigma[b]] + gain[b, sigma[a]] >= gain[a, sigma[a]] + gain[b, sigma[b]]:
            sigma[a], sigma[b] = sigma[b], sigma[a]
    return list(range(n)) if gain_of(gain, sigma) < 0 else sigma


def solve_dominant_rounds(values: DataFrame, n: int, value: str = "vol") -> DataFrame:
    """(role, site): greedy, distributed. values: (role, site, and a value): sparse volumes, where a pair without one retains
    nothing, or gains of all pairs (value "gain").

    A round keeps the pairs that are the best left for both ends under one strict order (value, then role, then site); this
    is what taking pairs one by one in that order gives. Roles without a pair in the end keep their own site if it is free,
    the rest is by rank. Each round's tables are dropped once the next ones are written."""
    spark = values.sparkSession
    values = values.select("role", "site", F.col(value).alias("x"))
    left = durable(values.filter("x > 0") if value == "vol" else values, "greedy")
    chosen: DataFrame | None = None
    rank = F.struct(F.col("x"), (-F.col("role")).alias("r"), (-F.col("site")).alias("s"))
    while not left.isEmpty():
        a = left.groupBy("role").agg(F.max(rank).alias("best")).select("role", (-F.col("best.s")).alias("site"))
        b = left.groupBy("site").agg(F.max(rank).alias("best")).select("site", (-F.col("best.r")).alias("role"))
        now = durable(a.join(b, ["role", "site"]), "greedy")
        chosen = now if chosen is None else chosen.union(now.select(chosen.columns))
        rest = durable(left.join(now.select("role"), "role", "left_anti").join(now.select("site"), "site", "left_anti").select("role", "site", "x"), "greedy")
        drop(left)
        left = rest
    drop(left)
    every = spark.range(n).select(F.col("id").cast("int").alias("role"))
    if chosen is None:
        return every.select("role", F.col("role").alias("site"))
    chosen = chosen.select("role", "site")
    roles = every.join(chosen, "role", "left_anti")
    sites = every.select(F.col("role").alias("site")).join(chosen, "site", "left_anti")
    home = roles.join(sites, F.col("role") == F.col("site"))
    by = lambda c: F.row_number().over(Window.orderBy(c))  # noqa: E731  at most n rows
    rest = roles.join(home.select("role"), "role", "left_anti").withColumn("k", by("role"))
    free = sites.join(home.select("site"), "site", "left_anti").withColumn("k", by("site"))
    return chosen.union(home.select("role", "site")).union(rest.join(free, "k").select("role", "site"))


def solve_auction(delta: DataFrame, n: int, eps: float | None = None, scale: float = 5.0) -> list[int]:
    """Within n * eps of the best; exact for whole gains if eps < 1 / n (the default). Bids of a round (best and second
    best value of each role without a site) are aggregated on the executors; only prices and bids, n rows, travel."""
    spark = delta.sparkSession
    final = eps if eps is not None else 1.0 / (n + 1)
    gains = delta.select("role", "site", F.col("gain").cast("double").alias("gain")).persist()
    top = gains.agg(F.max(F.abs("gain"))).first()[0] or 1.0
    price, step = np.zeros(n), max(top / scale, final)
    while True:
        held: dict[int, int] = {}  # site -> role
        while len(held) < n:
            free = sorted(set(range(n)) - set(held.values()))
            now = spark.createDataFrame([(i, float(p)) for i, p in enumerate(price)], "site int, price double")
            wait = spark.createDataFrame([(x,) for x in free], "role int")
            value = gains.join(F.broadcast(wait), "role").join(F.broadcast(now), "site").withColumn("value", F.col("gain") - F.col("price"))
            best = value.groupBy("role").agg(F.max(F.struct("value", (-F.col("site")).alias("s"))).alias("b"), F.slice(F.sort_array(F.collect_list("value"), asc=False), 1, 2).alias("two"))
            bid = best.select("role", (-F.col("b.s")).alias("site"), (F.element_at("two", 1) - F.coalesce(F.try_element_at("two", F.lit(2)), F.element_at("two", 1)) + step).alias("raise"))
            for site, won in bid.groupBy("site").agg(F.max(F.struct("raise", (-F.col("role")).alias("r"))).alias("w")).collect():  # n rows at most
                price[site] += won["raise"]
                held[site] = -won["r"]
        if step <= final:
            gains.unpersist()
            sigma = [0] * n
            for site, role in held.items():
                sigma[role] = site
            return sigma
        step = max(step / scale, final)


def certify(delta: DataFrame, sigma: list[int], u: np.ndarray, v: np.ndarray) -> DataFrame:
    """One row of two truths: prices cover every gain, and add up to the gain of sigma."""
    spark = delta.sparkSession
    us = F.broadcast(spark.createDataFrame([(i, float(x), s) for i, (x, s) in enumerate(zip(u, sigma, strict=True))], "role int, u double, at int"))
    vs = F.broadcast(spark.createDataFrame([(i, float(x)) for i, x in enumerate(v)], "site int, v double"))
    got = delta.join(us, "role").join(vs, "site").agg(
        F.bool_and(F.col("u") + F.col("v") >= F.col("gain") - 1e-6).alias("covers"), F.sum(F.when(F.col("site") == F.col("at"), F.col("gain"))).alias("gain")
    )
    return got.select("covers", (F.abs(F.col("gain") - F.lit(float(u.sum() + v.sum()))) < 1e-6).alias("tight"))


def feasible(x: DataFrame, n: int) -> DataFrame:
    """(feasible): x (role, site, x) has row and column sums 1 and no negative entry."""
    ok = F.abs(F.col("s") - 1) < 1e-9
    rows = x.groupBy("role").agg(F.sum("x").alias("s"), F.min("x").alias("least")).select(ok & (F.col("least") >= 0))
    cols = x.groupBy("site").agg(F.sum("x").alias("s")).select(ok)
    return rows.toDF("ok").union(cols.toDF("ok")).agg((F.bool_and("ok") & (F.count(F.lit(1)) == 2 * n)).alias("feasible"))


def matching_valid(sigma: DataFrame, n: int) -> DataFrame:
    """(valid): n pairs, no two of which share a role or a site."""
    return sigma.agg(((F.count(F.lit(1)) == n) & (F.count_distinct("role") == n) & (F.count_distinct("site") == n)).alias("valid"))
