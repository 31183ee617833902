"""Overlays of two layouts and the parcels that follow: who sends how much to whom.

Every piece of the overlay starts at a bound of one of the two splits and ends at the next bound of either: a closed
form for each starting point. There is no sort and no window, so overlays of any length are embarrassingly parallel.
Two site grids never need their pieces: row and column tables factor the volumes.
"""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from relayout.plans.layout import Layout, Splits, numbers

ELEM_BYTES = 8


def _starts(spark: SparkSession, splits: Splits, off: int, extent: int, name: str = "lo") -> DataFrame:
    """Bounds of splits inside a window, counted from it, its beginning included."""
    inside = splits.frame(spark).select((F.greatest("lo", F.lit(off)) - off).alias(name), "hi").filter((F.col("hi") > off) & (F.col(name) < extent))
    return inside.select(name)


def axis_overlay(spark: SparkSession, a: tuple[Splits, int, int], b: tuple[Splits, int, int]) -> DataFrame:
    """(k, lo, hi, ka, kb) of one axis; a and b: splits, offset, extent (equal extents). ka, kb: the covers' blocks."""
    (sa, oa, extent), (sb, ob, other) = a, b
    if extent != other:
        raise ValueError("the two axes differ in length")
    lo = _starts(spark, sa, oa, extent).union(_starts(spark, sb, ob, extent)).distinct()
    x = F.col("lo")
    hi = F.least(sa.end_after(x + oa) - oa, sb.end_after(x + ob) - ob, F.lit(extent).cast("long"))
    rank = _starts_below(sa, oa, x) + _starts_below(sb, ob, x) - _common_below(sa, oa, sb, ob, x)
    return lo.select(rank.cast("long").alias("k"), "lo", hi.alias("hi"), sa.block_of(x + oa).cast("long").alias("ka"), sb.block_of(x + ob).cast("long").alias("kb"))


def piece_start(a: tuple[Splits, int, int], b: tuple[Splits, int, int], x: Column) -> Column:
    """Where the piece of axis_overlay() that holds x begins; null outside the axis."""
    (sa, oa, extent), (sb, ob, _) = a, b
    lo = F.greatest(sa.start_of(sa.block_of(x + oa)) - oa, sb.start_of(sb.block_of(x + ob)) - ob, F.lit(0))
    return F.when((x >= 0) & (x < extent), lo.cast("long"))


def _starts_below(s: Splits, off: int, x: Column) -> Column:
    """How many of the splits' starting points in the window lie below x: blocks begun before x."""
    return F.when(x <= 0, F.lit(0)).otherwise(s.block_of(x + off - 1) - s.block_of(F.lit(off).cast("long")) + 1)


def _common_below(sa: Splits, oa: int, sb: Splits, ob: int, x: Column) -> Column:
    """Starting points that both splits share below x (0 is always one)."""
    if sa.block and sb.block:
        # shared points y > 0: y + oa and y + ob are whole multiples
        step = math.lcm(sa.block, sb.block)
        first = next((y for y in range(-oa % sa.block, step + sa.block, sa.block) if y > 0 and (y + oa) % sa.block == 0 and (y + ob) % sb.block == 0), None)
        if first is None:
            return F.when(x <= 0, F.lit(0)).otherwise(F.lit(1))
        later = F.when(x > first, ((x - 1 - first) - F.pmod(x - 1 - first, F.lit(step))) / step + 1).otherwise(0)
        return F.when(x <= 0, F.lit(0)).otherwise(F.lit(1) + later)
    table, off, other, off_other = (sa, oa, sb, ob) if sa.bounds else (sb, ob, sa, oa)
    shared = F.filter(F.array(*(F.lit(v - off).cast("long") for v in table.bounds)), lambda y: (y > 0) & (y < x) & (other.start_of(other.block_of(y + off_other)) == y + off_other))
    return F.when(x <= 0, F.lit(0)).otherwise(F.size(shared) + 1)


def grid_overlay(spark: SparkSession, la: Layout, lb: Layout) -> DataFrame:
    """(r_lo, r_hi, c_lo, c_hi, src, dst): pieces; lb is op(B)'s layout. src owns a piece there, dst in A."""
    if (la.m, la.n) != (lb.m, lb.n):
        raise ValueError(f"shapes differ: {la.m} x {la.n} and {lb.m} x {lb.n}")
    r = axis_overlay(spark, la.axis(0), lb.axis(0)).select(F.col("lo").alias("r_lo"), F.col("hi").alias("r_hi"), F.col("ka").alias("ra"), F.col("kb").alias("rb"))
    c = axis_overlay(spark, la.axis(1), lb.axis(1)).select(F.col("lo").alias("c_lo"), F.col("hi").alias("c_hi"), F.col("ka").alias("ca"), F.col("kb").alias("cb"))
    both = r.crossJoin(c)
    src, dst = lb.owner_of_block(F.col("rb"), F.col("cb")), la.owner_of_block(F.col("ra"), F.col("ca"))
    return both.select("r_lo", "r_hi", "c_lo", "c_hi", src.alias("src"), dst.alias("dst"))


def parcels(pieces: DataFrame, elem_bytes: int = ELEM_BYTES) -> DataFrame:
    """(src, dst, n_pieces, vol) of overlay pieces; vol in bytes."""
    area = (F.col("r_hi") - F.col("r_lo")) * (F.col("c_hi") - F.col("c_lo"))
    return pieces.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n_pieces"), F.sum(area * elem_bytes).alias("vol"))


def factored_parcels(spark: SparkSession, la: Layout, lb: Layout, elem_bytes: int = ELEM_BYTES) -> DataFrame:
    """parcels(grid_overlay(la, lb)) for cyclic site grids, from two axis tables: their sizes add, not multiply."""
    if la.grid is None or lb.grid is None:
        raise ValueError("factors exist for site grids; use parcels(grid_overlay(...))")
    if (la.m, la.n) != (lb.m, lb.n):
        raise ValueError("shapes differ")
    tables = []
    for which, (a, b, size, count) in enumerate((("ra", "rb", "r_len", "r_n"), ("ca", "cb", "c_len", "c_n"))):
        pa, pb = la.grid[which ^ la.flipped], lb.grid[which ^ lb.flipped]
        ha, hb = la.shift[which ^ la.flipped], lb.shift[which ^ lb.flipped]
        ax = axis_overlay(spark, la.axis(which), lb.axis(which))
        ax = ax.groupBy(F.pmod(F.col("ka") + ha, F.lit(pa)).alias(a), F.pmod(F.col("kb") + hb, F.lit(pb)).alias(b))
        tables.append(ax.agg(F.sum(F.col("hi") - F.col("lo")).alias(size), F.count(F.lit(1)).alias(count)))

    def site(layout: Layout, r: str, c: str) -> Column:
        r, c = (F.col(c), F.col(r)) if layout.flipped else (F.col(r), F.col(c))
        pr, pc = layout.grid
        s = r * pc + c if layout.site_order == "row" else c * pr + r
        if layout.sigma is not None:
            s = F.element_at(numbers(layout.sigma), (s + 1).cast("int"))
        return s.cast("int")

    both = tables[0].crossJoin(tables[1])
    return both.groupBy(site(lb, "rb", "cb").alias("src"), site(la, "ra", "ca").alias("dst")).agg(
        F.sum(F.col("r_n") * F.col("c_n")).alias("n_pieces"), F.sum(F.col("r_len") * F.col("c_len") * elem_bytes).alias("vol")
    )


#: Pieces of one axis that are counted on the driver; longer axes that don't repeat sooner are counted by Spark.
AXIS_PIECES = 4_000_000


def axis_counts(a: tuple[Splits, int, int], b: tuple[Splits, int, int], pa: int, pb: int, ha: int, hb: int) -> tuple[np.ndarray, np.ndarray] | None:
    """Length and pieces of an axis by (line of A's site grid, line of B's), without a job: equal blocks repeat after a
    common multiple, so one period and a remainder are counted. None if that is too long."""
    (sa, oa, extent), (sb, ob, _) = a, b
    if not (sa.block and sb.block):
        return None
    period = math.lcm(sa.block * pa, sb.block * pb)
    if (min(period, extent) // sa.block + min(period, extent) // sb.block) * 2 > AXIS_PIECES:
        return None

    def count(size: int, first: bool) -> tuple[np.ndarray, np.ndarray]:
        """0 to size; what begins at 0 is a new piece at the first period, later only if a block begins there."""
        length, pieces = np.zeros((pa, pb), np.int64), np.zeros((pa, pb), np.int64)
        if size <= 0:
            return length, pieces
        starts = np.unique(np.concatenate([[0], np.arange(-oa % sa.block, size, sa.block), np.arange(-ob % sb.block, size, sb.block)]))
        at = ((starts + oa) // sa.block + ha) % pa, ((starts + ob) // sb.block + hb) % pb
        new = np.ones(len(starts), np.int64)
        new[0] = first or oa % sa.block == 0 or ob % sb.block == 0
        np.add.at(length, at, np.diff(np.append(starts, size)))
        np.add.at(pieces, at, new)
        return length, pieces

    whole, rest = divmod(extent, period)
    parts_ = [(1, count(period, True))] * (whole > 0) + [(whole - 1, count(period, False))] * (whole > 1) + [(1, count(rest, whole == 0))]
    return sum(k * x[0] for k, x in parts_), sum(k * x[1] for k, x in parts_)


def grid_parcels(la: Layout, lb: Layout, elem_bytes: int = ELEM_BYTES) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray] | None:
    """src, dst, n_pieces and vol of factored_parcels() on the driver, or None where the axes are too long for that."""
    if la.grid is None or lb.grid is None:
        return None
    if (la.m, la.n) != (lb.m, lb.n):
        raise ValueError("shapes differ")
    axes = []
    for which in (0, 1):
        x, y = which ^ la.flipped, which ^ lb.flipped
        found = axis_counts(la.axis(which), lb.axis(which), la.grid[x], lb.grid[y], la.shift[x], lb.shift[y])
        if found is None:
            return None
        a, b = np.nonzero(found[1] + found[0])
        axes.append((a, b, found[0][a, b], found[1][a, b]))
    (ra, rb, r_len, r_n), (ca, cb, c_len, c_n) = axes

    def site(layout: Layout, r: np.ndarray, c: np.ndarray) -> np.ndarray:
        r, c = (c[None, :], r[:, None]) if layout.flipped else (r[:, None], c[None, :])
        out = (r * layout.grid[1] + c if layout.site_order == "row" else c * layout.grid[0] + r).ravel()
        return np.asarray(layout.sigma)[out] if layout.sigma is not None else out

    # a pair of lines of each grid is one site of each: no two entries share a parcel
    return site(lb, rb, cb), site(la, ra, ca), np.outer(r_n, c_n).ravel(), np.outer(r_len, c_len).ravel() * elem_bytes


def parcel_lines(pieces: DataFrame, order: str = "row", elem_bytes: int = ELEM_BYTES) -> DataFrame:
    """parcels() and n_lines: the runs of bytes that the pieces are stored in, by rows or by columns."""
    rows, cols = F.col("r_hi") - F.col("r_lo"), F.col("c_hi") - F.col("c_lo")
    return pieces.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n_pieces"), F.sum(rows * cols * elem_bytes).alias("vol"), F.sum(rows if order == "row" else cols).alias("n_lines"))


def layout_parcels(spark: SparkSession, la: Layout, lb: Layout, elem_bytes: int = ELEM_BYTES) -> DataFrame:
    if la.grid is not None and lb.grid is not None:
        return factored_parcels(spark, la, lb, elem_bytes)
    return parcels(grid_overlay(spark, la, lb), elem_bytes)


def parcels_from_rows(df: DataFrame, src: Column, dst: Column, vol: Column | None = None) -> DataFrame:
    """Parcels of a table whose rows say where they are and where they go; vol defaults to one a row."""
    vol = F.lit(1) if vol is None else vol
    return df.groupBy(src.cast("int").alias("src"), dst.cast("int").alias("dst")).agg(F.count(F.lit(1)).alias("n_pieces"), F.sum(vol).cast("long").alias("vol"))


def cell_parcels(cells: DataFrame, la: Layout, lb: Layout) -> DataFrame:
    """Parcels of a sparse matrix's own cells (i, j), one unit each, from lb to la."""
    i, j = F.col("i"), F.col("j")
    return parcels_from_rows(cells, lb.owner_of(i, j), la.owner_of(i, j))


def tensor_parcels(spark: SparkSession, a: list[tuple[Splits, int]], b: list[tuple[Splits, int]], elem_bytes: int = ELEM_BYTES, perm: list[int] | None = None) -> DataFrame:
    """Parcels of an n-dimensional tensor: for each axis the splits and the number of sites along it, in A and in B.
    Sites are numbered with the last axis fastest. With perm, axis k of A is axis perm[k] of B, whose sites keep the
    numbers of B's own order. One factor table for each axis."""
    perm = perm or list(range(len(b)))
    own, b = b, [b[p] for p in perm]
    tables = []
    for k, ((sa, pa), (sb, pb)) in enumerate(zip(a, b, strict=True)):
        ax = axis_overlay(spark, (sa, 0, sa.extent), (sb, 0, sb.extent))
        ax = ax.groupBy(F.pmod("ka", F.lit(pa)).alias(f"a{k}"), F.pmod("kb", F.lit(pb)).alias(f"b{k}"))
        tables.append(ax.agg(F.sum(F.col("hi") - F.col("lo")).alias(f"l{k}"), F.count(F.lit(1)).alias(f"n{k}")))
    both = reduce(lambda x, y: x.crossJoin(y), tables)
    number = lambda name, sizes: reduce(lambda s, kp: s * kp[1] + F.col(f"{name}{kp[0]}"), enumerate(sizes), F.lit(0))
    product = lambda name: reduce(lambda x, y: x * y, (F.col(f"{name}{k}") for k in range(len(a))))
    of_b = reduce(lambda s, kp: s * kp[1] + F.col(f"b{perm.index(kp[0])}"), enumerate(p for _, p in own), F.lit(0))
    src, dst = of_b, number("a", [p for _, p in a])
    return both.groupBy(src.cast("int").alias("src"), dst.cast("int").alias("dst")).agg(F.sum(product("n")).alias("n_pieces"), F.sum(product("l") * elem_bytes).alias("vol"))
