"""Layout descriptors: how a matrix is split into blocks and which site owns each.

Splits are a closed form (equal blocks) or a short table of bounds; owners are a closed form (cyclic over a site grid) or
a table. A descriptor never touches data: it yields Column expressions and small DataFrames, so a plan over 100 TB costs
what its descriptor costs.
"""

from __future__ import annotations

import json
from bisect import bisect_left, bisect_right
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def whole_div(a: Column, b: int) -> Column:
    """Integer division of whole numbers from 0 on (the quotient of exact multiples, so no rounding below 2 ** 53)."""
    return ((a - F.pmod(a, F.lit(b))) / F.lit(b)).cast("long")


def numbers(xs: tuple[int, ...] | list[int], kind: str = "int") -> Column:
    """An array constant. A long one is one string literal that the optimizer folds once: no expression for each entry, so
    plans stay small whatever the number of sites."""
    if len(xs) <= 64:
        return F.array(*(F.lit(int(x)).cast(kind) for x in xs))
    return F.split(F.lit(",".join(str(int(x)) for x in xs)), ",").cast(f"array<{kind}>")


@dataclass(frozen=True)
class Splits:
    """Half-open ranges of an axis: equal blocks of ``block``, or the table ``bounds`` (first 0, last the extent)."""

    extent: int
    block: int | None = None
    bounds: tuple[int, ...] | None = None

    def __post_init__(self) -> None:
        if (self.block is None) == (self.bounds is None):
            raise ValueError("give either a block size or bounds")
        if self.block is not None and self.block < 1:
            raise ValueError("a block holds one index at least")
        if self.bounds is not None and (self.bounds[0] != 0 or self.bounds[-1] != self.extent or any(a >= b for a, b in zip(self.bounds, self.bounds[1:], strict=False))):
            raise ValueError("bounds rise from 0 to the extent")

    @property
    def count(self) -> int:
        return -(-self.extent // self.block) if self.block else len(self.bounds) - 1

    def block_of(self, i: Column) -> Column:
        if self.block:
            return whole_div(i, self.block)
        return F.size(F.filter(self._array(), lambda b: b <= i)).cast("long") - 1

    def start_of(self, k: Column) -> Column:
        return k * F.lit(self.block) if self.block else F.element_at(self._array(), (k + 1).cast("int"))

    def end_after(self, i: Column) -> Column:
        """End of the block that holds i."""
        if self.block:
            return F.least(i - F.pmod(i, F.lit(self.block)) + F.lit(self.block), F.lit(self.extent).cast("long"))
        return F.array_min(F.filter(self._array(), lambda b: b > i))

    def _array(self) -> Column:
        return numbers(self.bounds, "long")

    def cuts(self, lo: int, hi: int) -> list[tuple[int, int, int]]:
        """(block, from, to) of the blocks that lo to hi meets, on the driver or in a kernel."""
        if lo >= hi:
            return []
        if self.block:
            return [(k, max(lo, k * self.block), min(hi, (k + 1) * self.block)) for k in range(lo // self.block, (hi - 1) // self.block + 1)]
        first = bisect_right(self.bounds, lo) - 1
        last = bisect_left(self.bounds, hi)
        return [(k, max(lo, self.bounds[k]), min(hi, self.bounds[k + 1])) for k in range(first, last)]

    def frame(self, spark: SparkSession) -> DataFrame:
        """(k, lo, hi)."""
        k = spark.range(self.count).select(F.col("id").alias("k"))
        lo = self.start_of(F.col("k"))
        return k.select("k", lo.cast("long").alias("lo"), self.end_after(lo).cast("long").alias("hi"))


@dataclass(frozen=True)
class Layout:
    m: int
    n: int
    rows: Splits
    cols: Splits
    n_sites: int
    grid: tuple[int, int] | None = None
    site_order: str = "row"
    shift: tuple[int, int] = (0, 0)
    owners: tuple[int, ...] | None = None
    flipped: bool = False
    offset: tuple[int, int] = (0, 0)
    sigma: tuple[int, ...] | None = None
    order: str = "row"

    # ---- constructors

    @classmethod
    def grid_of(cls, row_bounds: tuple[int, ...], col_bounds: tuple[int, ...], owners: list[list[int]], n_sites: int, order: str = "row") -> Layout:
        """Any splits, any owners."""
        rows, cols = Splits(row_bounds[-1], bounds=tuple(row_bounds)), Splits(col_bounds[-1], bounds=tuple(col_bounds))
        flat = tuple(int(x) for line in owners for x in line)
        if len(flat) != rows.count * cols.count or any(not 0 <= x < n_sites for x in flat):
            raise ValueError("owners: one site for each block, from 0 to n_sites - 1")
        return cls(rows.extent, cols.extent, rows, cols, n_sites, owners=flat, order=order)

    @classmethod
    def block_cyclic(cls, m: int, n: int, mb: int, nb: int, pr: int, pc: int, site_order: str = "row", r_src: int = 0, c_src: int = 0, order: str = "row") -> Layout:
        if site_order not in ("row", "col"):
            raise ValueError("site_order is row or col")
        return cls(m, n, Splits(m, mb), Splits(n, nb), pr * pc, (pr, pc), site_order, (r_src, c_src), order=order)

    @classmethod
    def contiguous(cls, m: int, n: int, pr: int, pc: int, site_order: str = "row") -> Layout:
        """One range of rows and of columns for each line of the site grid."""
        return cls.block_cyclic(m, n, max(1, -(-m // pr)), max(1, -(-n // pc)), pr, pc, site_order)

    @classmethod
    def slabs(cls, m: int, n: int, p: int) -> Layout:
        return cls.contiguous(m, n, p, 1)

    @classmethod
    def from_quantiles(cls, df: DataFrame, column: str, k: int, n: int = 1, exact: bool = False) -> Layout:
        """Row ranges of about equal mass of column, one site each; exact sorts, otherwise quantiles are sketched."""
        if exact:
            parts = df.select(F.col(column).cast("long").alias("x"), F.ntile(k).over(Window.orderBy(column)).alias("t")).groupBy("t").agg(F.max("x").alias("x"))
            cuts = [r["x"] + 1 for r in parts.orderBy("t").collect()]  # k rows
        else:
            cuts = [int(x) + 1 for x in df.agg(F.percentile_approx(F.col(column).cast("long"), [i / k for i in range(1, k + 1)], 10_000).alias("q")).first()["q"]]
        bounds = tuple(sorted({0, *cuts}))
        return cls.grid_of(bounds, (0, n), [[i % k] for i in range(len(bounds) - 1)], k)

    # ---- derived layouts

    def transposed(self) -> Layout:
        return replace(self, m=self.n, n=self.m, flipped=not self.flipped, offset=self.offset[::-1])

    def window(self, r0: int, r1: int, c0: int, c1: int) -> Layout:
        """Rows r0 to r1 and columns c0 to c1, counted from 0 again; the offset is kept for owners."""
        if not (0 <= r0 <= r1 <= self.m and 0 <= c0 <= c1 <= self.n):
            raise ValueError("the window lies within the matrix")
        return replace(self, m=r1 - r0, n=c1 - c0, offset=(self.offset[0] + r0, self.offset[1] + c0))

    def relabel(self, sigma: list[int] | dict[int, int]) -> Layout:
        """Role r is played by site sigma[r]."""
        line = [sigma[r] for r in range(self.n_sites)]
        if sorted(line) != list(range(self.n_sites)):
            raise ValueError("a relabeling is a permutation of the sites")
        before = self.sigma or tuple(range(self.n_sites))
        return replace(self, sigma=tuple(line[s] for s in before))

    def widened(self, n_sites: int) -> Layout:
        """The same layout within a larger set of sites."""
        return replace(self, n_sites=max(n_sites, self.n_sites), sigma=(*self.sigma, *range(self.n_sites, n_sites)) if self.sigma and n_sites > self.n_sites else self.sigma)

    # ---- expressions

    def _base(self) -> tuple[Splits, Splits]:
        return (self.cols, self.rows) if self.flipped else (self.rows, self.cols)

    def blocks_of(self, i: Column, j: Column) -> tuple[Column, Column]:
        """Block row and block column (of the whole matrix) of a cell."""
        r, c = self._base()
        return r.block_of(i + F.lit(self.offset[0])).cast("long"), c.block_of(j + F.lit(self.offset[1])).cast("long")

    def owner_of_block(self, bi: Column, bj: Column) -> Column:
        if self.flipped:
            bi, bj = bj, bi
        if self.owners is not None:
            line = numbers(self.owners)
            site = F.element_at(line, (bi * F.lit(self.cols.count) + bj + 1).cast("int"))
        else:
            (pr, pc), (sr, sc) = self.grid, self.shift
            r, c = F.pmod(bi + F.lit(sr), F.lit(pr)), F.pmod(bj + F.lit(sc), F.lit(pc))
            site = r * F.lit(pc) + c if self.site_order == "row" else c * F.lit(pr) + r
        if self.sigma is not None:
            site = F.element_at(numbers(self.sigma), (site + 1).cast("int"))
        return site.cast("int")

    def site_of(self, bi: int, bj: int) -> int:
        """owner_of_block() of two numbers."""
        if self.flipped:
            bi, bj = bj, bi
        if self.owners is not None:
            site = self.owners[bi * self.cols.count + bj]
        else:
            (pr, pc), (sr, sc) = self.grid, self.shift
            r, c = (bi + sr) % pr, (bj + sc) % pc
            site = r * pc + c if self.site_order == "row" else c * pr + r
        return self.sigma[site] if self.sigma is not None else site

    def owner_of(self, i: Column, j: Column) -> Column:
        return self.owner_of_block(*self.blocks_of(i, j))

    def axis(self, which: int) -> tuple[Splits, int, int]:
        """Splits, offset and extent of rows (0) or columns (1) as they now lie."""
        return self._base()[which], self.offset[which], (self.m, self.n)[which]

    def blocks(self, spark: SparkSession) -> DataFrame:
        """(bi, bj, r_lo, r_hi, c_lo, c_hi, site), clipped to the window and counted from it."""
        frames = []
        for which, (k, lo, hi) in enumerate((("bi", "r_lo", "r_hi"), ("bj", "c_lo", "c_hi"))):
            splits, off, extent = self.axis(which)
            f = splits.frame(spark).filter((F.col("hi") > off) & (F.col("lo") < off + extent))
            frames.append(f.select(F.col("k").alias(k), (F.greatest("lo", F.lit(off)) - off).alias(lo), (F.least("hi", F.lit(off + extent)) - off).alias(hi)))
        both = frames[0].crossJoin(F.broadcast(frames[1]) if self.axis(1)[0].count <= 100_000 else frames[1])
        return both.select("*", self.owner_of_block(F.col("bi"), F.col("bj")).alias("site"))

    # ---- descriptors

    def to_json(self) -> str:
        return json.dumps({k: v for k, v in {**self.__dict__, "rows": self.rows.__dict__, "cols": self.cols.__dict__}.items()})

    @classmethod
    def from_json(cls, text: str) -> Layout:
        x = json.loads(text)
        line = lambda v: None if v is None else tuple(v)
        split = lambda s: Splits(s["extent"], s["block"], line(s["bounds"]))
        return cls(**x | {"rows": split(x["rows"]), "cols": split(x["cols"]), **{k: line(x[k]) for k in ("grid", "shift", "owners", "offset", "sigma")}})

