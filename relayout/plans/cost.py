"""Cost models: a number for each parcel, as Column expressions over (src, dst, vol, n_pieces) and a table of links.

Every model is a sum of terms that depend on the sender, the receiver and the parcel's size, so that the cost of a parcel
if site ``dst`` were another site is the same expression with another ``dst``.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


class Cost:
    """cost(src, dst, parcel columns) -> Column; links: (src, dst, lat, bw) that it reads, or None."""

    links: DataFrame | None = None

    def of(self, src: Column, dst: Column, vol: Column, pieces: Column, lat: Column, bw: Column) -> Column:
        raise NotImplementedError

    def __add__(self, other: Cost) -> Cost:
        return Weighted(((1.0, self), (1.0, other)))

    def __rmul__(self, factor: float) -> Cost:
        return Weighted(((float(factor), self),))

    def attach(self, df: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
        """df with lat and bw of its (src, dst); a pair without a link is free."""
        if self.links is None:
            return df.withColumns({"lat": F.lit(0.0), "bw": F.lit(0.0)})
        near = F.broadcast(self.links.select(F.col("src").alias("_s"), F.col("dst").alias("_d"), "lat", "bw"))  # sites squared
        joined = df.join(near, (F.col(src) == F.col("_s")) & (F.col(dst) == F.col("_d")), "left").drop("_s", "_d")
        return joined.na.fill(0.0, ["lat", "bw"])

    def weight(self, df: DataFrame, src: str = "src", dst: str = "dst", name: str = "weight") -> DataFrame:
        x = self.attach(df, src, dst)
        return x.withColumn(name, self.of(F.col(src), F.col(dst), F.col("vol"), F.col("n_pieces"), F.col("lat"), F.col("bw"))).drop("lat", "bw")


@dataclass(frozen=True)
class VolumeCost(Cost):
    """Bytes that leave their site."""

    def of(self, src, dst, vol, pieces, lat, bw):  # noqa: ANN001, ANN201
        return F.when(src != dst, vol).otherwise(F.lit(0))


@dataclass(frozen=True)
class ItemCost(Cost):
    """The older model: each piece counts one, whatever its size, on a uniform net."""

    def of(self, src, dst, vol, pieces, lat, bw):  # noqa: ANN001, ANN201
        return F.when(src != dst, pieces).otherwise(F.lit(0))


@dataclass(frozen=True, eq=False)
class LinkCost(Cost):
    """Latency of the link and so much a byte; what stays is free if local_free."""

    links: DataFrame
    local_free: bool = True

    def of(self, src, dst, vol, pieces, lat, bw):  # noqa: ANN001, ANN201
        cost = lat + bw * vol
        return F.when(src != dst, cost).otherwise(F.lit(0.0)) if self.local_free else cost


@dataclass(frozen=True)
class TransformCost(Cost):
    """c for each byte that is transformed: all bytes or those that move; speed: site -> factor of the receiver; needs: a
    column of the parcels with the bytes that need a transform (else all do)."""

    c: float = 1.0
    charge: str = "all"
    speed: tuple[float, ...] | None = None
    needs: str | None = None

    def of(self, src, dst, vol, pieces, lat, bw):  # noqa: ANN001, ANN201
        cost = F.lit(self.c) * (F.col(self.needs) if self.needs else vol)
        if self.speed:
            cost = cost * F.element_at(F.array(*(F.lit(float(x)) for x in self.speed)), dst.cast("int") + 1)
        return cost if self.charge == "all" else F.when(src != dst, cost).otherwise(F.lit(0.0))


@dataclass(frozen=True)
class LocalityCost(Cost):
    """Bytes rounded up to a whole number of aligned stretches, times a penalty where storage is strided. lines: a column of
    the parcels with the number of runs that their pieces are stored in (overlay.parcel_lines, by the order of storage);
    without it a piece counts as one run."""

    stride_penalty: float = 1.5
    align: int = 64
    strided: bool = True
    lines: str | None = None

    def of(self, src, dst, vol, pieces, lat, bw):  # noqa: ANN001, ANN201
        runs = F.col(self.lines) if self.lines else pieces
        each = F.ceil(vol / runs / F.lit(self.align)) * F.lit(self.align) * runs
        return F.when(src != dst, each * F.lit(self.stride_penalty if self.strided else 1.0)).otherwise(F.lit(0.0))


@dataclass(frozen=True, eq=False)
class FnCost(Cost):
    """Any expression of (src, dst, vol, pieces)."""

    fn: Callable[[Column, Column, Column, Column], Column]

    def of(self, src, dst, vol, pieces, lat, bw):  # noqa: ANN001, ANN201
        return self.fn(src, dst, vol, pieces)


@dataclass(frozen=True, eq=False)
class Weighted(Cost):
    """A weighted sum of models."""

    terms: tuple[tuple[float, Cost], ...]

    def of(self, src, dst, vol, pieces, lat, bw):  # noqa: ANN001, ANN201
        if any(c.links is not None or isinstance(c, Weighted) for _, c in self.terms):
            raise ValueError("a sum of link costs has a table of links for each term: use weight()")
        out = F.lit(0.0)
        for w, c in self.terms:
            out = out + F.lit(w) * c.of(src, dst, vol, pieces, lat, bw)
        return out

    def weight(self, df: DataFrame, src: str = "src", dst: str = "dst", name: str = "weight") -> DataFrame:
        """Each term is priced with its own links."""
        depth = sum(c.startswith("_term") for c in df.columns)
        own = [f"_term{depth + k}" for k in range(len(self.terms))]
        for (_, c), column in zip(self.terms, own, strict=True):
            df = c.weight(df, src, dst, column)
        total = F.lit(0.0)
        for (w, _), column in zip(self.terms, own, strict=True):
            total = total + F.lit(w) * F.col(column)
        return df.withColumn(name, total).drop(*(c for c in own if c != name))


def region_links(spark, n: int = 5) -> DataFrame:  # noqa: ANN001
    """Links of sites in a row: latency 1000 times their distance, and the distance for each byte."""
    a, b = spark.range(n).select(F.col("id").cast("int").alias("src")), spark.range(n).select(F.col("id").cast("int").alias("dst"))
    far = F.abs(F.col("src") - F.col("dst")).cast("double")
    return a.crossJoin(b).select("src", "dst", (far * 1000).alias("lat"), far.alias("bw"))
