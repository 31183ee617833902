"""Tiles: the execution form of a dense matrix. One row a block: (mat, bi, bj, r0, c0, nr, nc, ld, ord, data).

``ord`` says whether data goes row by row or column by column, ``ld`` how far apart its lines begin (padding included).
Transposing a tile swaps its indices and flips ``ord``; no value is copied.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType, LongType, StringType, StructField, StructType

from relayout.plans.cost import Cost
from relayout.plans.layout import Layout
from relayout.plans.relabel import Plan, find_matrix_relabeling


def to_tiles(entries: DataFrame, layout: Layout, mat: str = "A", order: str = "row", pad: int = 0) -> DataFrame:
    """Dense tiles of a layout's blocks, one exchange of cells; absent cells are 0. pad: unused places behind each line.
    Values are numbers."""
    bi, bj = layout.blocks_of(F.col("i"), F.col("j"))
    held = entries.select(bi.alias("bi"), bj.alias("bj"), "i", "j", "v").groupBy("bi", "bj").agg(F.collect_list(F.struct(F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j"), "v")).alias("cells"))
    frame = layout.blocks(entries.sparkSession).join(held, ["bi", "bj"], "left").select("bi", "bj", F.col("r_lo").alias("r0"), F.col("c_lo").alias("c0"), (F.col("r_hi") - F.col("r_lo")).cast("int").alias("nr"), (F.col("c_hi") - F.col("c_lo")).cast("int").alias("nc"), F.col("site").alias("pid"), "cells")
    shape = StructType([StructField(c, LongType()) for c in ("bi", "bj", "r0", "c0")] + [StructField(c, IntegerType()) for c in ("nr", "nc", "ld")] + [StructField("ord", StringType()), StructField("data", ArrayType(entries.schema["v"].dataType)), StructField("pid", IntegerType())])

    def fill(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cells = batch.column("cells")
            kind = cells.type.value_type.field("v").type
            for k in range(batch.num_rows):  # a tile at a time
                bi, bj, r0, c0, nr, nc, pid = (batch.column(c)[k].as_py() for c in ("bi", "bj", "r0", "c0", "nr", "nc", "pid"))
                own = cells.slice(k, 1).flatten()
                tile = np.zeros((nr, nc), kind.to_pandas_dtype())
                tile[own.field("i").to_numpy() - r0, own.field("j").to_numpy() - c0] = own.field("v").to_numpy(zero_copy_only=False)
                flat, ld = _stored(tile, order, pad)
                yield pa.RecordBatch.from_arrays([pa.array([x], f.type) for x, f in zip((bi, bj, r0, c0, nr, nc, ld, order, flat, pid), TILE(pa.list_(kind)), strict=True)], schema=TILE(pa.list_(kind)))

    return frame.mapInArrow(fill, shape).select(F.lit(mat).alias("mat"), *(f.name for f in shape))


def _div(a, b):  # noqa: ANN001, ANN202
    return ((a - F.pmod(a, b)) / b).cast("long")


def from_tiles(tiles: DataFrame) -> DataFrame:
    """(i, j, v) of all cells, padding left out."""
    flat = tiles.select("r0", "c0", "nr", "nc", "ld", "ord", F.posexplode("data").alias("k", "v"))
    line, place = _div(F.col("k"), F.col("ld")), F.pmod("k", "ld")
    row = F.col("ord") == "row"
    return flat.filter(place < F.when(row, F.col("nc")).otherwise(F.col("nr"))).select(
        (F.col("r0") + F.when(row, line).otherwise(place)).alias("i"), (F.col("c0") + F.when(row, place).otherwise(line)).alias("j"), "v"
    )


def transpose_tiles(tiles: DataFrame) -> DataFrame:
    swap = {"bi": "bj", "bj": "bi", "r0": "c0", "c0": "r0", "nr": "nc", "nc": "nr"}
    other = F.when(F.col("ord") == "row", F.lit("col")).otherwise(F.lit("row"))
    return tiles.select(*(F.col(swap[c]).alias(c) if c in swap else other.alias(c) if c == "ord" else F.col(c) for c in tiles.columns))


def shuffle_tiles(
    b: DataFrame, lb: Layout, la: Layout, alpha: float | int = 1, beta: float | int = 0, a: DataFrame | None = None, op: str = "identity", order: str = "row", pad: int = 0,
    cost: Cost | None = None, relabel: str = "optimal", transform: str = "receive",
) -> tuple[DataFrame, Layout, Plan]:
    """A <- alpha op(B) + beta A over tiles: the target's tiles, its layout (relabelled), and the plan.

    b: tiles of lb, a: tiles of la, as to_tiles() gives them, in any order of storage and with any padding. Each tile is
    cut on the overlay; a piece is one packed row with its cells, its place and its order of storage, so 8 bytes a cell
    cross the one exchange and not an index for each. On receipt the pieces of a target tile are written into it, in the
    target's order and padding, scaled there (or before sending, with transform='send'); a transposed piece only has its
    indices and order swapped. Absent target tiles don't occur: layouts cover the matrix.
    """
    if op not in ("identity", "transpose"):
        raise ValueError("op is identity or transpose")
    if beta and a is None:
        raise ValueError("beta needs A")
    n = max(la.n_sites, lb.n_sites)
    plan = find_matrix_relabeling(b.sparkSession, la, lb, cost, op, {"optimal": "auto"}.get(relabel, relabel))
    home = la.widened(n).relabel(plan.sigma)
    send, turn = transform == "send", op == "transpose"
    kind = dict(b.dtypes)["data"]
    fields = ("bi", "bj", "r0", "c0", "nr", "nc", "ld", "ord", "data")

    def cut(turned: bool, own: int, factor: float | int):  # noqa: ANN202
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                out: list[list] = [[] for _ in range(8)]
                for bi, bj, tile, r0, c0 in _read_tiles(batch):
                    tile, r0, c0, src = (tile.T, c0, r0, lb.site_of(bi, bj)) if turned else (tile, r0, c0, home.site_of(bi, bj) if own else lb.site_of(bi, bj))
                    (rs, ro, _), (cs, co, _) = la.axis(0), la.axis(1)
                    for kr, lo_r, hi_r in rs.cuts(r0 + ro, r0 + ro + tile.shape[0]):
                        for kc, lo_c, hi_c in cs.cuts(c0 + co, c0 + co + tile.shape[1]):
                            r, c = lo_r - ro, lo_c - co
                            piece = tile[r - r0 : hi_r - ro - r0, c - c0 : hi_c - co - c0]
                            if factor != 1:
                                piece = piece * factor
                            flat = piece.T.ravel() if piece.flags.f_contiguous and not piece.flags.c_contiguous else piece.ravel()
                            lines = "col" if piece.flags.f_contiguous and not piece.flags.c_contiguous else "row"
                            for column, x in zip(out, (home.site_of(kr, kc), src, own, kr, kc, [r, c, *piece.shape], lines, flat), strict=True):
                                column.append(x)
                yield pa.RecordBatch.from_arrays([pa.array(x, t.type) for x, t in zip(out, PIECE(batch.schema.field("data").type), strict=True)], schema=PIECE(batch.schema.field("data").type))

        return run

    pieces = f"pid int, src int, own int, bi long, bj long, place array<long>, lines string, data {kind}"
    moved = b.select(*fields).mapInArrow(cut(turn, 0, alpha if send else 1), pieces)
    if beta:
        moved = moved.unionByName(a.select(*fields).mapInArrow(cut(False, 1, 1), pieces))
    # target tiles are written one after the other: a partition's pieces come in their order
    moved = moved.repartitionById(n, "pid").sortWithinPartitions("bi", "bj", "own")
    shape = StructType([StructField(c, LongType()) for c in ("bi", "bj", "r0", "c0")] + [StructField(c, IntegerType()) for c in ("nr", "nc", "ld")] + [StructField("ord", StringType()), StructField("data", b.schema["data"].dataType), StructField("pid", IntegerType())])

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, tile, old, pid = None, None, None, None

        def done() -> pa.RecordBatch:
            whole = tile * alpha if alpha != 1 and not send else tile
            if old is not None:
                whole = whole + beta * old
            flat, ld = _stored(whole, order, pad)
            (_, lo_r, _), (_, lo_c, _) = _block(la, 0, at[0]), _block(la, 1, at[1])
            values = [[x] for x in (*at, lo_r, lo_c, *tile.shape, ld, order, flat.astype(tile.dtype), pid)]
            return pa.RecordBatch.from_arrays([pa.array(v, f.type) for v, f in zip(values, TILE(kinds), strict=True)], schema=TILE(kinds))

        for batch in batches:
            kinds = batch.schema.field("data").type
            places, flat = batch.column("place").to_pylist(), batch.column("data")
            offsets, data = flat.offsets.to_numpy(), flat.values.to_numpy(zero_copy_only=False)
            columns = [batch.column(c).to_pylist() for c in ("bi", "bj", "own", "lines", "pid")]
            for k, (bi, bj, own, lines, site) in enumerate(zip(*columns, strict=True)):
                if at != (bi, bj):
                    if at is not None:
                        yield done()
                    at, pid = (bi, bj), site
                    (_, lo_r, hi_r), (_, lo_c, hi_c) = _block(la, 0, bi), _block(la, 1, bj)
                    tile, old = np.zeros((hi_r - lo_r, hi_c - lo_c), data.dtype), None
                r, c, h, w = places[k]
                values = data[offsets[k] : offsets[k + 1]]
                values = values.reshape(h, w) if lines == "row" else values.reshape(w, h).T
                if own and old is None:
                    old = np.zeros_like(tile)
                (old if own else tile)[r - lo_r : r - lo_r + h, c - lo_c : c - lo_c + w] = values
        if at is not None:
            yield done()

    out = moved.select("bi", "bj", "own", "place", "lines", "data", "pid").mapInArrow(place, shape)
    return out.select(F.lit("A").alias("mat"), *(f.name for f in shape)), home, plan


def PIECE(data: pa.DataType) -> pa.Schema:  # noqa: N802
    return pa.schema([("pid", pa.int32()), ("src", pa.int32()), ("own", pa.int32()), ("bi", pa.int64()), ("bj", pa.int64()), ("place", pa.list_(pa.int64())), ("lines", pa.string()), ("data", data)])


def TILE(data: pa.DataType) -> pa.Schema:  # noqa: N802
    return pa.schema([(c, pa.int64()) for c in ("bi", "bj", "r0", "c0")] + [(c, pa.int32()) for c in ("nr", "nc", "ld")] + [("ord", pa.string()), ("data", data), ("pid", pa.int32())])


def _block(layout: Layout, which: int, k: int) -> tuple[int, int, int]:
    """(k, from, to) of a block of rows (0) or columns (1), clipped to the window and counted from it."""
    splits, off, extent = layout.axis(which)
    lo, hi = (k * splits.block, (k + 1) * splits.block) if splits.block else (splits.bounds[k], splits.bounds[k + 1])
    return k, max(lo - off, 0), min(hi - off, extent)


def _read_tiles(batch: pa.RecordBatch) -> Iterator[tuple[int, int, np.ndarray, int, int]]:
    """(bi, bj, cells, r0, c0) of each tile; cells is a view of its storage, padding left out."""
    flat = batch.column("data")
    offsets, data = flat.offsets.to_numpy(), flat.values.to_numpy(zero_copy_only=False)
    columns = [batch.column(c).to_pylist() for c in ("bi", "bj", "r0", "c0", "nr", "nc", "ld", "ord")]
    for k, (bi, bj, r0, c0, nr, nc, ld, order) in enumerate(zip(*columns, strict=True)):
        lines = data[offsets[k] : offsets[k + 1]].reshape(-1, ld)
        yield bi, bj, lines[:, :nc] if order == "row" else lines[:, :nr].T, r0, c0


def _stored(tile: np.ndarray, order: str, pad: int) -> tuple[np.ndarray, int]:
    """A tile's values as they are stored, and how far apart its lines begin."""
    lines = tile if order == "row" else tile.T
    if pad:
        lines = np.concatenate([lines, np.zeros((len(lines), pad), lines.dtype)], axis=1)
    return lines.ravel(), lines.shape[1]


def tile_product(x: DataFrame, y: DataFrame) -> DataFrame:
    """(i, j, v) of X' Y from row tiles of both with the same row splits: a product of each pair of tiles of a row block in
    numpy on Arrow batches, then one sum of partial results."""
    import pandas as pd

    pairs = x.select("bi", "nr", F.col("nc").alias("xn"), F.col("c0").alias("xc"), F.col("data").alias("xd")).join(y.select("bi", F.col("nc").alias("yn"), F.col("c0").alias("yc"), F.col("data").alias("yd")), "bi")

    def run(frames):  # noqa: ANN001, ANN202
        for f in frames:
            out = []
            for nr, xn, xc, xd, yn, yc, yd in f[["nr", "xn", "xc", "xd", "yn", "yc", "yd"]].itertuples(index=False):
                v = np.reshape(xd, (nr, xn)).T @ np.reshape(yd, (nr, yn))
                i, j = np.meshgrid(np.arange(xn) + xc, np.arange(yn) + yc, indexing="ij")
                out.append(pd.DataFrame({"i": i.ravel(), "j": j.ravel(), "v": v.ravel()}))
            if out:
                yield pd.concat(out)

    return pairs.mapInPandas(run, "i long, j long, v long").groupBy("i", "j").agg(F.sum("v").alias("v"))
