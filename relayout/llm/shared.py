"""What the operators share: tables, durable intermediate results, text buffers and rolling hashes.

Texts stay in Arrow's UTF-8 buffers: numpy sees the bytes of a whole block of documents at once and no
Python string is made. Blocks are cut at less than half a million bytes, so memory doesn't follow the batch.
"""

from __future__ import annotations

import atexit
import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

BLOCK = 400_000
NO_ID = -(2**63)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors see. Where the session names none, a temporary one on a local master (tests), whose
    only machine this is; on a cluster that is an error."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        found = getattr(spark, "_relayout_shared", None) or tempfile.mkdtemp(prefix="relayout-")
        spark._relayout_shared = found
    return f"{found}/relayout-{spark.sparkContext.applicationId}"


def materialise(df: DataFrame, label: str, onto: DataFrame | None = None) -> DataFrame:
    """Writes df to the shared folder and reads it back: lineage is cut, and a lost executor loses nothing. onto: what was
    written before and grows by these rows."""
    spark = df.sparkSession
    root = shared_dir(spark)
    if not getattr(spark, "_relayout_cleanup", False):
        spark._relayout_cleanup = True
        atexit.register(_remove, spark, root)
    path = onto._relayout_path if onto is not None else f"{root}/{label}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").mode("append").parquet(path)
    release(spark)
    out = spark.read.schema(df.schema).parquet(path)
    out._relayout_path = path
    return out


def release(spark: SparkSession) -> None:
    """Lets Spark's cleaner drop shuffle files that nothing refers to any more."""
    gc.collect()
    spark._jvm.System.gc()


def discard(*written: DataFrame) -> None:
    """Deletes what materialise() wrote, once all that was read from it has been written down itself."""
    for df in written:
        _remove(df.sparkSession, df._relayout_path)


def _remove(spark: SparkSession, path: str) -> None:
    try:
        jvm, conf = spark._jvm, spark.sparkContext._jsc.hadoopConfiguration()
        at = jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(conf).delete(at, True)
    except Exception:  # noqa: BLE001  the session has ended before
        pass


def parts(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def identity(doc_id: str = "doc_id", text: str = "text") -> tuple[Column, Column]:
    """What tells documents apart: the id (a null one sorts first) and rid, a hash of id and text. Copies of one text have
    rids of their own, so a join on them spreads a text that a third of all rows hold."""
    number = F.coalesce(F.col(doc_id).cast("long"), F.lit(NO_ID))
    return number, F.xxhash64(number, F.coalesce(F.col(text).cast("string"), F.lit("")))


def keyed(docs: DataFrame) -> DataFrame:
    """(doc_id, rid, text) with identity()'s id and rid; a null text is empty."""
    number, rid = identity()
    return docs.select(number.alias("doc_id"), rid.alias("rid"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))


@lru_cache(1)
def _allocator():  # noqa: ANN202
    try:
        return ctypes.CDLL("libc.so.6").malloc_trim
    except (OSError, AttributeError):  # another C library
        return None


def trim() -> None:
    """Gives memory that numpy and Arrow have freed back to the system: a Python worker lives on between tasks, and a
    container counts what it holds."""
    pa.default_memory_pool().release_unused()
    if give_back := _allocator():
        give_back(0)


# ---- text buffers -------------------------------------------------------------------------------


def utf8(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string or binary column; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    if column.null_count:
        column = column.fill_null(b"" if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else "")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    if offsets is None or len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    at = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    return (np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8))[at[0] : at[-1]], at - at[0]


def blocks(offsets: np.ndarray, size: int = BLOCK) -> Iterator[tuple[int, int]]:
    """Ranges of documents of about size bytes each; a longer document stands alone."""
    n, first = len(offsets) - 1, 0
    while first < n:
        last = max(first + 1, int(np.searchsorted(offsets, offsets[first] + size, "right")) - 1)
        yield first, min(last, n)
        first = last
    trim()


def words_of(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the runs of bytes other than space and \\t\\n\\v\\f\\r."""
    solid = np.empty(len(data) + 2, bool)
    solid[0] = solid[-1] = False
    np.logical_not((data == 32) | ((data >= 9) & (data <= 13)), out=solid[1:-1])
    edges = np.flatnonzero(solid[1:] != solid[:-1])
    return edges[::2], edges[1::2]


def words_in_documents(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts, ends and, for each document, where its words begin (one more than documents).

    A word never crosses a document: where two touch, the run is cut."""
    starts, ends = words_of(data)
    cuts = offsets[1:-1]
    cuts = np.unique(cuts[(cuts > 0) & (cuts < len(data))])
    if len(cuts) and len(starts):
        k = np.searchsorted(starts, cuts, "right") - 1
        inside = (k >= 0) & (starts[np.maximum(k, 0)] < cuts) & (ends[np.maximum(k, 0)] > cuts)
        if inside.any():
            starts, ends = np.sort(np.concatenate([starts, cuts[inside]])), np.sort(np.concatenate([ends, cuts[inside]]))
    return starts, ends, np.searchsorted(starts, offsets, "left")


def lowered(data: np.ndarray) -> np.ndarray:
    """A-Z to a-z; all other bytes stay."""
    return data + ((data >= 65) & (data <= 90)).astype(np.uint8) * np.uint8(32)


# ---- hashes -------------------------------------------------------------------------------------


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every input bit (xor-shift-multiply)."""
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x81DADEF4BC2DD44D)
    return x ^ (x >> np.uint64(33))


class Powers:
    """Powers of an odd number and of its inverse, modulo 2**64, as far as asked for."""

    def __init__(self, base: int):
        self.base, self.inverse = base, pow(base, -1, 2**64)
        self.up = self.down = np.ones(1, np.uint64)

    def upto(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = max(1 << (n - 1).bit_length(), 1 << 16)
            for name, base in (("up", self.base), ("down", self.inverse)):
                row = np.full(size, base, np.uint64)
                row[0] = 1
                setattr(self, name, np.multiply.accumulate(row))
        return self.up, self.down


ONE, TWO = Powers(0x9E3779B97F4A7C15), Powers(0xD1342543DE82EF95)
BYTE_ONE = mix(np.arange(1, 257, dtype=np.uint64))
BYTE_TWO = mix(np.arange(1001, 1257, dtype=np.uint64))


class Rolling:
    """Hashes of any range of a sequence of 64-bit units in constant time, from sums of weighted units."""

    def __init__(self, units: np.ndarray, powers: Powers = ONE):
        up, self.down = powers.upto(len(units) + 1)
        self.sums = np.zeros(len(units) + 1, np.uint64)
        np.cumsum(units * up[: len(units)], out=self.sums[1:])

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((self.sums[end] - self.sums[start]) * self.down[start] + (end - start).astype(np.uint64))

    def every(self, length: int) -> np.ndarray:
        """Of each window of this length."""
        n = len(self.sums) - length
        if n <= 0:
            return np.zeros(0, np.uint64)
        return mix((self.sums[length:] - self.sums[:n]) * self.down[:n] + np.uint64(length))


def run_ends(begin: np.ndarray, n: int) -> np.ndarray:
    """Where runs that begin at these places of a sequence of n end."""
    return np.append(begin[1:], n)[: len(begin)]


def distinct(x: np.ndarray) -> np.ndarray:
    """Sorted, each value once (a sort is several times as fast here as numpy's hash table)."""
    x = np.sort(x)
    return x[np.append(True, x[1:] != x[:-1])] if len(x) else x


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    return Rolling(BYTE_ONE[data]).of(starts, ends)


def word_twins(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A second hash of each word, independent of the first: other values of bytes, other powers."""
    return Rolling(BYTE_TWO[data], TWO).of(starts, ends)


def in_pieces(hashes: Callable[[np.ndarray, np.ndarray, np.ndarray], np.ndarray], data: np.ndarray, starts: np.ndarray, ends: np.ndarray, size: int = 200_000) -> np.ndarray:
    """hashes of all words, so many at a time: sums over bytes need memory, and a text may be long."""
    out = np.empty(len(starts), np.uint64)
    for k in range(0, len(starts), size):
        a, b = starts[k : k + size], ends[k : k + size]
        out[k : k + size] = hashes(data[a[0] : b[-1]], a - a[0], b - a[0])
    return out


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each window, by doubling."""
    n, span = len(x) - width + 1, 1
    if n <= 0:
        return x[:0]
    while span * 2 <= width:
        x = np.minimum(x[:-span], x[span:])
        span *= 2
    return np.minimum(x[:n], x[width - span : width - span + n])
