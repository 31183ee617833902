"""Packing of token sequences: non-negative least squares over shallow combinations of lengths.

1. One pass over the texts: ids, then the end id. Full windows are cut off (each is a sequence of its own); what is
   left of a document, its tail (shorter than a window), is written down with its place among the tails of the same
   length in its task.
2. A histogram of tail lengths (fewer than ``window`` rows, whatever the input) reaches the driver. Combinations of two
   or three lengths that fill a window exactly are enumerated; non-negative least squares finds how often to repeat
   each so that they use up the histogram; the counts are rounded within what there is.
3. A tail's place among all tails of its length says by arithmetic which repeat of which combination it fills. Tails
   that no combination takes are laid end to end, longest first, and cut at the window; the last, partly filled window
   is cut into powers of two, which need no padding.

No group of rows is gathered anywhere: places are prefix sums of counts by task and length.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from relayout.llm.shared import NO_ID, keyed, materialise, table

WINDOW, END_ID = 1024, 0
#: Sequence ids: full windows, combinations and laid-out tails have ranges of their own.
COMBINED, LAID = 1 << 60, 1 << 61

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


# ---- tokens -------------------------------------------------------------------------------------


class Encoder:
    """Ids as the tokenizers library gives them for a byte-level BPE file.

    tiktoken with the same vocabulary is several times as fast. Its ids are taken where both split text by the same
    character classes for certain: no special token's string, and only characters below U+0250 other than the control
    and space characters above ASCII. All other texts go to tokenizers.
    """

    def __init__(self, path: str, ranks_path: str | None):
        import regex
        from tokenizers import Tokenizer

        self.exact = Tokenizer.from_file(path)
        self.fast = None
        if ranks_path:
            import base64

            import public_tokenizers
            import tiktoken

            with open(ranks_path, "rb") as f:
                ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
            self.fast = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        self.odd = regex.compile("[\\x1c-\\x1f\\x7f-\\xa0\\xad\\u0250-\\U0010ffff]|<\\|")

    def __call__(self, text: str) -> np.ndarray:
        if self.fast is not None and not self.odd.search(text):
            return self.fast.encode_to_numpy(text)
        return np.array(self.exact.encode(text, add_special_tokens=False).ids, np.uint32)


@lru_cache(2)
def encoder(path: str, ranks_path: str | None) -> Encoder:
    return Encoder(path, ranks_path)


def tokenise(docs: DataFrame, path: str, ranks_path: str | None, window: int = WINDOW) -> DataFrame:
    """A row a document: part and full_at (task, full windows before it in the task), crcs of its full windows, and its
    tail with tail_at (tails of the same length before it in the task)."""
    schema = "doc_id long, part long, n long, full_at long, crcs array<long>, tail_n int, tail_at long, tail binary"
    arrow = pa.schema([("doc_id", pa.int64()), ("part", pa.int64()), ("n", pa.int64()), ("full_at", pa.int64()), ("crcs", pa.list_(pa.int64())), ("tail_n", pa.int32()), ("tail_at", pa.int64()), ("tail", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, part, full = encoder(path, ranks_path), TaskContext.get().partitionId(), 0
        seen = np.zeros(window, np.int64)
        for batch in batches:
            rows = []
            for doc_id, text in zip(batch.column("doc_id"), batch.column("text"), strict=True):
                ids = np.append(encode(text.as_py()), END_ID).astype("<u4")
                n_full, rest = divmod(len(ids), window)
                crcs = [zlib.crc32(ids[k * window : (k + 1) * window]) for k in range(n_full)]
                tail = ids[n_full * window :]
                small = tail.astype("<u2") if rest and tail.max() < 1 << 16 else tail
                rows.append((doc_id.as_py(), part, len(ids), full, crcs, rest, int(seen[rest]), small.tobytes()))
                full += n_full
                seen[rest] += 1
                if len(rows) >= 2000:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), arrow, strict=True)], schema=arrow)
                    rows = []
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), arrow, strict=True)], schema=arrow)

    return docs.select("doc_id", "text").mapInArrow(run, schema)


# ---- combinations -------------------------------------------------------------------------------


def combinations(window: int) -> np.ndarray:
    """All sets of two or three lengths that sum to the window, as rows (a, b, c) with a <= b <= c, a = 0 for two."""
    a, b = np.meshgrid(np.arange(window // 3 + 1), np.arange(1, window), indexing="ij")
    c = window - a - b
    keep = (a <= b) & (b <= c)
    return np.stack([a[keep], b[keep], c[keep]], axis=1)


def least_squares(combos: np.ndarray, counts: np.ndarray, rounds: int = 400) -> np.ndarray:
    """x >= 0 that makes the lengths used by x repeats of each combination close to counts, in least squares.

    Multiplicative updates: x grows by the ratio of A'b to A'Ax, so it never leaves the non-negative orthant; A has
    three ones a column and stays an index array."""
    x = np.ones(len(combos)) * counts.sum() / max(1, 3 * len(combos))
    used = counts.astype(float).copy()
    used[0] = 0
    wanted = used[combos].sum(axis=1)
    for _ in range(rounds):
        got = np.bincount(combos.ravel(), np.repeat(x, 3), len(counts))
        got[0] = 0
        x *= wanted / np.maximum(got[combos].sum(axis=1), 1e-12)
    return x


@dataclass
class Plan:
    """For each length, its ranks in order: which combination they fill (first rank, first sequence, repeats of the
    length within a sequence, offset of the first of them), then where its unplaced tails begin in the laid-out row."""

    window: int
    first: list[np.ndarray]
    sequence: list[np.ndarray]
    times: list[np.ndarray]
    offset: list[np.ndarray]
    taken: np.ndarray
    laid: np.ndarray
    edges: np.ndarray  # ends of the laid-out row's last, power-of-two sequences
    n_combined: int


def plan(counts: np.ndarray, window: int = WINDOW) -> Plan:
    """counts[l]: tails of length l."""
    counts = counts.astype(np.int64).copy()
    counts[0] = 0
    left = counts.copy()
    combos = combinations(window)
    combos = combos[((counts[combos] > 0) | (combos == 0)).all(axis=1)]
    chosen: list[tuple[tuple[int, ...], int]] = []
    if len(combos):
        x = least_squares(combos, counts)
        order = np.argsort(-x, kind="stable")
        pairs = order[combos[order, 0] == 0]
        for row, most in [*((k, int(x[k] + 0.5)) for k in order if x[k] >= 0.5), *((k, None) for k in pairs), *((k, None) for k in order[:4096])]:
            lengths = [int(v) for v in combos[row] if v]
            fit = min(int(left[v]) // lengths.count(v) for v in lengths)
            fit = fit if most is None else min(fit, most)
            if fit > 0:
                chosen.append((tuple(lengths), fit))
                for v in lengths:
                    left[v] -= fit
    first, sequence, times, offset = ([[] for _ in counts] for _ in range(4))
    at, n = np.zeros(len(counts), np.int64), 0
    for lengths, fit in chosen:
        place = 0
        for v in dict.fromkeys(lengths):
            m = lengths.count(v)
            for rows, value in ((first, at[v]), (sequence, n), (times, m), (offset, place)):
                rows[v].append(int(value))
            at[v] += fit * m
            place += m * v
        n += fit
    lengths = np.arange(len(counts))
    over = left * lengths
    laid = over[::-1].cumsum()[::-1] - over  # longest first
    rest, edges = int(over.sum() % window), [int(over.sum() // window) * window]
    for bit in range(window.bit_length(), -1, -1):
        if rest >> bit & 1:
            edges.append(edges[-1] + (1 << bit))
    as_arrays = lambda x: [np.array(v, np.int64) for v in x]
    return Plan(window, as_arrays(first), as_arrays(sequence), as_arrays(times), as_arrays(offset), at, laid, np.array(edges, np.int64), n)


def place(p: Plan, length: int, rank: int) -> list[tuple[int, int, int, int]]:
    """(start in the tail, length, sequence id, offset) of the pieces of the rank-th tail of this length."""
    if rank < p.taken[length]:
        k = int(np.searchsorted(p.first[length], rank, "right")) - 1
        nth, which = divmod(rank - int(p.first[length][k]), int(p.times[length][k]))
        return [(0, length, COMBINED + int(p.sequence[length][k]) + nth, int(p.offset[length][k]) + which * length)]
    out, done = [], 0
    at = int(p.laid[length]) + (rank - int(p.taken[length])) * length
    while done < length:
        if at < p.edges[0]:
            begin = at - at % p.window
            end = begin + p.window
        else:
            k = int(np.searchsorted(p.edges, at, "right"))
            begin, end = int(p.edges[k - 1]), int(p.edges[k])
        step = min(length - done, end - at)
        out.append((done, step, LAID + begin, at - begin))
        done, at = done + step, at + step
    return out


# ---- the operator -------------------------------------------------------------------------------


def pack(docs: DataFrame, path: str, ranks_path: str | None = None, window: int = WINDOW) -> DataFrame:
    """One row a piece (columns PIECES); every id of every document lies in exactly one piece.

    A document is its ids and END_ID; a null or empty text is END_ID alone. Repeated rows are packed each. Null ids
    stay null. Texts of any length: only one document's ids are held at a time. An empty table gives no rows.
    """
    spark = docs.sparkSession
    t = materialise(tokenise(keyed(docs), path, ranks_path, window), "tokens")
    by_task = t.filter("tail_n > 0").groupBy("part", "tail_n").agg(F.count(F.lit(1)).alias("n_tails"))
    counts = np.zeros(window, np.int64)
    for row in by_task.groupBy("tail_n").agg(F.sum("n_tails").alias("n")).collect():  # fewer than window rows
        counts[row["tail_n"]] = row["n"]
    chosen = plan(counts, window)

    before = F.sum("n_tails").over(Window.partitionBy("tail_n").orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    before = by_task.select("part", "tail_n", F.coalesce(before, F.lit(0)).alias("before"))
    ranked = t.join(before, ["part", "tail_n"], "left")
    model = spark.sparkContext.broadcast(chosen)  # a few numbers for each length

    def cut(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        p = model.value
        names = [column.split()[0] for column in PIECES.split(", ")]
        for frame in frames:
            rows = []
            for d, part, n, full_at, crcs, tail_n, tail_at, tail, past in frame[["doc_id", "part", "n", "full_at", "crcs", "tail_n", "tail_at", "tail", "before"]].itertuples(index=False):
                doc_id = None if d == NO_ID else d
                for k, crc in enumerate(crcs):
                    rows.append((doc_id, k * p.window, p.window, crc, n, (part << 32) + full_at + k, 0))
                if tail_n:
                    ids = np.frombuffer(tail, "<u2" if len(tail) == 2 * tail_n else "<u4").astype("<u4")
                    for start, length, sequence, offset in place(p, tail_n, int(tail_at + past)):
                        rows.append((doc_id, n - tail_n + start, length, zlib.crc32(ids[start : start + length]), n, sequence, offset))
            yield pd.DataFrame(rows, columns=names).astype({"doc_id": "Int64"})

    return ranked.mapInPandas(cut, PIECES)


def padding(pieces: DataFrame, window: int = WINDOW) -> DataFrame:
    """Measure: sequences, tokens, and the padding they need (none at a power of two)."""
    size = pieces.groupBy("sequence_id").agg(F.sum("length").alias("tokens"))
    power = F.col("tokens").bitwiseAND(F.col("tokens") - 1) == 0
    return size.agg(
        F.count(F.lit(1)).alias("sequences"),
        F.coalesce(F.sum("tokens"), F.lit(0)).alias("tokens"),
        F.coalesce(F.sum(F.when(power, 0).otherwise(F.lit(window) - F.col("tokens"))), F.lit(0)).alias("padding"),
    )


def tokenizer_paths() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"), *tokenizer_paths())
