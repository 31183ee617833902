"""Dedup over the bytes of all suffixes: blockwise, with ranks of difference-cover samples.

Content anchors first drop the text that cannot repeat, and settle whole equal contexts (relayout.llm.repeats). What is left
is decided by suffix order (relayout.llm.suffix_order): samples of a difference cover get ranks in rounds, and one bucket of
suffixes at a time is sorted by rank and by the few bytes around, so no suffix is compared over its long tie. Repeats are read
off neighbours. Memory is that of one bucket, or of one part of the text, whatever the input.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from relayout.llm.repeats import Search, ask_once, default_buckets, find, fingerprints, ranges_of, unnull, with_ranges
from relayout.llm.shared import keyed, table, utf8
from relayout.llm.suffix_order import repeated_windows

SIZE, GRAM, COVER = 400, 64, 7


def repeated_ranges(docs: DataFrame, size: int = SIZE, gram: int = GRAM, cover: int = COVER, buckets: int | None = None) -> DataFrame:
    """(doc_id, rid, found) of the documents that have any: byte ranges under strings of ``size`` bytes that start
    anywhere else too. docs: (doc_id, rid, text) as keyed() gives it."""
    search = Search(words=False, window=size, gram=gram, later=False, cover=cover)
    buckets = buckets or default_buckets(docs)
    return find(docs, ask_once(fingerprints(docs, search, buckets), buckets), search, buckets, rest=repeated_windows)


def kept(text: bytes, ranges: np.ndarray) -> bytes:
    out, at = [], 0
    for f, t in ranges:
        out.append(text[at:f])
        at = int(t)
    return b"".join([*out, text[at:]])


def digest(docs: DataFrame, **how: int) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256). A null text is empty; repeated rows are documents of their own
    (each is a copy of the other); a null id stays null. Texts shorter than ``size`` keep all. No rows: no rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, at = utf8(batch.column("text"))
            found = [ranges_of(x) for x in batch.column("found").to_pylist()]
            bodies = [data[a:b].tobytes() for a, b in zip(at[:-1], at[1:], strict=True)]
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array(np.diff(at)), pa.array([int((r[:, 1] - r[:, 0]).sum()) for r in found], pa.int64()), pa.array([len(r) for r in found], pa.int64()),
                 pa.array([hashlib.sha256(kept(x, r)).hexdigest() for x, r in zip(bodies, found, strict=True)], pa.string())],
                ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"],
            )

    docs = keyed(docs)
    out = with_ranges(docs, repeated_ranges(docs, **how)).select("doc_id", "text", "found")
    out = out.mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")
    return out.select(unnull("doc_id"), "n_bytes", "n_removed", "n_spans", "kept_sha256")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest(table(spark, sf_dir, "documents").select("doc_id", "text"))

