"""Benchmark decontamination by greedy string tiling.

Words are runs of letters and digits, lower-cased. One pass over the documents, as Arrow buffers: every run of
``min_match`` words is hashed and looked up among the benchmark's (a bit map first, then a sorted array). Documents that
share a seed go on to the tiling, in the same task: the longest common run of unmarked words is marked in both texts,
again and again, down to ``min_match``, by Karp-Rabin fingerprints. Tiles don't overlap and may lie in any order, so a passage whose sentences were shuffled is still covered. The
share of a test item's words under tiles decides.

The benchmark is broadcast in chunks of a bounded number of bytes; a larger benchmark means more passes, each of which
writes its finds and frees its chunk before the next is read.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relayout.llm.shared import BYTE_ONE, Rolling, blocks, distinct, identity, materialise, table, utf8

MIN_MATCH, COVERAGE, CHUNK_BYTES = 4, 0.5, 4_000_000

_WORD = np.zeros(256, bool)
_WORD[[*range(48, 58), *range(97, 123), *range(128, 256)]] = True


def tokens(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word hashes of all texts, where each text's begin, and the texts' offsets in bytes (for blocks)."""
    data, offsets = utf8(column)
    solid = np.zeros(len(data) + 2, bool)
    solid[1:-1] = _WORD[data]
    edge = solid[1:] != solid[:-1]
    cuts = offsets[1:-1]
    cuts = np.unique(cuts[(cuts > 0) & (cuts < len(data))])
    inside = cuts[solid[cuts] & solid[cuts + 1]]
    starts, ends = np.flatnonzero(edge & solid[1:]), np.flatnonzero(edge & solid[:-1])
    if len(inside):
        starts, ends = np.sort(np.concatenate([starts, inside])), np.sort(np.concatenate([ends, inside]))
    return Rolling(BYTE_ONE[data]).of(starts, ends), np.searchsorted(starts, offsets, "left"), offsets


def tile(item: np.ndarray, doc: np.ndarray, min_match: int = MIN_MATCH) -> list[tuple[int, int, int]]:
    """(place in item, place in doc, length) of greedy tiles: always the longest left, of equals the first in item and doc.

    item and doc are word hashes. Shared seeds (runs of min_match words) are joined by their Karp-Rabin fingerprint; a
    match is then stretched over unmarked words by comparing fingerprints of doubled and halved lengths, for all places
    of the document at once. A heap holds, for each place of the item, the longest match it had when last looked at:
    marking only shortens matches, so one that still holds when it comes up is the longest of all. Work is at most
    (item's words) x (tiles + 1) looks at the document's places, whatever words repeat."""
    item, doc = np.asarray(item, np.uint64), np.asarray(doc, np.uint64)
    if min(len(item), len(doc)) < min_match:
        return []
    of_item, of_doc = Rolling(item), Rolling(doc)
    seeds = of_doc.every(min_match)
    order = np.argsort(seeds, kind="stable")
    wanted = of_item.every(min_match)
    first, last = (np.searchsorted(seeds[order], wanted, side) for side in ("left", "right"))
    marked_item, marked_doc = np.zeros(len(item), bool), np.zeros(len(doc), bool)
    free_item, free_doc = _free(marked_item), _free(marked_doc)

    def longest(a: int) -> tuple[int, int]:
        b = order[first[a] : last[a]]
        reach = np.minimum(free_item[a], free_doc[b])
        b, reach = b[reach >= min_match], reach[reach >= min_match]
        if not len(b):
            return 0, 0
        known = np.full(len(b), min_match)
        while (known < reach).any():
            tried = (known + reach + 1) // 2
            same = of_item.of(np.full(len(b), a), a + tried) == of_doc.of(b, b + tried)
            known, reach = np.where(same, tried, known), np.where(same, reach, tried - 1)
        k = int(known.argmax())
        return int(known[k]), int(b[k])

    heap = [(-n, a, b) for a in range(len(wanted)) for n, b in [longest(a)] if n]
    heapq.heapify(heap)
    tiles: list[tuple[int, int, int]] = []
    while heap:
        n, a, b = heapq.heappop(heap)
        now, at = longest(a)
        if (-now, at) != (n, b):
            if now:
                heapq.heappush(heap, (-now, a, at))
            continue
        marked_item[a : a + now] = marked_doc[b : b + now] = True
        free_item, free_doc = _free(marked_item), _free(marked_doc)
        tiles.append((a, b, now))
    return tiles


def _free(marked: np.ndarray) -> np.ndarray:
    """How many unmarked words follow from each place on."""
    n = len(marked)
    return np.minimum.accumulate(np.where(marked, np.arange(n), n)[::-1])[::-1] - np.arange(n)


@dataclass
class Bench:
    """A chunk of the benchmark: items' words, and the seeds in order with the item of each."""

    ids: list[int | None]
    words: list[np.ndarray]
    seeds: np.ndarray
    owner: np.ndarray
    bits: np.ndarray

    @classmethod
    def of(cls, rows: pa.Table, min_match: int) -> Bench:
        words, at, _ = tokens(pc.utf8_lower(rows.column("text")))
        lists = [words[a:b] for a, b in zip(at[:-1], at[1:], strict=True)]
        seeds = [distinct(Rolling(w).every(min_match)) for w in lists]
        owner = np.repeat(np.arange(len(lists)), [len(s) for s in seeds])
        all_seeds = np.concatenate([np.zeros(0, np.uint64), *seeds])
        order = np.argsort(all_seeds, kind="stable")
        bits = np.zeros(1 << 20, bool)
        bits[all_seeds >> np.uint64(44)] = True
        return cls(rows.column("item_id").to_pylist(), lists, all_seeds[order], owner[order], bits)

    def leaks(self, words: np.ndarray, at: np.ndarray, min_match: int, coverage: float) -> Iterator[tuple[int, int, int, int]]:
        """(document, item, covered words, words) of a block of documents."""
        every = Rolling(words).every(min_match)
        hit = np.flatnonzero(self.bits[every >> np.uint64(44)])
        hit = hit[self.seeds[np.minimum(np.searchsorted(self.seeds, every[hit]), len(self.seeds) - 1)] == every[hit]] if len(self.seeds) else hit[:0]
        doc = np.searchsorted(at, hit, "right") - 1
        whole = hit + min_match <= at[doc + 1]
        hit, doc = hit[whole], doc[whole]
        for d in np.unique(doc):
            places = hit[doc == d]
            first, last = np.searchsorted(self.seeds, every[places], "left"), np.searchsorted(self.seeds, every[places], "right")
            n = last - first
            items = self.owner[np.repeat(first - np.cumsum(n) + n, n) + np.arange(n.sum())]
            places = np.repeat(places, n)
            for i in np.unique(items):
                own = np.unique(places[items == i])
                size = len(self.words[i])
                reach = np.minimum(np.diff(own, append=own[-1] + min_match), min_match).sum()
                if reach < coverage * size:
                    # fewer words of the document are in seeds of this item than the tiles would have to cover
                    continue
                segments: list[np.ndarray] = []
                for k in np.split(own, np.flatnonzero(np.diff(own) > 1) + 1):
                    segments += [words[k[0] : k[-1] + min_match], ~np.array([len(segments)], np.uint64)]  # a border that is no word
                covered = sum(t[2] for t in tile(self.words[i], np.concatenate(segments), min_match))
                if covered >= coverage * size:
                    yield int(d), int(i), covered, size


def leaks(docs: DataFrame, benchmark: DataFrame, coverage: float = COVERAGE, min_match: int = MIN_MATCH, chunk_bytes: int = CHUNK_BYTES) -> DataFrame:
    """(doc_id, rid, item_id, covered, item_words) of each row of docs and item that it covers to ``coverage`` or more."""
    spark = docs.sparkSession
    items = benchmark.filter("text IS NOT NULL").select(F.col("item_id").cast("long").alias("item_id"), "text").distinct()
    total = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n_chunks = -(-int(total) // chunk_bytes)
    rows = docs.filter("text IS NOT NULL").select(F.col("doc_id").cast("long").alias("doc_id"), identity()[1].alias("rid"), "text")
    schema = "doc_id long, rid long, item_id long, covered int, item_words int"
    found = written = None
    for k in range(n_chunks):
        part = items.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(n_chunks)) == k)
        shared = spark.sparkContext.broadcast(Bench.of(part.toArrow(), min_match))  # chunk_bytes on average

        def scan(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            bench = shared.value
            for batch in batches:
                _, offsets = utf8(batch.column("text"))
                ids, rids, out = batch.column("doc_id"), batch.column("rid"), []
                for a, b in blocks(offsets):
                    words, at, _ = tokens(pc.utf8_lower(batch.column("text").slice(a, b - a)))
                    out += [(ids[a + d].as_py(), rids[a + d].as_py(), bench.ids[i], c, n) for d, i, c, n in bench.leaks(words, at, min_match, coverage)]
                columns = zip(*out, strict=True) if out else ([], [], [], [], [])
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], ["doc_id", "rid", "item_id", "covered", "item_words"])

        found = rows.mapInArrow(scan, schema)
        if n_chunks > 1:
            found = written = materialise(found, "leaks", written)
            shared.destroy()
    if found is None:
        found = spark.createDataFrame([], schema)
    return found


def contaminated(docs: DataFrame, benchmark: DataFrame, **how: object) -> DataFrame:
    """(doc_id, item_id, covered, item_words, coverage) of each document and item that it covers to ``coverage`` or more.

    Null and empty texts, and items of fewer than min_match words, match nothing. Whole texts are read, also those in
    which one word stands over and over. Repeated rows give one row; a null id is a value of its own. An empty table on
    either side gives no rows.
    """
    best = leaks(docs, benchmark, **how).groupBy("doc_id", "item_id").agg(F.max_by(F.struct("covered", "item_words"), F.col("covered") / F.col("item_words")).alias("x"))
    return best.select("doc_id", "item_id", "x.covered", "x.item_words", (F.col("x.covered") / F.col("x.item_words")).alias("coverage"))


def clean(docs: DataFrame, benchmark: DataFrame, **how: object) -> DataFrame:
    """docs without the contaminated ones; all columns stay. Of texts that share an id, or have none, each is judged alone."""
    number, rid = identity()
    bad = leaks(docs, benchmark, **how).select(identity()[0].alias("_doc"), F.col("rid").alias("_rid")).distinct()
    return docs.withColumns({"_doc": number, "_rid": rid}).join(bad, ["_doc", "_rid"], "left_anti").select(*docs.columns)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
