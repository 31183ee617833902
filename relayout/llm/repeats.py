"""Exact search for repeated windows of a fixed length, in any unit (bytes, words), over a whole corpus.

A window is ``window`` consecutive units of one document. All windows of 100 TB can't be sorted or shuffled, so the
search narrows, and every step is exact (a step only drops what cannot be repeated, or settles what must be):

1. *Anchors.* Of the ``gram``-unit strings in a window the one with the smallest hash is its anchor. Equal windows have
   equal anchors at equal places. A text has about 2 / (window - gram + 2) anchors a unit; only their fingerprints are
   exchanged. Windows whose anchor occurs once in the corpus are done.
2. *Contexts.* The text that can hold windows of an anchor (window - 1 units to the left, window to the right) is hashed.
   Equal contexts settle all their windows at once; one of them, the first in the corpus, goes on for the rest.
3. *Windows.* What is left is hashed to 128 bits and sorted, one bucket at a time; or ``rest`` decides on it (relayout.llm.
   suffix_order ranks samples of a difference cover and sorts suffixes by them).

Exchanges carry packed arrays, one row for each task (or part) and bucket, in which a key stands once: a text that a
third of all documents share costs a row a task, and a bucket's size follows the number of buckets.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relayout.llm.shared import BLOCK, BYTE_ONE, BYTE_TWO, NO_ID, TWO, Rolling, blocks, discard, in_pieces, materialise, mix, parts, run_ends, sliding_min, trim, utf8, word_hashes, word_twins, words_in_documents

PLACE = np.uint64((1 << 30) - 1)
PART_BYTES = 1_000_000
FLUSH = 1_000_000
RECORD = np.dtype([("a", "<u8"), ("b", "<u8"), ("doc", "<i8"), ("p", "<i4"), ("n", "<i4")])
ASK = np.dtype([("f", "<u8"), ("rid", "<i8")])
REPLY = np.dtype([("a", "<u8"), ("b", "<u8"), ("first", "<u1")])


@dataclass(frozen=True)
class Search:
    """What to look for. later: only windows that also start earlier (else: anywhere else)."""

    words: bool
    window: int
    gram: int
    later: bool
    cover: int = 0  # a prime q: difference cover of q + 1 residues modulo q * q + q + 1


# ---- units --------------------------------------------------------------------------------------


@dataclass
class Block:
    """Texts (or stretches of long ones) as units: at[i] to at[i+1] is stretch i, of document doc[i] from unit base[i]
    on; it owns the anchors from own[i, 0] to own[i, 1]. byte_at: where units begin and end in the data."""

    one: np.ndarray
    two: np.ndarray
    at: np.ndarray
    doc: np.ndarray
    base: np.ndarray
    own: np.ndarray
    unit_start: np.ndarray | None
    unit_end: np.ndarray | None


def units(search: Search, data: np.ndarray, offsets: np.ndarray, both: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray | None, np.ndarray | None]:
    """Two independent hashes of each unit (of words the second only if both are asked for), where documents begin, and
    where words begin and end."""
    if not search.words:
        return BYTE_ONE[data], BYTE_TWO[data], offsets, None, None
    starts, ends, at = words_in_documents(data, offsets)
    one = in_pieces(word_hashes, data, starts, ends)
    return one, in_pieces(word_twins, data, starts, ends) if both else one, at, starts, ends


def read_blocks(search: Search, data: np.ndarray, offsets: np.ndarray) -> Iterator[Block]:
    margin = search.window
    for a, b in blocks(offsets):
        low, high = offsets[a], offsets[b]
        if b == a + 1 and high - low > 2 * BLOCK and not search.words:
            for s in range(low, high, BLOCK):
                f, t = max(low, s - margin), min(high, s + BLOCK + margin)
                part = data[f:t]
                own = np.array([[s - f, min(high, s + BLOCK) - f]])
                yield Block(BYTE_ONE[part], BYTE_TWO[part], np.array([0, t - f]), np.array([a]), np.array([f - low]), own, np.arange(f, t), None)
            continue
        one, two, at, starts, ends = units(search, data[low:high], offsets[a : b + 1] - low, both=False)
        own = np.stack([at[:-1], at[1:]], axis=1)
        if starts is None:
            starts, ends = low + np.arange(high - low), None
        else:
            starts, ends = starts + low, ends + low
        yield Block(one, two, at, np.arange(a, b), np.zeros(b - a, np.int64), own, starts, ends)


def anchors(search: Search, block: Block) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of each anchor: its stretch, its place, the first and last window that it stands for, and its hash."""
    n, w, none = len(block.one), search.window, np.zeros(0, np.int64)
    if n < w:
        return none, none, none, none, np.zeros(0, np.uint64)
    grams = Rolling(block.one).every(search.gram)
    smallest = sliding_min((grams & ~PLACE) | np.arange(len(grams), dtype=np.uint64), w - search.gram + 1)
    count = np.maximum(block.at[1:] - block.at[:-1] - w + 1, 0)
    stretch = np.repeat(np.arange(len(count)), count)
    starts = np.arange(len(stretch)) + np.repeat(block.at[:-1] - (np.cumsum(count) - count), count)
    place = (smallest[starts] & PLACE).astype(np.int64)
    new = np.ones(len(place), bool)
    new[1:] = place[1:] != place[:-1]
    begin = np.flatnonzero(new)
    p, lo, hi, s = place[begin], starts[begin], starts[run_ends(begin, len(place)) - 1] if len(place) else none, stretch[begin]
    mine = (p >= block.own[s, 0]) & (p < block.own[s, 1])
    p, lo, hi, s = p[mine], lo[mine], hi[mine], s[mine]
    return s, p, lo, hi, grams[p]


@lru_cache(8)
def difference_cover(q: int) -> tuple[np.ndarray, int]:
    """q + 1 residues modulo v = q * q + q + 1 whose differences are all residues, for a prime q.

    Singer's construction: the powers of a primitive element of the field of q ** 3 elements that lie in a plane."""
    v = q * q + q + 1
    for c0 in range(1, q):
        for c1 in range(q):
            for c2 in range(q):
                x, seen = (1, 0, 0), []
                for i in range(q**3 - 1):
                    if x[2] == 0 and i < v:
                        seen.append(i)
                    x = ((c0 * x[2]) % q, (x[0] + c1 * x[2]) % q, (x[1] + c2 * x[2]) % q)
                    if x == (1, 0, 0):
                        break
                if i == q**3 - 2 and len({(a - b) % v for a in seen for b in seen}) == v:
                    return np.array(seen), v
    raise ValueError(f"{q} is not a prime")


# ---- packed exchange ----------------------------------------------------------------------------


def bucket_of(keys: np.ndarray, n: int) -> np.ndarray:
    return ((keys >> np.uint64(32)) * np.uint64(n) >> np.uint64(32)).astype(np.int64)


def by_bucket(records: np.ndarray, n: int) -> Iterator[tuple[int, bytes]]:
    """records, sorted by key, cut at the buckets' borders."""
    bucket = bucket_of(records["a"], n)
    cut = np.flatnonzero(np.diff(bucket, prepend=-1, append=-2))
    for a, b in zip(cut[:-1], cut[1:], strict=True):
        yield int(bucket[a]), records[a:b].tobytes()


def pack(a: np.ndarray, b: np.ndarray, doc: np.ndarray, p: np.ndarray) -> np.ndarray:
    """A record for each key: its first place and how many."""
    out = np.empty(len(a), RECORD)
    out["a"], out["b"], out["doc"], out["p"], out["n"] = a, b, doc, p, 1
    out = out[np.lexsort((p, doc, b, a))]
    new = np.ones(len(out), bool)
    new[1:] = (out["a"][1:] != out["a"][:-1]) | (out["b"][1:] != out["b"][:-1])
    begin = np.flatnonzero(new)
    n = np.diff(np.append(begin, len(out)))
    out = out[begin]
    out["n"] = np.minimum(n, 2)
    return out


def repeated(frame: pd.DataFrame) -> pd.DataFrame:
    """One bucket: (part, body) rows of records in; for each part the repeated keys and whether it holds the first."""
    records = [np.frombuffer(x, RECORD) for x in frame["body"]]
    part = np.repeat(frame["part"].to_numpy(), [len(x) for x in records])
    r = np.concatenate(records)
    order = np.lexsort((part, r["p"], r["doc"], r["b"], r["a"]))
    r, part = r[order], part[order]
    new = np.ones(len(r), bool)
    new[1:] = (r["a"][1:] != r["a"][:-1]) | (r["b"][1:] != r["b"][:-1])
    begin = np.flatnonzero(new)
    total = np.add.reduceat(r["n"], begin) if len(begin) else np.zeros(0)
    keep = np.repeat(total >= 2, np.diff(np.append(begin, len(r))))
    out = np.empty(int(keep.sum()), REPLY)
    out["a"], out["b"], out["first"] = r["a"][keep], r["b"][keep], new[keep]
    return per_part(out, part[keep])


def per_part(out: np.ndarray, part: np.ndarray) -> pd.DataFrame:
    order = np.argsort(part, kind="stable")
    out, part = out[order], part[order]
    cut = np.flatnonzero(np.diff(part, prepend=part[0] - 1, append=part[-1] + 1)) if len(part) else np.zeros(1, np.int64)
    return pd.DataFrame({"part": part[cut[:-1]], "body": [out[a:b].tobytes() for a, b in zip(cut[:-1], cut[1:], strict=True)]})


def decide(replies: np.ndarray, a: np.ndarray, b: np.ndarray, doc: np.ndarray, p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of each occurrence in a part: its key is repeated; it is the first of the corpus."""
    repeated_, first = np.zeros(len(a), bool), np.zeros(len(a), bool)
    if not len(replies) or not len(a):
        return repeated_, first
    replies = replies[np.lexsort((1 - replies["first"], replies["b"], replies["a"]))]
    new = np.ones(len(replies), bool)
    new[1:] = (replies["a"][1:] != replies["a"][:-1]) | (replies["b"][1:] != replies["b"][:-1])
    replies = replies[new]  # of the answers to one key the one that says first
    at = np.searchsorted(replies["a"], a)
    near = np.flatnonzero(replies["a"][np.minimum(at, len(replies) - 1)] == a)
    k = at[near]
    while len(near):
        hit = replies["b"][k] == b[near]
        repeated_[near[hit]], first[near[hit]] = True, replies["first"][k[hit]] == 1
        near, k = near[~hit], k[~hit] + 1
        more = (k < len(replies)) & (replies["a"][np.minimum(k, len(replies) - 1)] == a[near])
        near, k = near[more], k[more]
    some = np.flatnonzero(first)
    some = some[np.lexsort((p[some], doc[some], b[some], a[some]))]
    again = np.zeros(len(some), bool)
    again[1:] = (a[some][1:] == a[some][:-1]) & (b[some][1:] == b[some][:-1])
    first[some[again]] = False
    return repeated_, first


# ---- steps --------------------------------------------------------------------------------------


def fingerprints(docs: DataFrame, search: Search, buckets: int) -> DataFrame:
    """(bucket, kind, body): anchors' fingerprints as (64 bits, rid). One that stands once in a task
    asks its bucket; of one that stands several times the bucket gets a single note, and its documents an echo, which
    goes to any bucket: they need no answer."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        size = 0
        for batch in batches:
            data, offsets = utf8(batch.column("text"))
            rids = batch.column("rid").to_numpy(zero_copy_only=False)
            for block in read_blocks(search, data, offsets):
                s, _, _, _, h = anchors(search, block)
                held.append((h, rids[block.doc[s]]))
                size += len(h)
                if size > FLUSH:
                    yield out(held)
                    held, size = [], 0
        if held:
            yield out(held)

    def out(held: list[tuple[np.ndarray, np.ndarray]]) -> pa.RecordBatch:
        h, rid = (np.concatenate(x) for x in zip(*held, strict=True))
        order = np.lexsort((rid, h))
        h, rid = h[order], rid[order]
        bucket = bucket_of(h, buckets)
        new = np.ones(len(h), bool)
        new[1:] = h[1:] != h[:-1]
        begin = np.flatnonzero(new)
        n = np.diff(np.append(begin, len(h)))
        once = np.repeat(n == 1, n)
        other = new.copy()  # first of its document and fingerprint
        other[1:] |= rid[1:] != rid[:-1]
        rows: list[tuple[int, int, bytes]] = []
        # kind 0: asks; 1: a note that it is repeated; 2: an echo
        for kind, pick in ((0, once), (1, new & ~once), (2, ~once & other)):
            b, x = bucket[pick], np.empty(int(pick.sum()), ASK)
            x["f"], x["rid"] = h[pick], rid[pick]
            if kind == 1:
                x["rid"] = 0
            cut = np.flatnonzero(np.diff(b, prepend=-1, append=-2))
            rows += [(int(b[i]), kind, x[i:j].tobytes()) for i, j in zip(cut[:-1], cut[1:], strict=True)]
        columns = list(zip(*rows, strict=True)) or [(), (), ()]
        return pa.RecordBatch.from_arrays([pa.array(columns[0], pa.int32()), pa.array(columns[1], pa.int32()), pa.array(columns[2], pa.binary())], ["bucket", "kind", "body"])

    return docs.select("rid", "text").mapInArrow(run, "bucket int, kind int, body binary")


def shared_fingerprints(asked: np.ndarray, noted: np.ndarray, known: np.ndarray | None = None) -> np.ndarray:
    """Of sorted asks those whose fingerprint stands elsewhere too: twice among the asks, in a note, or known."""
    f = asked["f"]
    twice = np.zeros(len(f), bool)
    same = f[1:] == f[:-1]
    twice[1:] |= same
    twice[:-1] |= same
    twice |= np.isin(f, noted["f"])
    if known is not None and len(known):
        twice |= np.isin(f, known)
    return asked[twice]


def answers(hit: np.ndarray) -> tuple[np.ndarray, list[bytes]]:
    """Hits by document: rids, and the fingerprints of each."""
    hit = hit[np.argsort(hit["rid"], kind="stable")]
    full = np.ascontiguousarray(hit["f"])
    cut = np.flatnonzero(np.diff(hit["rid"], prepend=0, append=0) | (np.arange(len(hit) + 1) == 0) | (np.arange(len(hit) + 1) == len(hit))) if len(hit) else np.zeros(1, np.int64)
    return hit["rid"][cut[:-1]], [full[a:b].tobytes() for a, b in zip(cut[:-1], cut[1:], strict=True)]


def ask_once(entries: DataFrame, buckets: int) -> DataFrame:
    """(rid, body): the repeated fingerprints of each document."""

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        kinds = {k: np.sort(np.concatenate([np.frombuffer(x, ASK) for x in frame["body"][frame["kind"] == k]] or [np.zeros(0, ASK)]), order="f", kind="stable") for k in (0, 1, 2)}
        hit = np.concatenate([shared_fingerprints(kinds[0], kinds[1]), kinds[2]])
        rids, bodies = answers(hit)
        return pd.DataFrame({"rid": rids, "body": bodies})

    return by_buckets(entries, buckets).applyInPandas(run, "rid long, body binary")


def pieces(docs: DataFrame, hits: DataFrame, search: Search) -> DataFrame:
    """(part, doc_id, rid, start, body, anchors): stretches of the documents with repeated anchors. anchors: triples of
    place, first and last window within the stretch. part: at most about PART_BYTES of one task's stretches."""
    per_doc = hits.groupBy("rid").agg(F.collect_list("body").alias("found"))
    joined = docs.join(per_doc, "rid")
    w = search.window

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, size = TaskContext.get().partitionId() << 32, 0
        for batch in batches:
            data, offsets = utf8(batch.column("text"))
            ids, rids, found = (batch.column(c) for c in ("doc_id", "rid", "found"))
            known = [np.frombuffer(b"".join(x), "<u8") for x in found.to_pylist()]
            rows: list[tuple[int, int, int, int, bytes, bytes]] = []
            for block in read_blocks(search, data, offsets):
                s, p, lo, hi, h = anchors(search, block)
                cut = np.searchsorted(s, np.arange(len(block.doc) + 1))
                keep = np.zeros(len(s), bool)
                for i, d in enumerate(block.doc):
                    keep[cut[i] : cut[i + 1]] = np.isin(h[cut[i] : cut[i + 1]], known[d])
                s, p, lo, hi = s[keep], p[keep], lo[keep], hi[keep]
                c0, c1 = np.maximum(p - w + 1, block.at[s]), np.minimum(p + w, block.at[s + 1])
                apart = np.ones(len(s), bool)
                apart[1:] = (s[1:] != s[:-1]) | (c0[1:] > c1[:-1])
                begin = np.flatnonzero(apart)
                for i, j in zip(begin, run_ends(begin, len(s)), strict=True):
                    f, t, d = int(c0[i]), int(c1[j - 1]), block.doc[s[i]]
                    f_byte = int(block.unit_start[f])
                    t_byte = int(block.unit_start[t - 1]) + 1 if block.unit_end is None else int(block.unit_end[t - 1])
                    triples = np.stack([p[i:j], lo[i:j], hi[i:j]], axis=1) - f
                    rows.append((part, ids[int(d)].as_py(), rids[int(d)].as_py(), int(block.base[s[i]] + f - block.at[s[i]]), data[f_byte:t_byte].tobytes(), triples.astype("<i4").tobytes()))
                    size += t_byte - f_byte
                    if size > PART_BYTES:
                        part, size = part + 1, 0
            if rows:
                columns = zip(*rows, strict=True)
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], ["part", "doc_id", "rid", "start", "body", "ranges"])

    return joined.select("doc_id", "rid", "text", "found").mapInArrow(run, "part long, doc_id long, rid long, start long, body binary, ranges binary")


@dataclass
class Stretches:
    """Stretches of one part, or batch, end to end."""

    doc: np.ndarray
    rid: np.ndarray
    start: np.ndarray
    at: np.ndarray
    one: np.ndarray
    two: np.ndarray
    ranges: np.ndarray
    of: np.ndarray  # stretch of each range
    part: np.ndarray
    data: np.ndarray
    byte_from: np.ndarray
    byte_to: np.ndarray

    @classmethod
    def read(cls, search: Search, table: pa.Table | pa.RecordBatch, width: int) -> Stretches:
        data, offsets = utf8(table.column("body"))
        one, two, at, starts, ends = units(search, data, offsets)
        if starts is None:
            starts = np.arange(len(data))
            ends = starts + 1
        flat, cut = utf8(table.column("ranges"))
        ranges = np.frombuffer(flat.tobytes(), "<i4").reshape(-1, width).astype(np.int64)
        of = np.repeat(np.arange(len(cut) - 1), np.diff(cut) // (4 * width))
        column = lambda c: np.asarray(table.column(c).to_numpy(zero_copy_only=False) if isinstance(table, pa.RecordBatch) else table.column(c).to_numpy())
        return cls(column("doc_id"), column("rid"), column("start"), at, one, two, ranges, of, column("part"), data, starts, ends)


def contexts(search: Search, x: Stretches) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """128 bits, document and place of the context of each anchor."""
    w, p = search.window, x.ranges[:, 0] + x.at[x.of]
    f, t = np.maximum(p - w + 1, x.at[x.of]), np.minimum(p + w, x.at[x.of + 1])
    left = mix((p - f).astype(np.uint64))
    return Rolling(x.one).of(f, t) ^ left, Rolling(x.two, TWO).of(f, t), x.doc[x.of], x.ranges[:, 0] + x.start[x.of]


def entries_of(part: np.ndarray, a: np.ndarray, b: np.ndarray, doc: np.ndarray, p: np.ndarray, buckets: int) -> pa.RecordBatch:
    rows: list[tuple[int, int, bytes]] = []
    for k in np.unique(part):
        own = part == k
        rows += [(bucket, int(k), body) for bucket, body in by_bucket(pack(a[own], b[own], doc[own], p[own]), buckets)]
    columns = list(zip(*rows, strict=True)) or [(), (), ()]
    return pa.RecordBatch.from_arrays([pa.array(columns[0], pa.int32()), pa.array(columns[1], pa.int64()), pa.array(columns[2], pa.binary())], ["bucket", "part", "body"])


ENTRY = "bucket int, part long, body binary"


def _each(frame: DataFrame, search: Search, width: int, what: Callable[[Stretches], pa.RecordBatch], schema: str) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            _, offsets = utf8(batch.column("body"))
            for a, b in blocks(offsets):
                yield what(Stretches.read(search, batch.slice(a, b - a), width))

    return frame.mapInArrow(run, schema)


def _with_replies(frame: DataFrame, replies: DataFrame, run: Callable[[pa.Table, np.ndarray], Iterator[pa.Table]], schema: str, kind: np.dtype = REPLY) -> DataFrame:
    """Each part with the answers to it."""

    def both(left: pa.Table, right: pa.Table) -> pa.Table:
        got = np.frombuffer(b"".join(right.column("body").to_pylist()), kind)
        out = pa.concat_tables([out_schema(schema).empty_table(), *run(left, got)])
        trim()
        return out

    return frame.groupBy("part").cogroup(replies.groupBy("part")).applyInArrow(both, schema)


def out_schema(schema: str) -> pa.Schema:
    kinds = {"long": pa.int64(), "int": pa.int32(), "binary": pa.binary()}
    return pa.schema([(c.split()[0], kinds[c.split()[1]]) for c in schema.split(", ")])


STRETCH = "kind int, part long, doc_id long, rid long, start long, body binary, ranges binary"


def settle(search: Search, found: DataFrame, replies: DataFrame) -> DataFrame:
    """Kind 0: settled ranges of units (ranges, from and to, 8 bytes each); kind 1: stretches with open windows."""
    w = search.window

    def run(left: pa.Table, got: np.ndarray) -> Iterator[pa.Table]:
        if not left.num_rows:
            return
        x = Stretches.read(search, left.combine_chunks(), 3)
        a, b, doc, p = contexts(search, x)
        same, first = decide(got, a, b, doc, p)
        sure = same & ~first if search.later else same
        yield spans_table(x, x.of[sure], x.ranges[sure, 1] + x.start[x.of[sure]], x.ranges[sure, 2] + x.start[x.of[sure]] + w, STRETCH)
        live = np.flatnonzero(~same | first)
        s, lo, hi = x.of[live], x.ranges[live, 1], x.ranges[live, 2]
        apart = np.ones(len(live), bool)
        apart[1:] = (s[1:] != s[:-1]) | (lo[1:] > hi[:-1] + w)
        begin = np.flatnonzero(apart)
        rows = []
        for i, j in zip(begin, run_ends(begin, len(live)), strict=True):
            k, f, t = s[i], int(lo[i]), int(hi[j - 1]) + w
            here = x.at[k]
            body = x.data[x.byte_from[here + f] : x.byte_to[here + t - 1]].tobytes()
            rows.append((1, int(x.part[k]), int(x.doc[k]), int(x.rid[k]), int(x.start[k]) + f, body, (np.stack([lo[i:j], hi[i:j]], axis=1) - f).astype("<i4").tobytes()))
        if rows:
            yield pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), out_schema(STRETCH), strict=True)], schema=out_schema(STRETCH))

    return _with_replies(found, replies, run, STRETCH)


def spans_table(x: Stretches, of: np.ndarray, f: np.ndarray, t: np.ndarray, schema: str) -> pa.Table:
    """Ranges by document, joined where they touch."""
    rows = []
    order = np.lexsort((f, x.rid[of], x.doc[of]))
    of, f, t = of[order], f[order], t[order]
    doc, rid = x.doc[of], x.rid[of]
    new = np.ones(len(of), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (rid[1:] != rid[:-1])
    begin = np.flatnonzero(new)
    for i, j in zip(begin, run_ends(begin, len(of)), strict=True):
        rows.append((0, int(x.part[of[i]]), int(doc[i]), int(rid[i]), 0, None, joined(f[i:j], t[i:j]).astype("<i8").tobytes()))
    columns = list(zip(*rows, strict=True)) or [()] * 7
    kinds = out_schema(schema)
    return pa.Table.from_arrays([pa.array(c, k.type) for c, k in zip(columns, kinds, strict=True)], schema=kinds)


def joined(f: np.ndarray, t: np.ndarray) -> np.ndarray:
    """Sorted ranges, as rows (from, to), with those that touch made one."""
    if not len(f):
        return np.zeros((0, 2), np.int64)
    order = np.argsort(f, kind="stable")
    f, reach = f[order], np.maximum.accumulate(t[order])
    gap = np.flatnonzero(f[1:] > reach[:-1]) + 1
    return np.stack([f[np.append(0, gap)], reach[np.append(gap, len(f)) - 1]], axis=1)


def open_windows(x: Stretches) -> tuple[np.ndarray, np.ndarray]:
    """Places (end to end) and stretches of the open windows."""
    n = x.ranges[:, 1] - x.ranges[:, 0] + 1
    of = np.repeat(x.of, n)
    places = np.arange(len(of)) + np.repeat(x.ranges[:, 0] + x.at[x.of] - (np.cumsum(n) - n), n)
    return places, of


def window_hashes(search: Search, x: Stretches, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return Rolling(x.one).of(at, at + search.window), Rolling(x.two, TWO).of(at, at + search.window)


def samples(search: Search, x: Stretches) -> tuple[np.ndarray, np.ndarray]:
    """Places of the cover samples among the first v places of open windows, and their ranks' names."""
    residues, v = difference_cover(search.cover)
    in_cover = np.zeros(v, bool)
    in_cover[residues] = True
    size = search.window - v + 1
    n = len(x.one)
    marks = np.zeros(n + 1, np.int64)
    f, t = x.ranges[:, 0] + x.at[x.of], np.minimum(x.ranges[:, 1] + v, x.at[x.of + 1] - x.at[x.of] - size + 1) + x.at[x.of]
    np.add.at(marks, f, 1)
    np.add.at(marks, t, -1)
    near = np.flatnonzero(np.cumsum(marks[:-1]) > 0)
    of = np.searchsorted(x.at, near, "right") - 1
    near = near[in_cover[(near - x.at[of] + x.start[of]) % v]]
    return near, Rolling(x.one).of(near, near + size)


def repeated_samples(frame: pd.DataFrame) -> pd.DataFrame:
    """One bucket of sample names, each once in a part with 1 or 2 (for more) behind: the repeated ones by part."""
    kind = np.dtype([("a", "<u8"), ("n", "<u1")])
    rows = [np.frombuffer(x, kind) for x in frame["body"]]
    part = np.repeat(frame["part"].to_numpy(), [len(x) for x in rows])
    r = np.concatenate(rows)
    order = np.argsort(r["a"], kind="stable")
    r, part = r[order], part[order]
    begin = np.flatnonzero(np.diff(r["a"], prepend=~r["a"][:1]) != 0)
    total = np.add.reduceat(r["n"].astype(np.int64), begin)
    keep = np.repeat(total >= 2, np.diff(np.append(begin, len(r))))
    return per_part(r["a"][keep].astype("<u8"), part[keep])


def sample_entries(search: Search, x: Stretches, buckets: int) -> pa.RecordBatch:
    near, name = samples(search, x)
    part = x.part[np.searchsorted(x.at, near, "right") - 1]
    rows: list[tuple[int, int, bytes]] = []
    for k in np.unique(part):
        a, n = np.unique(name[part == k], return_counts=True)
        out = np.empty(len(a), np.dtype([("a", "<u8"), ("n", "<u1")]))
        out["a"], out["n"] = a, np.minimum(n, 2)
        rows += [(bucket, int(k), body) for bucket, body in by_bucket(out, buckets)]
    columns = list(zip(*rows, strict=True)) or [(), (), ()]
    return pa.RecordBatch.from_arrays([pa.array(columns[0], pa.int32()), pa.array(columns[1], pa.int64()), pa.array(columns[2], pa.binary())], ["bucket", "part", "body"])


#: About how many bytes of records one bucket holds; a task sorts one bucket at a time.
BUCKET_BYTES = 16_000_000


def buckets_for(total: int | None, least: int) -> int:
    """How many buckets so many bytes of records need: they grow with the data, and no bucket does."""
    return max(least, -(-(total or 0) // BUCKET_BYTES))


def by_buckets(entries: DataFrame, n: int):  # noqa: ANN201
    """entries grouped by bucket, over as many partitions as there are buckets."""
    return entries.repartition(n, "bucket").groupBy("bucket")


def find(docs: DataFrame, hits: DataFrame, search: Search, buckets: int, spent: tuple[DataFrame, ...] = (), rest: Callable[[DataFrame, Search, int], DataFrame] | None = None) -> DataFrame:
    """(doc_id, rid, found): ranges of units under repeated windows, each a binary of (from, to), 8 bytes each.

    docs: (doc_id, rid, text) as keyed() gives it; hits: (rid, body), the repeated fingerprints of each document; spent:
    written tables that only hits needs; rest: what decides on the windows that contexts leave open (else: their hashes)."""
    found = materialise(pieces(docs, hits, search), "pieces")
    discard(*spent)

    n_contexts = buckets_for((found.agg(F.sum(F.octet_length("ranges"))).first()[0] or 0) // 12 * RECORD.itemsize, buckets)

    def of_contexts(x: Stretches) -> pa.RecordBatch:
        return entries_of(x.part[x.of], *contexts(search, x), n_contexts)

    replies = by_buckets(_each(found, search, 3, of_contexts, ENTRY), n_contexts).applyInPandas(repeated, "part long, body binary")
    settled = materialise(settle(search, found, replies), "settled")
    discard(found)
    open_ = settled.filter("kind = 1").drop("kind")
    if rest:
        return _together(settled, rest(open_, search, buckets))
    # a window begins at each byte, or at each word: words have a few bytes
    n_windows = buckets_for((open_.agg(F.sum(F.octet_length("body"))).first()[0] or 0) * RECORD.itemsize // (4 if search.words else 1), buckets)

    def all_windows(x: Stretches) -> pa.RecordBatch:
        at, of = open_windows(x)
        return entries_of(x.part[of], *window_hashes(search, x, at), x.doc[of], at - x.at[of] + x.start[of], n_windows)

    entries = _each(open_, search, 2, all_windows, ENTRY)
    same = by_buckets(entries, n_windows).applyInPandas(repeated, "part long, body binary")

    def final(left: pa.Table, got: np.ndarray) -> Iterator[pa.Table]:
        if not left.num_rows or not len(got):
            return
        x = Stretches.read(search, left.combine_chunks(), 2)
        at, of = open_windows(x)
        a, b = window_hashes(search, x, at)
        p = at - x.at[of] + x.start[of]
        again, first = decide(got, a, b, x.doc[of], p)
        sure = again & ~first if search.later else again
        yield spans_table(x, of[sure], p[sure], p[sure] + search.window, STRETCH)

    return _together(settled, _with_replies(open_, same, final, STRETCH))


def _together(settled: DataFrame, last: DataFrame) -> DataFrame:
    """By document what was settled early and last."""
    both = settled.filter("kind = 0").select("doc_id", "rid", "ranges").union(last.select("doc_id", "rid", "ranges"))
    both = materialise(both, "ranges")
    discard(settled)
    return both.groupBy("doc_id", "rid").agg(F.collect_list("ranges").alias("found"))


def with_ranges(docs: DataFrame, found: DataFrame) -> DataFrame:
    """docs (doc_id, rid, ...) with found, null where nothing is repeated."""
    return docs.join(found, ["doc_id", "rid"], "left")


def ranges_of(found: list[bytes] | None) -> np.ndarray:
    if not found:
        return np.zeros((0, 2), np.int64)
    both = np.frombuffer(b"".join(found), "<i8").reshape(-1, 2)
    return joined(both[:, 0], both[:, 1])


def unnull(column: str) -> F.Column:
    return F.when(F.col(column) == NO_ID, None).otherwise(F.col(column)).alias(column)


def default_buckets(docs: DataFrame) -> int:
    return parts(docs.sparkSession)

