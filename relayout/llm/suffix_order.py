"""Order of suffixes over a difference cover, block by block: which windows of a text stand elsewhere too.

Cover samples are the places whose index modulo v is in a difference cover; any two windows have a sample at the same
offset below v. Sorting every suffix of a text by its first ``window`` bytes would need that many bytes for each. Instead

1. samples whose next bytes occur once (by a hash: it only drops) are done;
2. the others are ranked: first by their next v bytes, then by pairs of ranks (the sample's, and that of the sample a number
   of blocks further on, which has the same residue), so depths grow from one block to ``depth`` blocks in a few rounds;
3. one bucket of ranks at a time is sorted by rank, which settles the long tie, and by the bytes left and right of it,
   at most v - 1 and window - v * depth of them. Repeated windows are read off neighbours: how far the sorted bytes agree.

Ranks compare bytes, not hashes, so equal ranks are equal text. A bucket is chosen by a hash of the key: ranks order texts
by bucket, then by bytes, and that is one order for all. A part of the text sends each key once, whatever its copies, and
gets the answers in the order it sent the keys in.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relayout.llm.repeats import ENTRY, Search, Stretches, _each, _with_replies, bucket_of, buckets_for, by_buckets, difference_cover, joined, out_schema, repeated_samples, run_ends, sample_entries, samples
from relayout.llm.shared import discard, materialise, mix, trim

HEAD = np.dtype([("doc", "<i8"), ("rid", "<i8"), ("start", "<i8"), ("at", "<i8")])
LIVE = "part long, heads binary, body binary, targets binary, ranks binary"
FOUND = "doc_id long, rid long, ranges binary"


@dataclass(frozen=True)
class Shape:
    """A window is at most v - 1 bytes left of a sample, depth blocks of v bytes from it on, and the rest to the right."""

    window: int
    v: int
    depth: int

    @classmethod
    def of(cls, search: Search) -> Shape:
        v = difference_cover(search.cover)[1]
        depth = (search.window - v + 1) // v
        if v > 64 or depth < 1 or search.words or search.later:
            raise ValueError("needs a cover of at most 64 residues, and windows of bytes of at least twice that less one, anywhere")
        return cls(search.window, v, depth)

    @property
    def rest(self) -> int:
        return self.window - self.v * self.depth

    def rounds(self) -> list[int]:
        """Of each round of ranks after the first by how many blocks the second of a pair lies behind the first."""
        out, have = [], 1
        while have < self.depth:
            out.append(min(have, self.depth - have))
            have += out[-1]
        return out


@dataclass
class Chunk:
    """The text around the samples of one part: heads say of which document and from which byte on it is."""

    part: int
    heads: np.ndarray
    body: np.ndarray
    targets: np.ndarray
    ranks: np.ndarray

    def places(self, shape: Shape) -> np.ndarray:
        """The samples, and those that lie whole blocks behind them within their depth."""
        return np.unique(self.targets[:, None] + shape.v * np.arange(shape.depth))

    def row(self) -> tuple[int, bytes, bytes, bytes, bytes]:
        return self.part, self.heads.tobytes(), self.body.tobytes(), self.targets.astype("<i8").tobytes(), self.ranks.astype("<u8").tobytes()


def chunks(table: pa.RecordBatch | pa.Table) -> Iterator[Chunk]:
    for r in table.to_pylist():
        yield Chunk(r["part"], np.frombuffer(r["heads"], HEAD), np.frombuffer(r["body"], np.uint8), np.frombuffer(r["targets"], "<i8"), np.frombuffer(r["ranks"], "<u8"))


def table_of(rows: list[tuple], schema: str) -> pa.Table:
    kinds = out_schema(schema)
    columns = list(zip(*rows, strict=True)) or [()] * len(kinds)
    return pa.Table.from_arrays([pa.array(c, k.type) for c, k in zip(columns, kinds, strict=True)], schema=kinds)


def cut_out(search: Search, shape: Shape, x: Stretches, shared: np.ndarray) -> Chunk | None:
    """The samples of one part with a shared name, and the text that their windows can hold."""
    near, name = samples(search, x)
    hit = near[np.isin(name, shared)]
    if not len(hit):
        return None
    of = np.searchsorted(x.at, hit, "right") - 1
    f, t = np.maximum(hit - shape.v + 1, x.at[of]), np.minimum(hit + shape.window, x.at[of + 1])
    apart = np.ones(len(hit), bool)
    apart[1:] = (of[1:] != of[:-1]) | (f[1:] > t[:-1])
    begin = np.flatnonzero(apart)
    first, last, which = f[begin], t[run_ends(begin, len(hit)) - 1], np.cumsum(apart) - 1
    heads = np.empty(len(begin), HEAD)
    heads["doc"], heads["rid"], heads["start"] = x.doc[of[begin]], x.rid[of[begin]], x.start[of[begin]] + first - x.at[of[begin]]
    heads["at"] = np.cumsum(last - first) - (last - first)
    body = np.concatenate([x.data[a:b] for a, b in zip(first, last, strict=True)])
    return Chunk(int(x.part[0]), heads, body, hit - first[which] + heads["at"][which], np.zeros(0, np.uint64))


# ---- keys and their exchange --------------------------------------------------------------------


def hashed(rows: np.ndarray) -> np.ndarray:
    words = np.zeros((len(rows), -(-rows.shape[1] // 8) * 8), np.uint8)
    words[:, : rows.shape[1]] = rows
    out = np.full(len(rows), rows.shape[1], np.uint64)
    for column in words.view("<u8").T:
        out = mix(out ^ column) + np.uint64(0x9E3779B97F4A7C15)
    return mix(out)


def distinct_rows(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows of bytes in their order, each once; where each of the given stands there; how many of each."""
    width = rows.shape[1]
    found, at, n = np.unique(np.ascontiguousarray(rows).view(f"V{width}").ravel(), return_inverse=True, return_counts=True)
    return found.view(np.uint8).reshape(-1, width), at.ravel(), n


def dealt(rows: np.ndarray, n: int, lead: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Distinct rows by bucket (a hash of their first ``lead`` bytes), where each row went, how many of each, and buckets."""
    found, at, count = distinct_rows(rows)
    bucket = bucket_of(hashed(found[:, :lead]), n)
    order = np.argsort(bucket, kind="stable")
    where = np.empty(len(order), np.int64)
    where[order] = np.arange(len(order))
    return found[order], where[at], count[order], bucket[order]


def blocks_of(shape: Shape, chunk: Chunk) -> np.ndarray:
    return chunk.body[chunk.places(shape)[:, None] + np.arange(shape.v)]


def pairs_of(shape: Shape, chunk: Chunk, behind: int) -> tuple[np.ndarray, np.ndarray]:
    """Places (by number) that have another so many blocks behind them, and both ranks as a key."""
    places = chunk.places(shape)
    other = np.searchsorted(places, places + behind * shape.v)
    some = np.flatnonzero(places[np.minimum(other, len(places) - 1)] == places + behind * shape.v)
    both = np.stack([chunk.ranks[some], chunk.ranks[other[some]]], axis=1)
    return some, both.astype(">u8").view(np.uint8).reshape(len(some), 16)


def suffixes_of(shape: Shape, chunk: Chunk) -> np.ndarray:
    """Of each sample its rank, the bytes to the left (nearest first) and behind its depth, and how many there are."""
    t, places = chunk.targets, chunk.places(shape)
    at = np.append(chunk.heads["at"], len(chunk.body))
    head = np.searchsorted(chunk.heads["at"], t, "right") - 1
    deep = t + shape.v * shape.depth
    n_left, n_right = np.minimum(t - at[head], shape.v - 1), np.minimum(at[head + 1] - deep, shape.rest)
    rank = chunk.ranks[np.searchsorted(places, t)].astype(">u8").view(np.uint8).reshape(-1, 8)
    k, m = np.arange(shape.v - 1), np.arange(shape.rest)
    left = np.where(k < n_left[:, None], chunk.body[np.maximum(t[:, None] - 1 - k, 0)], 0)
    right = np.where(m < n_right[:, None], chunk.body[np.minimum(deep[:, None] + m, len(chunk.body) - 1)], 0)
    return np.concatenate([rank, left, right, n_left[:, None], n_right[:, None]], axis=1).astype(np.uint8)


def ranked(width: int) -> Callable[[tuple, pd.DataFrame], pd.DataFrame]:
    """One bucket of keys: their ranks."""

    def run(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        rows = np.frombuffer(b"".join(frame["body"]), np.uint8).reshape(-1, width)
        _, at, _ = distinct_rows(rows)
        return replied(key, frame, width, (np.uint64(int(key[0]) << 32) | at.astype(np.uint64)))

    return run


def replied(key: tuple, frame: pd.DataFrame, width: int, values: np.ndarray) -> pd.DataFrame:
    cut = np.append(0, np.cumsum([len(x) // width for x in frame["body"]]))
    trim()
    return pd.DataFrame({"part": frame["part"], "bucket": int(key[0]), "body": [values[a:b].astype("<u8").tobytes() for a, b in zip(cut[:-1], cut[1:], strict=True)]})


def agreement(rows: np.ndarray) -> np.ndarray:
    """Of rows of bytes, with which one each agrees for how long: sorted order, and the bytes shared with the row before."""
    same = rows[1:] == rows[:-1]
    return np.append(0, np.where(same.all(axis=1), rows.shape[1], np.argmin(same, axis=1)) if len(rows) else []).astype(np.int64)[: len(rows)]


def shared_offsets(shape: Shape, rows: np.ndarray, count: np.ndarray) -> np.ndarray:
    """Of each suffix (suffixes_of's rows, distinct, with how often it stands) the offsets, as bits, at which the window
    around its sample stands elsewhere too.

    Two windows with samples of equal rank at offset k are equal if k bytes to the left and rest - k to the right are."""
    left, right = rows[:, 8 : 7 + shape.v], rows[:, 7 + shape.v : -2]
    n_left, n_right = rows[:, -2].astype(np.int64), rows[:, -1].astype(np.int64)
    k = np.arange(shape.v)
    there = (n_left[:, None] >= k) & (n_right[:, None] >= shape.rest - k)
    out = there & (count >= 2)[:, None]
    rank = rows[:, :8].copy().view(">u8").ravel().astype(np.uint64)
    edge = np.flatnonzero(np.diff(rank, prepend=~rank[:1], append=~rank[-1:]) != 0)
    some = np.flatnonzero(np.repeat(np.diff(edge) > 1, np.diff(edge)))  # rows are sorted by rank
    if len(some):
        group = rank[some]
        classes = []
        for side in (left[some], right[some]):
            keyed = np.concatenate([group.astype(">u8").view(np.uint8).reshape(-1, 8), side], axis=1)
            order = np.argsort(np.ascontiguousarray(keyed).view(f"V{keyed.shape[1]}").ravel(), kind="stable")
            classes.append((order, agreement(keyed[order]) - 8))
        for x in range(shape.v):
            ok = there[some, x]
            name = np.zeros(len(some), np.uint64)
            for (order, agrees), need in zip(classes, (x, shape.rest - x), strict=True):
                own = np.empty(len(order), np.uint64)
                own[order] = np.cumsum(agrees < need).astype(np.uint64)
                name = (name << np.uint64(32)) | own
            mine = np.flatnonzero(ok)
            order = mine[np.argsort(name[mine], kind="stable")]
            same = name[order[1:]] == name[order[:-1]]
            out[some[order[1:][same]], x] = True
            out[some[order[:-1][same]], x] = True
    return (out.astype(np.uint64) << k.astype(np.uint64)).sum(axis=1, dtype=np.uint64)


def looked_up(shape: Shape) -> Callable[[tuple, pd.DataFrame], pd.DataFrame]:
    """One bucket of suffixes (rows end with a count): offsets of repeated windows."""
    width = 8 + shape.v - 1 + shape.rest + 2

    def run(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        rows = np.frombuffer(b"".join(frame["body"]), np.uint8).reshape(-1, width + 1)
        found, at, _ = distinct_rows(rows[:, :width])
        count = np.bincount(at, rows[:, width], len(found))
        return replied(key, frame, width + 1, shared_offsets(shape, found, count)[at])

    return run


def ask(live: DataFrame, keys: Callable[[Chunk], np.ndarray], n: int, lead: int, answer: Callable[[tuple, pd.DataFrame], pd.DataFrame], counted: bool = False) -> DataFrame:
    """(part, bucket, body): the answers to the distinct keys of each part, in their order in dealt()."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for chunk in chunks(batch):
                rows, _, count, bucket = dealt(keys(chunk), n, lead)
                if counted:
                    rows = np.concatenate([rows, np.minimum(count, 2).astype(np.uint8)[:, None]], axis=1)
                cut = np.flatnonzero(np.diff(bucket, prepend=-1, append=-2))
                yield from table_of([(int(bucket[a]), chunk.part, rows[a:b].tobytes()) for a, b in zip(cut[:-1], cut[1:], strict=True)], ENTRY).to_batches()
                trim()

    return by_buckets(live.mapInArrow(run, ENTRY), n).applyInPandas(answer, "part long, bucket int, body binary")


def told(live: DataFrame, replies: DataFrame, keys: Callable[[Chunk], np.ndarray], n: int, lead: int, what: Callable[[Chunk, np.ndarray], list[tuple]], schema: str) -> DataFrame:
    """Each part with the answer to each of its keys."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        rows: list[tuple] = []
        got = np.frombuffer(b"".join(right.sort_by("bucket").column("body").to_pylist()), "<u8") if right.num_rows else np.zeros(0, np.uint64)
        for chunk in chunks(left):
            rows += what(chunk, got[dealt(keys(chunk), n, lead)[1]])
        trim()
        return table_of(rows, schema)

    return live.groupBy("part").cogroup(replies.groupBy("part")).applyInArrow(run, schema)


# ---- the search ---------------------------------------------------------------------------------


def repeated_windows(open_: DataFrame, search: Search, buckets: int) -> DataFrame:
    """(doc_id, rid, ranges): byte ranges under repeated windows. open_: stretches (part, doc_id, rid, start, body, ranges)
    with the windows that may be."""
    shape = Shape.of(search)
    names = buckets_for((open_.agg(F.sum(F.octet_length("body"))).first()[0] or 0) * 9 * (search.cover + 1) // shape.v, buckets)
    shared = by_buckets(_each(open_, search, 2, lambda x: sample_entries(search, x, names), ENTRY), names).applyInPandas(repeated_samples, "part long, body binary")

    def alive(left: pa.Table, got: np.ndarray) -> Iterator[pa.Table]:
        if left.num_rows and len(got) and (chunk := cut_out(search, shape, Stretches.read(search, left.combine_chunks(), 2), got)):
            yield table_of([chunk.row()], LIVE)

    live = materialise(_with_replies(open_, shared, alive, LIVE, np.dtype("<u8")), "live")
    total = (live.agg(F.sum(F.octet_length("targets"))).first()[0] or 0) // 8

    n = buckets_for(total * shape.v, buckets)
    first = lambda chunk: blocks_of(shape, chunk)
    live = _renewed(live, told(live, ask(live, first, n, shape.v, ranked(shape.v)), first, n, shape.v, _with_ranks, LIVE))
    for behind in shape.rounds():
        m = buckets_for(total * 16, buckets)
        keys = lambda chunk, behind=behind: pairs_of(shape, chunk, behind)[1]

        def deeper(chunk: Chunk, got: np.ndarray, behind: int = behind) -> list[tuple]:
            ranks = np.zeros(len(chunk.ranks), np.uint64)
            ranks[pairs_of(shape, chunk, behind)[0]] = got
            return _with_ranks(chunk, ranks)

        live = _renewed(live, told(live, ask(live, keys, m, 16, ranked(16)), keys, m, 16, deeper, LIVE))

    last = buckets_for(total * (shape.v + shape.rest + 10), buckets)
    suffixes = lambda chunk: suffixes_of(shape, chunk)

    def ranges(chunk: Chunk, got: np.ndarray) -> list[tuple]:
        sample, offset = np.nonzero((got[:, None] >> np.arange(shape.v, dtype=np.uint64)) & np.uint64(1))
        at = chunk.targets[sample]
        head = np.searchsorted(chunk.heads["at"], at, "right") - 1
        start = chunk.heads["start"][head] + at - chunk.heads["at"][head] - offset
        order = np.argsort(head, kind="stable")
        head, start = head[order], start[order]
        cut = np.flatnonzero(np.diff(head, prepend=-1, append=-2))
        heads = [chunk.heads[head[a]] for a in cut[:-1]]
        return [(int(h["doc"]), int(h["rid"]), joined(start[a:b], start[a:b] + shape.window).astype("<i8").tobytes()) for h, a, b in zip(heads, cut[:-1], cut[1:], strict=True)]

    found = materialise(told(live, ask(live, suffixes, last, 8, looked_up(shape), counted=True), suffixes, last, 8, ranges, FOUND), "found")
    discard(live)
    return found


def _with_ranks(chunk: Chunk, ranks: np.ndarray) -> list[tuple]:
    return [Chunk(chunk.part, chunk.heads, chunk.body, chunk.targets, ranks).row()]


def _renewed(old: DataFrame, new: DataFrame) -> DataFrame:
    out = materialise(new, "ranks")
    discard(old)
    return out
