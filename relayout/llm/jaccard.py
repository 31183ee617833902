"""Exact n-gram Jaccard join by vertical partitioning.

A document is its set of distinct word n-grams; two link at a similarity of ``num`` / ``den`` or more. Documents with the
same set are one class and are compared once.

1. *Who can link at all.* A partner holds all but n - ceil(t n) of a set's n grams, so of any part of the set nearly all.
   Each class shows the bucket of a gram a part of its set (those with the smallest hashes: a little more than what a
   partner may lack); a class of which too few of these stand elsewhere too is done. This drops nearly all documents,
   and also those that only share boilerplate.
2. *Global order.* Over the classes left, all grams are counted, and ordered from rare to frequent (by powers of two, then
   by hash). Classes that share a gram in their prefixes (the first n - ceil(t n) + 1) may link; the groups of this graph
   are found by relayout.llm.components. Frequent grams come last, so boilerplate doesn't tie groups together.
3. *Vertical partitioning.* The order is cut into fragments of about equal weight. A fragment of a group is a task of its own: it
   counts the partial overlaps of the pairs by a product of two incidence matrices. The partial counts are shuffled by pair
   of blocks, and summed there to the overlap of each pair, which decides. Only the links of a spanning forest and each
   class's number of links leave that step, never all pairs.
4. *Large groups.* A group larger than a block first gets representatives: the member whose grams are the most frequent, and
   all within half of the allowed distance of it are its ball. Jaccard distance is a metric, so all in a ball are linked
   and need no comparison; only blocks of different balls, and of members in none, are compared. A large group of near
   copies of one text costs a pass, not its square.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relayout.llm.components import components
from relayout.llm.repeats import bucket_of, per_part, unnull
from relayout.llm.shared import TWO, Rolling, blocks, discard, in_pieces, keyed, lowered, materialise, mix, parts, table, trim, utf8, word_hashes, word_twins, words_in_documents

GRAM, NUM, DEN = 5, 80, 100
FLUSH, PART_GRAMS, GROUP_BLOCK, COLUMNS = 1_000_000, 250_000, 512, 2048
#: Fragments of the global order; rounds of representatives of a large group; grams that share a task of small groups.
FRAGMENTS, ROUNDS, TASK_GRAMS = 8, 4, 4_000_000
ASK = np.dtype([("f", "<u8"), ("c", "<u8")])
PAIR = np.dtype([("u", "<i8"), ("v", "<i8"), ("n", "<i8")])
SEEN = np.dtype([("a", "<u8"), ("n", "<u4")])


def missing(n: np.ndarray, num: int = NUM, den: int = DEN) -> np.ndarray:
    """How many of its n grams a set's partner may lack: the overlap is at least t times the union, so t n."""
    return n - -(-num * n // den)


def gram_sets(column: pa.Array, gram: int, twins: bool = False) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """By block: the first document, all sets end to end, where each begins, and (if asked for) a second hash of each
    gram that is independent of the first from the bytes on. Sets are sorted."""
    data, offsets = utf8(column)
    for a, b in blocks(offsets):
        part = lowered(data[offsets[a] : offsets[b]])
        starts, ends, at = words_in_documents(part, offsets[a : b + 1] - offsets[a])
        rolling = Rolling(in_pieces(word_hashes, part, starts, ends))
        other = Rolling(in_pieces(word_twins, part, starts, ends), TWO) if twins else None
        none = np.zeros(0, np.uint64)
        every, second, sets, pairs = rolling.every(gram), other.every(gram) if twins else none, [], []
        for i, j in zip(at[:-1], at[1:], strict=True):
            if j - i >= gram:
                x = every[i : j - gram + 1]
                order = np.argsort(x, kind="stable") if twins else None
                x = x[order] if twins else np.sort(x)
                new = np.append(True, x[1:] != x[:-1])
                sets.append(x[new])
                pairs.append(second[i : j - gram + 1][order][new] if twins else none)
            else:
                sets.append(rolling.of(np.array([i]), np.array([j])) if j > i else none)
                pairs.append(other.of(np.array([i]), np.array([j])) if twins and j > i else none)
        yield a, np.concatenate([none, *sets]), np.concatenate([[0], np.cumsum([len(x) for x in sets])]).astype(np.int64), np.concatenate([none, *pairs])


def class_key(grams: np.ndarray, at: np.ndarray, salt: int = 0x2545F4914F6CDD1D) -> np.ndarray:
    """64 bits of each set, whatever the order; 0 for an empty one."""
    n = np.diff(at)
    sums = np.concatenate([[np.uint64(0)], np.cumsum(mix(grams ^ np.uint64(salt)))])
    return np.where(n > 0, mix(sums[at[1:]] - sums[at[:-1]] + n.astype(np.uint64)), np.uint64(0))


def document_classes(docs: DataFrame, gram: int) -> DataFrame:
    """(doc_id, rid, n_shingles, c1, c2) of each document; c1 and c2 rest on independent hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, grams, at, twins in gram_sets(batch.column("text"), gram, twins=True):
                c1, c2 = class_key(grams, at), class_key(twins, at, 0x9E6C63D0876A9A47)
                n = len(at) - 1
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(first, n), batch.column("rid").slice(first, n), pa.array(np.diff(at)), pa.array(c1.view(np.int64)), pa.array(c2.view(np.int64))], ["doc_id", "rid", "n_shingles", "c1", "c2"])

    return docs.mapInArrow(run, "doc_id long, rid long, n_shingles long, c1 long, c2 long")


# ---- 1. who can link ------------------------------------------------------------------------------


def shown(n: np.ndarray, num: int, den: int) -> tuple[np.ndarray, np.ndarray]:
    """How many grams each set shows, and how many of them must stand elsewhere."""
    need = np.maximum(1, n // 20)
    lack = missing(n, num, den)
    return np.minimum(n, lack + need), np.minimum(n, lack + need) - lack


def shown_grams(docs: DataFrame, gram: int, num: int, den: int, buckets: int) -> DataFrame:
    """(bucket, kind, body). Kind 0: grams that one class of the task shows, with the class; 1: grams that several show;
    2 (bucket -1): classes and how many of their grams are of that sort."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        size = 0
        for batch in batches:
            for _, grams, at, _ in gram_sets(batch.column("text"), gram):
                n = np.diff(at)
                k = shown(n, num, den)[0]
                c1 = class_key(grams, at)
                where = np.repeat(at[:-1] - (np.cumsum(k) - k), k) + np.arange(k.sum())
                held.append((mix(grams[where] ^ np.uint64(0xA0761D6478BD642F)), np.repeat(c1, k)))
                size += len(where)
                if size > FLUSH:
                    yield out(held)
                    held, size = [], 0
        if held:
            yield out(held)

    def out(held: list[tuple[np.ndarray, np.ndarray]]) -> pa.RecordBatch:
        h, c = (np.concatenate(x) for x in zip(*held, strict=True))
        order = np.lexsort((c, h))
        h, c = h[order], c[order]
        new = np.ones(len(h), bool)
        new[1:] = h[1:] != h[:-1]
        own = new.copy()
        own[1:] |= c[1:] != c[:-1]
        h, c, new = h[own], c[own], new[own]  # a class shows a gram once
        begin = np.flatnonzero(new)
        n = np.diff(np.append(begin, len(h)))
        once = np.repeat(n == 1, n)
        bucket = bucket_of(h, buckets)
        rows: list[tuple[int, int, bytes]] = []
        for kind, pick in ((0, once), (1, new & ~once)):
            b, x = bucket[pick], np.empty(int(pick.sum()), ASK)
            x["f"], x["c"] = h[pick], c[pick] if kind == 0 else 0
            cut = np.flatnonzero(np.diff(b, prepend=-1, append=-2))
            rows += [(int(b[i]), kind, x[i:j].tobytes()) for i, j in zip(cut[:-1], cut[1:], strict=True)]
        rows.append((-1, 2, counted(c[~once])))
        columns = zip(*rows, strict=True)
        return pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(columns, (pa.int32(), pa.int32(), pa.binary()), strict=True)], ["bucket", "kind", "body"])

    return docs.select("text").mapInArrow(run, "bucket int, kind int, body binary")


def counted(c: np.ndarray) -> bytes:
    out = np.empty(len(np.unique(c)), SEEN)
    out["a"], out["n"] = np.unique(c, return_counts=True)
    return out.tobytes()


def _summed(bodies: list[bytes]) -> np.ndarray:
    x = np.sort(np.concatenate([np.zeros(0, SEEN), *(np.frombuffer(b, SEEN) for b in bodies)]), order="a")
    begin = np.flatnonzero(np.append(True, x["a"][1:] != x["a"][:-1])) if len(x) else np.zeros(0, np.int64)
    out = x[begin].copy()
    out["n"] = np.add.reduceat(x["n"], begin) if len(x) else 0
    return out


def _shared_here(frame: pd.DataFrame, buckets: int) -> pd.DataFrame:
    """One bucket of grams: classes and how many of their grams stand with another class too, packed by class."""
    echo = [x for x in frame["body"][frame["kind"] == 2]]
    asks = np.unique(np.concatenate([np.zeros(0, ASK), *(np.frombuffer(x, ASK) for x in frame["body"][frame["kind"] == 0])]))
    notes = np.concatenate([np.zeros(0, ASK), *(np.frombuffer(x, ASK) for x in frame["body"][frame["kind"] == 1])])
    f = asks["f"]
    twice = np.isin(f, notes["f"])
    same = f[1:] == f[:-1]
    twice[1:] |= same
    twice[:-1] |= same
    seen = _summed([*echo, counted(asks["c"][twice])])
    owner = bucket_of(seen["a"], buckets)
    cut = np.flatnonzero(np.diff(owner, prepend=-1, append=-2))
    return pd.DataFrame({"owner": owner[cut[:-1]], "body": [seen[a:b].tobytes() for a, b in zip(cut[:-1], cut[1:], strict=True)]})


def _seen_of_classes(frame: pd.DataFrame) -> pd.DataFrame:
    """One bucket of classes: how many of its grams each shares, over all buckets of grams."""
    x = _summed(list(frame["body"]))
    return pd.DataFrame({"c1": np.ascontiguousarray(x["a"]).view(np.int64), "seen": x["n"].astype(np.int64)})


def may_link(docs: DataFrame, classes: DataFrame, gram: int, num: int, den: int, buckets: int) -> DataFrame:
    """Of classes (c1, c2, n, ...) those that can have a partner other than their own copies."""
    rows = shown_grams(docs, gram, num, den, buckets)
    rows = rows.withColumn("bucket", F.when(F.col("kind") == 2, F.pmod(F.xxhash64("body"), F.lit(buckets)).cast("int")).otherwise(F.col("bucket")))
    found = rows.groupBy("bucket").applyInPandas(lambda frame: _shared_here(frame, buckets), "owner int, body binary")
    seen = found.groupBy("owner").applyInPandas(_seen_of_classes, "c1 long, seen long")
    n = F.col("n")
    lack = n - F.expr(f"(n * {num} + {den - 1}) div {den}")
    need = F.greatest(F.lit(1), F.expr("n div 20"))
    must = F.least(n, lack + need) - lack
    return classes.join(seen, "c1").filter(F.col("seen") >= must).drop("seen")


# ---- 2. global order --------------------------------------------------------------------------------


def set_parts(docs: DataFrame, chosen: DataFrame, many: DataFrame, gram: int) -> DataFrame:
    """(part, node, n, weight, grams) of the chosen classes' first documents, node their rid, one row each: chosen has
    (doc_id, rid, weight), many the (doc_id, rid) of rows that are repeated."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, size = TaskContext.get().partitionId() << 32, 0
        for batch in batches:
            for first, grams, at, _ in gram_sets(batch.column("text"), gram):
                n = np.diff(at)
                own = (np.cumsum(n) + size) // PART_GRAMS
                yield pa.RecordBatch.from_arrays([pa.array(part + own), batch.column("rid").slice(first, len(n)), pa.array(n), batch.column("weight").slice(first, len(n)), pa.array([grams[i:j].tobytes() for i, j in zip(at[:-1], at[1:], strict=True)], pa.binary())], ["part", "node", "n", "weight", "grams"])
                size += int(n.sum())

    joined = docs.join(chosen, ["doc_id", "rid"]).select("doc_id", "rid", "text", "weight")
    # partial overlaps are summed by node, so a repeated row must come once; only such rows move for that
    several = joined.join(many, ["doc_id", "rid"], "left_semi").dropDuplicates(["doc_id", "rid"])
    joined = joined.join(many, ["doc_id", "rid"], "left_anti").unionByName(several).select("rid", "text", "weight")
    return joined.mapInArrow(run, "part long, node long, n long, weight long, grams binary")


def cell_of(grams: np.ndarray, count: np.ndarray) -> np.ndarray:
    """Where a gram lies in the global order, coarsely: by the power of two below its count, then by its first four bits."""
    return np.floor(np.log2(np.maximum(count, 1))).astype(np.int64) * 16 + (grams >> np.uint64(60)).astype(np.int64)


def gram_counts(sets: DataFrame, buckets: int) -> DataFrame:
    """(part, body, cell, n): grams of the part that stand in two classes or more of the corpus, with the number of classes
    (cell null); and with part null, how many occurrences of such grams lie in a cell of the global order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            flat, at = utf8(batch.column("grams"))
            grams = np.frombuffer(flat.tobytes(), "<u8")
            part = np.repeat(batch.column("part").to_numpy(zero_copy_only=False), np.diff(at) // 8)
            rows: list[tuple[int, int, bytes]] = []
            for p in np.unique(part):
                a, n = np.unique(grams[part == p], return_counts=True)
                bucket = bucket_of(mix(a), buckets)
                order = np.argsort(bucket, kind="stable")
                out = np.empty(len(a), SEEN)
                out["a"], out["n"] = a[order], n[order]
                cut = np.flatnonzero(np.diff(bucket[order], prepend=-1, append=-2))
                rows += [(int(bucket[order[i]]), int(p), out[i:j].tobytes()) for i, j in zip(cut[:-1], cut[1:], strict=True)]
            columns = list(zip(*rows, strict=True)) or [(), (), ()]
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(columns, (pa.int32(), pa.int64(), pa.binary()), strict=True)], ["bucket", "part", "body"])

    def total(frame: pd.DataFrame) -> pd.DataFrame:
        rows = [np.frombuffer(x, SEEN) for x in frame["body"]]
        part = np.repeat(frame["part"].to_numpy(), [len(x) for x in rows])
        r = np.concatenate(rows)
        order = np.argsort(r["a"], kind="stable")
        r, part = r[order], part[order]
        begin = np.flatnonzero(np.append(True, r["a"][1:] != r["a"][:-1]))
        n = np.diff(np.append(begin, len(r)))
        sums = np.repeat(np.add.reduceat(r["n"].astype(np.int64), begin), n)
        out = np.empty(int((sums > 1).sum()), SEEN)
        out["a"], out["n"] = r["a"][sums > 1], np.minimum(sums[sums > 1], 2**32 - 1)
        found = per_part(out, part[sums > 1])
        each = sums[begin] > 1
        weight = np.bincount(cell_of(r["a"][begin][each], sums[begin][each]), sums[begin][each]) if each.any() else np.zeros(0)
        cells = np.flatnonzero(weight)
        replies = {"part": pd.array([*found["part"], *[None] * len(cells)], "Int64"), "body": [*found["body"], *[None] * len(cells)]}
        return pd.DataFrame(replies | {"cell": pd.array([*[None] * len(found), *cells], "Int32"), "n": pd.array([*[None] * len(found), *weight[cells].astype(np.int64)], "Int64")})

    return sets.select("part", "grams").mapInArrow(run, "bucket int, part long, body binary").groupBy("bucket").applyInPandas(total, "part long, body binary, cell int, n long")


def fragment_cuts(counts: DataFrame, fragments: int = FRAGMENTS) -> np.ndarray:
    """The cells of the global order at which fragments of about equal weight begin, but for the first."""
    rows = sorted((r["cell"], r["n"]) for r in counts.filter("cell IS NOT NULL").groupBy("cell").agg(F.sum("n").alias("n")).collect())  # 64 x 16 cells at most
    if not rows:
        return np.zeros(0, np.int64)
    cell, n = np.array(rows).T
    return np.unique(cell[np.searchsorted(np.cumsum(n), [n.sum() * k / fragments for k in range(1, fragments)])])


#: What prefix_segments() writes: links within a part, least holders of prefix grams, sets, and their segments.
LOCAL, STAR, NODE, SEGMENT = 0, 1, 2, 3
HOLDER = np.dtype([("a", "<u8"), ("v", "<i8")])
PLACED = "kind int, bucket int, u long, v long, n long, weight long, score double, body binary"


def prefix_segments(sets: DataFrame, counts: DataFrame, cuts: np.ndarray, num: int, den: int, buckets: int) -> DataFrame:
    """PLACED rows, from one pass over the sets with the counts of their grams. Links: (u, v). Stars: (bucket, body). Sets:
    (u the node, n, weight, score: how frequent its grams are). Segments: (u the node, v the fragment, body: its grams
    there that another class holds too)."""
    schema = pa.schema([("kind", pa.int32()), ("bucket", pa.int32()), ("u", pa.int64()), ("v", pa.int64()), ("n", pa.int64()), ("weight", pa.int64()), ("score", pa.float64()), ("body", pa.binary())])

    def place(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return schema.empty_table()
        known = np.sort(np.frombuffer(b"".join(right.column("body").to_pylist()), SEEN), order="a")
        known = known[np.append(True, known["a"][1:] != known["a"][:-1])] if len(known) else known
        flat, at = utf8(left.column("grams"))
        grams, at = np.frombuffer(flat.tobytes(), "<u8"), at // 8
        n, node, weight = np.diff(at), left.column("node").to_numpy(), left.column("weight").to_numpy()
        k = np.minimum(np.searchsorted(known["a"], grams), max(len(known) - 1, 0))
        count = np.where(known["a"][k] == grams, known["n"][k], 1).astype(np.int64) if len(known) else np.ones(len(grams), np.int64)
        owner = np.repeat(np.arange(len(n)), n)
        power = np.floor(np.log2(count)).astype(np.int64)
        order = np.lexsort((grams, power, owner))
        nth = np.arange(len(grams)) - np.repeat(at[:-1], n)
        take = order[nth < np.repeat(missing(n, num, den) + 1, n)]
        take = take[count[take] > 1]
        g, who = grams[take], node[owner[take]]
        first = np.lexsort((who, g))
        g, who = g[first], who[first]
        begin = np.flatnonzero(np.append(True, g[1:] != g[:-1])) if len(g) else np.zeros(0, np.int64)
        star = np.repeat(who[begin], np.diff(np.append(begin, len(g)))) if len(g) else who
        rows = [(LOCAL, None, int(a), int(b), None, None, None, None) for a, b in np.unique(np.stack([who, star], axis=1)[who != star], axis=0)]
        out = np.empty(len(begin), HOLDER)
        out["a"], out["v"] = g[begin], who[begin]
        bucket = bucket_of(mix(out["a"]), buckets)
        first = np.argsort(bucket, kind="stable")
        out, bucket = out[first], bucket[first]
        cut = np.flatnonzero(np.diff(bucket, prepend=-1, append=-2))
        rows += [(STAR, int(bucket[i]), None, None, None, None, None, out[i:j].tobytes()) for i, j in zip(cut[:-1], cut[1:], strict=True)]
        score = np.bincount(owner, power, len(n)) / np.maximum(n, 1)
        rows += [(NODE, None, int(u), None, int(size), int(w), float(x), None) for u, size, w, x in zip(node, n, weight, score, strict=True)]
        order = order[count[order] > 1]  # rare to frequent within each set; a gram of one class overlaps with none
        fragment = np.searchsorted(cuts, cell_of(grams[order], count[order]), "right")
        cut = np.flatnonzero(np.diff(owner[order] * (FRAGMENTS + 1) + fragment, prepend=-1, append=-2))
        rows += [(SEGMENT, None, int(node[owner[order[i]]]), int(fragment[i]), None, None, None, grams[order[i:j]].tobytes()) for i, j in zip(cut[:-1], cut[1:], strict=True)]
        return pa.Table.from_arrays([pa.array(x, f.type) for x, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)

    return sets.select("part", "node", "weight", "grams").groupBy("part").cogroup(counts.filter("cell IS NULL").groupBy("part")).applyInArrow(place, PLACED)


def prefix_links(placed: DataFrame) -> DataFrame:
    """(u, v): classes that may link, as stars around the least holder of each gram in a prefix."""

    def stars(frame: pd.DataFrame) -> pd.DataFrame:
        r = np.sort(np.concatenate([np.frombuffer(x, HOLDER) for x in frame["body"]]), order=["a", "v"])
        begin = np.flatnonzero(np.append(True, r["a"][1:] != r["a"][:-1]))
        star = np.repeat(r["v"][begin], np.diff(np.append(begin, len(r))))
        pairs = np.unique(np.stack([r["v"], star], axis=1)[r["v"] != star], axis=0)
        return pd.DataFrame({"u": pairs[:, 0], "v": pairs[:, 1]})

    across = placed.filter(F.col("kind") == STAR).select("bucket", "body").groupBy("bucket").applyInPandas(stars, "u long, v long")
    return placed.filter(F.col("kind") == LOCAL).select("u", "v").union(across).distinct()


# ---- 3. vertical partitioning -----------------------------------------------------------------------


def overlaps(left: list[np.ndarray], right: list[np.ndarray], columns: int = COLUMNS) -> np.ndarray:
    """Of each pair the number of common grams: products of incidence matrices of so many grams at a time, summed."""
    def flat(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        return np.concatenate([np.zeros(0, np.uint64), *sets]), np.repeat(np.arange(len(sets)), [len(x) for x in sets])

    (a, row), (b, column) = flat(left), flat(right)
    common = np.intersect1d(a, b)
    at_a, at_b = np.searchsorted(common, a), np.searchsorted(common, b)
    in_a = common[np.minimum(at_a, max(len(common) - 1, 0))] == a if len(common) else np.zeros(len(a), bool)
    in_b = common[np.minimum(at_b, max(len(common) - 1, 0))] == b if len(common) else np.zeros(len(b), bool)
    at_a, row, at_b, column = at_a[in_a], row[in_a], at_b[in_b], column[in_b]
    total = np.zeros((len(left), len(right)), np.int64)
    for f in range(0, len(common), columns):
        x, y = np.zeros((len(left), min(columns, len(common) - f)), np.float32), np.zeros((len(right), min(columns, len(common) - f)), np.float32)
        i, j = (at_a >= f) & (at_a < f + columns), (at_b >= f) & (at_b < f + columns)
        x[row[i], at_a[i] - f] = 1
        y[column[j], at_b[j] - f] = 1
        total += (x @ y.T).astype(np.int64)
    return total


def forest(hit: np.ndarray) -> list[tuple[int, int]]:
    """Links that connect what hit (symmetric) connects, one fewer than nodes in each tree."""
    n, out = len(hit), []
    unseen = np.ones(n, bool)
    for root in range(n):
        if not unseen[root]:
            continue
        unseen[root] = False
        todo = [root]
        while todo:
            u = todo.pop()
            new = np.flatnonzero(hit[u] & unseen)
            unseen[new] = False
            out += [(u, int(v)) for v in new]
            todo += new.tolist()
    return out


def with_representatives(info: DataFrame, segments: DataFrame, num: int, den: int, block: int) -> DataFrame:
    """(node, ball, common): of the members of groups larger than a block (info: grp, node, n, score, size) those within
    half of the allowed distance of a representative, ball its node; round by round among those left, while some group
    has more than a block of them."""
    found: DataFrame | None = None
    left = materialise(info, "left")
    for _ in range(ROUNDS):
        if left.isEmpty():
            break
        best = left.groupBy("grp").agg(F.max_by(F.struct("node", "n"), F.struct("score", "n", -F.col("node"))).alias("b"), F.count(F.lit(1)).alias("members"))
        best = best.select("grp", F.col("b.node").alias("ball"), F.col("b.n").alias("ball_n"), F.ceil(F.col("members") / block).cast("int").alias("salts"))
        mine = left.join(best, "grp").withColumn("salt", F.pmod(F.xxhash64("node"), F.col("salts")).cast("int"))
        mine = mine.select("node", "ball", "salt").join(segments, "node").select("ball", "salt", "fragment", "node", "body")
        # a representative's segments go to every salt of its group: no task holds a whole group
        theirs = best.select(F.col("ball").alias("node"), "salts").join(segments, "node").select(F.col("node").alias("ball"), F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"), "fragment", "body").toDF("ball", "salt", "fragment", "body")

        def partial(members: pa.Table, centre: pa.Table) -> pa.Table:
            kind = pa.schema([("node", pa.int64()), ("common", pa.int64())])
            if not members.num_rows or not centre.num_rows:
                return kind.empty_table()
            grams = np.sort(np.frombuffer(centre.column("body")[0].as_py(), "<u8"))
            n = [int(np.isin(np.frombuffer(x, "<u8"), grams).sum()) for x in members.column("body").to_pylist()]
            return pa.table([members.column("node").combine_chunks(), pa.array(n, pa.int64())], schema=kind)

        keys = ["ball", "salt", "fragment"]
        common = mine.groupBy(*keys).cogroup(theirs.groupBy(*keys)).applyInArrow(partial, "node long, common long").groupBy("node").agg(F.sum("common").alias("common"))
        near = left.join(best.select("grp", "ball", "ball_n"), "grp").join(common, "node", "left").withColumn("common", F.when(F.col("node") == F.col("ball"), F.col("n")).otherwise(F.coalesce("common", F.lit(0))))
        union = F.col("n") + F.col("ball_n") - F.col("common")
        near = materialise(near.withColumn("inside", F.lit(2 * den) * F.col("common") >= F.lit(den + num) * union), "near")
        inside = near.filter("inside").select("node", "ball")
        found = inside if found is None else found.union(inside)
        rest = near.filter("NOT inside").select(info.columns)
        large = rest.groupBy("grp").agg(F.count(F.lit(1)).alias("m")).filter(F.col("m") > block).select("grp")
        left = materialise(rest.join(large, "grp", "left_semi"), "left")
    return found if found is not None else info.select("node", F.col("node").alias("ball")).limit(0)


def group_links(placed: DataFrame, groups: DataFrame, num: int, den: int, buckets: int, block: int) -> DataFrame:
    """(u, v, links): links of a spanning forest with links null, and for each class u (v null) how many documents of
    other classes it links with."""
    info = placed.filter(F.col("kind") == NODE).select(F.col("u").alias("node"), "n", "weight", "score").join(groups.select("node", F.col("component").alias("grp")), "node")
    sizes = info.groupBy("grp").agg(F.count(F.lit(1)).alias("size"))
    info = materialise(info.join(sizes, "grp"), "members")
    segments = placed.filter(F.col("kind") == SEGMENT).select(F.col("u").alias("node"), F.col("v").alias("fragment"), "body")
    balls = materialise(with_representatives(info.filter(F.col("size") > block), segments, num, den, block), "balls")
    # within a ball: a star around the representative, and all others of the ball
    member = info.join(balls, "node").select("node", "ball", "weight")
    whole = member.groupBy("ball").agg(F.sum("weight").alias("all"))
    in_ball = member.filter("node <> ball").select(F.col("node").alias("u"), F.col("ball").alias("v"), F.lit(None).cast("long").alias("links"))
    in_ball = in_ball.union(member.join(whole, "ball").select(F.col("node").alias("u"), F.lit(None).cast("long").alias("v"), (F.col("all") - F.col("weight")).alias("links")))

    # blocks: of each ball, and of the members of a group in none; pairs of blocks, but for two of one ball
    info = info.join(balls, "node", "left").withColumn("loose", F.col("ball").isNull()).withColumn("ball", F.coalesce("ball", "grp"))
    parts_of = info.groupBy("grp", "ball", "loose").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("cuts"))
    info = info.join(parts_of, ["grp", "ball", "loose"]).withColumn("cut", F.pmod(F.xxhash64("node", F.lit(5)), F.col("cuts")).cast("int"))
    x, y = (parts_of.select("grp", *(F.col(c).alias(f"{c}_{k}") for c in ("ball", "loose", "cuts"))) for k in ("x", "y"))
    order = F.struct("loose_x", "ball_x") < F.struct("loose_y", "ball_y")
    same = F.col("loose_x") & F.col("loose_y")
    pairs = x.join(y, "grp").filter(same | order)  # a few balls a group
    pairs = pairs.withColumn("cut_x", F.explode(F.sequence(F.lit(0), F.col("cuts_x") - 1))).withColumn("cut_y", F.explode(F.sequence(F.when(same, F.col("cut_x")).otherwise(0), F.col("cuts_y") - 1)))
    total = info.agg(F.sum("n")).first()[0] or 0
    shared = max(buckets * 4, -(-total // TASK_GRAMS))
    alone = same & (F.col("cuts_x") == 1) & (F.col("cuts_y") == 1)
    # pairs of small groups share tasks; each pair of blocks of a large one is a task
    one = F.xxhash64("grp", "ball_x", "loose_x", "cut_x", "ball_y", "loose_y", "cut_y")
    pairs = pairs.withColumns({"pair": one, "key": F.when(alone, F.pmod(F.xxhash64("grp"), F.lit(shared))).otherwise(one)})
    both = same & (F.col("cut_x") == F.col("cut_y"))
    sides = pairs.select("key", "pair", "grp", F.col("ball_x").alias("ball"), F.col("loose_x").alias("loose"), F.col("cut_x").alias("cut"), F.when(both, 2).otherwise(0).alias("side"))
    sides = sides.union(pairs.filter(~both).select("key", "pair", "grp", "ball_y", "loose_y", "cut_y", F.lit(1)))
    rows = materialise(info.join(sides, ["grp", "ball", "loose", "cut"]).select("key", "pair", "side", "node", "n", "weight"), "pairs")

    def partial(frame: pd.DataFrame) -> pd.DataFrame:
        """One fragment of one task: (key, pair, body), the partial overlaps of each pair of classes."""
        out = []
        for pair, r in frame.groupby("pair", sort=False):
            node, n, side = r["node"].to_numpy(), r["n"].to_numpy(), r["side"].to_numpy()
            held = [np.frombuffer(x, "<u8") for x in r["body"]]
            a, b = np.flatnonzero(side != 1), np.flatnonzero(side != 0)
            common = overlaps([held[i] for i in a], [held[i] for i in b])
            # of a block with itself each pair once; sizes that are too far apart can't link
            some = (common > 0) & (np.minimum(n[a][:, None], n[b][None, :]) * den >= num * np.maximum(n[a][:, None], n[b][None, :]))
            if (side == 2).any():
                some &= a[:, None] < b[None, :]
            i, j = np.nonzero(some)
            if len(i):
                body = np.empty(len(i), PAIR)
                body["u"], body["v"], body["n"] = node[a[i]], node[b[j]], common[i, j]
                swap = body["u"] > body["v"]
                body["u"][swap], body["v"][swap] = body["v"][swap], body["u"][swap]
                out.append((int(frame["key"].iloc[0]), int(pair), body.tobytes()))
        trim()
        return pd.DataFrame(out, columns=["key", "pair", "body"])

    counted = rows.join(segments, "node").select("key", "pair", "side", "fragment", "node", "n", "body").groupBy("key", "fragment").applyInPandas(partial, "key long, pair long, body binary")
    ends = rows.select("key", "pair", "node", "n", "weight", F.lit(None).cast("binary").alias("body")).unionByName(counted.withColumns({c: F.lit(0).cast("long") for c in ("node", "n", "weight")}))  # a null long would turn into a float in pandas

    def decide(frame: pd.DataFrame) -> pd.DataFrame:
        """One task: the partial overlaps of each pair summed over fragments, and what links."""
        edges: list[tuple[int, int]] = []
        links: list[tuple[int, int]] = []
        for _, r in frame.groupby("pair", sort=False):
            known = r[r["body"].isna()]
            got = np.concatenate([np.zeros(0, PAIR), *(np.frombuffer(x, PAIR) for x in r["body"].dropna())])
            if not len(got):
                continue
            got = np.sort(got, order=["u", "v"])
            begin = np.flatnonzero(np.append(True, (got["u"][1:] != got["u"][:-1]) | (got["v"][1:] != got["v"][:-1])))
            u, v, common = got["u"][begin], got["v"][begin], np.add.reduceat(got["n"], begin)
            by = known.sort_values("node")
            node, n, weight = (by[c].to_numpy(np.int64) for c in ("node", "n", "weight"))
            i, j = np.searchsorted(node, u), np.searchsorted(node, v)
            ok = den * common >= num * (n[i] + n[j] - common)
            hit = np.zeros((len(node), len(node)), bool)
            hit[i[ok], j[ok]] = hit[j[ok], i[ok]] = True
            edges += [(int(node[a]), int(node[b])) for a, b in forest(hit)]
            m = hit @ weight
            links += [(int(node[k]), int(m[k])) for k in np.flatnonzero(m)]
        u, v = [a for a, _ in edges] + [a for a, _ in links], [b for _, b in edges] + [None] * len(links)
        trim()
        return pd.DataFrame({"u": pd.array(u, "Int64"), "v": pd.array(v, "Int64"), "links": pd.array([None] * len(edges) + [m for _, m in links], "Int64")})

    return ends.groupBy("key").applyInPandas(decide, "u long, v long, links long").union(in_ball)


def join(docs: DataFrame, gram: int = GRAM, num: int = NUM, den: int = DEN, buckets: int | None = None, block: int = GROUP_BLOCK) -> DataFrame:
    """(doc_id, rid, n_shingles, component_id, n_links, component_rid) of each document, whole texts.

    docs: (doc_id, rid, text) as keyed() gives it. A-Z are lower-cased. component_id: the smallest doc_id that links
    reach, itself included, and component_rid the least rid of that id: ids may be missing or repeated; n_links: documents that it links with directly, copies too. Null and empty texts, and those
    without a word, have no set and no links. Fewer words than ``gram``: the whole sequence is the one gram. Repeated
    rows link with each other. No rows: no rows.
    """
    buckets = buckets or parts(docs.sparkSession)
    of = materialise(document_classes(docs, gram), "classes")
    classes = of.filter("n_shingles > 0").groupBy("c1", "c2").agg(F.min(F.struct("doc_id", "rid")).alias("first"), F.first("n_shingles").alias("n"), F.count(F.lit(1)).alias("weight"))
    classes = materialise(classes, "classes")
    chosen = may_link(docs, classes, gram, num, den, buckets).select(F.col("first.doc_id").alias("doc_id"), F.col("first.rid").alias("rid"), "weight")
    many = materialise(of.groupBy("doc_id", "rid").agg(F.count(F.lit(1)).alias("copies")).filter("copies > 1").select("doc_id", "rid"), "copies")
    sets = materialise(set_parts(docs, chosen, many, gram), "sets")
    counts = materialise(gram_counts(sets, buckets), "counts")
    placed = materialise(prefix_segments(sets, counts, fragment_cuts(counts), num, den, buckets), "placed")
    discard(sets, counts)
    groups = components(prefix_links(placed))
    links = materialise(group_links(placed, groups, num, den, buckets, block), "links")
    discard(placed)
    reach = components(links.filter("v IS NOT NULL").select("u", "v"))
    count = links.filter("v IS NULL").groupBy(F.col("u").alias("node")).agg(F.sum("links").alias("links"))
    nodes = classes.select("c1", "c2", F.col("first.rid").alias("node"), "first", "weight")
    least = reach.join(nodes, "node").groupBy("component").agg(F.min("first").alias("least"))
    named = nodes.join(reach.join(least, "component").select("node", "least"), "node", "left").join(count, "node", "left")
    named = named.select("c1", "c2", F.coalesce("least", "first").alias("least"), (F.coalesce("links", F.lit(0)) + F.col("weight") - 1).alias("links"))
    out = of.join(named, ["c1", "c2"], "left")
    return out.select("doc_id", "rid", "n_shingles", F.coalesce("least.doc_id", "doc_id").alias("component_id"), F.coalesce("links", F.lit(0)).alias("n_links"), F.coalesce("least.rid", "rid").alias("component_rid"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = join(keyed(table(spark, sf_dir, "documents").select("doc_id", "text")))
    return found.select(unnull("doc_id"), "n_shingles", unnull("component_id"), "n_links")


#: All pairs that share a gram, and the closure of links.
ORACLE = r"""
WITH RECURSIVE d AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
grams AS (SELECT DISTINCT doc_id, array_to_string(w[s : s + 4], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 4, 1) + 1)) AS s FROM d WHERE len(w) > 0)),
size AS (SELECT doc_id, count(*) AS n FROM grams GROUP BY 1),
common AS (SELECT a.doc_id AS u, b.doc_id AS v, count(*) AS n FROM grams a JOIN grams b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
links AS (SELECT u, v FROM common c JOIN size a ON a.doc_id = u JOIN size b ON b.doc_id = v WHERE 100 * c.n >= 80 * (a.n + b.n - c.n)),
reach AS (SELECT u, v FROM links UNION SELECT reach.u, links.v FROM reach JOIN links ON reach.v = links.u)
SELECT d.doc_id, coalesce(size.n, 0) AS n_shingles, least(d.doc_id, coalesce((SELECT min(v) FROM reach WHERE u = d.doc_id), d.doc_id)) AS component_id, (SELECT count(*) FROM links WHERE u = d.doc_id) AS n_links
FROM d LEFT JOIN size ON size.doc_id = d.doc_id
"""
