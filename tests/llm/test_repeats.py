"""Suffix dedup, the substring index, the Jaccard join and components, against brute force on small corpora."""

from __future__ import annotations

import hashlib
import random
import re

import numpy as np
import pyarrow as pa
import pytest

from relayout.llm import jaccard, repeats, substring_index, suffix_dedup
from relayout.llm.components import components
from relayout.llm.shared import keyed

SF = "/root/testdata/sf0.001"


def frame(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string").repartition(5)


def corpus(seed, n=40, words=False):
    """Short documents over few words with copies, shared passages, runs of one letter, and odd texts."""
    draw = random.Random(seed)
    vocab = ["ab", "c", "dé", "the", "of", "xyz", "日本", "q"]
    make = lambda k: " ".join(draw.choice(vocab) for _ in range(k))
    shared = [make(60) for _ in range(4)]
    rows = []
    for i in range(n):
        kind = draw.random()
        text = make(draw.randint(0, 90))
        if kind < 0.3:
            text = make(draw.randint(0, 9)) + " " + draw.choice(shared) + " " + make(draw.randint(0, 9))
        elif kind < 0.45 and rows:
            text = draw.choice(rows)[1] or ""
        elif kind < 0.55:
            text = "a" * draw.randint(0, 300)
        elif kind < 0.6:
            text = "go " * draw.randint(0, 100)
        rows.append((i, text))
    return [*rows, (n, None), (n + 1, ""), (n + 2, " \n\t "), (-5, rows[0][1]), (n + 3, "x" * 1000), (n + 4, "\u00a0".join(["nb"] * 50))]


def brute_bytes(rows, size):
    texts = [(t or "").encode() for _, t in rows]
    seen = {}
    for b in texts:
        for i in range(len(b) - size + 1):
            seen[b[i : i + size]] = seen.get(b[i : i + size], 0) + 1
    out = []
    for (doc_id, _), b in zip(rows, texts, strict=True):
        cut = np.zeros(len(b), bool)
        for i in range(len(b) - size + 1):
            if seen[b[i : i + size]] > 1:
                cut[i : i + size] = True
        spans = int(np.sum(np.diff(np.concatenate([[0], cut.astype(int)])) == 1))
        out.append((doc_id, len(b), int(cut.sum()), spans, hashlib.sha256(bytes(np.frombuffer(b, np.uint8)[~cut])).hexdigest()))
    return sorted(out, key=str)


@pytest.mark.parametrize("seed", range(3))
def test_suffixes_against_brute_force(spark, seed):
    rows = corpus(seed)
    got = suffix_dedup.digest(frame(spark, rows), size=40, gram=9, cover=3)
    assert sorted(map(tuple, got.collect()), key=str) == brute_bytes(rows, 40)


def test_suffixes_on_the_given_table(spark):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{SF}/documents.parquet").collect()]
    assert sorted(map(tuple, suffix_dedup.query(spark, SF).collect()), key=str) == brute_bytes(rows, 400)


def test_long_text_in_stretches(spark):
    draw = random.Random(1)
    long = "".join(draw.choice("abcdefgh") for _ in range(2_500_000))
    rows = [(1, long), (2, long[999_800:1_000_600]), (3, "z" + long[2_100_000:2_100_399]), (4, long[5:405])]
    got = {r.doc_id: (r.n_removed, r.n_spans) for r in suffix_dedup.digest(frame(spark, rows)).collect()}
    assert got == {1: (1200, 2), 2: (800, 1), 3: (0, 0), 4: (400, 1)}


def test_rows_that_repeat_or_are_missing(spark):
    rows = [(None, "k" * 30 + "l" * 30), (7, "k" * 30 + "l" * 30), (7, "k" * 30 + "l" * 30), (7, "other"), (None, None)]
    got = suffix_dedup.digest(frame(spark, rows).selectExpr("doc_id", "text", "1 AS found", "2 AS rid"), size=40, gram=9, cover=3)
    assert sorted((str(r.doc_id), r.n_bytes, r.n_removed) for r in got.collect()) == [("7", 5, 0), ("7", 60, 60), ("7", 60, 60), ("None", 0, 0), ("None", 60, 60)]
    assert suffix_dedup.digest(frame(spark, [])).count() == 0 and substring_index.digest(frame(spark, [])).count() == 0


@pytest.mark.parametrize("q", [2, 3, 5, 7])
def test_difference_cover(q):
    d, v = repeats.difference_cover(q)
    assert len(d) == q + 1 and v == q * q + q + 1 and {(a - b) % v for a in d for b in d} == set(range(v))


def brute_words(rows, size):
    seen, out = set(), []
    for doc_id, text in sorted(rows, key=lambda r: r[0]):
        w = re.findall(r"[^\x20\x09-\x0D]+", text or "")
        cut = [False] * len(w)
        for i in range(len(w) - size + 1):
            key = tuple(w[i : i + size])
            if key in seen:
                cut[i : i + size] = [True] * size
            seen.add(key)
        out.append((doc_id, len(w), sum(cut), hashlib.sha256(" ".join(x for x, c in zip(w, cut, strict=True) if not c).encode()).hexdigest()))
    return sorted(out)


@pytest.mark.parametrize(("seed", "batches"), [(3, 1), (4, 2), (5, 5)])
def test_substrings_against_brute_force(spark, seed, batches):
    rows = corpus(seed)
    got = substring_index.digest(frame(spark, rows), window=8, gram=3, batches=batches)
    assert sorted(map(tuple, got.collect())) == brute_words(rows, 8)


def test_one_of_equal_rows_keeps_its_words(spark):
    long = " ".join(f"w{k}" for k in range(30))
    rows = [(7, long), (7, long), (8, "vorn " + long), (9, "kurz"), (9, "kurz"), (5, long + " z"), *[(4, "noch " + long[:80])] * 3, *[(3, " ".join(f"u{k}" for k in range(25)))] * 4]
    got = substring_index.digest(frame(spark, rows))
    assert sorted(map(tuple, got.collect())) == brute_words(rows, 20)
    twice = substring_index.digest(frame(spark, [(None, long), (None, long), (7, "x")]))
    assert sorted((str(r.doc_id), r.n_words, r.n_removed) for r in twice.collect()) == [("7", 1, 0), ("None", 30, 0), ("None", 30, 30)]


def test_index_runs_are_compacted(spark):
    rows = corpus(6, 60)
    docs = keyed(frame(spark, rows)).persist()
    search = repeats.Search(words=True, window=8, gram=3, later=True)
    index, one = (substring_index.SubstringIndex(spark, search, 4, fanout=2) for _ in range(2))
    hits = None
    for k in range(5):
        found = index.add(docs.filter(f"doc_id % 5 = {k}"))
        hits = found if hits is None else hits.union(found)
        assert len(index.runs) <= 3  # two, and the batch's own
    whole = one.add(docs)
    pairs = lambda h: {(r.rid, x) for r in h.collect() for x in np.frombuffer(r.body, "<u8").tolist()}
    # added at once or in batches, the same documents are hit by the same fingerprints
    assert pairs(hits) == pairs(whole)


def test_index_lives_on(spark, tmp_path):
    rows = sorted((r for r in corpus(8, 70) if r[0] >= 0), key=lambda r: r[0])
    docs = keyed(frame(spark, rows)).persist()
    search = repeats.Search(words=True, window=8, gram=3, later=True)
    cuts, got = [0, 20, 40, 60, 100], {}
    index = substring_index.SubstringIndex(spark, search, 4, fanout=1)
    for k in range(4):
        batch, history = docs.filter(f"doc_id >= {cuts[k]} AND doc_id < {cuts[k + 1]}"), docs.filter(f"doc_id < {cuts[k]}")
        for r in index.repeated(batch, history).collect():
            got[r.doc_id] = repeats.ranges_of(r.found)
        index.save(f"{tmp_path}/{k}")
        index = substring_index.SubstringIndex.open(spark, f"{tmp_path}/{k}")  # each batch by another index
        assert len(index.runs) <= 2
    want = {doc_id: n for doc_id, _, n, _ in brute_words(rows, 8) if n}
    assert {k: int((r[:, 1] - r[:, 0]).sum()) for k, r in got.items()} == want


def test_columns_that_clash(spark):
    rows = corpus(2)
    docs = frame(spark, rows).selectExpr("doc_id", "text", *(f"7 AS {c}" for c in ("rid", "found", "copies", "n", "c1", "node", "component", "part", "bucket")))
    assert sorted(map(tuple, substring_index.digest(docs, window=8, gram=3).collect())) == brute_words(rows, 8)
    got = jaccard.join(keyed(docs), gram=2, num=60)
    assert sorted((r.doc_id, r.n_shingles, r.component_id, r.n_links) for r in got.collect()) == brute_join(rows, 2, 60, 100)


def test_large_groups_are_not_compared_pair_by_pair(spark):
    draw = random.Random(5)
    base = [f"t{k}" for k in range(300)]
    rows = [(0, " ".join(base))]
    for i in range(1, 120):
        words = list(base)
        words[draw.randrange(300)] = f"own{i}"
        rows.append((i, " ".join(words)))
    docs = keyed(frame(spark, rows))
    classes = jaccard.join(docs, block=8)
    assert sorted((r.doc_id, r.n_shingles, r.component_id, r.n_links) for r in classes.collect()) == brute_join(rows, 5, 80, 100)
    info = spark.createDataFrame([(1, k, 296, 1.0 + (k == 0)) for k in range(120)], "grp long, node long, n long, score double")
    sets = {k: next(iter(jaccard.gram_sets(pa.array([t]), 5)))[1] for k, t in rows}
    segments = spark.createDataFrame([(k, 0, bytearray(x.tobytes())) for k, x in sets.items()], "node long, fragment long, body binary")
    balls = jaccard.with_representatives(info, segments, 80, 100, 8).collect()
    assert len(balls) == 120 and {r.ball for r in balls} == {0}  # the common ancestor is everybody's representative


def brute_sets(rows, gram):
    out = []
    for doc_id, text in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
        out.append((doc_id, {tuple(w[i : i + gram]) for i in range(len(w) - gram + 1)} if len(w) >= gram else {tuple(w)} if w else set()))
    return out


def brute_join(rows, gram, num, den):
    sets = brute_sets(rows, gram)
    up = list(range(len(sets)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    links = [0] * len(sets)
    for i, (_, a) in enumerate(sets):
        for j, (_, b) in enumerate(sets):
            if i != j and a and b and den * len(a & b) >= num * len(a | b):
                links[i] += 1
                up[root(i)] = root(j)
    least = {}
    for i, (doc_id, _) in enumerate(sets):
        least[root(i)] = min(least.get(root(i), doc_id), doc_id)
    return sorted((doc_id, len(s), least[root(i)], links[i]) for i, (doc_id, s) in enumerate(sets))


def near_copies(seed, n=60):
    draw = random.Random(seed)
    vocab = [f"w{k}" for k in range(400)]
    base = [[draw.choice(vocab) for _ in range(draw.randint(1, 60))] for _ in range(6)]
    rows = []
    for i in range(n):
        words = list(draw.choice(base))
        for _ in range(draw.choice([0, 0, 1, 1, 2, 5])):
            words[draw.randrange(len(words))] = draw.choice(vocab)
        if draw.random() < 0.3:
            words += ["all", "rights", "reserved", "by", "law", "and", "custom"]
        rows.append((i, draw.choice([" ", "\n"]).join(words).replace("w1", "W1" if draw.random() < 0.5 else "w1")))
    return [*rows, (n, None), (n + 1, ""), (n + 2, "\t"), (-9, rows[3][1]), (n + 3, "one"), (n + 4, "ONE"), (n + 5, "long " * 30_000)]


@pytest.mark.parametrize(("seed", "block"), [(1, 1024), (2, 4), (3, 1024)])
def test_join_against_brute_force(spark, seed, block):
    rows = near_copies(seed)
    for gram, num in ((5, 80), (2, 60)):
        got = jaccard.join(keyed(frame(spark, rows)), gram=gram, num=num, block=block)
        assert sorted((r.doc_id, r.n_shingles, r.component_id, r.n_links) for r in got.collect()) == brute_join(rows, gram, num, 100)


def test_join_with_repeated_rows(spark):
    rows = near_copies(4, 40)
    rows += [*rows[:25], rows[3], rows[3]]
    for block in (4, 1024):
        got = jaccard.join(keyed(frame(spark, rows)), gram=2, num=60, block=block)
        assert sorted((r.doc_id, r.n_shingles, r.component_id, r.n_links) for r in got.collect()) == brute_join(rows, 2, 60, 100)


def test_join_on_the_given_table(spark):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{SF}/documents.parquet").collect()]
    assert sorted(map(tuple, jaccard.query(spark, SF).collect())) == brute_join(rows, 5, 80, 100)
    assert jaccard.join(keyed(frame(spark, []))).count() == 0


def test_overlaps_sum_over_fragments():
    draw = np.random.default_rng(0)
    sets = [np.unique(draw.integers(0, 50, k).astype(np.uint64)) for k in (0, 3, 20, 40, 40)]
    want = [[len(set(a.tolist()) & set(b.tolist())) for b in sets] for a in sets]
    for fragment in (1, 7, 4096):
        assert jaccard.overlaps(sets, sets, fragment).tolist() == want


def test_components_against_a_walk(spark):
    draw = random.Random(8)
    edges = [(draw.randint(0, 60), draw.randint(0, 60)) for _ in range(35)] + [(k, k + 1) for k in range(100, 180)] + [(500, 500)]
    up = {x: x for e in edges for x in e}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in edges:
        a, b = root(a), root(b)
        up[max(a, b)] = min(a, b)
    got = {r.node: r.component for r in components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert got == {x: root(x) for x in up}
    assert components(spark.createDataFrame([], "u long, v long")).count() == 0
