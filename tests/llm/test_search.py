"""URL filters, language, packing, top-k, decontamination, quality and quotes: brute force, contracts, odd inputs."""

from __future__ import annotations

import itertools
import math
import random
import re
import zlib

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from relayout.llm import decontam, jaccard, language_id, packing, quality, quotes, substring_index, topk, url_filter

SF = "/root/testdata/sf0.01"
DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def docs_of(spark, rows):
    return spark.createDataFrame([(i, t, k, s, None if t is None else len(t)) for i, t, k, s in rows], DOCS)


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in ("pages", "embeddings", "documents"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


@pytest.mark.parametrize("module", [url_filter, topk, jaccard, substring_index])
def test_against_sql(spark, duck, module):
    got = sorted(map(tuple, module.query(spark, SF).collect()), key=str)
    assert got == sorted(duck.execute(module.ORACLE).fetchall(), key=str)


# ---- URL filters


def brute_url(url, rules, default="allow"):
    rest = url.split("://", 1)[1] if url and "://" in url else ""
    host, path = rest, ""
    for k, c in enumerate(rest):
        if c in "/?#":
            host, path = rest[:k], rest[k:]
            break
    for c in "?#":
        path = path.split(c, 1)[0]
    host = "".join(c.lower() if "A" <= c <= "Z" else c for c in host)
    fit = [(len(h + (p or "")), v, h + (p or "")) for h, p, v in rules if h and (host == h or host.endswith("." + h)) and path.startswith(p or "")]
    best = max(fit, default=None)
    return host, path, best and best[2], best[1] if best else default


def test_url_rules_nest(spark):
    draw = random.Random(5)
    labels = ["a", "b", "net", "example", "", "x-y", "é"]
    rules = [(".".join(draw.choice(labels[:4]) for _ in range(draw.randint(1, 3))), draw.choice(["", "/", "/en/", "/en/a", None]), draw.choice(["allow", "block"])) for _ in range(25)]
    rules = list({(h, p): (h, p, v) for h, p, v in rules}.values()) + [("", "/", "block"), (None, "/", "block")]
    urls = [None, "", "no scheme", "://", "http://", "http://NET", "HTTP://a.NET/EN/", "http://a.net?x", "http://a.net#x", "http://u@a.net:80/en/", "x://a//b?c#d", "http://a.net/en/a\nb"]
    urls += ["http://" + ".".join(draw.choice(labels) for _ in range(draw.randint(1, 4))) + draw.choice(["", "/", "/en/", "/en/ab?q", "/EN/"]) for _ in range(200)]
    pages = spark.createDataFrame([(k, u, "old") for k, u in enumerate(urls + urls[:5])], "page_id long, url string, verdict string")
    got = url_filter.judge_urls(pages, spark.createDataFrame(rules, "host string, path string, verdict string"))
    assert got.columns == ["page_id", "url", "host", "path", "rule", "verdict"]
    for r in got.collect():
        assert (r.host, r.path, r.rule, r.verdict) == brute_url(r.url, rules), r.url
    assert got.count() == len(urls) + 5
    assert url_filter.judge_urls(pages.limit(0), spark.createDataFrame(rules, "host string, path string, verdict string")).count() == 0
    assert {r.verdict for r in url_filter.judge_urls(pages, spark.createDataFrame([], "host string, path string, verdict string")).collect()} == {"allow"}


def test_url_plan_is_native(spark):
    text = url_filter.query(spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert not any(x in text for x in ("Python", "Pandas", "Arrow"))


# ---- language


@pytest.fixture(scope="module")
def model(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    return language_id.train(docs.filter(~language_id.held_out(F.col("doc_id"))))


def test_held_out_accuracy(spark):
    truth = {r.doc_id: r.lang for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    got = language_id.query(spark, SF).collect()
    assert len(got) == len(truth) and all(0 <= r.score <= 1 for r in got)
    for r in got:
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0)
    held = [r for r in got if r.held_out and truth[r.doc_id]]
    assert sum(r.lang_pred == truth[r.doc_id] for r in held) / len(held) > 0.98


def brute_labels(scores, penalty):
    """The best labels of a short text by trying all sequences; ties to what Viterbi may choose are compared by value."""
    value = lambda seq: sum(scores[t][k] for t, k in enumerate(seq)) - penalty * sum(a != b for a, b in zip(seq, seq[1:], strict=False))
    return value, max(value(seq) for seq in itertools.product(range(len(scores[0])), repeat=len(scores)))


def test_viterbi_against_all_sequences():
    draw = np.random.default_rng(4)
    model = language_id.Model(["a", "b", "c"], np.zeros((1, 3), np.float32), np.ones((1, 3), bool), 1, penalty=2.0)
    for _ in range(25):
        sizes = draw.integers(0, 7, 5)
        doc = np.repeat(np.arange(5), sizes)
        scores = draw.normal(0, 2, (len(doc), 3)).astype(np.float32)
        labels = model.label(scores, doc, 5)
        for d in range(5):
            own = scores[doc == d].astype(float).tolist()
            if own:
                value, best = brute_labels(own, 2.0)
                assert abs(value(labels[doc == d].tolist()) - best) < 1e-4


def test_a_whole_word_counts():
    words = ["unabhängigkeitserklärung", "unabhängigkeitserklärungen", "unabhängigkeitserklxrung"]
    cells = [language_id.read_words([w], 18).cells[-1] for w in words]
    assert len(set(cells)) == 3 and cells[0] == language_id.read_words(["x " + words[0].upper() + " y"], 18).cells[-2]


def test_spans_of_mixed_text(spark, model):
    texts = {r.lang: r.text for r in spark.read.parquet(f"{SF}/documents.parquet").filter("length(text) BETWEEN 900 AND 1500").collect()}
    joined = texts["en"] + "\n" + texts["de"] + "\n" + texts["fr"]
    names, _, runs = model.predict([joined])
    assert [k for a, b, k in runs[0] if b - a > 200] == ["en", "de", "fr"] and names[0] in ("en", "de", "fr")
    cut = runs[0][0][1]
    assert abs(cut - len(texts["en"])) < 60


def test_odd_texts(spark, model):
    rows = [(1, None, None, "s"), (2, "", None, "s"), (3, "12 !? \n", "en", "s"), (None, "and the of", None, None), (5, "ÄÖÜ" * 60_000, None, "s"), (6, "漢字 и слово", None, "s"), (5, "ÄÖÜ" * 60_000, None, "s")]
    got = language_id.identify(docs_of(spark, rows).withColumn("score", F.lit("mine")), model, spans=True)
    by = {}
    for r in got.collect():
        by.setdefault(r.doc_id, []).append(r)
    assert [by[k][0].lang_pred for k in (1, 2, 3)] == ["und"] * 3 and [by[k][0].score for k in (1, 2, 3)] == [0.0] * 3
    assert by[None][0].lang_pred == "en" and by[6][0].lang_pred in model.languages and len(by[5]) == 2
    assert language_id.identify(docs_of(spark, []), model).count() == 0
    empty = language_id.train(docs_of(spark, []))
    assert empty.languages == [] and language_id.identify(docs_of(spark, rows[3:4]), empty).first().lang_pred == "und"


# ---- packing


def check_packing(spark, docs, rows, tok):
    by, seq = {}, {}
    for r in rows:
        by.setdefault(r.doc_id, []).append(r)
        seq.setdefault(r.sequence_id, []).append(r)
    for doc_id, text in docs.items():
        ids = np.array([*tok.encode(text or "", add_special_tokens=False).ids, 0], "<u4")
        at = 0
        for p in sorted(by[doc_id], key=lambda r: r.start):
            assert (p.start, p.doc_tokens, p.ids_crc32) == (at, len(ids), zlib.crc32(ids[at : at + p.length]))
            at += p.length
        assert at == len(ids)
    pad = 0
    for pieces in seq.values():
        at = 0
        for p in sorted(pieces, key=lambda r: r.offset):
            assert p.offset == at and p.length > 0
            at += p.length
        assert at <= 1024
        pad += 0 if at & (at - 1) == 0 else 1024 - at
    return pad


def test_packing_round_trip(spark):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(packing.tokenizer_paths()[0])
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    assert check_packing(spark, docs, packing.query(spark, SF).collect(), tok) == 0
    odd = {1: None, 2: "", 3: "<|endoftext|> a <| b", 4: "  \u00a0\u2003x\u0085\u200b y\t\n", 5: "word " * 5000, 6: "日本語 кириллица 𝒳", 7: "a\u0301\u00ad\x1f\x7f!!"}
    got = packing.pack(docs_of(spark, [(k, t, None, None) for k, t in odd.items()]), *packing.tokenizer_paths()).collect()
    assert check_packing(spark, odd, got, tok) == 0
    slow = packing.pack(docs_of(spark, [(k, t, None, None) for k, t in odd.items()]), packing.tokenizer_paths()[0]).collect()
    assert sorted((r.doc_id, r.start, r.ids_crc32) for r in slow) == sorted((r.doc_id, r.start, r.ids_crc32) for r in got)
    assert packing.pack(docs_of(spark, []), *packing.tokenizer_paths()).count() == 0
    twice = packing.pack(docs_of(spark, [(None, "a b", None, None)] * 3), *packing.tokenizer_paths())
    assert twice.count() == 3 and packing.padding(twice).first().padding == 16 - 9 - 7 or packing.padding(twice).first().padding == 0


def test_plan_uses_up_the_histogram():
    draw = np.random.default_rng(1)
    for counts in (draw.integers(0, 40, 1024), np.eye(1, 1024, 700, dtype=int)[0] * 999, np.zeros(1024, int)):
        p = packing.plan(counts)
        filled: dict[tuple[int, int], int] = {}
        for length in range(1, 1024):
            for rank in range(int(counts[length])):
                for start, n, s, off in packing.place(p, length, rank):
                    assert (s, off) not in filled
                    filled[s, off] = n
        ends: dict[int, int] = {}
        for (s, off), n in sorted(filled.items()):
            assert off == ends.get(s, 0)
            ends[s] = off + n
        assert all(n <= 1024 and (n & (n - 1)) == 0 for n in ends.values())


# ---- top-k


def test_topk_odd_vectors(spark):
    inf, nan = math.inf, math.nan
    rows = [(0, [1.0, 0.0]), (50, [0.5, -0.25]), (1, [1.0, 1.0]), (2, [1.0, 1.0]), (3, [1.0, 1.0]), (4, None), (5, [None, 1.0]), (6, [nan, 1.0]), (7, [inf, 0.0]), (None, [1.0, 1.0]), (8, [-1.0, 0.0]), (9, [1.0, 1.0]), (10, [1.0, 1.0]), (10, [1.0, 1.0]), (11, [1.0, 1.0, 9.0])]
    v = topk.quantised(spark.createDataFrame(rows, "vec_id long, embedding array<double>"))
    got = topk.top_k(v.filter("vec_id % 50 = 0"), v, 5)
    by = {}
    for r in got.orderBy("query_id", "rank").collect():
        by.setdefault(r.query_id, []).append((r.vec_id, r.score))
    assert by[0] == [(1, 65536), (2, 65536), (3, 65536), (9, 65536), (10, 65536)]
    assert by[50][0] == (0, 32768) and len(by[50]) == 5
    few = v.filter("vec_id IN (0, 8)")
    assert [(r.vec_id, r.rank) for r in topk.top_k(few.filter("vec_id = 0"), few).collect()] == [(8, 1)]
    assert topk.top_k(few.filter("vec_id = 77"), few).count() == 0
    same = spark.range(400).select(F.col("id").alias("vec_id"), F.array(F.lit(1.0), F.lit(2.0)).alias("v"))
    tied = topk.top_k(same.filter("vec_id % 50 = 0"), same, 3, batch=2)
    assert [r.vec_id for r in tied.filter("query_id = 0").orderBy("rank").collect()] == [1, 2, 3] and tied.count() == 24


def test_topk_bins_end_with_their_range(spark):
    # bins 39,063 wide, then 39: the last of the finer ones would reach 15 past the end of its range
    top = 20_000_000
    ends = [-(top + 1) + k * 39_063 for k in (600, 1000)]
    for end in ends:
        scores = [-top, end - 1, end, end + 1, end + 2, end + 3]
        v = spark.createDataFrame([(0, [1.0]), *[(k, [float(x)]) for k, x in enumerate(scores, 1)]], "vec_id long, v array<double>")
        got = topk.top_k(v.filter("vec_id = 0"), v, 5).orderBy("rank").collect()
        assert [(r.vec_id, r.score) for r in got] == [(6, end + 3), (5, end + 2), (4, end + 1), (3, end), (2, end - 1)]


def test_topk_of_huge_components(spark):
    draw = random.Random(3)
    for size in (1e6, 1e12, 1e17):  # floats, 64-bit integers, Python's own integers
        rows = [(k, [float(int(draw.uniform(-size, size))), float(draw.randint(-9, 9)), 1.0]) for k in range(60)]
        rows += [(60 + k, [rows[7][1][0], float(k), 1.0]) for k in range(5)]  # scores that differ in the last digits
        exact = {k: [int(x) for x in v] for k, v in rows}
        vectors = spark.createDataFrame(rows, "vec_id long, v array<double>").repartition(3)
        got = {}
        for r in topk.top_k(vectors.filter("vec_id % 10 = 7"), vectors, 5, batch=4).orderBy("query_id", "rank").collect():
            got.setdefault(r.query_id, []).append((r.vec_id, r.score))
        for q in range(7, 65, 10):
            every = sorted(((sum(a * b for a, b in zip(exact[q], x, strict=True)), k) for k, x in exact.items() if k != q), key=lambda t: (-t[0], t[1]))[:5]
            assert [k for k, _ in got[q]] == [k for _, k in every]
            assert [s for _, s in got[q]] == [max(min(s, 2**63 - 1), -(2**63)) for s, _ in every]


def test_topk_beyond_all_digits(spark):
    v = spark.createDataFrame([(k, [1e38, 1.0]) for k in range(4)] + [(9, [-1e38])], "vec_id long, v array<double>")
    assert [(r.vec_id, r.score) for r in topk.top_k(v.filter("vec_id = 0"), v).orderBy("rank").collect()] == [(1, 2**63 - 1), (2, 2**63 - 1), (3, 2**63 - 1), (9, -(2**63))]


def test_topk_ignores_other_columns(spark):
    rows = [(k, [float(k), 1.0], k, "x") for k in range(6)]
    v = spark.createDataFrame(rows, "vec_id long, v array<double>, rank int, query_id string")
    assert [r.vec_id for r in topk.top_k(v.filter("vec_id = 0"), v, 2).orderBy("rank").collect()] == [1, 2]


# ---- decontamination


def test_tiles_survive_reordering():
    item = list(range(40))
    doc = [99, *item[20:40], 98, *item[10:20], *item[0:10], 97]
    tiles = decontam.tile(item, doc)
    assert sum(n for _, _, n in tiles) == 40 and all(item[a : a + n] == doc[b : b + n] for a, b, n in tiles)
    assert decontam.tile([1, 1, 1, 1, 1], [1] * 50) and decontam.tile([], [1, 2]) == [] and decontam.tile([1, 2, 3], [1, 2, 3]) == []
    draw = random.Random(2)
    for _ in range(40):
        a, b = ([draw.randint(0, 2) for _ in range(draw.randint(0, 25))] for _ in range(2))
        used_a, used_b = set(), set()
        for x, y, n in decontam.tile(a, b):
            assert n >= 4 and a[x : x + n] == b[y : y + n]
            assert not used_a & set(range(x, x + n)) and not used_b & set(range(y, y + n))
            used_a |= set(range(x, x + n))
            used_b |= set(range(y, y + n))
        for x in range(len(a) - 3):  # no tile of the least length is left
            for y in range(len(b) - 3):
                assert a[x : x + 4] != b[y : y + 4] or set(range(x, x + 4)) & used_a or set(range(y, y + 4)) & used_b


def brute_tiles(item, doc, least=4):
    """Greedy string tiling by looking at all pairs of places after each tile."""
    free_a, free_b, out = [True] * len(item), [True] * len(doc), []
    while True:
        best = (0, 0, 0)
        for a in range(len(item)):
            for b in range(len(doc)):
                n = 0
                while a + n < len(item) and b + n < len(doc) and item[a + n] == doc[b + n] and free_a[a + n] and free_b[b + n]:
                    n += 1
                best = min(best, (-n, a, b))
        n, a, b = best
        if -n < least:
            return out
        free_a[a : a - n] = free_b[b : b - n] = [False] * -n
        out.append((a, b, -n))


def test_tiles_against_brute_force():
    draw = random.Random(9)
    for words in (1, 2, 3, 6):
        for _ in range(25):
            item, doc = ([draw.randrange(words) for _ in range(draw.randint(0, n))] for n in (24, 40))
            assert decontam.tile(item, doc) == brute_tiles(item, doc)


def test_one_word_over_and_over_is_quick():
    import time

    began = time.perf_counter()
    assert decontam.tile([1] * 100, [1] * 100_000) == [(0, 0, 100)]
    assert sum(n for _, _, n in decontam.tile([*[1] * 50, 2, *[1] * 50], [1] * 100_000)) == 100
    assert time.perf_counter() - began < 20


def brute_leaks(rows, items, least=4, share=0.5):
    """Tiles of whole texts, word by word, without seeds, filters or hashes."""
    words = lambda t: re.findall(r"[0-9a-z\x80-\xff]+", (t or "").lower().encode().decode("latin-1"))
    found = set()
    for doc_id, text in rows:
        for item_id, item in items:
            w, own = words(item), words(text)
            if len(w) >= least and len({tuple(w[k : k + least]) for k in range(len(w))} & {tuple(own[k : k + least]) for k in range(len(own))}):
                covered = sum(n for _, _, n in brute_tiles(w, own, least))
                if covered >= share * len(w):
                    found.add((doc_id, item_id, covered, len(w)))
    return found


def test_leaks_against_brute_force(spark):
    draw = random.Random(12)
    vocab = "red blue green tall small house river runs falls over under near".split()
    items = [(k, " ".join(draw.choice(vocab) for _ in range(draw.randint(2, 18)))) for k in range(8)] + [(90, "go " * 9), (91, None)]
    rows = []
    for k in range(40):
        text = [draw.choice(vocab) for _ in range(draw.randint(0, 25))]
        for _ in range(draw.randint(0, 2)):
            w = (draw.choice(items[:9])[1]).split()
            cut = draw.randint(0, len(w))
            text = [*w[cut:], *text, *w[:cut]] if draw.random() < 0.5 else [*text, *w]
        rows.append((k, " ".join(text)))
    rows += [(50, None), (51, ""), (52, "Go, go! GO go. " * 4)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    bench = spark.createDataFrame(items, "item_id long, text string")
    want = brute_leaks(rows, items)
    assert {(r.doc_id, r.item_id, r.covered, r.item_words) for r in decontam.contaminated(docs, bench).collect()} == want and len(want) > 8
    assert {(r.doc_id, r.item_id, r.covered, r.item_words) for r in decontam.contaminated(docs, bench, chunk_bytes=60).collect()} == want


def test_planted_leaks(spark):
    bench = [r.text for r in spark.read.parquet(f"{SF}/benchmark.parquet").orderBy("item_id").limit(3).collect()]
    words = bench[0].split()
    half = len(words) // 2
    rows = [(1, "x y z. " + bench[0].upper() + " w", None, None), (2, " ".join(words[half:] + ["zz"] + words[:half]), None, None), (3, " ".join(words[:5]), None, None), (4, None, None, None), (5, "", None, None), (None, bench[1], None, None), (7, "a " * 100_000 + bench[2], None, None), (7, "a " * 100_000 + bench[2], None, None), (8, "nothing of the sort", None, None)]
    items = spark.createDataFrame([(k, t) for k, t in enumerate(bench)] + [(9, None), (10, "a b"), (0, bench[0])], "item_id long, text string")
    docs = docs_of(spark, rows).withColumn("coverage", F.lit(1))
    got = {(r.doc_id, r.item_id): r.coverage for r in decontam.contaminated(docs, items).collect()}
    assert set(got) == {(1, 0), (2, 0), (None, 1), (7, 2)} and got[1, 0] == 1.0 and got[2, 0] > 0.9
    assert {r.doc_id for r in decontam.clean(docs, items).collect()} == {3, 4, 5, 8}
    small = {(r.doc_id, r.item_id) for r in decontam.contaminated(docs, items, chunk_bytes=200).collect()}
    assert small == set(got)
    assert decontam.contaminated(docs, items.limit(0)).count() == 0 and decontam.contaminated(docs.limit(0), items).count() == 0


# ---- quality


def test_quality_keeps_clean_and_rejects_bad(spark):
    labels = {r.doc_id: r for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    got = [r for r in quality.query(spark, SF).collect() if r.doc_id in labels]
    clean = [r.rejected for r in got if labels[r.doc_id].quality == 1 and labels[r.doc_id].toxic == 0]
    bad = [r.rejected for r in got if labels[r.doc_id].quality == 0 or labels[r.doc_id].toxic == 1]
    assert sum(clean) / len(clean) < 0.02 and sum(bad) / len(bad) > 0.9


def test_sparse_sites_shrink(spark):
    rows = [("big", "a", -4.0)] * 400 + [("bad", "a", 4.0)] * 200 + [("bad", "b", 4.0)] + [("new", "a", 4.0)]
    scored = spark.createDataFrame([(h, p, z, z) for h, p, z in rows], "h string, p string, z_low double, z_toxic double")
    got = {(r.host, r.path): r for r in quality.site_posteriors(scored, F.col("h"), F.col("p")).collect()}
    rate = got["new", "a"].low_global
    assert 0.3 < rate < 0.4 and got["bad", "a"].low_path > 0.9 and got["big", "a"].low_path < 0.05
    assert rate < got["new", "a"].low_path < got["bad", "b"].low_path < 0.985
    assert quality.site_posteriors(scored.limit(0), F.col("h"), F.col("p")).count() == 0


def brute_rates(rows, head):
    """Posterior of every document's path without the document, by plain loops; z is the log-odds of the text."""
    p = [1 / (1 + math.exp(-r[2][head])) for r in rows]
    rate = (sum(p) + 0.5) / (len(p) + 1)
    members = lambda k: [i for i, r in enumerate(rows) if (r[0], r[1])[: len(k)] == k]
    hosts, paths = {(r[0],) for r in rows}, {(r[0], r[1]) for r in rows}
    mean = {k: sum(p[i] for i in members(k)) / len(members(k)) for k in hosts | paths}

    def strength(children, parent):
        squares = sum(len(members(k)) * (mean[k] - parent(k)) ** 2 for k in children)
        noise = sum(parent(k) * (1 - parent(k)) for k in children)
        spread = (squares - noise) / len(rows)
        return min(max(noise / len(children) / spread - 1, 5), 500) if spread > 0 else 500

    s_host, s_path = strength(hosts, lambda k: rate), strength(paths, lambda k: mean[k[:1]])
    out = []
    for i, r in enumerate(rows):
        in_host, in_path = (sum(p[j] for j in members(k)) for k in ((r[0],), (r[0], r[1])))
        host = (s_host * rate + in_host - p[i]) / (s_host + len(members((r[0],))) - 1)
        out.append((rate, (s_path * host + in_path - p[i]) / (s_path + len(members((r[0], r[1]))) - 1)))
    return out


def test_rates_without_the_document_against_brute_force(spark):
    draw = random.Random(6)
    tilt = {h: draw.uniform(-2, 2) for h in "abcd"}
    rows = [(h, draw.choice([f"{h}1", f"{h}2", None]), (draw.gauss(tilt[h], 1), draw.gauss(-1, 1))) for h in draw.choices("abcd", k=90)] + [(None, None, (0.3, 0.1))]
    scored = spark.createDataFrame([(k, h, p, *z) for k, (h, p, z) in enumerate(rows)], "k int, h string, p string, z_low double, z_toxic double")
    sums, priors = quality.site_sums(scored, F.col("h"), F.col("p"))
    both = scored.join(sums, F.col("h").eqNullSafe(F.col("host")) & F.col("p").eqNullSafe(F.col("path")))
    for k, head in enumerate(quality.HEADS):
        got = {r.k: r.x for r in both.select("k", quality.posterior(head, priors[head], F.col(f"z_{head}"))[1].alias("x")).collect()}
        for i, (rate, x) in enumerate(brute_rates(rows, k)):
            assert abs(got[i] - x) < 1e-9 and abs(priors[head][0] - rate) < 1e-9


def test_quality_keeps_clashing_columns(spark):
    docs = docs_of(spark, [(1, "fine words", "en", "s"), (2, "other words", "de", "s")]).withColumns({c: F.lit(7) for c in ("n", "host", "path", "low_sum", "_h2", "host_n", "_n", "p_low")})
    labels = spark.createDataFrame([(1, 1, 0), (2, 0, 1)], "doc_id long, quality int, toxic int")
    got = quality.judge(docs, labels)
    assert [r.n + r.host + r.path + r.low_sum + r._h2 + r.host_n + r["_n"] for r in got.collect()] == [49, 49] and 0 <= got.first().p_low <= 1


def test_quality_odd_rows(spark):
    docs = docs_of(spark, [(1, None, None, None), (2, "", "en", "s"), (None, "fine words here", "en", "s"), (3, "### $$$ " * 20_000, "en", "s"), (3, "### $$$ " * 20_000, "en", "s")]).withColumn("p_low", F.lit(5))
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    got = quality.judge(docs, none).collect()
    assert len(got) == 5 and not any(r.rejected for r in got)
    labels = spark.createDataFrame([(2, 1, 0), (3, 0, None), (None, 0, 1)], "doc_id long, quality int, toxic int")
    assert quality.judge(docs, labels).count() == 5 and quality.judge(docs.limit(0), labels).count() == 0


# ---- quotes


def test_quotes_are_linked(spark):
    m = spark.createDataFrame([
        (1, 0, "user", "Hello there friend.\nHow are you?"), (1, 1, "assistant", "> How are you?\nFine, thanks."), (1, 2, "user", "On Monday Bob wrote:\n>> How are you?\n> Fine, thanks.\nGood."),
        (1, 3, "assistant", "> Hello there   FRIEND\nHi again"), (1, 4, "user", "ok"), (2, 0, "user", "> Good.\nwhat?"), (3, None, None, None), (3, None, None, None), (None, 0, "user", ""), (4, 0, "user", "> never said\n> twice\n\nmine"),
    ], "conv_id long, turn long, role string, text string").withColumn("position", F.lit("mine"))
    got = {(r.conv_id, r.turn): r for r in quotes.link(m).collect()}
    assert [got[1, k].reply_to for k in range(5)] == [None, 0, 1, 0, 3]
    assert [got[1, k].position for k in range(5)] == [1, 2, 3, 4, 5] and [got[1, k].thread for k in range(5)] == [0, 0, 0, 3, 3]
    assert got[1, 2].clean == "Good." and got[1, 2].n_quotes == 2 and got[1, 2].n_linked == 2
    assert (got[2, 0].reply_conv, got[2, 0].reply_to) == (1, 2)
    assert got[3, None].clean is None and got[None, 0].clean == "" and got[4, 0].reply_to is None and got[4, 0].n_quotes == 1 and got[4, 0].clean == "mine"
    assert quotes.link(m).count() == 10 and quotes.link(m.limit(0)).count() == 0
    assert quotes.render(quotes.link(m)).filter("conv_id = 1 AND position = 2").first().chat == "<|assistant|>\nFine, thanks.\n<|end|>"


def test_wrapped_and_partial_quotes_are_linked(spark):
    said = "The river rises every spring, and the old mill stands in water. Nobody has lived there for years! Still the wheel turns at night."
    wrapped = "> The river rises every\n> spring, and the old mill\n> stands in water. Nobody has\n> lived there for years! Still the wheel turns at night.\nReally?"
    m = spark.createDataFrame([
        (1, 0, "user", said), (1, 1, "user", "Something else was said here, at some length too."), (1, 2, "user", wrapped),
        (1, 3, "user", "> spring, and the old mill stands\nA part of a sentence."), (1, 4, "user", ">> NOBODY has lived\n>> there for years\n> Really?\nNo."),
        (1, 5, "user", "> the old mill was never in\nfive words that nobody wrote"), (2, 0, "user", "> has lived there for years! Still the wheel [...]\nfrom afar"), (3, 0, "user", "a\x02b\x03c"),
    ], "conv_id long, turn long, role string, text string")
    got = {(r.conv_id, r.turn): r for r in quotes.link(m).collect()}
    assert [got[1, k].reply_to for k in range(6)] == [None, 0, 0, 0, 2, 4] and [got[1, k].n_linked for k in range(6)] == [0, 0, 1, 1, 2, 0]
    assert (got[2, 0].reply_conv, got[2, 0].reply_to, got[2, 0].clean) == (1, 0, "from afar") and got[1, 2].clean == "Really?" and got[3, 0].clean


def test_a_hot_conversation_lies_in_many_ranges(spark):
    rows = [(1, t, "user", f"> this was said in turn {t - 7} of all\nthis was said in turn {t} of all" if t % 50 == 9 else f"this was said in turn {t} of all") for t in range(400)]
    rows += [(1, 20, "user", "again"), (2, 0, "user", "short"), (2, 1, "user", "one"), (None, 0, "user", "x"), (None, 5, "user", "y")]
    got = quotes.link(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").repartition(3)).collect()
    hot = sorted((r for r in got if r.conv_id == 1), key=lambda r: r.position)
    assert [r.position for r in hot] == list(range(1, 402)) and len(got) == 405
    starts = [0, *range(9, 400, 50)]
    for r in hot:
        assert r.thread == max(s for s in starts if s <= r.turn)
        assert r.reply_to == (None if r.turn == 0 else r.turn - 7 if r.turn % 50 == 9 else r.turn - 1)
    assert [(r.thread, r.turn) for r in hot] == sorted((r.thread, r.turn) for r in hot)
    assert {(r.conv_id, r.turn): r.position for r in got if r.conv_id != 1} == {(2, 0): 1, (2, 1): 2, (None, 0): 1, (None, 5): 2}


def test_a_long_message_is_parsed_in_one_pass(spark):
    long = "\n".join(f"> quoted line number {k}" if k % 3 else f"own line {k}" for k in range(20_000))
    m = spark.createDataFrame([(1, 0, "user", "quoted line number 1\nquoted line number 2"), (1, 1, "user", long), (1, 2, "user", "x " * 100_000)], "conv_id long, turn long, role string, text string")
    got = {r.turn: r for r in quotes.link(m).collect()}
    assert got[1].n_quotes == 6667 - (20_000 % 3 == 1) and got[1].reply_to == 0 and got[1].n_linked == 1


def test_replies_against_a_plain_search(spark):
    draw = random.Random(4)
    said, rows = {}, []
    for conv in range(12):
        for turn in range(draw.randint(1, 9)):
            own = f"line {draw.randint(0, 6)} of {conv}"
            quoted = [said[conv, t] for t in range(turn) if draw.random() < 0.3]
            rows.append((conv, turn, "user", "\n".join([*(f"> {q}" for q in quoted), own])))
            said[conv, turn] = own
    got = {(r.conv_id, r.turn): r for r in quotes.link(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    for conv, turn, _, text in rows:
        hits = [max((t for t in range(turn) if said[conv, t] == line[2:]), default=None) for line in text.split("\n") if line[0] == ">"]
        want = max((h for h in hits if h is not None), default=turn - 1 if turn else None)
        assert got[conv, turn].reply_to == want and got[conv, turn].clean == said[conv, turn]
        parent = got[conv, turn].reply_to
        assert parent is None or got[conv, parent].position < got[conv, turn].position
