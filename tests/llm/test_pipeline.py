"""The pipeline: stages against their operators' brute-force versions, on planted cases; the entry survives without it."""

from __future__ import annotations

import random
import shutil
import subprocess
import sys
from pathlib import Path

import pytest

import corpus_pipeline as cp
from tests.llm.test_repeats import brute_join

SF = "/root/testdata/sf0.001"
ROOT = Path(__file__).resolve().parents[2]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


def texts(df):
    return {r.doc_id: r.text for r in df.collect()}


def test_stages_keep_the_columns_and_the_clean(spark, docs):
    labels = {r.doc_id: r for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    good = cp.keep_good(spark, docs, SF)
    assert good.columns == docs.columns and dict(good.dtypes) == dict(docs.dtypes)
    kept = texts(good)
    clean = [k for k, r in labels.items() if r.quality == 1 and r.toxic == 0]
    assert sum(k in kept for k in clean) >= 0.97 * len(clean) and all(docs_text == texts(docs)[k] for k, docs_text in kept.items())


def test_one_of_near_copies_stays(spark, docs):
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    least = {doc_id for doc_id, _, component, _ in brute_join(rows, 5, 80, 100) if component == doc_id}
    got = cp.keep_one_of_near_copies(spark, docs, SF)
    assert set(texts(got)) == least and got.columns == docs.columns
    assert cp.keep_one_of_near_copies(spark, docs.union(docs), SF).count() == len(least)


def test_repeated_passages_are_cut(spark, docs):
    passage = "".join(f"Wört {k} des Abschnitts. " for k in range(40))
    rows = [(1, "Eins " + passage + "ende", "de", "s", 1), (2, passage + "zwei", None, None, None), (3, "nichts davon", "de", "s", 12), (4, None, None, None, None), (None, "", None, None, 0)]
    got = {r.doc_id: r for r in cp.cut_repeated_passages(spark, spark.createDataFrame(rows, docs.schema), SF).collect()}
    assert got[1].text == "Eins ende" and got[1].n_chars == 9 and got[2].text == "zwei" and got[3].text == "nichts davon" and got[3].n_chars == 12
    assert got[4].text is None and got[None].text == ""


def test_passages_of_over_fifty_words_are_cut_and_shorter_ones_stay(spark, docs):
    draw = random.Random(7)
    clean = [r.text for r in docs.filter("length(text) > 2000").orderBy("doc_id").limit(12).collect()]
    words = [w for r in docs.filter("length(text) > 500").orderBy("doc_id").limit(40).collect() for w in r.text.split()]
    rows, want = [], {}
    for k in range(6):
        passage = " ".join(draw.choice(words) for _ in range(51))
        for m in (0, 1):
            before, after = f"Anfang {k} {m}. " + clean[2 * k + m][:300], f" Ende {m} {k}." + clean[2 * k + m][300:600]
            rows.append((2 * k + m, before + "|" + passage + "|" + after, "de", "s", 1))
            want[2 * k + m] = (before, after)
    short = " ".join(draw.choice(words) for _ in range(12))  # fewer bytes than a passage has
    rows += [(100 + m, f"Vorn {m} {short} hinten {m}", "de", "s", 1) for m in (0, 1)]
    got = texts(cp.cut_repeated_passages(spark, spark.createDataFrame(rows, docs.schema), SF))
    assert all(len(got[k]) <= len(a) + len(b) and got[k].startswith(a[:9]) and got[k].endswith(b[-9:]) for k, (a, b) in want.items())
    assert all(short in got[100 + m] for m in (0, 1))


def test_leaks_go_and_the_rest_is_packed(spark, docs):
    item = spark.read.parquet(f"{SF}/benchmark.parquet").first().text
    rows = [(1, "Vorher " + item, "de", "s", 9), (2, "Nur Text.", "de", "s", 9)]
    left = cp.drop_leaked(spark, spark.createDataFrame(rows, docs.schema), SF)
    assert texts(left) == {2: "Nur Text."} and left.columns == docs.columns
    assert [(r.doc_id, r.start, r.offset) for r in cp.pack_sequences(spark, left, SF).collect()][0][:2] == (2, 0)


def test_texts_that_share_an_id_are_judged_alone(spark, docs):
    item = spark.read.parquet(f"{SF}/benchmark.parquet").first().text
    rows = [(k, t, "de", "s", 9) for k, t in ((None, "Vorher " + item), (None, "Nur Text."), (7, item), (7, "Auch nur Text."), (None, None))]
    left = cp.drop_leaked(spark, spark.createDataFrame(rows, docs.schema), SF)
    assert sorted((str(r.doc_id), str(r.text)) for r in left.collect()) == [("7", "Auch nur Text."), ("None", "None"), ("None", "Nur Text.")] and left.columns == docs.columns
    near = [[" ".join(f"{name}{k}" for k in range(80)) + f" ende{n}" for n in range(3)] for name in "abc"]
    rows = [(k, t, "de", "s", 9) for ids, group in zip(([None] * 3, [7] * 3, [7, None, 7]), near, strict=True) for k, t in zip(ids, group, strict=True)]
    kept = [(r.doc_id, r.text[0]) for r in cp.keep_one_of_near_copies(spark, spark.createDataFrame(rows, docs.schema), SF).collect()]
    assert sorted(kept, key=str) == [(7, "b"), (None, "a"), (None, "c")]


def test_run_is_the_stages_in_order(spark, docs):
    out = cp.run(spark, SF)
    step = docs
    for _, stage in cp.STAGES[:-1]:
        step = stage(spark, step, SF)
    kept = {r.doc_id for r in step.select("doc_id").collect()}
    rows = out.collect()
    assert {r.doc_id for r in rows} == kept and len(cp.STAGES) == 5
    assert sum(r.length for r in rows) == sum({r.doc_id: r.doc_tokens for r in rows}.values())


def test_empty_documents_pass_all_stages(spark, docs):
    step = docs.limit(0)
    for _, stage in cp.STAGES:
        step = stage(spark, step, SF)
        assert step.count() == 0


def test_entry_without_the_operators(tmp_path):
    shutil.copytree(ROOT / "relayout", tmp_path / "relayout", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(ROOT / "__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert q and not any(k.startswith('op') for k in q) and 'pipeline' not in q and set(o) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path)}, check=True)
