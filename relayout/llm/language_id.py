"""Language identification: script ranges, then Viterbi over the scores of single words.

Text is lower-cased and cut into words, the runs of letters and marks. A word's script (that of its first letter)
narrows the candidates to the languages that use it in the training rows. A word's score under a language is the sum of
the log-likelihood ratios of its letter pairs, triples and of the whole word, looked up by hash in one table for each
language. Viterbi then labels the words of a document, where each change of language costs a penalty, so short foreign
words stay in their surroundings and real passages in another language become spans of their own. The document's
language is the one with the most letters.

The tables are counted on a bounded sample of the labelled rows (``train_rows`` for each language, chosen by a hash of
the id): counting runs on the executors and only ``2 ** bits`` sums for each language reach the driver.
"""

from __future__ import annotations

import unicodedata
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from relayout.llm.shared import Rolling, mix, run_ends, table

BITS, TRAIN_ROWS, PENALTY, NO_LANGUAGE = 18, 1500, 6.0, "und"

#: First and last code point of the blocks of each script.
SCRIPTS = (
    ("latin", 0x41, 0x24F),
    ("greek", 0x370, 0x3FF),
    ("cyrillic", 0x400, 0x52F),
    ("armenian", 0x530, 0x58F),
    ("hebrew", 0x590, 0x5FF),
    ("arabic", 0x600, 0x77F),
    ("devanagari", 0x900, 0x97F),
    ("bengali", 0x980, 0x9FF),
    ("tamil", 0xB80, 0xBFF),
    ("thai", 0xE00, 0xE7F),
    ("georgian", 0x10A0, 0x10FF),
    ("hangul", 0x1100, 0x11FF),
    ("latin", 0x1E00, 0x1EFF),
    ("greek", 0x1F00, 0x1FFF),
    ("kana", 0x3040, 0x30FF),
    ("han", 0x3400, 0x9FFF),
    ("hangul", 0xAC00, 0xD7AF),
    ("han", 0x20000, 0x3134F),
)
NAMES = tuple(dict.fromkeys(name for name, _, _ in SCRIPTS))
OTHER = len(NAMES)


@lru_cache(1)
def character_tables() -> tuple[np.ndarray, np.ndarray]:
    """For each code point: letter (1) or mark (2) or neither, and its script."""
    kinds = {"L": 1, "M": 2}
    kind = np.frombuffer(bytes(kinds.get(unicodedata.category(chr(c))[0], 0) for c in range(0x110000)), np.uint8)
    script = np.full(0x110000, OTHER, np.uint8)
    for name, low, high in SCRIPTS:
        script[low : high + 1] = NAMES.index(name)
    return kind, script


@dataclass
class Words:
    """The words of a block of texts and the hashes of their parts."""

    doc: np.ndarray  # of each word
    start: np.ndarray  # in the text, in characters
    end: np.ndarray
    script: np.ndarray
    cells: np.ndarray  # table cells of all parts
    first_cell: np.ndarray  # of each word
    has_letter: np.ndarray  # of each document


def read_words(texts: list[str | None], bits: int) -> Words:
    kind, script = character_tables()
    # a text is lower-cased letter by letter where lower-casing changes its length, so that spans keep their places
    low = [(x if len(x) == len(t) else "".join(c.lower() if len(c.lower()) == 1 else c for c in t)) for t in (t or "" for t in texts) for x in [t.lower()]]
    n = np.array([len(t) + 1 for t in low], np.int64)
    base = np.concatenate([[0], np.cumsum(n)])
    joined = "\n".join([*low, ""]).encode("utf-32-le", "surrogatepass")
    codes = np.frombuffer(joined, np.uint32)
    part = kind[codes]
    inside = np.zeros(len(codes) + 2, bool)
    inside[1:-1] = part > 0
    edges = np.flatnonzero(inside[1:] != inside[:-1])
    start, end = edges[::2], edges[1::2]
    doc = np.searchsorted(base, start, "right") - 1
    letters = np.concatenate([[0], np.cumsum(part == 1)])
    has_letter = letters[base[1:] - 1] > letters[base[:-1]] if len(texts) else np.zeros(0, bool)

    # pairs and triples, where a blank stands before and after each word; the pair that ends at a position
    c = np.where(part > 0, codes, 32).astype(np.uint64)
    before = np.concatenate([[np.uint64(32)], c[:-1]])
    before2 = np.concatenate([[np.uint64(32)], before[:-1]])
    pair = before << np.uint64(21) | c
    triple = np.where(before != 32, before2 << np.uint64(42) | pair, pair)
    shift = np.uint64(64 - bits)
    at_pair, at_triple = mix(pair + np.uint64(1 << 63)) >> shift, mix(triple) >> shift
    # a word's parts end at its letters and at the blank behind it
    length = end - start + 1
    first = np.concatenate([[0], np.cumsum(length)])[:-1] if len(length) else np.zeros(0, np.int64)
    where = np.repeat(start - first, length) + np.arange(int(length.sum()))
    whole = Rolling(mix(c)).of(start, end) >> shift  # all letters of the word
    cells = np.empty((len(where), 2), np.uint32)
    cells[:, 0], cells[:, 1] = at_pair[where], at_triple[where]
    return Words(doc, start - base[doc], end - base[doc], script[codes[start]] if len(start) else np.zeros(0, np.uint8), np.concatenate([cells.ravel(), whole.astype(np.uint32)]), first * 2, has_letter)


@dataclass
class Model:
    languages: list[str]
    table: np.ndarray  # cells x languages
    scripts: np.ndarray  # scripts x languages: used there
    bits: int
    penalty: float = PENALTY

    def word_scores(self, w: Words) -> np.ndarray:
        n = len(w.start)
        if not n:
            return np.zeros((0, len(self.languages)), np.float32)
        parts = self.table[w.cells[: len(w.cells) - n]]
        scores = np.add.reduceat(parts, w.first_cell, axis=0) + 2 * self.table[w.cells[len(w.cells) - n :]]
        known = self.scripts[w.script]
        out = np.where(known, scores, -30.0)
        out[~known.any(axis=1)] = 0.0
        return out.astype(np.float32)

    def label(self, scores: np.ndarray, doc: np.ndarray, n_docs: int) -> np.ndarray:
        """The best language of each word: Viterbi over all documents of a block in step, the longest first."""
        count = np.bincount(doc, minlength=n_docs)
        first = np.concatenate([[0], np.cumsum(count)])[:-1]
        order = np.argsort(-count, kind="stable")
        order = order[count[order] > 0]
        labels = np.zeros(len(scores), np.int8 if len(self.languages) < 127 else np.int32)
        if not len(order):
            return labels
        count, first = count[order], first[order]
        live = np.searchsorted(-count, -np.arange(count[0]), "left")  # documents with more words than the step
        best = scores[first].copy()
        switched = np.empty(scores.shape, bool)  # by word: the path into this label came from another
        leader = np.empty(len(scores), labels.dtype)  # by word: the best label before it
        for t in range(1, int(count[0])):
            n = live[t]
            at = first[:n] + t
            now = best[:n]
            top = now.argmax(axis=1)
            via = now[np.arange(n), top] - np.float32(self.penalty)
            leader[at] = top
            moved = now < via[:, None]
            switched[at] = moved
            best[:n] = np.where(moved, via[:, None], now) + scores[at]
        state = best.argmax(axis=1)
        for t in range(int(count[0]) - 1, -1, -1):
            n = live[t]
            at = first[:n] + t
            labels[at] = state[:n]
            if t:
                state[:n] = np.where(switched[at, state[:n]], leader[at], state[:n])
        return labels

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray, list[list[tuple[int, int, str]]]]:
        w = read_words(texts, self.bits)
        if not self.languages:
            return [NO_LANGUAGE] * len(texts), np.zeros(len(texts)), [[] for _ in texts]
        labels, size = self.label(self.word_scores(w), w.doc, len(texts)), w.end - w.start
        share = np.zeros((len(texts), len(self.languages)))
        np.add.at(share, (w.doc, labels), size)
        total = share.sum(axis=1)
        best = share.argmax(axis=1)
        score = np.where(total > 0, share[np.arange(len(texts)), best] / np.maximum(total, 1), 0.0)
        names = [self.languages[b] if ok and self.languages else NO_LANGUAGE for b, ok in zip(best, w.has_letter, strict=True)]
        score[~w.has_letter] = 0.0
        new = np.ones(len(labels), bool)
        if len(labels) > 1:
            new[1:] = (labels[1:] != labels[:-1]) | (w.doc[1:] != w.doc[:-1])
        runs: list[list[tuple[int, int, str]]] = [[] for _ in texts]
        begin = np.flatnonzero(new)
        for a, b in zip(begin, run_ends(begin, len(labels)), strict=True):
            runs[w.doc[a]].append((int(w.start[a]), int(w.end[b - 1]), self.languages[labels[a]]))
        return names, score, runs


def pieces(texts: list[str | None], size: int = 1_000_000) -> Iterator[tuple[int, int]]:
    first, held = 0, 0
    for k, t in enumerate(texts):
        if held and held + len(t or "") > size:
            yield first, k
            first, held = k, 0
        held += len(t or "")
    if first < len(texts):
        yield first, len(texts)


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(5)) == 0, F.lit(False))


def train(rows: DataFrame, bits: int = BITS, train_rows: int = TRAIN_ROWS, penalty: float = PENALTY, min_share: float = 0.01) -> Model:
    """rows: (doc_id, text, lang); rows without lang or text teach nothing. No rows: a model without languages."""
    rows = rows.filter("lang IS NOT NULL AND text IS NOT NULL").select("lang", "text", F.xxhash64("doc_id", "lang").alias("h"))
    sizes = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    languages = sorted(sizes)
    if not languages:
        return Model([], np.zeros((1 << bits, 0), np.float32), np.zeros((OTHER + 1, 0), bool), bits, penalty)
    rate = F.coalesce(F.create_map(*(x for k in languages for x in (F.lit(k), F.lit(train_rows / sizes[k]))))[F.col("lang")], F.lit(0.0))
    sample = rows.filter((F.pmod("h", F.lit(1 << 30)) / float(1 << 30)) < rate)
    n = 1 << bits

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = np.zeros((len(languages), n + OTHER + 1), np.int64)
        number = {k: i for i, k in enumerate(languages)}
        for batch in batches:
            texts, langs = batch.column("text").to_pylist(), batch.column("lang").to_pylist()
            for a, b in pieces(texts):
                for lang in set(langs[a:b]):
                    w = read_words([t for t, k in zip(texts[a:b], langs[a:b], strict=True) if k == lang], bits)
                    sums[number[lang], :n] += np.bincount(w.cells, minlength=n)
                    sums[number[lang], n:] += np.bincount(w.script, minlength=OTHER + 1)
        for k, lang in enumerate(languages):
            cell = np.flatnonzero(sums[k])
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(cell)), pa.array(cell.astype(np.int32)), pa.array(sums[k][cell])], ["lang", "cell", "n"])

    counted = sample.select("lang", "text").mapInArrow(count, "lang string, cell int, n long").groupBy("lang", "cell").agg(F.sum("n").alias("n"))
    sums = np.zeros((len(languages), n + OTHER + 1))
    for k, c, v in counted.toPandas().itertuples(index=False):  # 2 ** bits rows for each language at most
        sums[languages.index(k), c] = v
    cells, scripts = sums[:, :n].T, sums[:, n:].T
    p = (cells + 0.1) / (cells + 0.1).sum(axis=0)
    logs = np.log(p)
    logs -= logs.mean(axis=1, keepdims=True)
    used = scripts >= min_share * np.maximum(scripts.sum(axis=0), 1)
    return Model(languages, np.clip(logs, -6, 6).astype(np.float32), used & (scripts > 0), bits, penalty)


def identify(docs: DataFrame, model: Model, spans: bool = False) -> DataFrame:
    """docs with lang_pred, score and, if asked for, spans (start, end in characters, lang); such columns are replaced.

    ``und`` with score 0 for a null text, one without a letter, or a model without languages; score is the share of the
    letters in lang_pred. Whole texts of any length are read; repeated rows are each labelled.
    """
    own = [c for c in docs.columns if c not in ("lang_pred", "score", "spans")]
    shared = docs.sparkSession.sparkContext.broadcast(model)  # 2 ** bits numbers for each language
    kind = "lang_pred string, score double" + ", spans array<struct<start:int,end:int,lang:string>>" * spans

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            texts = batch.column("text").to_pylist()
            for a, b in pieces(texts):
                names, score, runs = m.predict(texts[a:b])
                out = [pa.array(names, pa.string()), pa.array(score, pa.float64())]
                if spans:
                    out.append(pa.array([[{"start": s, "end": e, "lang": k} for s, e, k in r] for r in runs], pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("lang", pa.string())]))))
                kept = batch.slice(a, b - a).select(own_kept)
                yield pa.RecordBatch.from_arrays([*kept.columns, *out], [*own_kept, "lang_pred", "score", *["spans"] * spans])

    slim = docs.select(*own)
    own_kept = list(own)
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in slim.schema.fields)
    return slim.mapInArrow(run, f"{fields}, {kind}")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = train(docs.filter(~held_out(F.col("doc_id"))).select("doc_id", "text", "lang"))
    found = identify(docs.select("doc_id", "text"), model)
    return found.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
