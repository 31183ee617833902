"""Substring dedup over words by a log-structured fingerprint index.

The index is a list of immutable runs. A run has, for each bucket of the fingerprint space, the sorted 64-bit hashes of
the anchor windows (relayout.llm.repeats) of one batch of documents: with the document's rid where it is the only holder
so far, without one where several hold it. Adding a batch merge-joins its sorted fingerprints with the runs, bucket by
bucket, and gives the batch's and, once, the historical document's hits. A new run is written each time; when a batch
comes and there are more than ``fanout`` runs, they are compacted into one first. Hits are then verified: their windows
are compared by 128-bit hashes of all words.

The index lives on: ``save`` writes runs and hits below a path, ``open`` reads them in another session, and ``repeated``
takes a batch and tells what of it stood before, reading the batch, and of the history only documents with hits.

A fingerprint that a third of all documents hold is one entry of a run.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relayout.llm.repeats import ASK, Search, answers, bucket_of, default_buckets, find, fingerprints, ranges_of, unnull, with_ranges
from relayout.llm.shared import keyed, materialise, mix, table, utf8

#: With three batches and one run at most, the third batch is merged with a compacted run.
WINDOW, GRAM, FANOUT, BATCHES = 20, 8, 1, 3
HIT, RUN = 0, 1
MERGED = "kind int, bucket int, rid long, body binary"


def _sorted(frame: pd.DataFrame, kind: int) -> np.ndarray:
    held = [np.frombuffer(x, ASK) for x in frame["body"][frame["kind"] == kind]]
    return np.sort(np.concatenate([np.zeros(0, ASK), *held]), order=["f", "rid"])


def _distinct(run: np.ndarray) -> np.ndarray:
    """One entry a fingerprint; without a rid if any entry has none, or if there are several."""
    if not len(run):
        return run
    run = np.sort(run, order=["f", "rid"])
    begin = np.flatnonzero(np.append(True, run["f"][1:] != run["f"][:-1]))
    n = np.diff(np.append(begin, len(run)))
    noted = np.maximum.reduceat(run["rid"] == 0, begin)
    out = run[begin].copy()
    out["rid"][noted | (n > 1)] = 0
    return out


def _merge(buckets: int, key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
    """One bucket: asks, notes and echoes of the batch (kinds 0, 1, 2) and the runs (3) in; the new run out, and hits, packed
    by the bucket of their document: rows follow the buckets, not the documents."""
    asks, notes, echoes, history = (_sorted(frame, k) for k in (0, 1, 2, 3))
    history = _distinct(history)
    f = asks["f"]
    twice = np.zeros(len(f), bool)
    same = f[1:] == f[:-1]
    twice[1:] |= same
    twice[:-1] |= same
    twice |= np.isin(f, notes["f"]) | np.isin(f, history["f"])
    # a single holder in the history hears of it once; the new run's entry without a rid says that it has
    woken = history[(history["rid"] != 0) & (np.isin(history["f"], f) | np.isin(history["f"], notes["f"]))]
    hits = np.concatenate([asks[twice], woken, echoes])
    owner = bucket_of(mix(np.ascontiguousarray(hits["rid"]).view(np.uint64)), buckets)
    order = np.argsort(owner, kind="stable")
    hits, owner = hits[order], owner[order]
    cut = np.flatnonzero(np.diff(owner, prepend=-1, append=-2))
    single, shared = asks[~twice], np.unique(np.concatenate([f[twice], notes["f"]]))
    fresh = np.zeros(len(shared), ASK)
    fresh["f"] = shared
    run = np.sort(np.concatenate([single, fresh]), order=["f", "rid"])
    rows = pd.DataFrame({"kind": HIT, "bucket": owner[cut[:-1]], "rid": 0, "body": [hits[a:b].tobytes() for a, b in zip(cut[:-1], cut[1:], strict=True)]})
    if len(run):
        rows = pd.concat([rows, pd.DataFrame({"kind": [RUN], "bucket": [key[0]], "rid": [0], "body": [run.tobytes()]})])
    return rows


def _by_document(frame: pd.DataFrame) -> pd.DataFrame:
    """One bucket of documents: (rid, body), all hit fingerprints of each."""
    rids, bodies = answers(np.concatenate([np.frombuffer(x, ASK) for x in frame["body"]]))
    return pd.DataFrame({"rid": rids, "body": bodies})


def by_document(packed: DataFrame) -> DataFrame:
    """(rid, body) of packed hits (bucket, body)."""
    return packed.groupBy("bucket").applyInPandas(_by_document, "rid long, body binary")


def _compact(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
    return pd.DataFrame({"kind": [RUN], "bucket": [key[0]], "rid": [0], "body": [_distinct(_sorted(frame, 3)).tobytes()]})


class SubstringIndex:
    """Fingerprints of all documents added so far. Batches come in the order that decides which copy is the earlier."""

    def __init__(self, spark: SparkSession, search: Search, buckets: int, fanout: int = FANOUT):
        self.spark, self.search, self.buckets, self.fanout = spark, search, buckets, fanout
        self.runs: list[DataFrame] = []
        self.hits: list[DataFrame] = []
        self.written: list[DataFrame] = []

    def add(self, docs: DataFrame) -> DataFrame:
        """docs as keyed() gives them; (rid, body) of hits, of this batch and of earlier ones."""
        if len(self.runs) > self.fanout:
            self.compact()
        rows = fingerprints(docs, self.search, self.buckets)
        for run in self.runs:
            rows = rows.union(run.select("bucket", F.lit(3).alias("kind"), "body"))
        buckets = self.buckets

        def merge(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
            return _merge(buckets, key, frame)

        merged = materialise(rows.groupBy("bucket").applyInPandas(merge, MERGED), "index")
        self.written.append(merged)
        self.runs.append(merged.filter(F.col("kind") == RUN))
        self.hits.append(merged.filter(F.col("kind") == HIT).select("bucket", "body"))
        return by_document(self.hits[-1])

    def all_hits(self) -> DataFrame:
        return by_document(reduce(DataFrame.union, self.hits))

    def compact(self) -> None:
        rows = reduce(DataFrame.union, self.runs).select("bucket", F.lit(3).alias("kind"), "body").groupBy("bucket").applyInPandas(_compact, MERGED)
        self.runs = [materialise(rows, "compacted")]
        self.written.append(self.runs[0])

    def repeated(self, docs: DataFrame, history: DataFrame) -> DataFrame:
        """Adds a batch, and gives (doc_id, rid, found) of its documents that hold a window which stands earlier, in the batch
        or in the history: what was added before, as keyed() gives it. Ids rise from batch to batch."""
        self.add(docs)
        hits = materialise(self.all_hits(), "hits")
        told = hits.select("rid").distinct()
        both = docs.select("doc_id", "rid", "text").unionByName(history.select("doc_id", "rid", "text").join(told, "rid", "left_semi"))
        found = find(both, hits, self.search, self.buckets)
        return found.join(docs.select("doc_id", "rid").distinct(), ["doc_id", "rid"], "left_semi")

    def save(self, path: str) -> None:
        """Runs, hits and parameters below path, which must not exist."""
        s = self.search
        about = json.dumps({"window": s.window, "gram": s.gram, "buckets": self.buckets, "fanout": self.fanout, "runs": len(self.runs)})
        for k, run in enumerate(self.runs):
            run.write.parquet(f"{path}/run{k}")
        if self.hits:
            reduce(DataFrame.union, self.hits).write.parquet(f"{path}/hits")
        self.spark.createDataFrame([(about,)], "about string").coalesce(1).write.text(f"{path}/about")  # last: it says that all is there

    @classmethod
    def open(cls, spark: SparkSession, path: str) -> SubstringIndex:
        about = json.loads(spark.read.text(f"{path}/about").first()[0])
        out = cls(spark, Search(words=True, window=about["window"], gram=about["gram"], later=True), about["buckets"], about["fanout"])
        out.runs = [spark.read.schema(MERGED).parquet(f"{path}/run{k}") for k in range(about["runs"])]
        out.hits = [spark.read.schema("bucket int, body binary").parquet(f"{path}/hits")] if about["runs"] else []
        return out


def in_batches(docs: DataFrame, n: int) -> list[DataFrame]:
    """docs (doc_id, ...) cut by doc_id into about equal batches, in order; null ids come first."""
    if n < 2:
        return [docs]
    cuts = docs.agg(F.percentile_approx("doc_id", [k / n for k in range(1, n)], 1000).alias("c")).first()["c"] or []
    cuts = sorted(set(cuts))
    out, low = [], None
    for high in [*cuts, None]:
        keep = F.lit(True) if low is None and high is None else F.col("doc_id") > low if high is None else F.col("doc_id") <= high if low is None else (F.col("doc_id") > low) & (F.col("doc_id") <= high)
        out.append(docs.filter(keep | F.col("doc_id").isNull() if low is None else keep))
        low = high
    return out


def one_of_equals(docs: DataFrame) -> DataFrame:
    """(doc_id, rid, text, copies) of docs as keyed() gives them: rows of one id and one text are one row, and how many
    there were. Texts that stand once don't move."""
    many = materialise(docs.groupBy("doc_id", "rid").agg(F.count(F.lit(1)).alias("copies")).filter("copies > 1"), "copies")
    once = docs.join(many, ["doc_id", "rid"], "left_anti").withColumn("copies", F.lit(1).cast("long"))
    several = docs.join(many, ["doc_id", "rid"]).groupBy("doc_id", "rid").agg(F.first("text").alias("text"), F.first("copies").alias("copies"))
    return once.unionByName(several)


def repeated_words(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, buckets: int | None = None, batches: int = BATCHES) -> DataFrame:
    """docs (doc_id, text) to (doc_id, rid, text, copies, found): the ranges of words under windows that start earlier
    too; rows of one id and one text are one row here."""
    search = Search(words=True, window=window, gram=gram, later=True)
    buckets = buckets or default_buckets(docs)
    index = SubstringIndex(docs.sparkSession, search, buckets)
    docs = one_of_equals(keyed(docs))
    for batch in in_batches(docs, batches):
        index.add(batch)
    return with_ranges(docs, find(docs, index.all_hits(), search, buckets, tuple(index.written)))


def kept(text: bytes, ranges: np.ndarray) -> tuple[int, bytes]:
    """How many words there are, and those outside the ranges joined by one space."""
    words = text.split()
    n, out, at = len(words), [], 0
    for f, t in ranges:
        out += words[at:f]
        at = int(t)
    return n, b" ".join(out + words[at:] if len(ranges) else words)


def digest(docs: DataFrame, window: int = WINDOW, **how: int) -> DataFrame:
    """(doc_id, n_words, n_removed, kept_sha256). A null text has no words. Earlier means a smaller doc_id (null is the
    smallest), then an earlier start. Repeated rows: of equal doc_id and text, one stands first and the others lose all
    their windows. No rows: no rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, at = utf8(batch.column("text"))
            found = [ranges_of(x) for x in batch.column("found").to_pylist()]
            done = [kept(data[a:b].tobytes(), r) for a, b, r in zip(at[:-1], at[1:], found, strict=True)]
            yield out_batch(batch.column("doc_id"), [n for n, _ in done], [int((r[:, 1] - r[:, 0]).sum()) for r in found], [hashlib.sha256(x).hexdigest() for _, x in done])
            more = batch.column("copies").to_numpy(zero_copy_only=False) - 1
            for k in np.flatnonzero(more):
                n, text = done[k][0], data[at[k] : at[k + 1]].tobytes()
                whole = np.array([[0, n]] if n >= window else np.zeros((0, 2), np.int64))
                sha = hashlib.sha256(kept(text, whole)[1]).hexdigest()
                for f in range(0, more[k], 10_000):
                    size = int(min(more[k] - f, 10_000))
                    yield out_batch(pa.array([batch.column("doc_id")[k].as_py()] * size, pa.int64()), [n] * size, [n if n >= window else 0] * size, [sha] * size)

    def out_batch(doc_id: pa.Array, n_words: list[int], n_removed: list[int], sha: list[str]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([doc_id, pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(sha, pa.string())], ["doc_id", "n_words", "n_removed", "kept_sha256"])

    out = repeated_words(docs.select("doc_id", "text"), window, **how).select("doc_id", "text", "copies", "found")
    out = out.mapInArrow(run, "doc_id long, n_words long, n_removed long, kept_sha256 string")
    return out.select(unnull("doc_id"), "n_words", "n_removed", "kept_sha256")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest(table(spark, sf_dir, "documents"))


#: Every window of every text, in the order that decides which is the first.
ORACLE = r"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
windows AS (SELECT doc_id, s, array_to_string(w[s : s + 19], ' ') AS key FROM (SELECT doc_id, w, unnest(range(1, len(w) - 18)) AS s FROM d)),
again AS (SELECT doc_id, s FROM (SELECT doc_id, s, row_number() OVER (PARTITION BY key ORDER BY doc_id, s) AS k FROM windows) WHERE k > 1),
gone AS (SELECT DISTINCT doc_id, i FROM (SELECT doc_id, unnest(range(s, s + 20)) AS i FROM again)),
words AS (SELECT doc_id, unnest(w) AS x, unnest(range(1, len(w) + 1)) AS i FROM d),
kept AS (SELECT words.doc_id, string_agg(x, ' ' ORDER BY words.i) AS x, count(*) AS n FROM words ANTI JOIN gone ON words.doc_id = gone.doc_id AND words.i = gone.i GROUP BY 1)
SELECT d.doc_id, len(w) AS n_words, len(w) - coalesce(kept.n, 0) AS n_removed, sha256(coalesce(kept.x, '')) AS kept_sha256 FROM d LEFT JOIN kept ON kept.doc_id = d.doc_id
"""
