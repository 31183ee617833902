"""A corpus pipeline of five training-data operators; each stage's table is written and read again by the next.

Quality classifier, n-gram Jaccard join, suffix-array dedup, benchmark decontamination, packing. All but the last return
the columns of ``documents``; a stage works on all that the one before kept. A stage that cuts text sets n_chars anew.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relayout.llm import decontam, jaccard, packing, quality, suffix_dedup
from relayout.llm.repeats import ranges_of
from relayout.llm.shared import identity, keyed, materialise, table, utf8

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: Bytes of a repeated passage: fifty words of three letters and a blank. Words of running text are longer than that, so a
#: passage of over fifty words has more bytes, and the stage finds it; op2's own query keeps its 400.
PASSAGE_WORDS, WORD_BYTES = 50, 4
PASSAGE = PASSAGE_WORDS * WORD_BYTES


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier doesn't reject."""
    judged = quality.judge(docs.select(*COLUMNS), table(spark, sf_dir, "labels"))
    return judged.filter("NOT rejected").select(*COLUMNS)


def keep_one_of_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each component of linked documents the one with the smallest doc_id, of equal ids the smallest rid; of repeated
    rows one."""
    found = jaccard.join(keyed(docs)).filter("component_id = doc_id AND component_rid = rid").select(F.col("doc_id").alias("_doc"), F.col("rid").alias("_rid")).distinct()
    number, rid = identity()
    rows = docs.select(*COLUMNS, number.alias("_doc"), rid.alias("_rid"))
    kept = rows.join(found, ["_doc", "_rid"], "left_semi")
    # repeated rows (one id, one text) are one document
    return kept.dropDuplicates(["_doc", "_rid"]).select(*COLUMNS)


def cut_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the bytes under strings of PASSAGE bytes that stand anywhere else; a cut character goes with its
    bytes."""
    found = suffix_dedup.repeated_ranges(keyed(docs), PASSAGE)
    number, rid = identity()
    own = docs.select(*COLUMNS, number.alias("_doc"), rid.alias("_rid"))
    joined = own.join(found.select(F.col("doc_id").alias("_doc"), F.col("rid").alias("_rid"), "found"), ["_doc", "_rid"], "left")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, at = utf8(batch.column("text"))
            texts, sizes = batch.column("text").to_pylist(), batch.column("n_chars").to_pylist()
            for k, ranges in enumerate(batch.column("found").to_pylist()):
                if ranges:
                    texts[k] = suffix_dedup.kept(data[at[k] : at[k + 1]].tobytes(), ranges_of(ranges)).decode("utf-8", "ignore")
                    sizes[k] = len(texts[k])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(texts, pa.string()), batch.column("lang"), batch.column("source"), pa.array(sizes, pa.int64())], list(COLUMNS))

    return joined.select(*COLUMNS, "found").mapInArrow(cut, docs.select(*COLUMNS).schema)


def drop_leaked(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that don't contain a benchmark item."""
    return decontam.clean(docs.select(*COLUMNS), table(spark, sf_dir, "benchmark"))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of training sequences (relayout.llm.packing)."""
    return packing.pack(docs, *packing.tokenizer_paths())


STAGES = [
    ("quality classifier", keep_good),
    ("n-gram Jaccard join", keep_one_of_near_copies),
    ("suffix-array dedup", cut_repeated_passages),
    ("benchmark decontamination", drop_leaked),
    ("packing", pack_sequences),
]

#: Not SQL: a fitted classifier, byte ranges and tokens. Tested against brute-force versions in tests/llm.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = materialise(docs, f"stage{k}")
    return docs
