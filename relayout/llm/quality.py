"""Quality classifier: document evidence under a hierarchy of site posteriors (empirical Bayes).

Two logistic models (low quality; toxic) read hashed features of a document: which words and word beginnings occur, and
its shape (symbols, capitals, list bars, repetition, length). They are fitted on a bounded sample of the labelled rows;
everything after that runs over all documents:

* the expected number of bad documents is summed by path and host (partial sums before the shuffle),
* moments give each level a Beta prior of its own strength: how much hosts differ from the global rate, and how much
  paths differ from their host, beyond what sampling alone would do. A host's posterior is shrunk towards the global
  rate, a path's towards its host's: sites with few documents stay near their parent,
* a document's log-odds are its own evidence plus the log-odds of its path against the global rate, where the document
  itself is left out of the sums of its path and host: its evidence counts once.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from relayout.llm.shared import BYTE_ONE, Rolling, blocks, distinct, materialise, mix, table, utf8, words_in_documents

BITS, TRAIN_ROWS, REJECT = 18, 10_000, 0.5
SHAPE = 12
#: Standard deviations between the observed and the expected number of bad documents that hold a feature.
CERTAIN = 3.0
HEADS = ("low", "toxic")
#: How many documents' worth of evidence a parent gives its child at least and at most.
STRENGTH = (5.0, 500.0)
#: Sites with more groups than this are joined by a shuffle, not broadcast.
BROADCAST_GROUPS = 200_000


def _table(*ranges: tuple[int, int]) -> np.ndarray:
    out = np.zeros(256, np.int64)
    for low, high in ranges:
        out[low : high + 1] = 1
    return out


_UPPER, _LOWER, _DIGIT, _BAR, _MARK, _LINE, _NONE = _table((65, 90)), _table((97, 122), (128, 255)), _table((48, 57)), _table((124, 124)), _table((33, 33)), _table((10, 10)), _table()
#: Printable ASCII but letters, digits, comma and full stop.
_SYMBOL = _table((33, 43), (45, 45), (47, 47), (58, 64), (91, 96), (123, 126))


def features(column: pa.Array, bits: int = BITS) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, np.ndarray]]:
    """By block: first and last document, (document, cell) pairs without repeats, and the shape of each document."""
    _, offsets = utf8(column)
    for a, b in blocks(offsets):
        raw, at = utf8(column.slice(a, b - a))
        data, low_at = utf8(pc.utf8_lower(column.slice(a, b - a).fill_null("")))
        letter = ((data >= 97) & (data <= 122)) | (data >= 128)
        starts, ends, of = words_in_documents(np.where(letter, data, np.uint8(32)), low_at)
        sums = Rolling(BYTE_ONE[data])
        whole, head = sums.of(starts, ends), sums.of(starts, np.minimum(starts + 5, ends))
        doc = np.repeat(np.arange(b - a), np.diff(of))
        shift = np.uint64(64 - bits)
        cells = np.concatenate([whole >> shift, (mix(head + np.uint64(7)) >> shift)])
        pairs = distinct((np.concatenate([doc, doc]).astype(np.uint64) << np.uint64(bits)) | cells)
        yield a, b, (pairs >> np.uint64(bits)).astype(np.int64), (pairs & np.uint64((1 << bits) - 1)).astype(np.int64), _shape(raw, at, whole, of)


def _shape(raw: np.ndarray, at: np.ndarray, words: np.ndarray, of: np.ndarray) -> np.ndarray:
    """Shares and logarithms between 0 and about 1."""

    def count(low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Sums of two tables over the bytes of each document, both in one pass."""
        sums = np.zeros(len(at), np.int64)
        full = np.flatnonzero(np.diff(at))
        if len(full):
            sums[full] = np.add.reduceat(low[raw] + (high[raw] << 32), at[full])
        return (sums[:-1] & 0xFFFFFFFF).astype(float), (sums[:-1] >> 32).astype(float)

    n_bytes, n_words = np.maximum(np.diff(at), 1).astype(float), np.maximum(np.diff(of), 1).astype(float)
    n, doc = len(at) - 1, np.repeat(np.arange(len(of) - 1), np.diff(of))
    (upper, lower), (symbol, bar), (mark, digit) = count(_UPPER, _LOWER), count(_SYMBOL, _BAR), count(_MARK, _DIGIT)
    line = count(_LINE, _NONE)[0]
    same = np.zeros(len(words), bool)
    same[1:] = (words[1:] == words[:-1]) & (doc[1:] == doc[:-1])
    pair = np.flatnonzero((raw[1:] == raw[:-1]) & (_SYMBOL[raw[1:]] > 0)) + 1
    twin = np.diff(np.searchsorted(pair, at)).astype(float)
    distinct_words = np.bincount((distinct(doc.astype(np.uint64) << np.uint64(40) | words >> np.uint64(24)) >> np.uint64(40)).astype(np.int64), minlength=n).astype(float)
    out = np.empty((n, SHAPE))
    out[:, 0] = 1.0
    out[:, 1] = np.minimum(1, 5 * symbol / n_bytes)
    out[:, 2] = upper / np.maximum(upper + lower, 1)
    out[:, 3] = np.minimum(1, 5 * bar / n_words)
    out[:, 4] = np.bincount(doc, same, n) / n_words
    out[:, 5] = 1 - distinct_words / n_words
    out[:, 6] = np.minimum(1, 5 * twin / n_words)
    out[:, 7] = np.minimum(1, 3 * mark / n_words)
    out[:, 8] = np.log1p(n_words) / 10
    out[:, 9] = digit / n_bytes
    out[:, 10] = np.minimum(1, n_bytes / n_words / 20)
    out[:, 11] = np.minimum(1, 20 * line / n_bytes)
    return out


@dataclass
class Heads:
    """Weights of the two models: cells x 2, shape x 2, and the log-odds that they had as a prior."""

    cells: np.ndarray
    shape: np.ndarray
    prior: np.ndarray
    bits: int

    def log_odds(self, doc: np.ndarray, cell: np.ndarray, shape: np.ndarray) -> np.ndarray:
        out = shape @ self.shape
        for k in range(out.shape[1]):
            out[:, k] += np.bincount(doc, self.cells[cell, k], len(out))
        return out


def fit(docs: DataFrame, labels: DataFrame, train_rows: int = TRAIN_ROWS, bits: int = BITS, rounds: int = 300) -> Heads:
    """Weights from a sample of about train_rows labelled documents, taken by a hash of the id. No labels: all zero."""
    labels = labels.filter("doc_id IS NOT NULL AND (quality IS NOT NULL OR toxic IS NOT NULL)").groupBy("doc_id").agg(F.min("quality").alias("quality"), F.max("toxic").alias("toxic"))
    n = labels.count()
    heads = Heads(np.zeros((1 << bits, 2), np.float32), np.zeros((SHAPE, 2)), np.zeros(2), bits)
    if not n:
        return heads
    share = min(1.0, train_rows / n)
    sample = labels.filter(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < int(share * (1 << 30)))
    rows = docs.filter("text IS NOT NULL").select("doc_id", "text").join(sample, "doc_id").select("text", "quality", "toxic")

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            quality, toxic = (batch.column(c).cast(pa.int32()).fill_null(-1).to_numpy(zero_copy_only=False) for c in ("quality", "toxic"))
            for a, b, doc, cell, shape in features(batch.column("text"), bits):
                cut = np.searchsorted(doc, np.arange(b - a + 1))
                yield pa.RecordBatch.from_arrays(
                    [pa.array([cell[i:j].astype("<u4").tobytes() for i, j in zip(cut[:-1], cut[1:], strict=True)], pa.binary()), pa.array([r.astype("<f4").tobytes() for r in shape], pa.binary()), pa.array(quality[a:b]), pa.array(toxic[a:b])],
                    ["cells", "shape", "quality", "toxic"],
                )

    got = rows.mapInArrow(read, "cells binary, shape binary, quality int, toxic int").toArrow()  # the bounded sample
    if not got.num_rows:
        return heads
    bytes_, cut = utf8(got.column("cells"))
    cell = np.frombuffer(bytes_.tobytes(), "<u4").astype(np.int64)
    doc = np.repeat(np.arange(got.num_rows), np.diff(cut) // 4)
    shape = np.frombuffer(utf8(got.column("shape"))[0].tobytes(), "<f4").reshape(-1, SHAPE).astype(float)
    for k, (name, bad) in enumerate((("quality", 0), ("toxic", 1))):
        y = got.column(name).to_numpy()
        known = y >= 0
        target = (y == bad).astype(float)
        if not known.any() or target[known].all() or not target[known].any():
            continue
        rate = target[known].mean()
        heads.prior[k] = np.log(rate / (1 - rate))
        # only cells that tell the classes apart for certain: the others would be fitted to noise
        held, bad_held = np.bincount(cell, known[doc], 1 << bits), np.bincount(cell, (known * target)[doc], 1 << bits)
        z = (bad_held - held * rate) / np.sqrt(np.maximum(held * rate * (1 - rate), 1e-9))
        told = ((np.abs(z) >= CERTAIN) & (held >= 3))[cell]
        heads.cells[:, k], heads.shape[:, k] = _logistic(doc[told], cell[told], shape, target, known.astype(float), 1 << bits, rounds)
    return heads


def _logistic(doc: np.ndarray, cell: np.ndarray, shape: np.ndarray, y: np.ndarray, weight: np.ndarray, n_cells: int, rounds: int, ridge: float = 0.5) -> tuple[np.ndarray, np.ndarray]:
    """Ridge-penalised logistic regression by whole-sample steps, each weight at its own pace (AdaGrad)."""
    w, s = np.zeros(n_cells), np.zeros(shape.shape[1])
    gw, gs = np.full(n_cells, 1e-6), np.full(shape.shape[1], 1e-6)
    for _ in range(rounds):
        z = shape @ s + np.bincount(doc, w[cell], len(y))
        r = weight * (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y)
        dw, ds = np.bincount(cell, r[doc], n_cells) + ridge * w, shape.T @ r
        gw += dw * dw
        gs += ds * ds
        w -= dw / np.sqrt(gw)
        s -= 1.5 * ds / np.sqrt(gs)
    return w, s


def evidence(docs: DataFrame, heads: Heads, keep_text: bool = True) -> DataFrame:
    """docs (or all but their text) with z_low and z_toxic, the log-odds by the text alone; a null text gets the prior."""
    shared = docs.sparkSession.sparkContext.broadcast(heads)  # 2 ** bits weights
    own = [c for c in docs.columns if c not in ("z_low", "z_toxic") and (keep_text or c != "text")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        h = shared.value
        for batch in batches:
            texts = batch.column("text")
            z = np.tile(h.prior, (batch.num_rows, 1))
            for a, b, doc, cell, shape in features(texts, h.bits):
                z[a:b] = h.log_odds(doc, cell, shape)
            z[texts.is_null().to_numpy(zero_copy_only=False)] = h.prior
            z = np.clip(z, -30, 30)
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in own), pa.array(z[:, 0]), pa.array(z[:, 1])], [*own, "z_low", "z_toxic"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.select(*own).schema.fields)
    return docs.select(*dict.fromkeys(["text", *own])).mapInArrow(run, f"{fields}, z_low double, z_toxic double")


def _probability(z: Column) -> Column:
    return 1 / (1 + F.exp(-z))


def _logit(p: Column) -> Column:
    p = F.greatest(F.least(p, F.lit(1 - 1e-6)), F.lit(1e-6))
    return F.log(p / (1 - p))


def site_sums(scored: DataFrame, host: Column, path: Column) -> tuple[DataFrame, dict[str, tuple[float, float, float]]]:
    """(host, path, n, host_n, <head>_sum, <head>_host_sum) of each path, and for each head the global rate and the
    strengths of the priors of hosts and of paths.

    scored has z_low and z_toxic. All levels are sums over all documents. A null host or path is a group of its own."""
    sums = [F.sum(_probability(F.col(f"z_{h}"))).alias(f"{h}_sum") for h in HEADS]
    paths = scored.groupBy(host.alias("host"), path.alias("path")).agg(F.count(F.lit(1)).alias("n"), *sums)
    hosts = paths.groupBy("host").agg(F.sum("n").alias("host_n"), *(F.sum(f"{h}_sum").alias(f"{h}_host_sum") for h in HEADS))
    total = hosts.agg(F.sum("host_n").alias("n"), F.count(F.lit(1)).alias("k"), *(F.sum(f"{h}_host_sum").alias(h) for h in HEADS)).first()
    both = paths.join(hosts, paths["host"].eqNullSafe(hosts["host"])).drop(hosts["host"])
    if not total["n"]:
        return both, {h: (0.5, STRENGTH[1], STRENGTH[1]) for h in HEADS}
    rates = {h: (total[h] + 0.5) / (total["n"] + 1) for h in HEADS}
    own = {h: F.col(f"{h}_host_sum") / F.col("host_n") for h in HEADS}
    of_hosts = hosts.agg(*(F.sum(F.col("host_n") * (own[h] - rates[h]) ** 2).alias(h) for h in HEADS)).first()
    of_paths = both.agg(
        F.count(F.lit(1)).alias("k"),
        *(F.sum(F.col("n") * (F.col(f"{h}_sum") / F.col("n") - own[h]) ** 2).alias(f"{h}_squares") for h in HEADS),
        *(F.sum(own[h] * (1 - own[h])).alias(f"{h}_noise") for h in HEADS),
    ).first()
    priors = {}
    for h, rate in rates.items():
        at_host = _moment(of_hosts[h], total["k"] * rate * (1 - rate), rate * (1 - rate), total["n"])
        mean = of_paths[f"{h}_noise"] / of_paths["k"]
        priors[h] = (rate, at_host, _moment(of_paths[f"{h}_squares"], of_paths[f"{h}_noise"], mean, total["n"]))
    return both, priors


def _moment(squares: float, noise: float, variance: float, n: float) -> float:
    """Strength of a Beta prior (documents' worth of evidence): squares is the sum of n (rate - parent's) ** 2 over
    children, noise what it would be if each had its parent's rate, variance rate (1 - rate)."""
    spread = (squares - noise) / n
    return min(max(variance / spread - 1, STRENGTH[0]), STRENGTH[1]) if spread > 0 else STRENGTH[1]


def posterior(h: str, prior: tuple[float, float, float], z: Column | None = None) -> tuple[Column, Column]:
    """Shrunk rates of a row's host and path, from columns of site_sums(); with z, the row's own probability is left out."""
    rate, at_host, at_path = prior
    left_out, one = (F.lit(0.0), F.lit(0)) if z is None else (_probability(z), F.lit(1))
    host = (F.lit(at_host * rate) + F.greatest(F.col(f"{h}_host_sum") - left_out, F.lit(0.0))) / (F.lit(at_host) + F.col("host_n") - one)
    path = (F.lit(at_path) * host + F.greatest(F.col(f"{h}_sum") - left_out, F.lit(0.0))) / (F.lit(at_path) + F.col("n") - one)
    return host, path


def site_posteriors(scored: DataFrame, host: Column, path: Column) -> DataFrame:
    """(host, path, n, <head>_host, <head>_path, <head>_global): shrunk rates of bad documents of each path."""
    sums, priors = site_sums(scored, host, path)
    for h, prior in priors.items():
        sums = sums.withColumns(dict(zip((f"{h}_host", f"{h}_path"), posterior(h, prior), strict=True)) | {f"{h}_global": F.lit(prior[0])})
    return sums.select("host", "path", "n", *(f"{h}_{x}" for h in HEADS for x in ("host", "path", "global")))


def judge(docs: DataFrame, labels: DataFrame, host: Column | None = None, path: Column | None = None, reject: float = REJECT, train_rows: int = TRAIN_ROWS, keep_text: bool = True) -> DataFrame:
    """docs (without the text, if it isn't to be kept) with p_low, p_toxic (probabilities), site_low, site_toxic (path posteriors) and rejected.

    host defaults to ``source``, path to (``source``, ``lang``). Rejected: a probability above ``reject``. A null text
    has its site's rate as evidence; an empty one that of its shape. Without labels all evidence is even and nothing is
    rejected. Repeated rows count each. Columns of these names are replaced, all others kept, whatever their names (but for
    z_low and z_toxic, which go).
    """
    host = F.col("source") if host is None else host
    path = F.col("lang") if path is None else path
    heads = fit(docs, labels, train_rows)
    added = ("p_low", "p_toxic", "site_low", "site_toxic", "rejected")
    own = [c for c in docs.columns if c not in added and (keep_text or c != "text")]
    # each text is read once: what it says is written down, then summed by site
    scored = evidence(docs.select("text", *(c for c in own if c != "text")).withColumns({"_quality_host": host, "_quality_path": path}), heads, keep_text)
    scored = materialise(scored, "evidence")
    sites, priors = site_sums(scored, F.col("_quality_host"), F.col("_quality_path"))
    sites = sites.withColumnsRenamed({c: f"_{c}" for c in sites.columns})
    if sites.limit(BROADCAST_GROUPS + 1).count() <= BROADCAST_GROUPS:
        sites = F.broadcast(sites)
    both = scored.withColumnsRenamed({c: f"_own_{c}" for c in own}).join(sites, F.col("_quality_host").eqNullSafe(F.col("_host")) & F.col("_quality_path").eqNullSafe(F.col("_path")), "left")
    both = both.withColumnsRenamed({"_n": "n", "_host_n": "host_n"} | {f"_{h}_{x}": f"{h}_{x}" for h in HEADS for x in ("sum", "host_sum")})
    for h, prior in priors.items():
        both = both.withColumn(f"_site_{h}", F.coalesce(posterior(h, prior)[1], F.lit(0.5)))
        alone = F.coalesce(posterior(h, prior, F.col(f"z_{h}"))[1], F.lit(0.5))
        both = both.withColumn(f"_p_{h}", _probability(F.col(f"z_{h}") + _logit(alone) - _logit(F.lit(prior[0]))))
    found = [F.col(f"_{x}").alias(x) for x in ("p_low", "p_toxic", "site_low", "site_toxic")]
    return both.select(*(F.col(f"_own_{c}").alias(c) for c in own), *found, ((F.col("_p_low") > reject) | (F.col("_p_toxic") > reject)).alias("rejected"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    found = judge(docs, table(spark, sf_dir, "labels"), keep_text=False)
    r = lambda c: F.round(c, 4).alias(c)
    return found.select("doc_id", r("p_low"), r("p_toxic"), r("site_low"), r("site_toxic"), "rejected")
