"""Toxicity severity by cumulative-link ordinal regression over sparse word features.

Grades are ordered: 0 clean, 1 toxic, 2 toxic with several typical words.  One weight vector serves all
thresholds: P(grade <= j) = logistic(threshold_j - w . x), with x the presence of selected words.  The model is fitted on a
bounded sample of labelled rows per class (``SAMPLE``), weighted back to the table's class counts, and
scoring reads every document once.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textbytes as tb
from .runtime import broadcast_if_small, drop_table, materialise

#: Labelled rows per class that the fit may see.
SAMPLE = 8_000
#: Least likelihood-ratio statistic of a word against the label, and most words kept.
LEAST_G2, MOST_WORDS = 30.0, 4_000
#: Typical words a toxic text needs for the upper grade.
SEVERE_WORDS = 3
RIDGE = 0.05
REJECT = 0.5


@dataclass
class Model:
    """Sorted word hashes with weights, and ascending thresholds."""

    words: np.ndarray
    weights: np.ndarray
    thresholds: np.ndarray

    def __post_init__(self):
        self.sieve = np.zeros(1 << 18, dtype=bool)
        self.sieve[(self.words & np.uint64(0x3FFFF)).astype(np.int64)] = True

    def presence(self, words: tb.Words) -> tuple[np.ndarray, np.ndarray]:
        """(document, word number) pairs, each once."""
        h = words.hashes
        if not len(self.words) or not len(h):
            return np.empty(0, np.int64), np.empty(0, np.int64)
        at = np.flatnonzero(self.sieve[(h & np.uint64(0x3FFFF)).astype(np.int64)])
        k = np.searchsorted(self.words, h[at])
        k[k == len(self.words)] = 0
        ok = self.words[k] == h[at]
        pair = np.unique(words.doc[at[ok]] * len(self.words) + k[ok])
        return pair // len(self.words), pair % len(self.words)

    def probabilities(self, score: np.ndarray) -> np.ndarray:
        """Row per document, column per grade."""
        upto = 1 / (1 + np.exp(-(self.thresholds[None, :] - score[:, None])))
        ends = np.concatenate((np.zeros((len(score), 1)), upto, np.ones((len(score), 1))), axis=1)
        return np.diff(ends, axis=1)


def select_words(table: DataFrame, rate: float, base: float) -> np.ndarray:
    """Hashes of words that are in more toxic texts than chance allows, by a likelihood-ratio test on document counts.

    ``table``: (toxic, words).  Counts combine before their shuffle, and at most ``MOST_WORDS`` hashes reach the driver.  ``rate``: the
    toxic share of the sample, whose counts carry the evidence; ``base``: that of the table.
    """
    counts = table.select("toxic", F.explode("words").alias("word")).groupBy("word").agg(F.sum("toxic").alias("bad"), F.count("*").alias("n"))
    good = F.col("n") - F.col("bad")
    part = lambda k, share: F.when(k > 0, k * F.log(k / (F.col("n") * share))).otherwise(0.0)
    g2 = 2 * (part(F.col("bad"), rate) + part(good, 1 - rate))
    best = counts.where((F.col("bad") > F.col("n") * max(rate, base)) & (g2 >= LEAST_G2)).select("word", g2.alias("g2")).orderBy(F.desc("g2"), "word").limit(MOST_WORDS)
    return np.sort(np.array([r["word"] for r in best.collect()], dtype=np.int64).view(np.uint64))


def fit_ordinal(row: np.ndarray, col: np.ndarray, n_words: int, grade: np.ndarray, weight: np.ndarray, grades: int, rounds: int = 800, rate: float = 0.05) -> tuple[np.ndarray, np.ndarray]:
    """Weights and thresholds by weighted maximum likelihood with a ridge, by adaptive gradient steps.

    (row, col): the present words of each text; one pass over these pairs a step.
    """
    weight = weight / weight.sum()
    share = np.cumsum([weight[grade == j].sum() for j in range(grades)])[:-1].clip(1e-4, 1 - 1e-4)
    first = np.log(share / (1 - share))
    # thresholds stay ordered: each is the one before plus a positive gap
    p = np.concatenate((np.zeros(n_words), first[:1], np.log(np.diff(first).clip(1e-2))))
    m, v, k = np.zeros_like(p), np.zeros_like(p), n_words
    ridge = RIDGE / max(1, len(grade))
    for t in range(1, rounds + 1):
        gaps = np.exp(p[k + 1 :])
        cuts = p[k] + np.concatenate(([0.0], np.cumsum(gaps)))
        score = np.bincount(row, p[col], len(grade))
        edge = np.concatenate(([-np.inf], cuts, [np.inf]))
        with np.errstate(over="ignore"):
            high, low = 1 / (1 + np.exp(score - edge[grade + 1])), 1 / (1 + np.exp(score - edge[grade]))
        like = np.maximum(high - low, 1e-12)
        d_high, d_low = weight * high * (1 - high) / like, weight * low * (1 - low) / like
        g_cut = np.array([(d_low[grade == j + 1]).sum() - (d_high[grade == j]).sum() for j in range(grades - 1)])
        g = np.concatenate((np.bincount(col, (d_high - d_low)[row], k) + ridge * p[:k], [g_cut.sum()], gaps * np.cumsum(g_cut[::-1])[::-1][1:]))
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        p = p - rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-9)
    return p[:k], p[k] + np.concatenate(([0.0], np.cumsum(np.exp(p[k + 1 :]))))


def _distinct_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        toxic, doc_id = (batch.column(batch.schema.get_field_index(c)) for c in ("toxic", "doc_id"))
        for i, j, data, offsets in tb.slices(tb.text_column(batch)):
            words = tb.Words(data, offsets, tb.ALNUM)
            own = [np.unique(words.hashes[a:b]).view(np.int64) for a, b in zip(words.bounds[:-1], words.bounds[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([doc_id.slice(i, j - i), toxic.slice(i, j - i), pa.array(own, pa.list_(pa.int64()))], names=["doc_id", "toxic", "words"])


def _numbers(batches: Iterator[pa.RecordBatch], known: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Words of each text that are among the selected ones, by their number."""
    for batch in batches:
        words = batch.column(batch.schema.get_field_index("words"))
        flat = words.flatten().to_numpy(zero_copy_only=False).view(np.uint64)
        at = np.minimum(np.searchsorted(known, flat), len(known) - 1)
        hit = known[at] == flat
        ends = np.cumsum(np.concatenate(([0], hit)))[np.concatenate(([0], np.cumsum(pc.list_value_length(words).to_numpy(zero_copy_only=False))))]
        own = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(at[hit], pa.int32()))
        yield pa.RecordBatch.from_arrays([batch.column(batch.schema.get_field_index(c)) for c in ("doc_id", "toxic")] + [own], names=["doc_id", "toxic", "numbers"])


def fit_model(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Model:
    """A model from ``labels`` (doc_id, toxic 0/1); without any toxic label it rates everything clean."""
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where("doc_id is not null and toxic in (0, 1)").distinct()
    totals = {r["toxic"]: r["count"] for r in known.groupBy("toxic").count().collect()}
    none = Model(np.empty(0, np.uint64), np.empty(0), np.array([30.0, 40.0]))
    if not totals.get(1) or not totals.get(0):
        return none
    uniform = F.shiftrightunsigned(F.xxhash64("doc_id"), 11) / F.lit(float(1 << 53))
    drawn = known.where(uniform * F.when(F.col("toxic") == 1, totals[1]).otherwise(totals[0]) <= sample)
    drawn = materialise(drawn, "labelled")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(broadcast_if_small(drawn), "doc_id").select("doc_id", "toxic", "text")
    table = materialise(rows.mapInArrow(_distinct_words, "doc_id long, toxic int, words array<long>"), "words")
    counts = {r["toxic"]: r["count"] for r in table.groupBy("toxic").count().collect()}
    if not counts.get(0) or not counts.get(1):
        return none
    words = select_words(table, counts[1] / (counts[0] + counts[1]), totals[1] / (totals[0] + totals[1]))
    if not len(words):
        return none
    # a row per sampled text reaches the driver, with the numbers of its selected words only
    sample_ = table.mapInArrow(lambda it: _numbers(it, words), "doc_id long, toxic int, numbers array<int>").toArrow().sort_by([("doc_id", "ascending"), ("toxic", "ascending")])
    drop_table(table)
    toxic = sample_.column("toxic").to_numpy().astype(np.int64)
    own = sample_.column("numbers").combine_chunks()
    n_typical = pc.list_value_length(own).to_numpy(zero_copy_only=False).astype(np.int64)
    owner, at = np.repeat(np.arange(len(toxic)), n_typical), own.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
    weight = np.array([totals[0] / counts[0], totals[1] / counts[1]])[toxic]
    grade = np.where(toxic == 1, 1 + (n_typical >= SEVERE_WORDS), 0)
    weights, thresholds = fit_ordinal(owner, at, len(words), grade, weight, 3)
    return Model(words, weights, thresholds)


def _scores(words: tb.Words, model: Model) -> np.ndarray:
    doc, k = model.presence(words)
    return model.probabilities(np.bincount(doc, model.weights[k], len(words.offsets) - 1) if len(doc) else np.zeros(len(words.offsets) - 1))


def _rate(batches: Iterator[pa.RecordBatch], shared: Broadcast) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids = batch.column(batch.schema.get_field_index("doc_id"))
        for i, j, data, offsets in tb.slices(tb.text_column(batch)):
            p = _scores(tb.Words(data, offsets, tb.ALNUM), shared.value)
            yield pa.RecordBatch.from_arrays(
                [ids.slice(i, j - i), pa.array(p[:, 1]), pa.array(p[:, 2]), pa.array(p @ np.arange(3)), pa.array(p.argmax(axis=1), pa.int64()), pa.array(p[:, 1:].sum(axis=1) >= REJECT)],
                names=["doc_id", "p_mild", "p_severe", "severity", "grade", "toxic"],
            )


def rate_toxicity(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(doc_id, p_mild, p_severe, severity, grade, toxic) for each row of ``docs`` (doc_id, text, ...).

    ``severity`` is the expected grade, ``toxic`` says that grade 1 or more is at least as likely as not.  Null and blank texts have no
    words and get the base rates.  Null ids and repeated rows get a row each.  Labels with nulls are left out; contradicting
    labels of one document both count.  Texts of any length are read whole; extra columns are not read.
    """
    shared = docs.sparkSession.sparkContext.broadcast(fit_model(docs, labels))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(lambda it: _rate(it, shared), "doc_id long, p_mild double, p_severe double, severity double, grade long, toxic boolean")


def _harmless(batches: Iterator[pa.RecordBatch], shared: Broadcast) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i, j, data, offsets in tb.slices(tb.text_column(batch)):
            p = _scores(tb.Words(data, offsets, tb.ALNUM), shared.value)
            yield batch.slice(i, j - i).filter(pa.array(p[:, 1:].sum(axis=1) < REJECT))


def without_toxic(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of ``docs``, with all their columns, that are not rated toxic."""
    shared = docs.sparkSession.sparkContext.broadcast(fit_model(docs, labels))
    return docs.mapInArrow(lambda it: _harmless(it, shared), docs.schema)
