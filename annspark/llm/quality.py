"""Quality classifier: hashed word n-gram logistic regression, trained by follow-the-regularised-leader.

Features of a text: its words and pairs of neighbouring words, in two spellings hashed into ``BINS`` weights each:
as written, and by shape (runs of upper-case letters, lower-case letters, digits and of each other character made one), and whether a
word repeats the one before it. Each counts by its share of the text's features, so texts of any length compare. A text's score
is the sigmoid of the sparse dot product.

Training: proximal per-coordinate FTRL with L1 and L2 terms, the intercept one of the coordinates (without L1), over about ``each`` labelled documents of
each class and of at most ``LONGEST`` characters (documented bounds) chosen by a hash of the id, in ``rounds`` seeded passes in one task;
the scores are brought back from equal classes to the labels' own ratio by the intercept.

Edge cases: empty and null texts have no features and get the score of the intercept; with no
labelled document (an empty table) every score is 0.5; repeated rows get the same score, and of a repeated id one row is learned from; a document with two labels has the larger; null labels
and ids are not learned from; very long texts are scored whole, run by run of ``SLICE_BYTES``; further columns pass through ``score``, and one named quality_score is replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SLICE_BYTES, mix, span_hashes, table, text_slices, without, word_runs, word_spans
from .learning import bounded_ids, bounded_texts, fit_in_one_task, fold

BINS = 1 << 18
EACH = 2_500
THRESHOLD = 0.3
#: Value of the intercept's coordinate in every example.
INTERCEPT = 0.1
#: Class of each byte in a word's shape: letters by case, digits, and every other ASCII byte for itself.
_CLASS = np.array([1 if 65 <= c <= 90 else 2 if 97 <= c <= 122 or c >= 128 else 3 if 48 <= c <= 57 else c for c in range(256)], np.uint8)


def feature_runs(buf: np.ndarray, offsets: np.ndarray, limit: int = SLICE_BYTES) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(text, bins): the number of the text, and the bins of the features, of each word (row), a run of words at a time; the word before is carried from run to run."""
    starts, ends, first = word_spans(buf, offsets)
    opening = np.zeros(len(starts), bool)
    opening[first[:-1][np.diff(first) > 0]] = True
    carried = np.uint64(1), np.uint64(1)
    for i, j, lo, hi in word_runs(starts, ends, limit):
        part, begin, end = buf[lo:hi], starts[i:j] - lo, ends[i:j] - lo
        written = span_hashes(part, begin, end)
        kinds = _CLASS[part]
        lead = np.ones(len(part), bool)
        lead[1:] = kinds[1:] != kinds[:-1]
        lead[begin] = True
        runs = np.flatnonzero(lead)
        shape = span_hashes(kinds[runs], np.searchsorted(runs, begin), np.searchsorted(runs, end))
        # the word before; the first word of a text has a fixed one
        before, shape_before = (np.where(opening[i:j], np.uint64(1), np.append(last, x[:-1])) for x, last in ((written, carried[0]), (shape, carried[1])))
        carried = written[-1], shape[-1]
        again = (written == before).astype(np.uint64)
        columns = [mix(written + np.uint64(11)), mix(written + before * np.uint64(3) + np.uint64(13)), mix(shape + np.uint64(17)), mix(shape + shape_before * np.uint64(5) + np.uint64(19)), mix(again + np.uint64(23))]
        yield np.searchsorted(first, np.arange(i, j), "right") - 1, np.stack([(c & np.uint64(BINS - 1)).astype(np.int64) for c in columns], axis=1)


@dataclass
class Model:
    weights: np.ndarray
    intercept: float

    def score(self, buf: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        count = len(offsets) - 1
        total, sizes = np.zeros(count), np.zeros(count)
        for text, bins in feature_runs(buf, offsets):
            total += np.bincount(text, self.weights[bins].sum(axis=1, dtype=np.float64), count)
            sizes += np.bincount(text, minlength=count) * bins.shape[1]
        z = self.intercept + total / np.maximum(sizes, 1)
        return 1 / (1 + np.exp(-np.clip(z, -35, 35)))


def ftrl(examples: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, alpha: float = 2.0, beta: float = 0.1, l1: float = 2e-3, l2: float = 1e-3, rounds: int = 4, bins: int = BINS) -> tuple[np.ndarray, float]:
    """Weights and intercept after ``rounds`` passes over (bins, values) examples, one proximal step each. The intercept is a coordinate of value ``INTERCEPT`` without the L1 term."""
    z, n = np.zeros(bins + 1), np.zeros(bins + 1)
    penalty = np.append(np.full(bins, l1), 0.0)
    rng = np.random.default_rng(0)

    def weights(at):
        return np.where(np.abs(z[at]) <= penalty[at], 0.0, -(z[at] - np.sign(z[at]) * penalty[at]) / ((beta + np.sqrt(n[at])) / alpha + l2))

    for _ in range(rounds):
        for i in rng.permutation(len(examples)):
            at, x = np.append(examples[i][0], bins), np.append(examples[i][1], INTERCEPT)
            weight = weights(at)
            p = 1 / (1 + np.exp(-np.clip(weight @ x, -35, 35)))
            g = (p - labels[i]) * x
            z[at] += g - (np.sqrt(n[at] + g * g) - np.sqrt(n[at])) / alpha * weight
            n[at] += g * g
    w = weights(np.arange(bins + 1))
    return w[:-1].astype(np.float32), float(w[-1] * INTERCEPT)


def _fit(rows: pa.Table, prior_log_odds: float) -> Model:
    labels = rows.column("label").to_numpy().astype(float)
    examples: list = []
    for lo, hi, buf, offsets in text_slices(rows.column("text")):
        per: list[list[np.ndarray]] = [[] for _ in range(hi - lo)]
        for text, bins in feature_runs(buf, offsets):
            cuts = np.flatnonzero(np.diff(text)) + 1
            for at, part in zip(text[np.append(0, cuts)], np.split(bins, cuts)):
                per[at].append(part.ravel())
        for parts in per:
            own, counts = np.unique(np.concatenate([np.zeros(0, np.int64), *parts]), return_counts=True)
            examples.append((own, counts / max(1, counts.sum())))
    weights, bias = ftrl(examples, labels)
    seen = np.log((labels.sum() + 1) / (len(labels) - labels.sum() + 1))
    return Model(weights, bias + prior_log_odds - seen)


def train(docs: DataFrame, labels: DataFrame, label: str = "quality", each: int = EACH) -> Model | None:
    """A model of (doc_id, ``label``) over the texts of (doc_id, text): about ``each`` documents of each class."""
    known = labels.where(F.col("doc_id").isNotNull() & F.col(label).isin(0, 1)).groupBy("doc_id").agg(F.max(label).alias("label"))
    ids = bounded_ids(known, "doc_id", "label", each)
    counts = {r[0]: r[1] for r in known.groupBy("label").count().collect()}
    prior = np.log((counts.get(1, 0) + 1) / (counts.get(0, 0) + 1))
    # at most 4 * each ids, and as many rows
    return fit_in_one_task(bounded_texts(docs, ids, "label"), lambda rows: _fit(rows.sort_by([("label", "ascending"), ("text", "ascending")]), prior))


def score(docs: DataFrame, model: Model | None) -> DataFrame:
    """``docs`` with quality_score."""
    docs = without(docs, "quality_score")
    if model is None:
        return docs.withColumn("quality_score", F.lit(0.5))
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = [c.lower() for c in docs.columns].index("text")

    def scored(batches):
        for batch in batches:
            out = np.zeros(batch.num_rows)
            for lo, hi, buf, offsets in text_slices(batch.column(at)):
                out[lo:hi] = shared.value.score(buf, offsets)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out)], names=[*batch.schema.names, "quality_score"])

    return docs.mapInArrow(scored, f"{docs.schema.toDDL()}, quality_score double")


def query(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    held_out = F.coalesce(fold("doc_id", 5) == 0, F.lit(False))
    model = train(docs.where(~held_out), table(spark, sf_dir, "labels").where(~held_out))
    found = score(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), model)
    return found.select("doc_id", held_out.alias("held_out"), F.col("quality_score").alias("score"), (F.col("quality_score") >= THRESHOLD).cast("int").alias("predicted"))
