"""Language identification in two steps: the family, then one-versus-one linear SVMs within it.

Features: the text with ASCII letters lower-cased and everything but letters (ASCII letters and non-ASCII bytes) made a
space, its byte n-grams of the ``ORDERS`` hashed into ``BINS`` counts, square roots taken and scaled to length 1. Whole texts
count. Both steps are linear support vector machines (hinge loss, primal sub-gradient steps with averaging): one family
against the rest, then one per pair of languages of a family, whose votes decide (ties: the larger sum
of margins). Families are those of ``FAMILIES``; a language that stands in none is a family of its own.

Training: about ``each`` documents of every language, of at most ``LONGEST`` characters (documented bounds), chosen by a hash of the id,
fitted in one task. Scoring is a narrow map.

Edge cases: a text that is null or has no letter is ``und`` with score 0; with one learned language
every other text is that language; with none (an empty table) all are ``und``; ties of families go to the first by name, ties of votes and margins to the first language by code; repeated rows
get the same answer, and of a repeated id one row is learned from; ids and languages may be null (such rows are scored and not learned from); very long texts count whole, worked through
in pieces of ``SLICE_BYTES``; further columns pass through ``predict``, and columns named lang_pred or lang_score are replaced.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SLICE_BYTES, free, table, text_slices, without
from .learning import bounded_ids, bounded_texts, fit_in_one_task, fold

BINS = 1 << 13
ORDERS = (2, 3)
EACH = 400
#: Texts that are counted at once: BINS counts for each.
BLOCK_TEXTS = 256
#: Branches of languages by their ISO 639-1 codes.
FAMILIES = {
    "germanic": ("af", "da", "de", "en", "fy", "is", "lb", "nb", "nl", "nn", "no", "sv", "yi"),
    "romance": ("ca", "es", "fr", "gl", "it", "oc", "pt", "rm", "ro"),
    "slavic": ("be", "bg", "bs", "cs", "hr", "mk", "pl", "ru", "sk", "sl", "sr", "uk"),
    "uralic": ("et", "fi", "hu"),
    "turkic": ("az", "kk", "tr", "uz"),
    "indic": ("bn", "gu", "hi", "mr", "ne", "pa", "ur"),
}
UNDECIDED = "und"
_FOLD = np.array([c + 32 if 65 <= c <= 90 else c if 97 <= c <= 122 or c >= 128 else 32 for c in range(256)], np.uint8)


def family(lang: str) -> str:
    return next((name for name, members in FAMILIES.items() if lang in members), f"only {lang}")


def features(buf: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """A row of ``BINS`` values of length 1 (or 0) for each text."""
    count = len(offsets) - 1
    out = np.zeros(count * BINS)
    for order in ORDERS:
        # pieces of n-gram starts; each piece sees the bytes that its last n-grams reach
        for lo in range(0, max(0, len(buf) - order + 1), SLICE_BYTES):
            hi = min(len(buf) - order + 1, lo + SLICE_BYTES)
            folded = _FOLD[buf[lo : hi + order - 1]].astype(np.uint32)
            code = np.zeros(hi - lo, np.uint32)
            for k in range(order):
                code = code * np.uint32(0x01000193) + folded[k : k + hi - lo] + np.uint32(order)
            code = (code ^ (code >> np.uint32(15))) * np.uint32(0x2C1B3C6D)
            owner = np.repeat(np.arange(count), np.diff(np.clip(offsets, lo, hi + order - 1)))
            inside = owner[: hi - lo] == owner[order - 1 :]
            out += np.bincount((owner[: hi - lo] * BINS + (code >> np.uint32(19)).astype(np.int64))[inside], minlength=len(out))
    out = np.sqrt(out.reshape(count, BINS))
    return (out / np.maximum(np.linalg.norm(out, axis=1, keepdims=True), 1e-9)).astype(np.float32)


def linear_svm(x: np.ndarray, y: np.ndarray, reg: float = 1e-4, rounds: int = 40, batch: int = 64) -> np.ndarray:
    """Weights and, last, the bias of a linear SVM for labels +1 and -1, classes weighed alike."""
    rng = np.random.default_rng(0)
    x = np.hstack([x, np.ones((len(x), 1), np.float32)])
    weight = np.where(y > 0, 0.5 / max(1, (y > 0).sum()), 0.5 / max(1, (y < 0).sum())) * len(y)
    w, mean, step = np.zeros(x.shape[1]), np.zeros(x.shape[1]), 0
    for _ in range(rounds):
        order = rng.permutation(len(x))
        for lo in range(0, len(x), batch):
            some, step = order[lo : lo + batch], step + 1
            wrong = some[y[some] * (x[some] @ w) < 1]
            rate = 1 / (reg * (step + 1000))
            w = (1 - rate * reg) * w + rate / len(some) * ((weight[wrong] * y[wrong]) @ x[wrong])
            mean += (w - mean) / step
    return mean


@dataclass
class Model:
    families: list[str]
    of_family: np.ndarray  # BINS + 1 x families
    members: dict[str, list[str]]
    pairs: dict[str, np.ndarray]  # BINS + 1 x pairs of members

    @classmethod
    def fit(cls, rows: pa.Table) -> Model:
        langs = np.array(rows.column("lang").to_pylist())
        x = np.vstack([part for _, part in _feature_blocks(rows.column("text"))])
        kind = np.array([family(v) for v in langs])
        names = sorted(set(kind))
        one = np.stack([linear_svm(x, np.where(kind == f, 1, -1)) for f in names], axis=1)
        members = {f: sorted(set(langs[kind == f])) for f in names}
        pairs = {}
        for f, inside in members.items():
            duels = [linear_svm(x[some], np.where(langs[some] == a, 1, -1)) for a, b in combinations(inside, 2) for some in [np.flatnonzero((langs == a) | (langs == b))]]
            pairs[f] = np.stack(duels, axis=1) if duels else np.zeros((x.shape[1] + 1, 0))
        return cls(names, one, members, pairs)

    def predict(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        margins = x @ self.of_family[:-1] + self.of_family[-1]
        best = margins.argmax(axis=1)
        lead = np.full(len(x), 2.0)
        if len(self.families) > 1:
            top = np.sort(margins, axis=1)
            lead = top[:, -1] - top[:, -2]
        langs, scores = np.empty(len(x), object), np.empty(len(x))
        for k, f in enumerate(self.families):
            some = np.flatnonzero(best == k)
            inside = self.members[f]
            if not len(some):
                continue
            duel = x[some] @ self.pairs[f][:-1] + self.pairs[f][-1]
            votes, sums = np.zeros((len(some), len(inside))), np.zeros((len(some), len(inside)))
            least = np.full((len(some), len(inside)), np.inf)
            for c, (a, b) in enumerate(combinations(range(len(inside)), 2)):
                for who, m in ((a, duel[:, c]), (b, -duel[:, c])):
                    votes[:, who] += m > 0
                    sums[:, who] += m
                    least[:, who] = np.minimum(least[:, who], 2 * m)
            winner = (votes + 1e-3 * np.tanh(sums)).argmax(axis=1)
            langs[some] = np.array(inside, object)[winner]
            scores[some] = 1 / (1 + np.exp(-2 * np.minimum(lead[some], least[np.arange(len(some)), winner])))
        return langs, scores


def _feature_blocks(column):
    for lo, hi, buf, offsets in text_slices(column):
        for at in range(0, hi - lo, BLOCK_TEXTS):
            ends = offsets[at : at + BLOCK_TEXTS + 1]
            yield lo + at, features(buf[ends[0] : ends[-1]], ends - ends[0])


def train(docs: DataFrame, each: int = EACH) -> Model | None:
    """A model of the rows of (doc_id, text, lang) given: about ``each`` documents of each language are looked at."""
    ids = bounded_ids(docs.where("doc_id IS NOT NULL AND lang IS NOT NULL").select("doc_id", "lang"), "doc_id", "lang", each)
    # at most 2 * each ids for a language, and as many rows
    return fit_in_one_task(bounded_texts(docs.where(F.col("text").rlike(r"\p{L}")), ids, "lang").withColumnRenamed("label", "lang"), lambda rows: Model.fit(rows.sort_by([("lang", "ascending"), ("text", "ascending")])))


def predict(docs: DataFrame, model: Model | None) -> DataFrame:
    """``docs`` with lang_pred and lang_score."""
    docs = without(docs, "lang_pred", "lang_score")
    if model is None:
        return docs.withColumns({"lang_pred": F.lit(UNDECIDED), "lang_score": F.lit(0.0)})
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = [c.lower() for c in docs.columns].index("text")

    def scored(batches):
        for batch in batches:
            langs, scores = np.full(batch.num_rows, UNDECIDED, object), np.zeros(batch.num_rows)
            for lo, x in _feature_blocks(batch.column(at)):
                langs[lo : lo + len(x)], scores[lo : lo + len(x)] = shared.value.predict(x)
            blank = ~batch.column(batch.num_columns - 1).to_numpy(zero_copy_only=False).astype(bool)
            langs[blank], scores[blank] = UNDECIDED, 0.0
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(langs, pa.string()), pa.array(scores)], names=[*batch.schema.names[:-1], "lang_pred", "lang_score"])

    lettered = docs.withColumn(free(docs, "_lettered"), F.coalesce(F.col("text").rlike(r"\p{L}"), F.lit(False)))
    return lettered.mapInArrow(scored, f"{docs.schema.toDDL()}, lang_pred string, lang_score double")


def query(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    held_out = F.coalesce(fold("doc_id", 4) == 2, F.lit(False))
    model = train(docs.where(~held_out))
    found = predict(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), model)
    return found.select("doc_id", held_out.alias("held_out"), "lang_pred", F.col("lang_score").alias("score"))
