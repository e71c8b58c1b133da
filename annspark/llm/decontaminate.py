"""Benchmark decontamination: rare n-gram seeds, then Smith-Waterman alignment of words.

Words are runs of ASCII letters and digits and of non-ASCII characters, lower-cased. Every n-gram of a
benchmark item is counted over all documents (documents that hold it), and every one that a document holds is a
seed. Around a rare seed, held by at most ``rare`` of the documents, document and item are
aligned at once. Around hot seeds only, the words that the item shares with the place (repeats counted) are
counted first: an alignment has no more equal words than that, so places that cannot reach ``min_score`` are
passed over without loss. ``rare`` decides how much is aligned and never what is found. Local alignment, +2 for an equal word, -1 for another word or a
gap. The score is the alignment's points over twice the item's words: 1 for a verbatim copy. Copies that
were edited or paraphrased word by word keep most of it. A pair is reported from ``min_score`` up.

Items of fewer than ``min_words`` words are too short for a score to be evidence: they match where a document holds all their words in a row, and only there.

The benchmark is read in blocks of at most about ``block_items`` items and ``BLOCK_CHARS`` characters (one item may be longer), each a broadcast of bounded size
and one pass over the documents; the documents are never shuffled. Equal items are searched once and reported by their smallest id. Words are
hashed run by run of ``SLICE_BYTES``, so what a very long text holds is a few numbers a word. An item of m words is aligned with a window of 4 m words, row by row: memory is linear in m, time quadratic.

Edge cases: null and empty texts and items without words hold and match nothing; a copy with no n-gram intact has no seed and is not found; repeated documents are reported alike;
of tied alignments of one pair the one that ends first is reported; a document that holds several items is reported with each; empty tables give no rows; further columns
of the documents pass through ``clean``, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import free, mix, table, text_slices, word_hashes, word_spans

NGRAM = 3
MIN_WORDS = 6
MIN_SCORE = 0.45
RARE = 1e-3
BLOCK_ITEMS = 5_000
BLOCK_CHARS = 8 << 20
#: Rows of the alignment that are worked on at once.
CELLS = 1 << 20
BREAKS = np.array([not (chr(i).isascii() and chr(i).isalnum()) and i < 128 for i in range(256)])


def _words(buf, offsets):
    starts, ends, first = word_spans(buf, offsets, BREAKS)
    return word_hashes(buf, starts, ends), first


def _ngrams(words: np.ndarray, first: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash and start of every n-gram that stays inside its text."""
    if len(words) < n:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    total = np.zeros(len(words) - n + 1, np.uint64)
    for k in range(n):
        total = mix(total * np.uint64(3) + words[k : k + len(total)])
    inside = np.ones(len(total), bool)
    for k in range(1, n):
        cuts = first[1:-1] - k
        inside[cuts[(cuts >= 0) & (cuts < len(total))]] = False
    at = np.flatnonzero(inside)
    return total[at], at


@dataclass
class Items:
    """A block of benchmark items: words, the index from n-grams to (item, position), and each item's bag of words."""

    ids: np.ndarray
    words: list[np.ndarray]
    grams: np.ndarray  # sorted distinct
    items: np.ndarray  # CSR over grams: the item, and where the n-gram first stands in it
    places: np.ndarray
    bounds: np.ndarray
    n: int
    hot: np.ndarray  # for each of grams: whether more documents hold it than is rare
    vocabulary: np.ndarray  # sorted distinct words
    bag: np.ndarray  # sorted item * len(vocabulary) + word, and how often the item has it
    bag_counts: np.ndarray
    short: dict[int, dict[int, int]]  # number of words -> hash of them all -> item id

    @classmethod
    def of(cls, rows, n: int, min_words: int) -> Items | None:
        by_words: dict[bytes, tuple[int, np.ndarray]] = {}
        short: dict[int, dict[int, int]] = {}
        for item_id, text in sorted(rows, key=lambda r: r[0]):
            raw = np.frombuffer((text or "").lower().encode(), np.uint8)
            words, first = _words(raw, np.array([0, len(raw)]))
            if len(words) >= max(n, min_words):
                by_words.setdefault(words.tobytes(), (item_id, words))
            elif len(words):
                short.setdefault(len(words), {}).setdefault(int(_ngrams(words, first, len(words))[0][0]), item_id)
        if not by_words:
            none = np.zeros(0, np.int64)
            return cls(none, [], none.astype(np.uint64), none, none, np.zeros(1, np.int64), n, none.astype(bool), none.astype(np.uint64), none, none, short) if short else None
        ids = np.array([i for i, _ in by_words.values()], np.int64)
        words = [w for _, w in by_words.values()]
        entries = [(g, k, p) for k, w in enumerate(words) for g, p in zip(*_ngrams(w, np.array([0, len(w)]), n))]
        gram, item, place = (np.array(x, t) for x, t in zip(zip(*entries), (np.uint64, np.int64, np.int64)))
        order = np.lexsort((place, item, gram))
        gram, item, place = gram[order], item[order], place[order]
        new = np.ones(len(gram), bool)
        new[1:] = (gram[1:] != gram[:-1]) | (item[1:] != item[:-1])
        gram, item, place = gram[new], item[new], place[new]
        grams, at = np.unique(gram, return_index=True)
        vocabulary, word = np.unique(np.concatenate(words), return_inverse=True)
        bag, counts = np.unique(np.repeat(np.arange(len(words)), [len(w) for w in words]) * len(vocabulary) + word, return_counts=True)
        return cls(ids, words, grams, item, place, np.append(at, len(gram)), n, np.zeros(len(grams), bool), vocabulary, bag, counts, short)

    def hits(self, words: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(index of the n-gram, word position) wherever the texts hold an n-gram of an item."""
        got, at = _ngrams(words, first, self.n)
        if not len(self.grams):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        sieve = np.zeros(1 << 20, bool)
        sieve[self.grams & np.uint64((1 << 20) - 1)] = True
        may = np.flatnonzero(sieve[got & np.uint64((1 << 20) - 1)])
        got, at = got[may], at[may]
        index = np.minimum(np.searchsorted(self.grams, got), len(self.grams) - 1)
        same = self.grams[index] == got
        return index[same], at[same]

    def verbatim(self, words: np.ndarray, first: np.ndarray) -> Iterator[tuple[int, int, int]]:
        """(text, item id, end word in the text) of the first place where a text holds a short item."""
        for length, known in self.short.items():
            got, at = _ngrams(words, first, length)
            seen = set()
            for k in np.flatnonzero(np.isin(got, np.array(list(known), np.uint64))):
                text = int(np.searchsorted(first, at[k], "right")) - 1
                item = known[int(got[k])]
                if (text, item) not in seen:
                    seen.add((text, item))
                    yield text, item, int(at[k] + length - first[text])

    def seeds(self, held_by: np.ndarray, limit: float) -> Items:
        """Only the n-grams that documents hold; those that more than ``limit`` documents hold are hot."""
        held = held_by > 0
        sizes = np.diff(self.bounds)
        entry = np.repeat(held, sizes)
        bounds = np.append(0, np.cumsum(sizes[held]))
        return replace(self, grams=self.grams[held], items=self.items[entry], places=self.places[entry], bounds=bounds, hot=held_by[held] > limit)

    def shared(self, words: np.ndarray, item: np.ndarray, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
        """How many words, repeats counted, each item shares with its stretch of the texts' words."""
        size = len(self.vocabulary)
        at = np.minimum(np.searchsorted(self.vocabulary, words), size - 1)
        known = np.flatnonzero(self.vocabulary[at] == words)
        at = at[known]
        start, stop = np.searchsorted(known, start), np.searchsorted(known, stop)
        out, upto = np.zeros(len(item), np.int64), np.cumsum(stop - start)
        lo = 0
        while lo < len(item):
            hi = max(lo + 1, int(np.searchsorted(upto, (upto[lo - 1] if lo else 0) + CELLS, "right")))
            n = (stop - start)[lo:hi]
            word = at[np.repeat(start[lo:hi], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)]
            key, times = np.unique(np.repeat(np.arange(hi - lo), n) * size + word, return_counts=True)
            row = key // size
            wanted = item[lo:hi][row] * size + key % size
            found = np.minimum(np.searchsorted(self.bag, wanted), len(self.bag) - 1)
            both = np.where(self.bag[found] == wanted, np.minimum(times, self.bag_counts[found]), 0)
            out[lo:hi] = np.bincount(row, both, hi - lo)
            lo = hi
        return out

    def windows(self, gram: np.ndarray, at: np.ndarray, first: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, ...]:
        """Distinct (text, item, block, whether a rare seed lies there) around the hits; blocks are one item length apart."""
        reps = self.bounds[gram + 1] - self.bounds[gram]
        upto = np.cumsum(reps)
        span = int(np.diff(first).max()) // int(lengths.min()) + 2
        keys, lo = [], 0
        while lo < len(gram):
            # a hot n-gram of many items is spread over its items piece by piece
            hi = max(lo + 1, int(np.searchsorted(upto, (upto[lo - 1] if lo else 0) + CELLS, "right")))
            n = reps[lo:hi]
            entry = np.repeat(self.bounds[gram[lo:hi]], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            place, item = np.repeat(at[lo:hi], n), self.items[entry]
            text = np.searchsorted(first, place, "right") - 1
            block = (place - self.places[entry] - first[text]) // lengths[item]
            keys.append(np.unique((((text * len(self.ids) + item) * span) + block + 1) * 2 + np.repeat(self.hot[gram[lo:hi]], n)))
            lo = hi
        key = np.unique(np.concatenate(keys))
        new = np.append(True, key[1:] // 2 != key[:-1] // 2)  # rare sorts before hot
        key = key[new]
        where = key // 2
        return where // span // len(self.ids), where // span % len(self.ids), where % span - 1, key % 2 == 0


def align(items: np.ndarray, texts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Best local score and where it ends (a column of ``texts``), for each row pair of word hashes; 0 is padding."""
    count, width = texts.shape
    row = np.zeros((count, width + 1), np.int32)
    best, end = np.zeros(count, np.int32), np.zeros(count, np.int64)
    ramp = np.arange(width + 1, dtype=np.int32)
    for i in range(items.shape[1]):
        word = items[:, i : i + 1]
        gain = np.where((texts == word) & (word != 0), np.int32(2), np.int32(-1))
        new = np.maximum(row - 1, 0)
        new[:, 1:] = np.maximum(new[:, 1:], row[:, :-1] + gain)
        # a gap in the text costs 1 a word: the best earlier column, less the distance
        row = np.maximum.accumulate(new + ramp, axis=1) - ramp
        at = row.argmax(axis=1)
        top = row[np.arange(count), at]
        better = top > best
        best[better], end[better] = top[better], at[better]
    return best, end


def _matches(index: Items, words, first, min_score):
    """(text, item id, score, end word in the text) of the texts of one slice that hold an item."""
    found = _aligned(index, words, first, min_score)
    short = list(index.verbatim(words, first)) if index.short else []
    if short:
        text, item, end = (np.array(x, np.int64) for x in zip(*short))
        found = [np.concatenate(pair) for pair in zip(found, (text, item, np.ones(len(text)), end))]
    return found


def _aligned(index: Items, words, first, min_score):
    gram, at = index.hits(words, first)
    if not len(gram):
        return [np.zeros(0, t) for t in (np.int64, np.int64, float, np.int64)]
    lengths = np.array([len(w) for w in index.words])
    # windows of three item lengths, whose starts are one item length apart
    text, item, block, rare = index.windows(gram, at, first, lengths)
    start = np.clip(first[text] + (block - 1) * lengths[item], first[text], first[text + 1])
    stop = np.minimum(first[text] + (block + 3) * lengths[item], first[text + 1])
    may = rare.copy()
    hot = np.flatnonzero(~rare)
    may[hot] = 2 * index.shared(words, item[hot], start[hot], stop[hot]) / (2 * lengths[item[hot]]) >= min_score
    text, item, start, stop = text[may], item[may], start[may], stop[may]
    score, end = np.zeros(len(text)), np.zeros(len(text), np.int64)
    order = np.argsort(lengths[item], kind="stable")
    lo = 0
    while lo < len(order):
        hi = min(len(order), lo + max(1, CELLS // (4 * int(lengths[item[order[min(len(order) - 1, lo + CELLS // 64)]]]) + 1)))
        some = order[lo:hi]
        width = int((stop[some] - start[some]).max())
        column = start[some][:, None] + np.arange(width)
        texts = np.where(column < stop[some][:, None], words[np.minimum(column, len(words) - 1)], np.uint64(0))
        long = int(lengths[item[some]].max())
        padded = np.zeros((len(some), long), np.uint64)
        for k, i in enumerate(item[some]):
            padded[k, : lengths[i]] = index.words[i]
        points, column = align(padded, texts)
        score[some] = points / (2 * lengths[item[some]])
        end[some] = start[some] + column - first[text[some]]
        lo = hi
    keep = np.flatnonzero(score >= min_score)
    keep = keep[np.lexsort((end[keep], -score[keep], item[keep], text[keep]))]
    if len(keep):
        new = np.ones(len(keep), bool)
        new[1:] = (text[keep][1:] != text[keep][:-1]) | (item[keep][1:] != item[keep][:-1])
        keep = keep[new]
    return text[keep], index.ids[item[keep]], score[keep], end[keep]


def _blocks(benchmark: DataFrame, n: int, min_words: int, block_items: int):
    size = benchmark.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(F.length("text")), F.lit(0)).alias("chars")).first()
    parts = max(1, -(-size.n // block_items), -(-size.chars // BLOCK_CHARS))
    for k in range(parts):
        rows = benchmark.where(F.pmod(F.xxhash64("item_id"), F.lit(parts)) == k).select(F.col("item_id").cast("long"), "text").where("item_id IS NOT NULL")
        if (found := Items.of([(r[0], r[1]) for r in rows.collect()], n, min_words)) is not None:
            yield found


def _seeded(docs: DataFrame, index: Items, rare: float) -> Items:
    def held(batches):
        for batch in batches:
            total = np.zeros(len(index.grams), np.int64)
            for _, _, buf, offsets in text_slices(batch.column("text")):
                words, first = _words(buf, offsets)
                gram, at = index.hits(words, first)
                text = np.searchsorted(first, at, "right") - 1
                total += np.bincount(np.unique(text * len(index.grams) + gram) % len(index.grams), minlength=len(total))
            some = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(np.append(some, -1)), pa.array(np.append(total[some], batch.num_rows))], names=["gram", "n"])

    counts = docs.select(F.lower("text").alias("text")).mapInArrow(held, "gram long, n long").groupBy("gram").agg(F.sum("n").alias("n"))
    found = {r[0]: r[1] for r in counts.collect()}  # at most one row for each n-gram of the block
    held_by = np.array([found.get(g, 0) for g in range(len(index.grams))], np.int64)
    return index.seeds(held_by, rare * found.get(-1, 0))


def matches(docs: DataFrame, benchmark: DataFrame, n: int = NGRAM, min_score: float = MIN_SCORE, rare: float = RARE, min_words: int = MIN_WORDS, block_items: int = BLOCK_ITEMS) -> DataFrame:
    """(doc_id, item_id, score, end_word): every document and item that it holds, the best alignment of each pair."""
    out = docs.sparkSession.createDataFrame([], "doc_id long, item_id long, score double, end_word long")
    for block in _blocks(benchmark, n, min_words, block_items):
        index = docs.sparkSession.sparkContext.broadcast(_seeded(docs, block, rare))

        def find(batches, index=index):
            for batch in batches:
                ids = batch.column("doc_id")
                for lo, _, buf, offsets in text_slices(batch.column("text")):
                    text, item, score, end = _matches(index.value, *_words(buf, offsets), min_score)
                    yield pa.RecordBatch.from_arrays([ids.take(pa.array(text + lo)), pa.array(item), pa.array(score), pa.array(end)], names=["doc_id", "item_id", "score", "end_word"])

        found = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.lower("text").alias("text")).mapInArrow(find, out.schema)
        out = out.unionByName(found)
    return out


def clean(docs: DataFrame, benchmark: DataFrame, n: int = NGRAM, min_score: float = MIN_SCORE, rare: float = RARE, min_words: int = MIN_WORDS, block_items: int = BLOCK_ITEMS) -> DataFrame:
    """``docs`` without the documents that hold an item. A narrow map: nothing is joined or shuffled."""
    for block in _blocks(benchmark, n, min_words, block_items):
        index = docs.sparkSession.sparkContext.broadcast(_seeded(docs, block, rare))

        def passing(batches, index=index):
            for batch in batches:
                keep = np.ones(batch.num_rows, bool)
                for lo, _, buf, offsets in text_slices(batch.column(batch.num_columns - 1)):
                    keep[_matches(index.value, *_words(buf, offsets), min_score)[0] + lo] = False
                yield pa.RecordBatch.from_arrays(batch.columns[:-1], names=batch.schema.names[:-1]).filter(pa.array(keep))

        docs = docs.withColumn(free(docs, "_lower"), F.lower("text")).mapInArrow(passing, docs.schema)
    return docs


def query(spark, sf_dir):
    return matches(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
