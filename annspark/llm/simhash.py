"""SimHash near-duplicates: positional-byte inverted index, count filter, verification, components.

Fingerprint: ASCII letters lower-cased, words split at space and \\t\\n\\v\\f\\r, shingles of three words
joined by a space (all words of a shorter text), each hashed by XXH64 with seed 42; a bit is set where
more than half of the hashes (repeats counted) have it. A text without words, or null, has fingerprint 0,
which links like any other. Two fingerprints link when at most two bits differ.

Candidates. A fingerprint is eight positional bytes. Two fingerprints within two bits share at least
six of them, so of the four pairs of neighbouring bytes at least two are equal. The inverted index has
one posting list per equal *pair of byte pairs* (six lists per fingerprint, 32 bits each): every link meets in
at least one list. In a list the shared positional bytes of each pair are tallied, pairs with fewer
than six are dropped, and the rest are verified by their differing bits. The index holds distinct
fingerprints only, so exact copies never pair.

Hot lists. A list of more than ``list_limit`` fingerprints is not paired. Its fingerprints emit
themselves and their 64 one-bit neighbours instead: two fingerprints differ in at most two bits exactly
when they have such a neighbour in common, at most 65 fingerprints share one, and all of those are
within two bits of each other, so a star to the smallest of them is made of true links and keeps the
components. That is linear in the list and loses nothing.

Edge cases: a document with a null doc_id links like any other and lends no id (component_id
is the smallest id reachable, null if there is none); ``keep_one`` keeps one row of each component, with or without ids; repeated rows give repeated rows; an
empty table gives no rows; of tied links every one counts; of a text only the hashes of its shingles are held, 8 bytes each, however long it is; further columns of the input are ignored by
``near_duplicates`` and pass through ``keep_one``, whatever their names.
"""

from __future__ import annotations

from array import array
from itertools import repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, forget, free, table

SEED = 42
MAX_BITS = 2
BYTE_GROUPS = ((0, 1), (2, 3), (4, 5), (6, 7))
_LANES = np.uint64(0x0101010101010101)


def majority(hashes: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Fingerprint of each run of ``sizes`` hashes (0 for an empty run), as uint64."""
    bounds = np.concatenate([[0], np.cumsum(sizes)])
    out = np.zeros(len(sizes), np.uint64)
    full = np.flatnonzero(sizes)
    if not len(full):
        return out
    # byte lanes hold up to 255, so runs are summed in pieces of at most 255
    pieces = -(-sizes[full] // 255)
    owner = np.repeat(np.arange(len(full)), pieces)
    first = np.concatenate([[0], np.cumsum(pieces)[:-1]])
    starts = bounds[full][owner] + 255 * (np.arange(len(owner)) - first[owner])
    for bit in range(8):
        lanes = np.add.reduceat((hashes >> np.uint64(bit)) & _LANES, starts).view(np.uint8).reshape(-1, 8)
        counts = np.add.reduceat(lanes.astype(np.int64), first, axis=0)
        for byte in range(8):
            out[full] |= (2 * counts[:, byte] > sizes[full]).astype(np.uint64) << np.uint64(8 * byte + bit)
    return out


def shingle_hashes(text: bytes) -> array:
    words = text.lower().split()
    if len(words) < 3:
        return array("Q", [xxhash.xxh64_intdigest(b" ".join(words), SEED)] if words else [])
    return array("Q", map(xxhash.xxh64_intdigest, map(b" ".join, zip(words, words[1:], words[2:])), repeat(SEED)))


def _fingerprint_batches(batches):
    for batch in batches:
        texts = batch.column("text").cast(pa.binary())
        out = np.empty(len(texts), np.uint64)
        held, at = [], 0
        for i in range(len(texts)):
            held.append(shingle_hashes(texts[i].as_py() or b""))
            if i + 1 == len(texts) or sum(map(len, held[-64:])) > 1 << 16 or len(held) >= 256:
                out[at : i + 1] = majority(np.concatenate([np.frombuffer(h, np.uint64) for h in held]), np.array([len(h) for h in held]))
                held, at = [], i + 1
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(out.view(np.int64)), *batch.columns[2:]], names=["doc_id", "fp", *batch.schema.names[2:]])


def fingerprints(docs: DataFrame, hashed: bool = False) -> DataFrame:
    """(doc_id, fp), and text_hash if ``hashed``: one row per document, the fingerprint as a signed 64-bit integer."""
    more = [F.xxhash64("text").alias("text_hash")] * hashed
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", *more).mapInArrow(_fingerprint_batches, "doc_id long, fp long" + ", text_hash long" * hashed)


def _index(fps: DataFrame) -> DataFrame:
    """(list_no, bytes, fp): six posting lists per distinct fingerprint."""
    pair = [F.shiftrightunsigned("fp", 8 * a).bitwiseAND(0xFFFF) for a, _ in BYTE_GROUPS]
    lists = [F.struct(F.lit(i * 4 + j).alias("list_no"), F.shiftleft(pair[i], 16).bitwiseOR(pair[j]).alias("bytes")) for i in range(4) for j in range(i + 1, 4)]
    return fps.select("fp", F.inline(F.array(*lists)))


def _shared_bytes(a: str, b: str):
    """How many positional bytes two fingerprints share."""
    differ = F.col(a).bitwiseXOR(F.col(b))
    return sum((F.shiftrightunsigned(differ, 8 * k).bitwiseAND(0xFF) == 0).cast("int") for k in range(8))


def links(fps: DataFrame, list_limit: int = 8) -> DataFrame:
    """(a, b) with a < b: links among distinct fingerprints, enough of them to keep every component."""
    index = _index(fps)
    sizes = index.groupBy("list_no", "bytes").agg(F.count(F.lit(1)).alias("size")).where("size > 1")
    sizes = cut(sizes, "simhash-lists")
    # a list is gathered only when it is known to be short; written first, so that a long one can be split in the join
    held = cut(index.join(sizes, ["list_no", "bytes"]), "simhash-postings")
    short = held.where(F.col("size") <= list_limit).groupBy("list_no", "bytes").agg(F.array_sort(F.collect_list("fp")).alias("fps"))
    pairs = short.select(
        # only pairs that can share six bytes at all leave the list
        F.explode(F.expr("flatten(transform(fps, (x, i) -> transform(filter(slice(fps, i + 2, size(fps)), y -> bit_count(x ^ y) <= 16), y -> struct(x AS a, y AS b))))")).alias("p")
    ).select("p.a", "p.b")
    tallied = pairs.where(_shared_bytes("a", "b") >= 8 - MAX_BITS)
    verified = tallied.where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= MAX_BITS)
    hot = held.where(F.col("size") > list_limit).select("fp").distinct()
    near = hot.select("fp", F.explode(F.expr("concat(array(fp), transform(sequence(0, 63), k -> fp ^ shiftleft(1L, k)))")).alias("variant"))
    stars = (
        near.groupBy("variant").agg(F.array_sort(F.collect_list("fp")).alias("fps")).where("size(fps) > 1")
        .select(F.element_at("fps", 1).alias("a"), F.explode(F.expr("slice(fps, 2, size(fps))")).alias("b"))
    )
    return verified.unionByName(stars).distinct()


def components(links_: DataFrame, nodes: DataFrame) -> DataFrame:
    """(node, label): the smallest ``own`` label reachable. links (a, b), nodes (node, own)."""
    return _roots(links_, nodes).select("node", F.col("label.own").alias("label"))


def _roots(links_: DataFrame, nodes: DataFrame) -> DataFrame:
    """(node, label): the smallest (own, node) reachable, as a struct; any ``own`` comes before null.

    Each round takes the smallest label among the neighbours and then the label of the label's node
    (so paths halve); rounds end when no label falls. Tables are cut to the shared folder each round.
    """
    both = cut(links_.select("a", "b").unionByName(links_.select(F.col("b").alias("a"), F.col("a").alias("b"))), "links")
    touched = both.select(F.col("a").alias("node")).distinct()
    # a label is the node that stands for it: nodes are ordered by (own, node), those without own last
    labels = cut(nodes.join(touched, "node").select("node", _label("node").alias("label")), "labels")
    total = None
    while True:
        heard = both.join(labels.select(F.col("node").alias("b"), "label"), "b").select(F.col("a").alias("node"), "label")
        low = cut(labels.unionByName(heard).groupBy("node").agg(F.min("label").alias("label")), "heard")
        above = low.select(F.col("node").alias("root"), F.col("label").alias("up"))
        jumped = low.withColumn("root", F.col("label.node")).join(above, "root").select("node", F.least("label", "up").alias("label"))
        forget(labels)
        labels = cut(jumped, "labels")
        forget(low)
        # labels only fall, so the exact sum of their nodes' ids and numbers stays only when all of them do
        now = labels.agg(*[F.sum(F.col(f"label.{c}").cast("decimal(38,0)")) for c in ("none", "own", "node")]).first()
        if total == now:
            return labels
        total = now


def _label(node: str):
    return F.struct(F.col("own").isNull().cast("int").alias("none"), "own", F.col(node).alias("node"))


def _grouped(prints: DataFrame, list_limit: int) -> DataFrame:
    """``prints`` (doc_id, fp, ...) with the label of each row's component."""
    classes = cut(prints.groupBy("fp").agg(F.min("doc_id").alias("own")), "classes")
    found = _roots(links(classes.select("fp"), list_limit), classes.withColumnRenamed("fp", "node"))
    resolved = cut(classes.join(found.withColumnRenamed("node", "fp"), "fp", "left").select("fp", F.coalesce("label", _label("fp")).alias("label")), "resolved")
    return prints.join(resolved, "fp")


def near_duplicates(docs: DataFrame, list_limit: int = 8) -> DataFrame:
    """(doc_id, fp, component_id) for every document."""
    prints = cut(fingerprints(docs), "fingerprints")
    return _grouped(prints, list_limit).select("doc_id", "fp", F.col("label.own").alias("component_id"))


def keep_one(docs: DataFrame, list_limit: int = 8) -> DataFrame:
    """``docs`` with one document of each group: the one of the group's smallest id, or without an id if none has one.

    A row is known by its id and its text, so rows that share an id and hold texts of different groups stay apart.
    """
    prints = cut(fingerprints(docs, hashed=True), "fingerprints")
    best = F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "text_hash"))
    # the semi join and the choice among equal rows share one shuffle by these two
    h, k, copy = (free(docs, c) for c in ("_hash", "_key", "_copy"))
    firsts = _grouped(prints, list_limit).groupBy("label.node").agg(best.alias("m")).select(F.col("m.text_hash").alias(h), _row_key(F.col("m.doc_id"), F.col("m.text_hash")).alias(k))
    keyed = docs.withColumn(h, F.xxhash64("text")).withColumn(k, _row_key(F.col("doc_id").cast("long"), F.col(h)))
    one = Window.partitionBy(h, k).orderBy(*[c for c in docs.columns if c != "doc_id"])
    return keyed.join(firsts, [h, k], "left_semi").withColumn(copy, F.row_number().over(one)).where(F.col(copy) == 1).select(docs.columns)


def _row_key(doc_id, text_hash):
    return F.xxhash64(doc_id.isNull(), doc_id, text_hash)


def query(spark, sf_dir):
    found = near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
