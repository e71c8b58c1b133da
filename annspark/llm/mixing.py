"""Mixing sources to target weights by a multivariate-hypergeometric splitting tree over blocks.

Sizes are words. Sources, in order of their names' code points and null last, weigh ``WEIGHTS`` in
turn and share the total size in proportion; no source's target exceeds ``CAP`` times its own size, and what
is over is shared again among the rest by weight until none is above.

A source's documents are cut into blocks by a hash of the id, or of the text where there is none (``blocks_for`` says how many in all, dealt to the sources by
their numbers of documents, at least one each). A source of target r times its size gives each block floor(r) times,
and of one permutation of its blocks once more as many as fit the rest of the target. Where the next block does not fit, the largest of those left that fit
follow, and the smallest block left gives only its first documents, in a permutation of its own. All draws of blocks of a source are its exact
quota. A binary tree over the output shards splits the vector of quotas in two by a multivariate hypergeometric draw
at every node, down to one vector per shard; the shards then take their quotas from each source's
permuted draws, disjoint and complete. In a shard documents are shuffled locally by a seeded hash: ``place``.

The tables that the driver holds are of one row per source (their number is checked) and one per block, at most ``MAX_BLOCKS`` plus the number of
sources; documents are never shuffled. Of the blocks that are cut, one per source, ids and sizes are gathered, without texts.

Edge cases: null and empty texts have size 0, count for their source's documents and are drawn like others; a source whose sizes are all 0 has target 0
and takes nothing; rows that agree in id, size and (without an id) text are taken alike; ties (blocks of one size, documents of one place in the order) go
to the smaller block number and to all rows of the tie; an empty table gives no rows; further columns pass through, and columns named like
those that ``mix`` adds (_size, _source_size, _target, _draws) are replaced by them.
"""

from __future__ import annotations

from bisect import bisect_right
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, free, table, without

WEIGHTS = (5.0, 2.0, 1.0)
CAP = 3
SHARDS = 16
#: Blocks for small tables, documents of a block beyond that, and the most blocks.
BLOCKS, BLOCK_DOCS, MAX_BLOCKS = 16_384, 1_000, 1 << 20
MAX_SOURCES = 1 << 20
SEED = 20


def targets(sizes: list[int], weights: list[float], cap: float = CAP) -> list[float]:
    """Shares of the total by weight, none above ``cap`` times its size; the excess goes to the others by weight."""
    out, open_ = [0.0] * len(sizes), [i for i in range(len(sizes)) if sizes[i]]
    left = float(sum(sizes))
    while open_:
        unit = left / sum(weights[i] for i in open_)
        over = [i for i in open_ if unit * weights[i] > cap * sizes[i]]
        if not over:
            for i in open_:
                out[i] = unit * weights[i]
            break
        for i in over:
            out[i] = float(cap * sizes[i])
            left -= out[i]
        open_ = [i for i in open_ if i not in over]
    return out


def split_tree(quotas: np.ndarray, shards: int, rng: np.random.Generator) -> np.ndarray:
    """Quotas of each shard (rows): halve the shards, draw the left half's blocks without replacement, and go on in both."""
    if shards == 1:
        return quotas[None]
    left = shards // 2
    total = int(quotas.sum())
    drawn = np.zeros_like(quotas)
    rest, want = total, total * left // shards
    # one source after another: the multivariate draw as a chain of hypergeometric ones
    for i, q in enumerate(quotas):
        drawn[i] = rng.hypergeometric(q, rest - q, want) if want and q else 0
        rest, want = rest - q, want - drawn[i]
    return np.vstack([split_tree(drawn, left, rng), split_tree(quotas - drawn, shards - left, rng)])


@dataclass
class Source:
    number: int
    name: str | None
    docs: int
    size: int
    target: float
    blocks: int


def blocks_for(docs: int) -> int:
    """Blocks grow with the documents, so that a block stays small: at most one for each document."""
    return max(1, min(docs, max(BLOCKS, docs // BLOCK_DOCS), MAX_BLOCKS))


def _sized(docs: DataFrame) -> DataFrame:
    return without(docs, "_size").withColumn("_size", F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long"))


def count_sources(docs: DataFrame, blocks: int | None = None) -> list[Source]:
    """The sources in order, with their numbers of documents and of blocks; sizes and targets are not known yet. Reads no text."""
    rows = docs.groupBy("source").agg(F.count(F.lit(1)).alias("docs")).limit(MAX_SOURCES + 1).collect()
    if len(rows) > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources: group them first")
    rows.sort(key=lambda r: (r[0] is None, (r[0] or "").encode()))
    total = sum(r.docs for r in rows)
    whole = min(blocks or blocks_for(total), max(1, total))
    return [Source(i, r[0], r.docs, 0, 0.0, max(1, whole * r.docs // max(1, total))) for i, r in enumerate(rows)]


def _unit(seed: int, *columns):
    return F.xxhash64(F.lit(seed), *columns)


def mix(docs: DataFrame, weights=WEIGHTS, cap: float = CAP, shards: int = SHARDS, blocks: int | None = None, seed: int = SEED) -> DataFrame:
    """``docs`` with _size, _source_size, _target and _draws, an array of (shard, turn, place): once for each time the mix takes the document.

    ``place`` orders a shard: sorting by it is the local shuffle.
    """
    docs = without(docs, "_size", "_source_size", "_target", "_draws")
    spark, sources = docs.sparkSession, count_sources(docs, blocks)
    if not sources:
        return _sized(docs).withColumns({"_source_size": F.lit(0).cast("long"), "_target": F.lit(0.0), "_draws": F.expr("CAST(array() AS array<struct<shard:int,turn:int,place:bigint>>)")})
    key, name, own, n_blocks, block, deal = (free(docs, c) for c in ("_key", "_name", "_own", "_n_blocks", "_block", "_deal"))

    def placed(rows: DataFrame) -> DataFrame:
        """With the document's key (its id, or its text where it has none) and its source's number and block."""
        heads = spark.createDataFrame([(s.number, s.name, s.blocks) for s in sources], f"{own} int, {name} string, {n_blocks} int")
        keyed = rows.withColumn(key, F.when(F.col("doc_id").isNull(), F.xxhash64(F.lit("text"), "text")).otherwise(_unit(seed, "doc_id")))
        # heads has a row for each source, and their number was checked
        joined = keyed.join(F.broadcast(heads), F.col("source").eqNullSafe(F.col(name)))
        return joined.withColumn(block, F.pmod(F.col(key), F.col(n_blocks)).cast("int")).drop(name, n_blocks)

    held = _sized(placed(docs)).groupBy(own, block).agg(F.sum("_size").alias("size")).collect()  # at most MAX_BLOCKS plus sources
    for r in held:
        sources[r[0]].size += r[2]
    for s, t in zip(sources, targets([s.size for s in sources], [weights[s.number % len(weights)] for s in sources], cap)):
        s.target = t
    turns, cut_rows = _draw(sources, held, shards, seed)
    draws = spark.createDataFrame([(k, b, sorted(v)) for (k, b), v in turns.items()], f"{own} int, {block} int, turns array<struct<turn:int,shard:int>>")
    cuts = spark.createDataFrame(cut_rows, f"{own} int, {block} int, rest double, cut_turn int")  # at most one row a source
    # of the cut blocks keys and sizes travel, no texts: those whose middle lies before the cut give the last turn too
    inside = placed(docs.select("doc_id", "source", "text")).join(F.broadcast(cuts), [own, block])
    sizes = _sized(inside).groupBy(own, block, "rest", _place(seed, key).alias("at")).agg(F.sum("_size").alias("all"))
    upto = F.sum("all").over(Window.partitionBy(own, block).orderBy("at").rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("all") / 2
    last = sizes.withColumn("upto", upto).where("upto <= rest").groupBy(own, block).agg(F.max("at").alias("last"))
    # a row for each block that is drawn
    deals = draws.join(F.broadcast(cuts), [own, block], "left").join(F.broadcast(last), [own, block], "left").select(own, block, F.struct("turns", "rest", "cut_turn", "last").alias(deal))
    heads = spark.createDataFrame([(s.number, s.size, s.target) for s in sources], f"{own} int, _source_size long, _target double")
    dealt = placed(docs).join(F.broadcast(deals), [own, block], "left").join(F.broadcast(heads), own)
    whole = F.col(f"{deal}.rest").isNull() | F.coalesce(_place(seed, key) <= F.col(f"{deal}.last"), F.lit(False))
    taken = F.filter(F.coalesce(f"{deal}.turns", F.expr("CAST(array() AS array<struct<turn:int,shard:int>>)")), lambda t: whole | (t["turn"] != F.col(f"{deal}.cut_turn")))
    final = F.transform(taken, lambda t: F.struct(t["shard"].alias("shard"), t["turn"].alias("turn"), _unit(seed + 2, t["shard"], t["turn"], key).alias("place")))
    return _sized(dealt).select(*docs.columns, "_size", "_source_size", "_target", final.alias("_draws"))


def _place(seed: int, key: str):
    """Where a document stands in its block's permutation."""
    return F.struct(_unit(seed + 1, key).alias("a"), F.col(key).alias("b"))


def _draw(sources: list[Source], held, shards: int, seed: int) -> tuple[dict[tuple[int, int], list[tuple[int, int]]], list[tuple]]:
    """(turn, shard) of every draw of a block, and (source, block, what is left of the target, turn) of the blocks that are cut."""
    rng = np.random.default_rng(seed)
    by_source: dict[int, list] = {s.number: [] for s in sources}
    for r in sorted(held, key=lambda r: (r[0], r[1])):
        by_source[r[0]].append((r[1], r[2]))
    turns: dict[tuple[int, int], list] = {}
    cut_rows, order_of = [], []
    for s in sources:
        full = int(s.target // s.size) if s.size else 0
        rest = s.target - full * s.size
        own = [by_source[s.number][i] for i in rng.permutation(len(by_source[s.number]))]
        drawn = [(b, t) for t in range(full) for b, _ in own]
        # whole blocks in the permutation's order while they fit, then the largest of the others that fit, then a part of the smallest
        left = []
        for b, size in own if s.size else ():
            if not left and size <= rest:
                drawn.append((b, full))
                rest -= size
            else:
                left.append((size, b))
        left.sort()
        while left and left[0][0] <= rest:
            size, b = left.pop(bisect_right(left, rest, key=lambda x: x[0]) - 1)
            drawn.append((b, full))
            rest -= size
        if left and rest >= 0.5:
            drawn.append((left[0][1], full))
            cut_rows.append((s.number, left[0][1], float(rest), full))
        order_of.append([drawn[i] for i in rng.permutation(len(drawn))])
    quotas = split_tree(np.array([len(d) for d in order_of], np.int64), shards, rng)
    at = [0] * len(sources)
    for shard in range(shards):
        for k, draws in enumerate(order_of):
            for b, t in draws[at[k] : at[k] + int(quotas[shard][k])]:
                turns.setdefault((k, b), []).append((t, shard))
            at[k] += int(quotas[shard][k])
    return turns, cut_rows


def shards_of(mixed: DataFrame, columns: list[str]) -> DataFrame:
    """One row for each time that a document is taken: ``columns``, shard, turn and place. Columns of these three names are replaced."""
    kept = [c for c in columns if c.lower() not in ("shard", "turn", "place")]
    return mixed.select(*kept, F.inline("_draws"))


def query(spark, sf_dir):
    """Contract digest, and as ``draws`` the shard, turn and place of each time that the mix takes the document, as the tree dealt them."""
    mixed = mix(table(spark, sf_dir, "documents"))
    written = F.array_join(F.transform("_draws", lambda t: F.concat_ws(":", t["shard"], t["turn"], t["place"])), ",")
    return mixed.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("_size").alias("size"), F.col("_source_size").alias("source_size"), F.col("_target").alias("target"), (F.col("_size") * F.size("_draws")).alias("taken"), written.alias("draws"))
