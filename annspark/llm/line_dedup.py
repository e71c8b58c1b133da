"""Cross-site boilerplate lines, found by how many distinct sites a line is spread over.

A line is what stands between newlines; lines without ink are never boilerplate. A site is the value of
``source`` (null is one site of its own). Lines are known by two independent 64-bit hashes. A line is boilerplate on at least ``min_sites``
sites. Lines with fewer occurrences than that cannot reach it and are left out exactly. For the others a
HyperLogLog sketch of the sites is built per line and merged by aggregation. Where the estimate is
further from the threshold than three standard errors (and than one site) it decides; only the lines between get an
exact distinct count. The threshold also keeps this step apart from near-duplicate removal: lines of whole documents that were copied to a few sites
stay, for a document that has lost some of its lines is no longer seen as a copy. A boilerplate line is removed from every document but the one with
the smallest doc_id, which keeps all its copies.

Edge cases: a null text stays null and has no lines; a document with a null doc_id, or a repeated one, is treated by its own
text, and a null doc_id never counts as the first document; of tied first documents (a repeated id) all keep the line; repeated rows are treated alike; very long texts cost
time in proportion to their lines; an empty
table gives no rows; further columns pass through, and columns named like those that ``remove_boilerplate`` adds (_lines, _removed) are replaced by them.
"""

from __future__ import annotations

from math import sqrt

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, free, table, without

MIN_SITES = 10
LG_CONFIG = 12
#: Positions that one number of a line mask holds.
BITS = 62


def _occurrences(docs: DataFrame) -> DataFrame:
    """(doc_id, text_hash, site, pos, h1, h2) of every line with ink."""
    lines = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("text_hash"),
        F.coalesce("source", F.lit("\0")).alias("site"), F.posexplode(F.split("text", "\n")).alias("pos", "line"),
    )
    inked = lines.where(F.col("line").rlike(r"[^\x20\x09-\x0D]"))
    return inked.select("doc_id", "text_hash", "site", "pos", F.xxhash64("line").alias("h1"), F.xxhash64(F.lit(7), "line").alias("h2"))


def boilerplate(occurrences: DataFrame, min_sites: int = MIN_SITES, lg_config: int = LG_CONFIG) -> tuple[DataFrame, DataFrame]:
    """(h1, h2, first_doc) of the lines on at least ``min_sites`` sites, and the occurrences that can be among them."""
    often = occurrences.groupBy("h1", "h2").agg(F.count(F.lit(1)).alias("n"), F.min("doc_id").alias("first_doc")).where(F.col("n") >= min_sites)
    held = cut(occurrences.join(cut(often.drop("n"), "lines-often"), ["h1", "h2"]), "lines-held")
    spread = cut(
        held.groupBy("h1", "h2").agg(F.hll_sketch_agg("site", lg_config).alias("sketch"), F.min("first_doc").alias("first_doc"))
        .select("h1", "h2", "first_doc", F.hll_sketch_estimate("sketch").alias("sites")),
        "lines-spread",
    )
    band = max(1.0, 3 * 1.04 / sqrt(1 << lg_config) * min_sites)
    off = F.col("sites") - min_sites
    near = spread.where(F.abs(off) <= band).select("h1", "h2", "first_doc")
    # the occurrences of near lines alone are counted one by one
    counted = held.select("h1", "h2", "site").join(near, ["h1", "h2"]).groupBy("h1", "h2", "site").agg(F.min("first_doc").alias("first_doc"))
    exact = counted.groupBy("h1", "h2").agg(F.count(F.lit(1)).alias("sites"), F.min("first_doc").alias("first_doc")).where(F.col("sites") >= min_sites)
    return spread.where(off > band).select("h1", "h2", "first_doc").unionByName(exact.select("h1", "h2", "first_doc")), held


def _masks(gone: DataFrame) -> DataFrame:
    """(id, hash, mask, n): for each document an array of numbers whose bits are the positions (doc_id, text_hash, pos) given, and how many they are."""
    words = gone.groupBy("doc_id", "text_hash", F.expr(f"pos DIV {BITS}").cast("int").alias("word")).agg(F.bit_or(F.expr(f"shiftleft(1L, pos % {BITS})")).alias("bits"))
    sparse = words.groupBy("doc_id", "text_hash").agg(F.array_sort(F.collect_list(F.struct("word", "bits"))).alias("held"), F.sum(F.bit_count("bits")).alias("n"))
    # between two numbers as many zeros as there are words without a removal
    before = F.expr("transform(held, (x, i) -> concat(array_repeat(0L, x.word - 1 - if(i = 0, -1, get(held, i - 1).word)), array(x.bits)))")
    return sparse.select(F.col("doc_id").alias("id"), F.col("text_hash").alias("hash"), F.flatten(before).alias("mask"), "n")


def remove_boilerplate(docs: DataFrame, min_sites: int = MIN_SITES, lg_config: int = LG_CONFIG) -> DataFrame:
    """``docs`` with ``text`` and, where there is one, ``n_chars`` after the removal, and the columns _lines and _removed."""
    docs = without(docs, "_lines", "_removed")
    found, held = boilerplate(_occurrences(docs), min_sites, lg_config)
    gone = held.drop("first_doc").join(cut(found, "lines-found"), ["h1", "h2"]).where("NOT doc_id <=> first_doc").select("doc_id", "text_hash", "pos")
    own = free(docs, "_gone")
    masks = _masks(gone).select(F.col("id").alias(f"{own}i"), F.col("hash").alias(f"{own}h"), F.struct("mask", "n").alias(own))
    joined = docs.join(masks.hint("shuffle_hash"), F.col("doc_id").cast("long").eqNullSafe(F.col(f"{own}i")) & (F.xxhash64("text") == F.col(f"{own}h")), "left")
    lines = F.split("text", "\n")

    def stays(_, i):
        return F.coalesce(F.get(F.col(f"{own}.mask"), F.floor(i / BITS).cast("int")).bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("long"), i % BITS)), F.lit(0)) == 0

    kept = F.when(F.col(own).isNull(), F.col("text")).otherwise(F.array_join(F.filter(lines, stays), "\n"))
    columns = [kept.alias(c) if c.lower() == "text" else F.length(kept).cast(docs.schema[c].dataType).alias(c) if c.lower() == "n_chars" else F.col(c) for c in docs.columns]
    return joined.select(*columns, F.greatest(F.coalesce(F.size(lines), F.lit(0)), F.lit(0)).cast("long").alias("_lines"), F.coalesce(f"{own}.n", F.lit(0)).cast("long").alias("_removed"))


def query(spark, sf_dir):
    cleaned = remove_boilerplate(table(spark, sf_dir, "documents"))
    return cleaned.select("doc_id", F.col("_lines").alias("n_lines"), F.col("_removed").alias("n_removed"), F.md5("text").alias("text_md5"))


SQL = rf"""
WITH lines AS (
  SELECT doc_id, coalesce(source, chr(1)) AS site, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS pos
  FROM documents WHERE text IS NOT NULL
), spread AS (
  SELECT line, min(doc_id) AS first_doc FROM lines WHERE regexp_matches(line, '[^\x20\x09-\x0D]')
  GROUP BY line HAVING count(DISTINCT site) >= {MIN_SITES}
), judged AS (
  SELECT l.doc_id, l.line, l.pos, s.first_doc IS NOT NULL AND s.first_doc <> l.doc_id AS gone FROM lines l LEFT JOIN spread s USING (line)
), folded AS (
  SELECT doc_id, count(*) AS n_lines, count(*) FILTER (gone) AS n_removed, coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '') AS text
  FROM judged GROUP BY doc_id
)
SELECT d.doc_id, coalesce(n_lines, 0) AS n_lines, coalesce(n_removed, 0) AS n_removed, CASE WHEN d.text IS NOT NULL THEN md5(f.text) END AS text_md5
FROM documents d LEFT JOIN folded f USING (doc_id)
"""
