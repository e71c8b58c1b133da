"""Corpus pipeline: language ID, line dedup, near-duplicate removal, benchmark decontamination, source mixing.

Each stage takes (spark, docs, sf_dir) and works on all that the stage before kept, written as Parquet and read
again. All but the last return the columns of documents; the last one has a row for each time that the mix takes a document, with shard, turn and place
(the order within the shard) besides.

Edge cases, in every stage: repeated rows are treated alike (but for near-duplicate removal, which keeps one); an empty table gives an empty one; very long texts are worked on whole;
further columns pass through, whatever their names, but for the last stage's shard, turn and place, which replace columns of these names. Null ids, sources and texts are told stage by stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from annspark.llm import decontaminate, language_id, line_dedup, mixing, simhash
from annspark.llm.common import cut, table, without
from annspark.llm.learning import fold

#: A document is rejected if its language is undecided, or decided by less than this (0.5: no margin at all).
MIN_LANGUAGE_SCORE = 0.55


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a recognised language; ``lang`` stays as it came.

    Null and letterless texts have none and go. A null id or ``lang`` is scored like any other and not learned from. With no language to learn from, all go.
    """
    model = language_id.train(docs.where(~F.coalesce(fold("doc_id", 4) == 2, F.lit(False))))
    found = language_id.predict(docs, model)
    return without(found.where((F.col("lang_pred") != language_id.UNDECIDED) & (F.col("lang_score") >= MIN_LANGUAGE_SCORE)), "lang_pred", "lang_score")


def remove_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without cross-site boilerplate lines; those of which nothing is left go.

    Null texts, and texts that were empty before, stay as they are. A null source is a site of its own; a document without an id never counts as a line's first.
    """
    cleaned = line_dedup.remove_boilerplate(docs)
    emptied = (F.col("_removed") > 0) & ~F.col("text").rlike(r"[^\x20\x09-\x0D]")
    return without(cleaned.where(~F.coalesce(emptied, F.lit(False))), "_lines", "_removed")


def remove_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, that of the smallest id, of each group of near copies.

    Null, empty and inkless texts are copies of each other. Documents without an id are kept only where their group has none with one. Rows that tie in id and text are told apart by their other
    columns' order; one stays.
    """
    return simhash.keep_one(docs)


def remove_benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item. Null and empty texts hold none; ids are not looked at; without a benchmark all stay."""
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix: a row for each time that a document is taken, in sixteen shards.

    Null and empty texts have size 0 and are drawn like others; a null source is the last source; documents without an id are dealt by their texts.
    """
    return mixing.shards_of(mixing.mix(docs), docs.columns)


STAGES = [
    ("language_id", identify_language),
    ("line_dedup", remove_repeated_lines),
    ("simhash_near_dedup", remove_near_duplicates),
    ("benchmark_decontamination", remove_benchmark_leaks),
    ("source_mixing", mix_sources),
]
#: Trained models, hashes and seeded draws: not for SQL. tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
