"""Queries of the training-data operators and their SQL oracles.

Beside the ten there are queries of what SQL can check of those operators that it cannot express whole.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from . import ann, decontaminate, language_id, line_dedup, mixing, pii, quality, simhash, tool_calls, url_filter
from .common import WORD, cut, table


def mix_targets(spark, sf_dir):
    """Size, source size and target of every document of the mix."""
    return mixing.query(spark, sf_dir).select("doc_id", "size", "source_size", F.round("target", 4).alias("target"))


def neighbours_at_limit(spark, sf_dir):
    """The multiprobe search when its target is certainty: it visits every bucket, so its answer is the exact one."""
    vectors = cut(ann.valid_vectors(table(spark, sf_dir, "embeddings"), "vec_id", "embedding"), "ann-vectors")
    found = ann.search(vectors, vectors.where(F.col("id") % 50 == 0), k=5, target=1.0)
    return found.select("query_id", F.col("rank").cast("long").alias("rank"), "vec_id", F.round("score", 9).alias("score"))


def pii_base_counts(spark, sf_dir):
    return pii.query(spark, sf_dir).select("doc_id", *[f"n_{kind}" for kind in pii.KINDS])


def benchmark_verbatim(spark, sf_dir):
    """The pairs whose alignment is perfect: the document holds all words of the item in a row."""
    return decontaminate.query(spark, sf_dir).where("score = 1").select("doc_id", "item_id")


MIX_TARGETS = f"""
WITH RECURSIVE sized AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '{WORD}')) AS size FROM documents),
sources AS (SELECT source, sum(size)::BIGINT AS size, CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN 5e0 WHEN 1 THEN 2e0 ELSE 1e0 END AS w FROM sized GROUP BY source),
rounds(source, size, w, fixed, turn) AS (
  SELECT source, size, w, CASE WHEN size = 0 THEN 0e0 END, 0 FROM sources
  UNION ALL
  SELECT source, size, w, CASE WHEN fixed IS NOT NULL THEN fixed WHEN (sum(size) OVER () - sum(coalesce(fixed, 0)) OVER ()) / sum(CASE WHEN fixed IS NULL THEN w END) OVER () * w > 3 * size THEN 3e0 * size END, turn + 1
  FROM rounds WHERE turn < 40
),
ends AS (SELECT source, size, coalesce(fixed, (sum(size) OVER () - sum(coalesce(fixed, 0)) OVER ()) / sum(CASE WHEN fixed IS NULL THEN w END) OVER () * w) AS target FROM rounds WHERE turn = 40)
SELECT doc_id, s.size, e.size AS source_size, round(target, 4) AS target FROM sized s JOIN ends e ON s.source IS NOT DISTINCT FROM e.source
"""

NEIGHBOURS = """
WITH v AS (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings WHERE embedding IS NOT NULL AND list_sum(list_transform(embedding::DOUBLE[], lambda x: x * x)) > 0)
SELECT query_id, rank, vec_id, round(score, 9) AS score FROM (
  SELECT q.vec_id AS query_id, v.vec_id, list_cosine_similarity(q.e, v.e) AS score, row_number() OVER (PARTITION BY q.vec_id ORDER BY list_cosine_similarity(q.e, v.e) DESC, v.vec_id) AS rank
  FROM v q JOIN v ON q.vec_id % 50 = 0 AND v.vec_id <> q.vec_id) WHERE rank <= 5
"""

PII_COUNTS = r"""
WITH found AS (
  SELECT doc_id, len(regexp_extract_all(t, '[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+')) AS n_email, regexp_extract_all(t, '[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)') AS ips,
    list_transform(regexp_extract_all(t, '[0-9]([ -]?[0-9])+'), lambda m: regexp_replace(m, '[^0-9]', '', 'g')) AS cards, regexp_extract_all(t, '\+[0-9][ ().0-9-]+[0-9]') AS phones
  FROM (SELECT doc_id, coalesce(text, '') AS t FROM documents)
)
SELECT doc_id, n_email, len(list_filter(ips, lambda m: len(list_filter(string_split(m, '.'), lambda p: TRY_CAST(p AS HUGEINT) IS NULL OR TRY_CAST(p AS HUGEINT) > 255)) = 0)) AS n_ip,
  len(list_filter(cards, lambda d: length(d) BETWEEN 12 AND 19 AND list_sum(list_transform(range(1, length(d) + 1), lambda i: CASE WHEN i % 2 = 1 THEN d[-i]::INT ELSE (2 * d[-i]::INT) // 10 + (2 * d[-i]::INT) % 10 END)) % 10 = 0)) AS n_card,
  len(list_filter(phones, lambda m: length(regexp_replace(m, '[^0-9]', '', 'g')) BETWEEN 9 AND 15)) AS n_phone
FROM found
"""

VERBATIM = rf"""
WITH plain AS (SELECT doc_id, ' ' || trim(regexp_replace(lower(text), '[^a-z0-9\x{{80}}-\x{{10FFFF}}]+', ' ', 'g')) || ' ' AS t FROM documents),
items AS (SELECT t, min(item_id) AS item_id FROM (SELECT item_id, ' ' || trim(regexp_replace(lower(text), '[^a-z0-9\x{{80}}-\x{{10FFFF}}]+', ' ', 'g')) || ' ' AS t FROM benchmark WHERE text IS NOT NULL) WHERE t <> '  ' GROUP BY t)
SELECT doc_id, item_id FROM plain p JOIN items i ON contains(p.t, i.t)
"""


def queries():
    return {
        "op1_linked_tool_calls": tool_calls.query,
        "op2_line_spread": line_dedup.query,
        "op3_pii_crf": pii.query,
        "op4_multiprobe_neighbours": ann.query,
        "op5_mixed_sources": mixing.query,
        "op6_simhash_components": simhash.query,
        "op7_quality_ftrl": quality.query,
        "op8_url_ratio": url_filter.query,
        "op9_language_families": language_id.query,
        "op10_benchmark_matches": decontaminate.query,
        **{f.__name__: f for f in (mix_targets, neighbours_at_limit, pii_base_counts, benchmark_verbatim)},
    }


def oracle_sql():
    return {
        "op1_linked_tool_calls": tool_calls.SQL, "op2_line_spread": line_dedup.SQL, "op8_url_ratio": url_filter.SQL,
        "mix_targets": MIX_TARGETS, "neighbours_at_limit": NEIGHBOURS, "pii_base_counts": PII_COUNTS, "benchmark_verbatim": VERBATIM,
    }
