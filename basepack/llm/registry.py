"""Queries of the training-data operators, and SQL for those that SQL can express."""

from __future__ import annotations

from pyspark.sql import functions as F

from . import decontaminate, html_text, language, lattice, mixing, quality, simhash, substrings, toxicity, vptree
from .common import table


def _docs(spark, sf):
    return table(spark, sf, "documents")


def queries():
    return {
        "op1_toxicity": lambda s, d: toxicity.toxicity_report(_docs(s, d), table(s, d, "labels")),
        "op2_decontamination": lambda s, d: decontaminate.contamination(s, _docs(s, d), table(s, d, "benchmark")),
        "op3_html_text": lambda s, d: html_text.extract_pages(table(s, d, "pages")),
        "op4_language": lambda s, d: language.language_report(_docs(s, d)),
        "op5_simhash": lambda s, d: simhash.near_duplicates(_docs(s, d)),
        "op6_lattice_score": lambda s, d: lattice.score(_docs(s, d)),
        "op7_substring_dedup": lambda s, d: substrings.dedup_report(_docs(s, d)),
        "op8_quality": lambda s, d: quality.quality_report(_docs(s, d), table(s, d, "labels")),
        "op9_nearest": lambda s, d: vptree.search_report(table(s, d, "embeddings")),
        "op10_mixing": lambda s, d: mixing.mix_report(_docs(s, d)),
    }


#: Exact windows found by string search: padded words of a text against padded windows of an item.
DECON_SQL = r"""
WITH w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
         '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS words FROM documents),
i AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
         '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS words FROM benchmark),
iw AS (
  SELECT DISTINCT item_id, least(13, len(words)) AS n, array_to_string(words[k:k + least(13, len(words)) - 1], ' ') AS win
  FROM (SELECT *, unnest(range(1, greatest(2, len(words) - 11))) AS k FROM i WHERE len(words) > 0)),
sizes AS (SELECT DISTINCT n FROM iw),
dw AS (
  SELECT doc_id, n, k, array_to_string(words[k:k + n - 1], ' ') AS win
  FROM (SELECT doc_id, words, n, unnest(range(1, len(words) - n + 2)) AS k FROM w CROSS JOIN sizes WHERE len(words) >= n)),
hits AS (SELECT dw.doc_id, dw.k, dw.n, iw.item_id FROM dw JOIN iw USING (n, win)),
pos AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(k, k + n)) AS p FROM hits) GROUP BY doc_id),
items AS (
  SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS list
  FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS item FROM hits) GROUP BY doc_id)
SELECT w.doc_id, len(words)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(list, '')) AS items_sha256,
       coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(words) AS contaminated
FROM w LEFT JOIN pos USING (doc_id) LEFT JOIN items USING (doc_id)
"""


def oracle_sql():
    return {"op2_decontamination": DECON_SQL, "op10_mixing": mixing.REPORT_SQL}
