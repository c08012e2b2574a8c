"""Queries of this package and their SQL; __spark_entry__.py adds them when the package is there."""

from __future__ import annotations

from codematch.llm import jaccard_join, language, packing, quality, repeats, spotsigs, token_counts, toxicity, warc, winnowing
from codematch.sources.io import read_table


def op1_spot_fingerprints(spark, sf_dir):
    """One row per document: its fingerprint and that of its edited text."""
    return spotsigs.fingerprint_edits(read_table(spark, sf_dir, "documents").select("doc_id", "text"))


def op2_decontamination(spark, sf_dir):
    """One row per document: how many of its words stand in windows of benchmark items, and of which."""
    return winnowing.contamination(read_table(spark, sf_dir, "documents").select("doc_id", "text"), read_table(spark, sf_dir, "benchmark").select("item_id", "text"))


OP2_SQL = r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents),
b AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark),
bw AS (
  SELECT DISTINCT item_id, n, array_to_string(ws[i:i+n-1], ' ') AS w
  FROM (SELECT item_id, ws, least(len(ws), 10) AS n, unnest(range(1, len(ws) - least(len(ws), 10) + 2)) AS i FROM b WHERE len(ws) > 0)),
dw AS (
  SELECT doc_id, i, n, array_to_string(ws[i:i+n-1], ' ') AS w
  FROM (SELECT doc_id, ws, n, unnest(range(1, len(ws) - n + 2)) AS i FROM d, (SELECT DISTINCT n FROM bw) WHERE len(ws) >= n)),
h AS (SELECT dw.doc_id, dw.i, dw.n, bw.item_id FROM dw JOIN bw ON dw.n = bw.n AND dw.w = bw.w),
p AS (SELECT doc_id, count(DISTINCT q) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS q FROM (SELECT DISTINCT doc_id, i, n FROM h)) GROUP BY 1),
t AS (SELECT doc_id, count(*) AS n_items, string_agg(v, ',' ORDER BY v) AS l FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS v FROM h) GROUP BY 1)
SELECT d.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
  sha256(coalesce(l, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN p USING (doc_id) LEFT JOIN t USING (doc_id)
"""


def op3_ngram_jaccard(spark, sf_dir):
    """One row per document: its shingle count and the smallest doc_id its links reach."""
    return jaccard_join.jaccard_components(read_table(spark, sf_dir, "documents").select("doc_id", "text"))


OP3_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (
  SELECT DISTINCT doc_id, CASE WHEN len(ws) < 5 THEN array_to_string(ws, ' ') ELSE array_to_string(ws[i:i+4], ' ') END AS sh
  FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 4, 1) + 1)) AS i FROM w WHERE len(ws) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.sh = b.sh AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS (SELECT x, y FROM p JOIN n nx ON nx.doc_id = x JOIN n ny ON ny.doc_id = y WHERE 100 * c >= 75 * (nx.n + ny.n - c)),
e AS (SELECT x, y FROM l UNION ALL SELECT y, x FROM l),
r(src, dst) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.src, e.y FROM r JOIN e ON r.dst = e.x)
SELECT d.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, q.component_id
FROM documents d LEFT JOIN n USING (doc_id) JOIN (SELECT src, min(dst) AS component_id FROM r GROUP BY 1) q ON q.src = d.doc_id
"""


def op6_repeated_bytes(spark, sf_dir):
    """One row per document: what is left when strings of 200 bytes that start anywhere else as well are cut."""
    return repeats.cut_repeats(read_table(spark, sf_dir, "documents").select("doc_id", "text"))


def op4_best_fit_packing(spark, sf_dir):
    """One row per piece of a document: the bin that holds it."""
    return packing.pack(read_table(spark, sf_dir, "documents").select("doc_id", "text", "source"))


def op5_warc_archives(spark, sf_dir):
    """One row per page, as read back from the archives written."""
    return warc.archived_pages(read_table(spark, sf_dir, "pages").select("page_id", "url", "html"))


def op8_toxicity(spark, sf_dir):
    """One row per document: its toxicity score."""
    return toxicity.score_documents(read_table(spark, sf_dir, "documents").select("doc_id", "text"), read_table(spark, sf_dir, "labels").select("doc_id", "toxic"))


def op9_quality(spark, sf_dir):
    """One row per document: its quality score."""
    return quality.score_documents(read_table(spark, sf_dir, "documents").select("doc_id", "text"), read_table(spark, sf_dir, "labels").select("doc_id", "quality"))


def op7_section_tokens(spark, sf_dir):
    """One row per document: its tokens, and those of each section."""
    return token_counts.section_tokens(read_table(spark, sf_dir, "documents").select("doc_id", "text"))


def op10_language_id(spark, sf_dir):
    """One row per document and per page: its language."""
    return language.documents_and_pages(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "pages"))


def queries():
    return {"op1_spot_fingerprints": op1_spot_fingerprints, "op2_decontamination": op2_decontamination, "op3_ngram_jaccard": op3_ngram_jaccard, "op4_best_fit_packing": op4_best_fit_packing, "op5_warc_archives": op5_warc_archives, "op6_repeated_bytes": op6_repeated_bytes, "op7_section_tokens": op7_section_tokens, "op8_toxicity": op8_toxicity, "op9_quality": op9_quality, "op10_language_id": op10_language_id}


def oracle_sql():
    return {"op2_decontamination": OP2_SQL, "op3_ngram_jaccard": OP3_SQL}
