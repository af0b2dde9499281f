"""Queries and SQL twins of the training-data operators, for the entry module."""

from __future__ import annotations

from cutstream.llm import decontaminate, language, licenses, ngram_join, packing, phrases, pseudonyms, secrets, token_files, warc

QUERIES = {
    "op1_license_scan": licenses.op1_license_scan,
    "op2_pii_pseudonyms": pseudonyms.op2_pii_pseudonyms,
    "op3_document_fingerprints": phrases.op3_document_fingerprints,
    "op4_secret_scan": secrets.op4_secret_scan,
    "op5_harmonic_packing": packing.op5_harmonic_packing,
    "op6_ngram_jaccard_join": ngram_join.op6_ngram_jaccard_join,
    "op7_token_files": token_files.op7_token_files,
    "op8_warc_dictionary": warc.op8_warc_dictionary,
    "op9_benchmark_decontamination": decontaminate.op9_benchmark_decontamination,
    "op10_language_id": language.op10_language_id,
}

ORACLES = {
    "op8_warc_dictionary": warc.ORACLE,
    "op6_ngram_jaccard_join": r"""
WITH RECURSIVE d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) >= 3 THEN list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])
                                      WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS sh FROM d),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
e AS (
  SELECT a.doc_id AS a, b.doc_id AS b FROM s a JOIN s b ON a.sh = b.sh AND a.doc_id <> b.doc_id JOIN n na ON na.doc_id = a.doc_id JOIN n nb ON nb.doc_id = b.doc_id
  GROUP BY a.doc_id, b.doc_id HAVING 100 * count(*) >= 90 * (any_value(na.n) + any_value(nb.n) - count(*))),
reach(doc_id, r) AS (SELECT doc_id, doc_id FROM d UNION SELECT reach.doc_id, e.b FROM reach JOIN e ON reach.r = e.a)
SELECT reach.doc_id AS doc_id, coalesce(any_value(n.n), 0) AS n_shingles, min(r) AS component_id FROM reach LEFT JOIN n ON n.doc_id = reach.doc_id GROUP BY reach.doc_id
""",
}
