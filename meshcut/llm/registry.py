"""Queries of the training-data operators, and SQL for those that SQL can express on whole tables."""

from __future__ import annotations

from meshcut.llm import contamination, line_dedup, packing, passage_chains, pii, quality, simhash, suffix_dedup, suffix_tree_lm, toxicity


def queries():
    return {
        "op1_simhash_groups": simhash.simhash_groups,
        "op2_personal_data": pii.pii,
        "op3_passage_chains": passage_chains.passage_pairs,
        "op4_curve_packing": packing.packing,
        "op5_quality_rules": quality.quality_rules,
        "op6_suffix_tree_lm": suffix_tree_lm.lm_scores,
        "op7_line_dedup": line_dedup.line_dedup,
        "op8_decontamination": contamination.decontamination,
        "op9_suffix_dedup": suffix_dedup.suffix_dedup,
        "op10_toxicity": toxicity.toxicity,
    }


#: Line dedup from its definition: windows of three non-blank lines that occurred before go, with what lies inside them.
LINE_DEDUP = r"""
WITH l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, unnest(range(len(string_split(text, chr(10))))) AS n FROM documents),
b AS (SELECT doc_id, n, line FROM l WHERE regexp_matches(line, '[^\x09-\x0D ]')),
w AS (SELECT doc_id, n AS a, lead(n, 2) OVER d AS z, line || chr(10) || lead(line, 1) OVER d || chr(10) || lead(line, 2) OVER d AS t
      FROM b WINDOW d AS (PARTITION BY doc_id ORDER BY n)),
o AS (SELECT doc_id, a, z, row_number() OVER (PARTITION BY t ORDER BY doc_id, a) AS k FROM w WHERE z IS NOT NULL),
gone AS (SELECT DISTINCT doc_id, unnest(range(a, z + 1)) AS n FROM o WHERE k > 1),
kept AS (SELECT doc_id, count(g.n) AS n_removed, coalesce(string_agg(line, chr(10) ORDER BY n) FILTER (g.n IS NULL), '') AS text
         FROM l LEFT JOIN gone g USING (doc_id, n) GROUP BY doc_id)
SELECT doc_id, coalesce(n_removed, 0)::BIGINT AS n_removed, sha256(coalesce(k.text, d.text, '')) AS kept_sha256
FROM (SELECT doc_id, text FROM documents) d LEFT JOIN kept k USING (doc_id)
"""


def oracle_sql():
    return {"op7_line_dedup": LINE_DEDUP}
