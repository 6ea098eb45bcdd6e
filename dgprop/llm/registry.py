"""The subpackage's queries and their SQL."""

from __future__ import annotations

from dgprop.llm.contexttree import op3_context_tree_score
from dgprop.llm.fingerprints import op4_document_fingerprints
from dgprop.llm.mixing import op2_source_mixing
from dgprop.llm.packing import op7_best_fit_packing
from dgprop.llm.personaldata import op6_personal_data
from dgprop.llm.prefixcounts import op10_prefix_token_counts
from dgprop.llm.qualityrules import op5_quality_rules
from dgprop.llm.shinglejoin import op1_ngram_jaccard_join
from dgprop.llm.tokenfiles import op8_token_files
from dgprop.llm.toxicity import op9_toxicity

QUERIES = {
    "op1_ngram_jaccard_join": op1_ngram_jaccard_join,
    "op2_source_mixing": op2_source_mixing,
    "op3_context_tree_score": op3_context_tree_score,
    "op4_document_fingerprints": op4_document_fingerprints,
    "op5_quality_rules": op5_quality_rules,
    "op6_personal_data": op6_personal_data,
    "op7_best_fit_packing": op7_best_fit_packing,
    "op8_token_files": op8_token_files,
    "op9_toxicity": op9_toxicity,
    "op10_prefix_token_counts": op10_prefix_token_counts,
}

#: The join by counting shared shingles of all pairs, and reachability by recursion.
_JOIN = r"""WITH RECURSIVE t AS (SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
    i AS (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 4, 1) + 1)) AS i FROM t WHERE len(w) > 0),
    s AS (SELECT DISTINCT doc_id, CASE WHEN len(w) >= 5 THEN w[i : i + 4] ELSE w END AS g FROM i),
    n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
    p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS k FROM s AS x JOIN s AS y ON x.g = y.g AND x.doc_id < y.doc_id GROUP BY 1, 2),
    l AS (SELECT a, b FROM p JOIN n AS na ON na.doc_id = a JOIN n AS nb ON nb.doc_id = b WHERE 100 * k >= 80 * (na.n + nb.n - k)),
    e AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
    r(doc_id, c) AS (SELECT doc_id, doc_id FROM documents UNION SELECT e.b, r.c FROM r JOIN e ON e.a = r.doc_id)
    SELECT r.doc_id, coalesce(any_value(n.n), 0) AS n_shingles, min(c) AS component_id FROM r LEFT JOIN n ON n.doc_id = r.doc_id GROUP BY r.doc_id"""

SQL: dict[str, str] = {"op1_ngram_jaccard_join": _JOIN}
