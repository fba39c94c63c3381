"""The queries of this subpackage and, where SQL can express them, their DuckDB oracles."""

from __future__ import annotations

from .decontamination import op3_simhash_leaks
from .html_layout import op10_layout_text
from .jaccard_join import op5_jaccard_components
from .language_id import op1_language_mixture
from .lm_scoring import op2_context_tree_score
from .mixing import op7_pfair_mix
from .quality_rules import op8_quality_votes
from .secret_scan import op4_secret_forest
from .sharding import op6_minimax_shards
from .toxicity import op9_factorization_toxicity

QUERIES = {
    "op1_language_mixture": op1_language_mixture,
    "op2_context_tree_score": op2_context_tree_score,
    "op3_simhash_leaks": op3_simhash_leaks,
    "op4_secret_forest": op4_secret_forest,
    "op5_jaccard_components": op5_jaccard_components,
    "op6_minimax_shards": op6_minimax_shards,
    "op7_pfair_mix": op7_pfair_mix,
    "op8_quality_votes": op8_quality_votes,
    "op9_factorization_toxicity": op9_factorization_toxicity,
    "op10_layout_text": op10_layout_text,
}
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: The other queries rest on models, fingerprints or layouts that SQL cannot express; tests hold them against brute force.
ORACLES: dict[str, str] = {
    "op5_jaccard_components": f"""WITH RECURSIVE texts AS (
        SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\\x20\\x09-\\x0D]+') AS w FROM documents),
      sets AS (SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
          ELSE list_distinct([array_to_string(w[i:i + 4], ' ') for i in range(1, len(w) - 3)]) END AS s FROM texts),
      rows AS (SELECT doc_id, len(s) AS n, unnest(s) AS g FROM sets),
      pairs AS (SELECT x.doc_id AS a, y.doc_id AS b FROM rows AS x JOIN rows AS y ON x.g = y.g AND x.doc_id < y.doc_id
          GROUP BY x.doc_id, y.doc_id, x.n, y.n HAVING 100 * count(*) >= 75 * (x.n + y.n - count(*))),
      links AS (SELECT a, b FROM pairs UNION SELECT b, a FROM pairs),
      reached AS (SELECT doc_id AS a, doc_id AS b FROM sets UNION SELECT reached.a, links.b FROM reached JOIN links ON reached.b = links.a)
      SELECT doc_id, CAST(len(s) AS BIGINT) AS n_shingles, (SELECT min(b) FROM reached WHERE a = doc_id) AS component_id FROM sets""",
}
