"""The queries of this subpackage, by name, and the SQL of those that SQL can express."""

from __future__ import annotations

from entitygraph.llm.decontaminate import op5_decontaminate
from entitygraph.llm.html_text import op2_html_text
from entitygraph.llm.packing import op8_packing
from entitygraph.llm.pii import op9_pii
from entitygraph.llm.quality import op4_quality
from entitygraph.llm.simhash import op3_simhash
from entitygraph.llm.suffix_dedup import op1_suffix_dedup
from entitygraph.llm.token_files import op7_token_files
from entitygraph.llm.toxicity import op6_toxicity
from entitygraph.llm.vector_join import op10_vector_join

QUERIES = {
    f.__name__: f
    for f in (
        op1_suffix_dedup, op2_html_text, op3_simhash, op4_quality, op5_decontaminate, op6_toxicity, op7_token_files, op8_packing, op9_pii, op10_vector_join,
    )
}

#: Labels are met in SQL by comparing all pairs of a label: fine on a fixture's scale, and independent of the join's method.
ORACLE_SQL = {
    "op10_vector_join": """
        WITH RECURSIVE v AS (
            SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings
            WHERE label IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
              AND len(list_filter(embedding, lambda x: x <> 0)) > 0
        ),
        u AS (SELECT vec_id, label, e, sqrt(list_dot_product(e, e)) AS n FROM v),
        pairs AS (
            SELECT a.vec_id AS a, b.vec_id AS b FROM u a JOIN u b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.e) = len(b.e)
            WHERE list_dot_product(a.e, b.e) / (a.n * b.n) >= 0.98
        ),
        reach(a, b) AS (SELECT a, b FROM pairs UNION SELECT r.a, p.b FROM reach r JOIN pairs p ON r.b = p.a),
        least AS (SELECT a, min(b) AS m FROM reach GROUP BY a),
        links AS (SELECT a, count(*) AS n FROM pairs GROUP BY a)
        SELECT e.vec_id, CAST(coalesce(l.n, 0) AS BIGINT) AS n_links, least(e.vec_id, coalesce(m.m, e.vec_id)) AS component_id,
               least(e.vec_id, coalesce(m.m, e.vec_id)) = e.vec_id AS kept
        FROM embeddings e LEFT JOIN links l ON l.a = e.vec_id LEFT JOIN least m ON m.a = e.vec_id
    """,
}
