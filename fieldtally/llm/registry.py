"""The queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from . import bpe_pieces, cross_entropy, id_coder, jaccard_join, media_boxes, merkle, pii_tagger, quality, raking, repeats


def queries() -> dict:
    import corpus_pipeline

    return {
        "op1_id_coder": id_coder.op1_id_coder,
        "op2_jaccard_join": jaccard_join.op2_jaccard_join,
        "op3_cross_entropy": cross_entropy.op3_cross_entropy,
        "op4_pii_tagger": pii_tagger.op4_pii_tagger,
        "op5_byte_bpe": bpe_pieces.op5_byte_bpe,
        "op6_repeats": repeats.op6_repeats,
        "op7_media_boxes": media_boxes.op7_media_boxes,
        "op8_quality": quality.op8_quality,
        "op9_merkle": merkle.op9_merkle,
        "op10_raking": raking.op10_raking,
        "pipeline": corpus_pipeline.run,
    }


_WORDS = "[^\\x20\\x09-\\x0D]+"

OP2_SQL = f"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{_WORDS}') AS ws FROM documents),
g AS (SELECT doc_id, CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')]
  ELSE list_distinct(list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i + 4], ' '))) END AS gs FROM w),
s AS (SELECT doc_id, unnest(gs) AS g FROM g),
n AS (SELECT doc_id, len(gs) AS n FROM g),
c AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
e AS MATERIALIZED (SELECT a, b FROM c JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 75 * (x.n + y.n - c)),
r(node, reach) AS (SELECT doc_id, doc_id FROM n UNION SELECT r.node, e.b FROM r JOIN e ON e.a = r.reach)
SELECT n.doc_id, n.n AS n_shingles, min(r.reach) AS component_id FROM n JOIN r ON r.node = n.doc_id GROUP BY 1, 2
"""

OP6_SQL = f"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '{_WORDS}') AS ws FROM documents),
x AS (SELECT doc_id, unnest(range(1, len(ws) - 33)) AS i, ws FROM w WHERE len(ws) >= 35),
h AS MATERIALIZED (SELECT doc_id, i, md5(array_to_string(ws[i:i + 34], ' ')) AS h FROM x),
m AS (SELECT h FROM h GROUP BY h HAVING count(*) > 1),
c AS (SELECT DISTINCT doc_id, i + unnest(range(0, 35)) AS p FROM h JOIN m USING (h)),
l AS (SELECT doc_id, list(p) AS ps FROM c GROUP BY 1),
k AS (SELECT w.doc_id, len(ws) AS n_words, coalesce(len(ps), 0) AS n_removed,
  CASE WHEN ps IS NULL THEN ws ELSE list_transform(list_filter(list_zip(ws, range(1, len(ws) + 1)), lambda z: NOT list_contains(ps, z[2])), lambda z: z[1]) END AS kept FROM w LEFT JOIN l USING (doc_id))
SELECT doc_id, n_words, n_removed, sha256(coalesce(array_to_string(kept, ' '), '')) AS kept_sha256 FROM k
"""


def oracle_sql() -> dict:
    return {"op2_jaccard_join": OP2_SQL, "op6_repeats": OP6_SQL, "op9_merkle": merkle.ORACLE_SQL, "op10_raking": raking.oracle_sql()}
