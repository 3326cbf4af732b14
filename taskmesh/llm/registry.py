"""The queries of this subpackage, and SQL for those that SQL can express."""

from __future__ import annotations

from taskmesh.llm.context_mixing import op5_context_mixing
from taskmesh.llm.minhash import op1_minhash
from taskmesh.llm.mixing import op9_mixing
from taskmesh.llm.multi_index import op3_multi_index
from taskmesh.llm.packing import op6_packing
from taskmesh.llm.pii import op10_pii
from taskmesh.llm.sstable import op4_sstable
from taskmesh.llm.toxicity import op2_toxicity
from taskmesh.llm.vector_dedup import op7_vector_dedup
from taskmesh.llm.viterbi import op8_viterbi


def queries() -> dict:
    return {
        "op1_minhash": op1_minhash,
        "op2_toxicity": op2_toxicity,
        "op3_multi_index": op3_multi_index,
        "op4_sstable": op4_sstable,
        "op5_context_mixing": op5_context_mixing,
        "op6_packing": op6_packing,
        "op7_vector_dedup": op7_vector_dedup,
        "op8_viterbi": op8_viterbi,
        "op9_mixing": op9_mixing,
        "op10_pii": op10_pii,
    }


#: All pairs that share a shingle, on whole texts; components by recursion.
MINHASH_SQL = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda w: w <> '') AS w FROM documents),
own AS (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')]
    ELSE list_sort(list_distinct(list_transform(range(1, len(w) - 1), lambda i: concat(w[i], ' ', w[i + 1], ' ', w[i + 2])))) END AS s FROM words),
shingles AS (SELECT doc_id, len(s) AS n, unnest(s) AS s FROM own),
links AS (
  SELECT a, b FROM (SELECT x.doc_id AS a, y.doc_id AS b, any_value(x.n) AS na, any_value(y.n) AS nb, count(*) AS c FROM shingles x JOIN shingles y ON x.s = y.s AND x.doc_id <> y.doc_id GROUP BY 1, 2)
  WHERE 100 * c >= 85 * (na + nb - c)),
reach AS (SELECT doc_id AS node, doc_id AS seen FROM own UNION SELECT l.b, r.seen FROM reach r JOIN links l ON l.a = r.node),
found AS (SELECT node, min(seen) AS component_id FROM reach GROUP BY node)
SELECT o.doc_id, len(s)::BIGINT AS n_shingles, component_id, o.doc_id = component_id AS kept, CASE WHEN len(s) = 0 THEN o.doc_id ELSE min(o.doc_id) OVER (PARTITION BY s) END AS class_id
FROM own o JOIN found f ON o.doc_id = f.node"""

#: All pairs of vectors, in double precision; components by recursion.
VECTOR_DEDUP_SQL = """
WITH RECURSIVE v AS (
  SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
unit AS (SELECT vec_id, e, sqrt(list_dot_product(e, e)) AS n FROM v WHERE list_dot_product(e, e) > 0),
links AS (SELECT a.vec_id AS a, b.vec_id AS b FROM unit a JOIN unit b ON a.vec_id <> b.vec_id WHERE list_dot_product(a.e, b.e) / (a.n * b.n) >= 0.95),
reach AS (SELECT vec_id AS node, vec_id AS seen FROM embeddings UNION SELECT l.b, r.seen FROM reach r JOIN links l ON l.a = r.node)
SELECT node AS vec_id, (SELECT count(*) FROM links WHERE a = node) AS n_links, min(seen) AS component_id, node = min(seen) AS kept FROM reach GROUP BY node"""


def mixing_sql(seeds: int = 32, most: int = 3) -> str:
    """Targets by the level that the sources below their ceiling share, rates, and the draws by md5 with the best of the seeds."""
    draw = "((('0x' || substr(m, 1, 8))::BIGINT + {seed}::BIGINT * ('0x' || substr(m, 9, 8))::BIGINT) % 4294967296) / 4294967296.0::DOUBLE"
    missing = "target - whole * source_size"
    tried = ", ".join(f"sum(CASE WHEN {draw.format(seed=s)} < part THEN size ELSE 0 END) AS s{s}" for s in range(seeds))
    best = ", ".join(f"[abs(s{s} - ({missing})), {s}]" for s in range(seeds))
    return rf"""WITH docs AS (SELECT doc_id, source, md5(coalesce(doc_id::VARCHAR, '')) AS m, coalesce(len(regexp_extract_all(text, '[^ 	-]+')), 0)::BIGINT AS size FROM documents),
      sizes AS (SELECT source, sum(size)::BIGINT AS source_size FROM docs GROUP BY source),
      weighed AS (SELECT *, [1.0, 2.0, 3.0][((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::INT]::DOUBLE AS weight, {most}.0::DOUBLE * source_size AS ceiling FROM sizes),
      levels AS (SELECT *, (sum(source_size) OVER ()::DOUBLE - coalesce(sum(ceiling) OVER b, 0)) / (sum(weight) OVER () - coalesce(sum(weight) OVER b, 0)) AS level, ceiling / weight AS reach FROM weighed
        WINDOW b AS (ORDER BY ceiling / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
      targets AS (SELECT source, source_size, least(ceiling, (SELECT max(level) FROM levels WHERE level <= reach) * weight) AS target FROM levels),
      rates AS (SELECT *, floor(rate) AS whole, rate - floor(rate) AS part FROM (SELECT *, CASE WHEN source_size > 0 THEN target / source_size ELSE 0.0 END + 1e-12::DOUBLE AS rate FROM targets)),
      sums AS (SELECT r.source, any_value(r.source_size) AS source_size, any_value(target) AS target, any_value(whole) AS whole, any_value(part) AS part, {tried} FROM docs d JOIN rates r ON d.source IS NOT DISTINCT FROM r.source GROUP BY r.source),
      chosen AS (SELECT *, list_min([{best}])[2]::BIGINT AS seed FROM sums)
      SELECT doc_id, size, source_size, target, size * copies AS taken, copies, source FROM
        (SELECT d.*, c.source_size, c.target, least(c.whole + CASE WHEN {draw.format(seed='c.seed')} < c.part THEN 1 ELSE 0 END, {most})::BIGINT AS copies FROM docs d JOIN chosen c ON d.source IS NOT DISTINCT FROM c.source)"""


def oracle_sql() -> dict[str, str]:
    return {"op1_minhash": MINHASH_SQL, "op7_vector_dedup": VECTOR_DEDUP_SQL, "op9_mixing": mixing_sql()}
