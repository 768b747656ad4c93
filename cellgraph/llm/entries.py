"""Queries of this package, and SQL that gives the same rows where SQL can."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from cellgraph.llm.ann import ann_query
from cellgraph.llm.htmltext import extraction_query
from cellgraph.llm.langid import langid_query
from cellgraph.llm.linededup import line_dedup_query
from cellgraph.llm.mixing import mix_query
from cellgraph.llm.packing import packing_query
from cellgraph.llm.simhash import simhash_query
from cellgraph.llm.tokencount import token_count_query
from cellgraph.llm.topk import top_k_query
from cellgraph.llm.toxicity import toxicity_query


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_mix_sources": lambda s, d: mix_query(s, d).select("doc_id", "size", "source_size", "target", "taken"),
        "op2_exact_topk": top_k_query,
        "op3_html_text": extraction_query,
        "op4_ann_multiprobe": ann_query,
        "op5_language_id": langid_query,
        "op6_line_dedup": line_dedup_query,
        "op7_toxicity": toxicity_query,
        "op8_token_counts": token_count_query,
        "op9_simhash": simhash_query,
        "op10_packing": packing_query,
    }


#: Every key's number of documents by plain grouping; the kept lines are joined again in order.
LINE_DEDUP_SQL = r"""
WITH lines AS (
  SELECT doc_id, i AS pos, parts[i] AS line
  FROM (SELECT doc_id, parts, unnest(range(1, len(parts) + 1)) AS i
        FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS parts FROM documents))
), keyed AS (
  SELECT doc_id, pos, line,
         translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
                   'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k
  FROM lines
), busy AS (
  SELECT k FROM keyed WHERE length(k) >= 1 GROUP BY k HAVING count(DISTINCT doc_id) >= 10
)
SELECT doc_id,
       count(*)::BIGINT AS n_lines,
       count(busy.k)::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE busy.k IS NULL), '')) AS kept_sha256
FROM keyed LEFT JOIN busy ON keyed.k = busy.k
GROUP BY doc_id
"""

TOPK_SQL = """
WITH whole AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(64 * x::DOUBLE)) AS v FROM embeddings
  WHERE embedding IS NOT NULL AND len(embedding) > 0
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), scored AS (
  SELECT q.vec_id AS query_id, c.vec_id, list_dot_product(q.v, c.v)::BIGINT AS score
  FROM whole q JOIN whole c ON c.vec_id <> q.vec_id AND len(c.v) = len(q.v) WHERE q.vec_id % 20 = 0
), ranked AS (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INT AS rank FROM scored
)
SELECT query_id, rank, vec_id, score FROM ranked WHERE rank <= 20
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_exact_topk": TOPK_SQL, "op6_line_dedup": LINE_DEDUP_SQL}
