"""Queries of this subpackage, by name, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from privq.llm.audio import op6_audio_features
from privq.llm.bpe import op10_bpe_round_trip
from privq.llm.mixing import op8_mixing
from privq.llm.ngram_join import op5_ngram_join, op5_ngram_join_links
from privq.llm.packing import op1_packing
from privq.llm.secrets import op4_secret_scan
from privq.llm.sharding import op3_sharding
from privq.llm.token_counts import op7_token_counts
from privq.llm.toxicity import op2_toxicity
from privq.llm.vector_search import op9_vector_search


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_packing": op1_packing,
        "op2_toxicity": op2_toxicity,
        "op3_sharding": op3_sharding,
        "op4_secret_scan": op4_secret_scan,
        "op5_ngram_join": op5_ngram_join,
        "op5_ngram_join_links": op5_ngram_join_links,
        "op6_audio_features": op6_audio_features,
        "op7_token_counts": op7_token_counts,
        "op8_mixing": op8_mixing,
        "op9_vector_search": op9_vector_search,
        "op10_bpe_round_trip": op10_bpe_round_trip,
    }


NGRAM_JOIN_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
  s AS (SELECT doc_id, CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')]
      ELSE list_distinct(list_transform(range(1, len(ws) - 3), lambda k: array_to_string(ws[k:k + 4], ' '))) END AS g FROM w),
  x AS (SELECT doc_id, len(g) AS n, unnest(g) AS h FROM s),
  p AS (SELECT a.doc_id AS i, b.doc_id AS j FROM x a JOIN x b ON a.h = b.h AND a.doc_id <> b.doc_id GROUP BY a.doc_id, b.doc_id, a.n, b.n
      HAVING 100 * count(*) >= 80 * (a.n + b.n - count(*))),
  r AS (SELECT doc_id, doc_id AS root FROM s UNION SELECT p.j, r.root FROM r JOIN p ON p.i = r.doc_id WHERE r.root < p.j)
SELECT s.doc_id, CAST(len(s.g) AS BIGINT) AS n_shingles, min(r.root) AS component_id FROM s JOIN r ON r.doc_id = s.doc_id GROUP BY s.doc_id, len(s.g)
"""

_CTES, _CLASSES = NGRAM_JOIN_SQL.rsplit("\n", 2)[0], NGRAM_JOIN_SQL.rsplit("\n", 2)[1]
NGRAM_LINKS_SQL = f"""{_CTES},
  c AS ({_CLASSES}), k AS (SELECT i, count(*) AS n FROM p GROUP BY i)
SELECT c.doc_id, c.n_shingles, c.component_id, coalesce(k.n, 0) AS n_links FROM c LEFT JOIN k ON k.i = c.doc_id
"""


def oracle_sql() -> dict[str, str]:
    """The other results hold models, library tokens or digests that DuckDB has no functions for."""
    return {"op5_ngram_join": NGRAM_JOIN_SQL, "op5_ngram_join_links": NGRAM_LINKS_SQL}
