"""Queries of the corpus operators, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .balltree import op4_exact_top_k
from .digest import op3_improbable_feature_digest
from .language import op10_language_id
from .maxent import op2_maxent_scores
from .mixing import op7_soft_membership_mixing
from .packing import op1_sum_of_squares_packing
from .packed_ids import op8_packed_token_ids
from .pagetext import op5_site_style_tree
from .secrets import op6_secret_scan
from .simhash import op9_simhash_near_dedup

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_sum_of_squares_packing": op1_sum_of_squares_packing,
    "op2_maxent_scores": op2_maxent_scores,
    "op3_improbable_feature_digest": op3_improbable_feature_digest,
    "op4_exact_top_k": op4_exact_top_k,
    "op5_site_style_tree": op5_site_style_tree,
    "op6_secret_scan": op6_secret_scan,
    "op7_soft_membership_mixing": op7_soft_membership_mixing,
    "op8_packed_token_ids": op8_packed_token_ids,
    "op9_simhash_near_dedup": op9_simhash_near_dedup,
    "op10_language_id": op10_language_id,
}

ORACLE_SQL: dict[str, str] = {
    "op4_exact_top_k": """
        WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * CAST(x AS DOUBLE))) AS q FROM embeddings
                   WHERE vec_id IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: isfinite(x))) = len(embedding)),
        p AS (SELECT a.vec_id AS query_id, b.vec_id, CAST(list_inner_product(a.q, b.q) AS BIGINT) AS score
              FROM v a JOIN v b ON a.vec_id <> b.vec_id AND len(a.q) = len(b.q) WHERE a.vec_id % 100 = 0),
        r AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INT) AS rank, vec_id, score FROM p)
        SELECT * FROM r WHERE rank <= 10""",
}
