"""The operators' queries and SQL, for __spark_entry__.py."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from momentbuf.llm.embeddings import op1_embedding_links
from momentbuf.llm.html import op10_main_text
from momentbuf.llm.near_dup import op7_near_duplicates
from momentbuf.llm.packing import op9_pack
from momentbuf.llm.pieces import op3_sampled_pieces
from momentbuf.llm.pipeline import run as pipeline
from momentbuf.llm.secrets import op8_secret_scan
from momentbuf.llm.sstable import op6_token_tables
from momentbuf.llm.suffix_dedup import op2_repeated_strings
from momentbuf.llm.topk import op4_exact_top_k
from momentbuf.llm.toxicity import op5_toxicity

QUERIES = {
    "pipeline": pipeline,
    "op1_embedding_links": op1_embedding_links,
    "op2_repeated_strings": op2_repeated_strings,
    "op3_sampled_pieces": op3_sampled_pieces,
    "op4_exact_top_k": op4_exact_top_k,
    "op5_toxicity": op5_toxicity,
    "op6_token_tables": op6_token_tables,
    "op7_near_duplicates": op7_near_duplicates,
    "op8_secret_scan": op8_secret_scan,
    "op9_pack": op9_pack,
    "op10_main_text": op10_main_text,
}
#: Exact search is plain SQL: floors, every product, the first twenty by score and id.
_TOP_K = """WITH e AS (SELECT vec_id, row_number() OVER () AS n, list_transform(embedding, lambda x: floor(64 * CAST(x AS DOUBLE))) AS v FROM embeddings
 WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_inner_product(q.v, c.v) AS BIGINT) AS score, c.n FROM e q JOIN e c ON q.n <> c.n WHERE q.vec_id % 20 = 0)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s) WHERE rank <= 20"""
ORACLES: dict[str, str] = {"op4_exact_top_k": _TOP_K}
