"""Explicit schemas of the given tables and of what the engine derives from them."""

from __future__ import annotations

# The given tables' columns.
TABLES = {
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "pages": "page_id bigint, url string, html string",
    "labels": "doc_id bigint, quality int, toxic int",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
    "benchmark": "item_id bigint, text string",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
}

BLOCK_FIELDS = "codec string, n int, ctrl binary, data binary, exc binary, ctrl_bits bigint, data_bits bigint, exc_bits bigint, head_bits bigint"
POSTINGS = "term string, doc_id bigint, tf bigint"
TOPK = "query_id bigint, rank int, doc_id bigint, score double"
