"""All queries of the engine and their oracles, by name."""

from __future__ import annotations

from quadpost.plans import codec_queries, index_queries, search_queries, surface_queries

_MODULES = (index_queries, codec_queries, search_queries, surface_queries)


def queries() -> dict:
    return {n: q for m in _MODULES for n, q in m.QUERIES.items()}


def oracles() -> dict[str, str]:
    return {n: o for m in _MODULES for n, o in m.ORACLES.items()}
