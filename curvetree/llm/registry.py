"""All queries of this subpackage, and their SQL."""

from __future__ import annotations

from . import bpe, embeddings, media, packing, passages, sharding, simhash, tokens, toxicity, urlfilter

MODULES = (sharding, tokens, simhash, urlfilter, bpe, media, embeddings, passages, toxicity, packing)
QUERIES = {name: fn for m in MODULES for name, fn in m.QUERIES.items()}
ORACLE = {name: sql for m in MODULES for name, sql in getattr(m, "ORACLE", {}).items()}
