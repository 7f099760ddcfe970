"""Queries and SQL of this subpackage."""

from ctxloom.llm import bytebpe, langid, lmscore, media, minhash, mixing, quality, sharding, simhash, toxicity

MODULES = (sharding, simhash, bytebpe, media, minhash, mixing, lmscore, toxicity, quality, langid)
QUERIES = {name: q for m in MODULES for name, q in m.QUERIES.items()}
ORACLES = {name: sql for m in MODULES for name, sql in m.ORACLES.items()}
