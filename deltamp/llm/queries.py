"""All queries of the corpus operators and their SQL."""

from deltamp.llm import q_chat, q_leaks, q_licenses, q_passages, q_pieces, q_pii, q_quality, q_revisits, q_simhash, q_urls

_MODULES = (q_pii, q_simhash, q_revisits, q_pieces, q_quality, q_passages, q_urls, q_leaks, q_licenses, q_chat)
QUERIES = {k: f for m in _MODULES for k, f in m.QUERIES.items()}
ORACLES = {k: s for m in _MODULES for k, s in m.ORACLES.items()}
