"""The queries of this subpackage and their SQL, gathered from its modules."""

from __future__ import annotations

from . import byte_bpe, decontamination, exact_dedup, html_text, line_dedup, quality, simhash, substring_dedup, suffix_dedup, token_counts

MODULES = (substring_dedup, decontamination, exact_dedup, quality, suffix_dedup, token_counts, html_text, byte_bpe, line_dedup, simhash)
QUERIES = {k: v for m in MODULES for k, v in m.QUERIES.items()}
ORACLES = {k: v for m in MODULES for k, v in m.ORACLES.items()}
