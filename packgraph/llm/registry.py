"""Queries of this subpackage and their SQL, by name."""

from __future__ import annotations

from . import audio_fingerprint, byte_bpe, host_rules, language_id, line_dedup, ngram_join, packing, quality_classifier, substring_dedup, token_file

MODULES = (token_file, audio_fingerprint, byte_bpe, language_id, line_dedup, ngram_join, substring_dedup, quality_classifier, host_rules, packing)
QUERIES = {k: f for m in MODULES for k, f in m.QUERIES.items()}
ORACLES = {k: q for m in MODULES for k, q in m.ORACLES.items()}
