"""All queries of this subpackage and their SQL."""

from __future__ import annotations

from . import byte_bpe, chat_rotation, decontamination, language_crf, line_dedup, main_text, simhash, substring_dedup, toxicity, webp

MODULES = (line_dedup, webp, main_text, substring_dedup, byte_bpe, toxicity, language_crf, decontamination, chat_rotation, simhash)

QUERIES = {k: v for m in MODULES for k, v in m.QUERIES.items()}
ORACLES = {k: v for m in MODULES for k, v in m.ORACLES.items()}
