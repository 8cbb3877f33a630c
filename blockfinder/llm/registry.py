"""The queries of this folder and their SQL."""

from __future__ import annotations

from . import counting, facts, language, lm, media, packing, pieces, pii, quality, sharding, simhash

QUERIES = {
    "op1_longest_first_shards": sharding.query,
    "op2_piece_lattice": pieces.query,
    "op3_class_ngram_scores": lm.query,
    "op4_feistel_pseudonyms": pii.query,
    "op5_compression_language": language.query,
    "op6_gray_simhash": simhash.query,
    "op7_best_fit_packing": packing.query,
    "op8_iso_media": media.query,
    "op9_edit_aware_counts": counting.query,
    "op10_quality_rules": quality.query,
    **facts.QUERIES,
}
ORACLES: dict[str, str] = dict(facts.ORACLES)
