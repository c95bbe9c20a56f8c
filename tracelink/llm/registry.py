"""Queries of this subpackage for the entry module."""

from __future__ import annotations

from . import fingerprints, gif, language_crf, near_dups, pieces, poisson_mix, shards, toxicity, url_rules, windows

QUERIES = {
    "op1_gif_media": gif.op1_gif_media,
    "op2_pieces": pieces.op2_pieces,
    "op3_toxicity": toxicity.op3_toxicity,
    "op4_language_crf": language_crf.op4_language_crf,
    "op5_fingerprints": fingerprints.op5_fingerprints,
    "op6_poisson_mix": poisson_mix.op6_poisson_mix,
    "op7_near_dups": near_dups.op7_near_dups,
    "op8_windows": windows.op8_windows,
    "op9_shards": shards.op9_shards,
    "op10_url_filter": url_rules.op10_url_filter,
}

ORACLES = {
    "op6_poisson_mix": poisson_mix.OP6_SQL,
    "op7_near_dups": near_dups.OP7_SQL,
    "op8_windows": windows.OP8_SQL,
    "op10_url_filter": url_rules.OP10_SQL,
}
