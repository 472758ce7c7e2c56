"""Queries ``opN_<name>`` over whole tables, and their SQL where SQL can express them."""

from __future__ import annotations

from . import bagminhash, bpe_transducer, flac_media, hilbert_ann, lim_packing, pii_feistel, quality_resampling, substring_dedup, suffix_dedup, toxicity_ordinal

QUERIES = {
    "op1_substring_dedup": substring_dedup.query,
    "op2_hilbert_ann": hilbert_ann.query,
    "op3_suffix_dedup": suffix_dedup.query,
    "op4_quality_resampling": quality_resampling.query,
    "op5_bagminhash": bagminhash.query,
    "op6_bpe_transducer": bpe_transducer.query,
    "op7_pii_feistel": pii_feistel.query,
    "op8_toxicity_ordinal": toxicity_ordinal.query,
    "op9_flac_media": flac_media.query,
    "op10_lim_packing": lim_packing.query,
}

ORACLE_SQL = {
    "op1_substring_dedup": substring_dedup.ORACLE_SQL,
    "op2_hilbert_ann": hilbert_ann.ORACLE_SQL,
}
