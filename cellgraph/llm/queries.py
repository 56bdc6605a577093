"""Queries of the subpackage and their DuckDB SQL, by name."""

from __future__ import annotations

from . import chat_pref, decontam, ef_ngram, exact_stream, jaccard_join, langid, packing, pu_toxicity, suffix_levels, warc_zstd

QUERIES = {
    "op1_preference_format": chat_pref.op1_preference_format,
    "op2_suffix_level_dedup": suffix_levels.op2_suffix_level_dedup,
    "op3_aho_decontamination": decontam.op3_aho_decontamination,
    "op4_exact_stream_dedup": exact_stream.op4_exact_stream_dedup,
    "op5_best_fit_packing": packing.op5_best_fit_packing,
    "op6_elias_fano_lm": ef_ngram.op6_elias_fano_lm,
    "op7_metric_jaccard_join": jaccard_join.op7_metric_jaccard_join,
    "op8_language_centroids": langid.op8_language_centroids,
    "op9_warc_seekable": warc_zstd.op9_warc_seekable,
    "op10_nnpu_toxicity": pu_toxicity.op10_nnpu_toxicity,
}

ORACLES = {
    "op1_preference_format": chat_pref.ORACLE_SQL,
    "op3_aho_decontamination": decontam.ORACLE_SQL,
    "op4_exact_stream_dedup": exact_stream.ORACLE_SQL,
    "op7_metric_jaccard_join": jaccard_join.ORACLE_SQL,
    "op9_warc_seekable": warc_zstd.ORACLE_SQL,
}
