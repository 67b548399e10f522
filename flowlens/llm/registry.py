"""Queries of the training-data operators and their SQL."""

from . import binary_output, hamming, matroska, mixing, near_dup, packing, quality, substring_dedup, toxicity, url_filter

QUERIES = {
    "op1_bfd_packed_ids": binary_output.op1_bfd_packed_ids,
    "op2_minhash_bayes": near_dup.op2_minhash_bayes,
    "op3_mix_hash_histogram": mixing.op3_mix_hash_histogram,
    "op4_ordinal_quality": quality.op4_ordinal_quality,
    "op5_suffix_array_dedup": substring_dedup.op5_suffix_array_dedup,
    "op6_best_fit_packing": packing.op6_best_fit_packing,
    "op7_multi_index_hamming": hamming.op7_multi_index_hamming,
    "op8_url_redirect_equivalence": url_filter.op8_url_redirect_equivalence,
    "op9_matroska": matroska.op9_matroska,
    "op10_toxic_span_crf": toxicity.op10_toxic_span_crf,
}

ORACLES = {
    "op3_mix_hash_histogram": mixing.ORACLE,
    "op7_multi_index_hamming": hamming.ORACLE,
    "op8_url_redirect_equivalence": url_filter.ORACLE,
}
