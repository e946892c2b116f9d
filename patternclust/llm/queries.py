"""The registered queries of this subpackage and their SQL."""

from __future__ import annotations

from . import exact_dedup, mixing, quality, sentencepiece_codec, simhash, substring_dedup, suffix_array_dedup, topk_search, url_filter, warc_zip

QUERIES = {
    "op1_simhash_near_dedup": simhash.op1_simhash_near_dedup,
    "op2_substring_dedup": substring_dedup.op2_substring_dedup,
    "op3_topk_search": topk_search.op3_topk_search,
    "op4_sentencepiece": sentencepiece_codec.op4_sentencepiece,
    "op5_url_filter": url_filter.op5_url_filter,
    "op6_exact_dedup": exact_dedup.op6_exact_dedup,
    "op7_quality_classifier": quality.op7_quality_classifier,
    "op8_warc": warc_zip.op8_warc,
    "op9_suffix_array_dedup": suffix_array_dedup.op9_suffix_array_dedup,
    "op10_mixing": mixing.op10_mixing,
}
ORACLES = {
    "op3_topk_search": topk_search.OP3_SQL,
    "op6_exact_dedup": exact_dedup.OP6_SQL,
    "op8_warc": warc_zip.OP8_SQL,
    "op10_mixing": mixing.OP10_SQL,
}
