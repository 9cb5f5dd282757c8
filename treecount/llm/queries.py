"""The queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from . import bytebpe, fingerprints, linededup, lmscore, neardup, packing, privacy, quality, tokens, warc

QUERIES = {
    "op1_warc": warc.op1_warc,
    "op2_line_dedup": linededup.op2_line_dedup,
    "op3_information_pii": privacy.op3_information_pii,
    "op4_weighted_fingerprints": fingerprints.op4_weighted_fingerprints,
    "op5_minhash_near_dedup": neardup.op5_minhash_near_dedup,
    "op6_min_slack_packing": packing.op6_min_slack_packing,
    "op7_byte_bpe": bytebpe.op7_byte_bpe,
    "op8_quality_rules": quality.op8_quality_rules,
    "op9_token_binary": tokens.op9_token_binary,
    "op10_masked_lm_score": lmscore.op10_masked_lm_score,
}

SQL = {
    "op1_warc": warc.SQL,
    "op5_minhash_near_dedup": neardup.SQL,
    "op8_quality_rules": quality.SQL,
}
