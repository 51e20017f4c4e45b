"""The queries of this subpackage, and SQL for those that SQL can express."""

from __future__ import annotations

from . import bpe, chat, compaction, line_rules, lm, mih, mixing, qda, simhash, suffix_dedup

QUERIES = {
    "op1_soft_membership_mixing": mixing.query,
    "op2_regularised_qda": qda.query,
    "op3_multi_index_hashing": mih.query,
    "op5_preference_format": chat.query,
    "op7_size_tiered_compaction": compaction.query,
    "op4_sparse_suffix_array": suffix_dedup.query,
    "op6_simhash_deletion_variants": simhash.query,
    "op8_bpe_codec": bpe.query,
    "op9_causal_attention": lm.query,
    "op10_line_frequency_rules": line_rules.query,
}

ORACLE_SQL: dict[str, str] = {
    "op3_multi_index_hashing": mih.ORACLE,
    "op5_preference_format": chat.ORACLE,
    "op10_line_frequency_rules": line_rules.ORACLE,
}
