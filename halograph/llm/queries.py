"""Queries and SQL twins of the operators of this subpackage, by name."""

from halograph.llm import bpe, chat, decontaminate, exact_dedup, near_dedup, quality, suffix_dedup, token_counts, toxicity, warc

QUERIES = {
    "op1_token_counts": token_counts.op1_token_counts,
    "op2_near_dedup": near_dedup.op2_near_dedup,
    "op3_suffix_dedup": suffix_dedup.op3_suffix_dedup,
    "op4_toxicity": toxicity.op4_toxicity,
    "op5_bpe_roundtrip": bpe.op5_bpe_roundtrip,
    "op6_quality_crf": quality.op6_quality_crf,
    "op7_exact_dedup": exact_dedup.op7_exact_dedup,
    "op8_warc": warc.op8_warc,
    "op9_chat_format": chat.op9_chat_format,
    "op10_decontaminate": decontaminate.op10_decontaminate,
}
ORACLE_SQL = {"op2_near_dedup": near_dedup.OP2_SQL, "op3_suffix_dedup": suffix_dedup.OP3_SQL, "op7_exact_dedup": exact_dedup.OP7_SQL, "op8_warc": warc.OP8_SQL, "op9_chat_format": chat.OP9_SQL}
