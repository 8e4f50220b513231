"""Queries and SQL of this subpackage, for the driver's entry module."""

from foldstar.llm import bpe, language, licences, lines, packing, quality, similar, simhash, substrings, token_counts, vectors

QUERIES = {
    "op1_token_counts": token_counts.op1_token_counts,
    "op2_language": language.op2_language,
    "op3_vectors": vectors.op3_vectors,
    "op4_line_dedup": lines.op4_line_dedup,
    "op5_quality_rules": quality.op5_quality_rules,
    "op6_simhash": simhash.op6_simhash,
    "op6_similar": similar.op6_similar,
    "op7_packing": packing.op7_packing,
    "op8_substrings": substrings.op8_substrings,
    "op9_byte_bpe": bpe.op9_byte_bpe,
    "op10_licences": licences.op10_licences,
}
ORACLES = {
    "op3_vectors": vectors.OP3_SQL,
    "op4_line_dedup": lines.OP4_SQL,
    "op5_quality_rules": quality.OP5_SQL,
    "op8_substrings": substrings.OP8_SQL,
}
