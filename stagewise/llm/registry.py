"""The queries of this subpackage by name, and their SQL where SQL can express them."""

from . import byte_bpe, exact_dedup, language_id, line_dedup, mixing, quality, simhash, substring_dedup, topk, toxicity

QUERIES = {
    f.__name__: f
    for f in (
        mixing.op1_mixing,
        byte_bpe.op2_byte_bpe,
        language_id.op3_language_id,
        quality.op4_quality,
        topk.op5_exact_topk,
        simhash.op6_simhash_near_dedup,
        line_dedup.op7_line_dedup,
        line_dedup.op7_single_line_dedup,
        toxicity.op8_toxicity,
        exact_dedup.op9_exact_dedup,
        substring_dedup.op10_substring_dedup,
    )
}

ORACLE_SQL = {"op5_exact_topk": topk.OP5_SQL, "op7_line_dedup": line_dedup.OP7_SQL, "op7_single_line_dedup": line_dedup.OP7_SINGLE_SQL, "op9_exact_dedup": exact_dedup.OP9_SQL, "op10_substring_dedup": substring_dedup.OP10_SQL}
