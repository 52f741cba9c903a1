"""The opN queries and their DuckDB twins."""

from __future__ import annotations

from hubsplit.llm import embedding_dedup, language, mixing, packing, quality, simhash, suffix_dedup, token_counts, token_output, url_filter


def queries():
    return {
        "op1_language_id": language.op1_language_id,
        "op2_best_fit_packing": packing.op2_best_fit_packing,
        "op3_quality_rules": quality.op3_quality_rules,
        "op4_mixing": mixing.op4_mixing,
        "op5_token_output": token_output.op5_token_output,
        "op6_suffix_dedup": suffix_dedup.op6_suffix_dedup,
        "op7_embedding_dedup": embedding_dedup.op7_embedding_dedup,
        "op8_token_counts": token_counts.op8_token_counts,
        "op9_simhash_dedup": simhash.op9_simhash_dedup,
        "op10_url_filter": url_filter.op10_url_filter,
    }


def oracle_sql():
    return {"op4_mixing": mixing.OP4_SQL}
