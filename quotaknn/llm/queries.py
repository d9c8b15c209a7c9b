"""The queries of this subpackage, by name, with SQL where SQL can express them."""

from __future__ import annotations

import corpus_pipeline
from quotaknn.llm import ann, exact_dedup, langid, minhash, mixing, packing, sharding, substring, suffix, tokens_out


def queries() -> dict:
    return {
        "op1_token_codes": tokens_out.query,
        "op2_mixing": mixing.query,
        "op3_suffix_dedup": suffix.query,
        "op4_exact_dedup": exact_dedup.query,
        "op5_line_dedup": substring.query,
        "op6_sharding": sharding.query,
        "op7_minhash": minhash.query,
        "op8_hash_forest": ann.query,
        "op9_language_id": langid.query,
        "op10_packing": packing.query,
        "pipeline": corpus_pipeline.run,
    }


def oracle_sql() -> dict[str, str]:
    return {"op4_exact_dedup": exact_dedup.SQL, "op5_line_dedup": substring.SQL}
