"""The queries of this subpackage and, where SQL can express one, its SQL."""

from __future__ import annotations

from gridsparse.llm import bpe, language, media, mixing, neardup, pii, quality, search, token_counts, toxicity

QUERIES = {
    "op1_mixing": mixing.op1_mixing,
    "op2_byte_bpe": bpe.op2_byte_bpe,
    "op3_media": media.op3_media,
    "op4_search": search.op4_search,
    "op5_token_counts": token_counts.op5_token_counts,
    "op6_neardup": neardup.op6_neardup,
    "op7_toxicity": toxicity.op7_toxicity,
    "op8_pii": pii.op8_pii,
    "op9_language": language.op9_language,
    "op10_quality": quality.op10_quality,
}
ORACLE_SQL: dict[str, str] = {"op4_search": search.ORACLE_SQL, "op6_neardup": neardup.ORACLE_SQL}
