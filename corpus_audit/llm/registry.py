"""The queries of this subpackage and the SQL of those that SQL can express."""

from __future__ import annotations

from corpus_audit.llm import extraction, language, line_dedup, media, mixing, near_dup, oracles, packing, quality, sharding, toxicity

QUERIES = {
    "op1_mixing": mixing.op1_mixing,
    "op2_line_dedup": line_dedup.op2_line_dedup,
    "op3_media": media.op3_media,
    "op4_sharding": sharding.op4_sharding,
    "op5_extraction": extraction.op5_extraction,
    "op6_language": language.op6_language,
    "op7_quality": quality.op7_quality,
    "op8_toxicity": toxicity.op8_toxicity,
    "op9_near_dup": near_dup.op9_near_dup,
    "op10_pack": packing.op10_pack,
}
ORACLES = {"op4_sharding": sharding.OP4_SQL, "op7_quality": quality.OP7_SQL, "op9_near_dup": oracles.NEAR_DUP_SQL}
