"""The queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from regpath.llm import decontaminate, language, licenses, lines, mixing, neardup, passages, quality, sharding, vectors

QUERIES = {
    "op1_mix_sources": mixing.op1_mix_sources,
    "op2_license_scan": licenses.op2_license_scan,
    "op3_embedding_dedup": vectors.op3_embedding_dedup,
    "op4_decontaminate": decontaminate.op4_decontaminate,
    "op5_shard": sharding.op5_shard,
    "op6_quality": quality.op6_quality,
    "op7_line_dedup": lines.op7_line_dedup,
    "op8_shared_passages": passages.op8_shared_passages,
    "op9_near_dedup": neardup.op9_near_dedup,
    "op10_language": language.op10_language,
    "page_language": language.page_language,
}
ORACLES = {
    "op1_mix_sources": mixing.ORACLE,
    "op2_license_scan": licenses.ORACLE,
    "op4_decontaminate": decontaminate.ORACLE,
    "op7_line_dedup": lines.ORACLE,
}
