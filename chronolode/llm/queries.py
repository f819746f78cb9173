"""The queries of this subpackage, and the SQL that gives the same rows where SQL can."""

from __future__ import annotations

from chronolode.llm import bpe, counts, embeddings, licenses, lines, media, mixing, quality, simhash, toxicity

QUERIES = {
    "op1_media": media.query,
    "op1_clips": media.clips_query,
    "op2_bpe": bpe.query,
    "op3_embedding_dedup": embeddings.query,
    "op4_token_counts": counts.query,
    "op5_simhash": simhash.query,
    "op6_licenses": licenses.query,
    "op6_notices": licenses.notices_query,
    "op6_license_texts": licenses.texts_query,
    "op7_quality": quality.query,
    "op8_toxicity": toxicity.query,
    "op9_mixing": mixing.query,
    "op10_line_dedup": lines.query,
}
ORACLES: dict[str, str] = {"op3_embedding_dedup": embeddings.ORACLE, "op6_licenses": licenses.ORACLE, "op6_notices": licenses.NOTICES_ORACLE, "op6_license_texts": licenses.TEXTS_ORACLE, "op9_mixing": mixing.ORACLE, "op10_line_dedup": lines.ORACLE}
