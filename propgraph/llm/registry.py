"""The training-data queries and their SQL."""

from __future__ import annotations

from . import op1_winnow, op2_token_planes, op3_harmonic, op4_language, op5_webp, op6_minhash, op7_secrets, op8_poisson, op9_line_chunks, op10_phrases

QUERIES = {
    "op1_winnowing": op1_winnow.op1_winnowing,
    "op1_likeness": op1_winnow.op1_likeness,
    "op2_token_planes": op2_token_planes.op2_token_planes,
    "op3_harmonic_packing": op3_harmonic.op3_harmonic_packing,
    "op4_language": op4_language.op4_language,
    "op5_webp": op5_webp.op5_webp,
    "op6_minhash": op6_minhash.op6_minhash,
    "op7_secret_scan": op7_secrets.op7_secret_scan,
    "op7_base_counts": op7_secrets.op7_base_counts,
    "op8_poisson_mix": op8_poisson.op8_poisson_mix,
    "op9_line_chunk_dedup": op9_line_chunks.op9_line_chunk_dedup,
    "op9_line_passages": op9_line_chunks.op9_line_passages,
    "op10_phrase_dedup": op10_phrases.op10_phrase_dedup,
}
ORACLES = {"op1_likeness": op1_winnow.ORACLE, "op6_minhash": op6_minhash.ORACLE, "op10_phrase_dedup": op10_phrases.ORACLE, "op7_base_counts": op7_secrets.BASE_COUNTS, "op8_poisson_mix": op8_poisson.ORACLE, "op9_line_chunk_dedup": op9_line_chunks.ORACLE, "op9_line_passages": op9_line_chunks.PASSAGES_ORACLE}
