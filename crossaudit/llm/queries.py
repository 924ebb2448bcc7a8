"""Thin queries over the operators of this subpackage, and their SQL."""

from __future__ import annotations

from crossaudit.llm import embeddings, langid, licenses, linededup, mixing, ogg, packing, simhash, suffixes, toxicity

QUERIES = {
    "op10_license_scan": licenses.query,
    "op1_pack_sequences": packing.query,
    "op2_simhash_groups": simhash.query,
    "op3_toxicity": toxicity.query,
    "op4_line_dedup": linededup.query,
    "op5_repeated_passages": suffixes.query,
    "op6_vector_groups": embeddings.query,
    "op7_language": langid.query,
    "op8_media_ogg": ogg.query,
    "op9_mix_sources": mixing.query,
}

ORACLES = {
    "op10_license_scan": licenses.oracle(),
    "op4_line_dedup": linededup.ORACLE,
    "op9_mix_sources": mixing.ORACLE,
}
