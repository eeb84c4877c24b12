"""Queries of the corpus operators and their DuckDB twins."""

from __future__ import annotations

from worldfold.llm import fingerprints, langid, linededup, mixing, packing, pii, secrets, sharding, simhash, tiff

QUERIES = {
    "op1_mix_sources": mixing.op1_mix_sources,
    "op2_fingerprints": fingerprints.op2_fingerprints,
    "op3_packing": packing.op3_packing,
    "op4_pii": pii.op4_pii,
    "op5_simhash": simhash.op5_simhash,
    "op6_sharding": sharding.op6_sharding,
    "op7_line_dedup": linededup.op7_line_dedup,
    "op8_tiff": tiff.op8_tiff,
    "op9_secrets": secrets.op9_secrets,
    "op10_language": langid.op10_language,
    "language_of_pages": langid.language_of_pages,
}

ORACLES = {"op1_mix_sources": mixing.ORACLE, "op7_line_dedup": linededup.ORACLE, "op9_secrets": secrets.oracle()}
