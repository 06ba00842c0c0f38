"""The registered queries of this subpackage, and DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from accord.llm import extract, langid, licences, mixing, packing, quality, repeats, secretscan, simhash, vectors

QUERIES = {
    "op1_quality": quality.op1_quality,
    "op2_packing": packing.op2_packing,
    "op3_secrets": secretscan.op3_secrets,
    "op4_repeats": repeats.op4_repeats,
    "op5_language": langid.op5_language,
    "op6_extract": extract.op6_extract,
    "op7_mix": mixing.op7_mix,
    "op8_vectors": vectors.op8_vectors,
    "op9_simhash": simhash.op9_simhash,
    "op10_licences": licences.op10_licences,
}

ORACLES = {
    "op3_secrets": secretscan.OP3_SQL,
    "op7_mix": mixing.OP7_SQL,
    "op8_vectors": vectors.OP8_SQL,
    "op10_licences": licences.OP10_SQL,
}
