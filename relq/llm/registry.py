"""Queries of this subpackage, with SQL where SQL can express them on whole tables."""

from __future__ import annotations

from . import decontaminate, embeddings, language, licenses, packing, quality, secrets, simhash, toxicity, warc

QUERIES = {
    "op1_decontamination": decontaminate.op1_decontamination,
    "op2_packing": packing.op2_packing,
    "op3_warc": warc.op3_warc,
    "op4_secrets": secrets.op4_secrets,
    "op5_language": language.op5_language,
    "op6_licenses": licenses.op6_licenses,
    "op7_simhash": simhash.op7_simhash,
    "op8_toxicity": toxicity.op8_toxicity,
    "op9_vectors": embeddings.op9_vectors,
    "op10_quality": quality.op10_quality,
}
ORACLES: dict[str, str] = {"op3_warc": warc.ORACLE}
