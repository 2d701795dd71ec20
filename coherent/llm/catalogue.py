"""Queries of the corpus operators and their SQL, by name."""

from __future__ import annotations

from . import decontamination, fingerprint, licenses, mixing, neardup, pii, sharding, substrings, toxicity, warc

QUERIES = {
    "op1_licenses": licenses.op1,
    "op2_fingerprints": fingerprint.op2,
    "op3_mixing": mixing.op3,
    "op4_near_duplicates": neardup.op4,
    "op5_pii": pii.op5,
    "op6_substrings": substrings.op6,
    "op7_warc": warc.op7,
    "op8_sharding": sharding.op8,
    "op9_decontamination": decontamination.op9,
    "op10_toxicity": toxicity.op10,
}
ORACLES = {"op7_warc": warc.ORACLE, "op9_decontamination": decontamination.ORACLE}
