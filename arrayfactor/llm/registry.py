"""Queries of the training-data operators and the SQL that gives the same rows."""

from __future__ import annotations

from . import decontaminate, exactdup, licenses, neardup, pieces, pii, quality, secrets, tokencount, toxicity

QUERIES = {
    "op1_pii": pii.op1_pii,
    "op2_quality": quality.op2_quality,
    "op3_exactdup": exactdup.op3_exactdup,
    "op4_licenses": licenses.op4_licenses,
    "op5_neardup": neardup.op5_neardup,
    "op8_secrets": secrets.op8_secrets,
    "op9_toxicity": toxicity.op9_toxicity,
    "op6_pieces": pieces.op6_pieces,
    "op7_decontaminate": decontaminate.op7_decontaminate,
    "op10_token_counts": tokencount.op10_token_counts,
}
ORACLES = {
    "op3_exactdup": exactdup.ORACLE,
    "op4_licenses": licenses.ORACLE,
    "op5_neardup": neardup.ORACLE,
    "op7_decontaminate": decontaminate.ORACLE,
}
