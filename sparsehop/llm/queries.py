"""Queries of the text operators and their SQL, for the driver's entry file."""

from __future__ import annotations

from . import bpe, decontaminate, licenses, lines, media, neardup, pii, secrets, suffix, toxicity

QUERIES = {
    "op1_license_scan": licenses.query,
    "op2_suffix_dedup": suffix.query,
    "op3_toxicity": toxicity.query,
    "op4_jaccard_join": neardup.query,
    "op5_secret_scan": secrets.query,
    "op6_pii": pii.query,
    "op7_media": media.query,
    "op8_line_dedup": lines.query,
    "op9_decontaminate": decontaminate.query,
    "op10_bpe": bpe.query,
}
SQL = {"op4_jaccard_join": neardup.ORACLE, "op5_secret_scan": secrets.ORACLE, "op8_line_dedup": lines.ORACLE, "op9_decontaminate": decontaminate.ORACLE}
