"""The queries of this subpackage and their SQL."""

from __future__ import annotations

from . import ann, bpe, decontaminate, licenses, line_dedup, ngram_join, quality, secrets_scan, substring, toxicity

QUERIES = {
    "op1_line_dedup": line_dedup.op1_line_dedup,
    "op2_bpe": bpe.op2_bpe,
    "op3_decontamination": decontaminate.op3_decontamination,
    "op4_licenses": licenses.op4_licenses,
    "op5_quality": quality.op5_quality,
    "op6_substring_dedup": substring.op6_substring_dedup,
    "op7_toxicity": toxicity.op7_toxicity,
    "op8_secrets": secrets_scan.op8_secrets,
    "op9_nearest": ann.op9_nearest,
    "op10_ngram_join": ngram_join.op10_ngram_join,
}
SQL = {
    "op1_line_dedup": line_dedup.OP1_SQL,
    "op3_decontamination": decontaminate.OP3_SQL,
}
