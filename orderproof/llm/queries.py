"""The registered queries of this subpackage and the SQL that checks them."""

from __future__ import annotations

from orderproof.llm import bpe_codec, exact_dedup, katz, licenses, line_dedup, nearest, ngram_join, packing, secrets, toxicity

QUERIES = {
    "op1_line_dedup": line_dedup.query,
    "op2_secret_scan": secrets.query,
    "op3_packing": packing.query,
    "op4_ngram_jaccard": ngram_join.query,
    "op5_nearest": nearest.query,
    "op6_byte_bpe": bpe_codec.query,
    "op7_toxicity": toxicity.query,
    "op8_katz": katz.query,
    "op9_licenses": licenses.query,
    "op10_exact_dedup": exact_dedup.query,
}
ORACLES = {"op4_ngram_jaccard": ngram_join.ORACLE, "op10_exact_dedup": exact_dedup.ORACLE}
