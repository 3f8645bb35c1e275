"""The queries of the training-data operators, and their SQL where SQL can express them."""

from __future__ import annotations

from . import ann, decontam, licenses, linededup, neardup, pii, secrets, spm, toxicity, warc

QUERIES = {
    "op1_pii_surrogates": pii.op1,
    "op2_benchmark_decontamination": decontam.op2,
    "op3_minhash_near_dedup": neardup.op3,
    "op4_license_scan": licenses.op4,
    "op5_warc_derivatives": warc.op5,
    "op6_sentencepiece": spm.op6,
    "op7_toxicity": toxicity.op7,
    "op8_secret_scan": secrets.op8,
    "secret_base_counts": secrets.base_counts,
    "op9_line_dedup": linededup.op9,
    "op10_nearest_neighbours": ann.op10,
}

ORACLES = {
    "op4_license_scan": licenses.oracle(),
    "secret_base_counts": secrets.BASE_SQL,
    "op9_line_dedup": linededup.SQL9,
}
