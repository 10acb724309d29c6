"""Queries of the corpus operators and the SQL that checks them."""

from __future__ import annotations

from . import bytebpe, chat, decontaminate, exactdup, htmltext, neardup, quality, secrets, surrogates, urlfilter

QUERIES = {
    "op1_secret_forest": secrets.op1_secret_forest,
    "op2_wu_manber": decontaminate.op2_wu_manber,
    "op3_min_max": neardup.op3_min_max,
    "op4_host_suffixes": htmltext.op4_host_suffixes,
    "op5_url_ngrams": urlfilter.op5_url_ngrams,
    "op6_keyed_surrogates": surrogates.op6_keyed_surrogates,
    "op7_ftrl_quality": quality.op7_ftrl_quality,
    "op8_snapshot_collapse": chat.op8_snapshot_collapse,
    "op9_counting_quotient": exactdup.op9_counting_quotient,
    "op10_byte_bpe": bytebpe.op10_byte_bpe,
}

ORACLES = {
    "op2_wu_manber": decontaminate.ORACLE,
    "op3_min_max": neardup.ORACLE,
    "op8_snapshot_collapse": chat.ORACLE,
    "op9_counting_quotient": exactdup.ORACLE,
}
