"""Queries of this subpackage and their SQL."""

from __future__ import annotations

from phasewarp.llm import bpe, exact_dedup, line_dedup, mixing, passage_dedup, simhash_golay, token_orc, toxicity, warc, weighted_sampling

QUERIES = {
    "op1_token_orc": token_orc.query,
    "op2_simhash_golay": simhash_golay.query,
    "op3_mixing": mixing.query,
    "op4_exact_dedup": exact_dedup.query,
    "op5_bpe": bpe.query,
    "op6_warc": warc.query,
    "op7_toxicity": toxicity.query,
    "op8_line_dedup": line_dedup.query,
    "op9_weighted_sampling": weighted_sampling.query,
    "op10_passage_dedup": passage_dedup.query,
}
SQL = {
    "op3_mixing": mixing.SQL,
    "op4_exact_dedup": exact_dedup.SQL,
}
