"""Queries of this folder and the SQL that checks them, for the entry module."""

from __future__ import annotations

from chunkset.llm.byte_bpe import op2_byte_bpe
from chunkset.llm.mixing import op9_mixing
from chunkset.llm.privacy import op1_privacy
from chunkset.llm.quality import op5_quality
from chunkset.llm.simhash import op8_simhash
from chunkset.llm.token_counts import op3_token_counts
from chunkset.llm.toxicity import op4_toxicity
from chunkset.llm.vectors import op6_additive_quantisation, op7_iterative_quantisation
from chunkset.llm.warc import op10_warc

QUERIES = {
    "op1_privacy": op1_privacy,
    "op2_byte_bpe": op2_byte_bpe,
    "op3_token_counts": op3_token_counts,
    "op4_toxicity": op4_toxicity,
    "op5_quality": op5_quality,
    "op6_additive_quantisation": op6_additive_quantisation,
    "op7_iterative_quantisation": op7_iterative_quantisation,
    "op8_simhash": op8_simhash,
    "op9_mixing": op9_mixing,
    "op10_warc": op10_warc,
}

ORACLES: dict[str, str] = {}
