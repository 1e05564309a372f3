"""The registered queries of this subpackage and their SQL."""

from __future__ import annotations

from . import decontam, hilbert, html, langid, neardup, packing, pii, setjoin, suffix, tokencount

QUERIES = {
    "op1_hilbert_shards": hilbert.op1_hilbert_shards,
    "op2_neighbour_descent": neardup.op2_neighbour_descent,
    "op3_byte_convolution": langid.op3_byte_convolution,
    "op4_suffix_shards": suffix.op4_suffix_shards,
    "op5_benchmark_index": decontam.op5_benchmark_index,
    "benchmark_proximity": decontam.benchmark_proximity,
    "op6_skip_chain": pii.op6_skip_chain,
    "op7_section_tokens": tokencount.op7_section_tokens,
    "document_field_tokens": tokencount.document_field_tokens,
    "op8_best_fit_packing": packing.op8_best_fit_packing,
    "op9_recurrent_blocks": html.op9_recurrent_blocks,
    "op10_part_enum": setjoin.op10_part_enum,
}
ORACLES = {"op5_benchmark_index": decontam.OP5_SQL, "op10_part_enum": setjoin.OP10_SQL}
