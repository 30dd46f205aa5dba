"""The queries of this package and their SQL."""

from __future__ import annotations

from metricblock.llm import embedding_dedup, line_crf, mixing, neighbours, packing, passage_dedup, simhash, suffix_dedup, toxicity, url_cascade

QUERIES = {
    "op1_packing": packing.op1_packing,
    "op2_projection_tree": neighbours.op2_projection_tree,
    "op3_toxicity": toxicity.op3_toxicity,
    "op4_suffix_array": suffix_dedup.op4_suffix_array,
    "op5_sorted_passes": embedding_dedup.op5_sorted_passes,
    "op6_simhash": simhash.op6_simhash,
    "op7_passages": passage_dedup.op7_passages,
    "op8_url_cascade": url_cascade.op8_url_cascade,
    "op9_line_crf": line_crf.op9_line_crf,
    "op10_mixing": mixing.op10_mixing,
}
ORACLE_SQL = {
    "op8_url_cascade": url_cascade.OP8_SQL,
}
