"""Queries of the training-data operators, for __spark_entry__.py."""

from __future__ import annotations

from . import byte_contexts, jaccard_join, kneser_ney, line_templates, lookup_sketch, mixing, packing, skip_chain, transport_stream, url_filters

QUERIES = {
    "op1_skip_chain": skip_chain.op1_skip_chain,
    "op8_lookup_sketch": lookup_sketch.op8_lookup_sketch,
    "op9_language_id": byte_contexts.op9_language_id,
    "op5_quality_classifier": kneser_ney.op5_quality_classifier,
    "op6_jaccard_join": jaccard_join.op6_jaccard_join,
    "op3_line_templates": line_templates.op3_line_templates,
    "op10_source_mixing": mixing.op10_source_mixing,
    "op2_url_filters": url_filters.op2_url_filters,
    "op4_best_fit_packing": packing.op4_best_fit_packing,
    "op7_media_columns": transport_stream.op7_media_columns,
}
ORACLES = {"op6_jaccard_join": jaccard_join.SQL, "op3_line_templates": line_templates.SQL, "op2_url_filters": url_filters.SQL}
