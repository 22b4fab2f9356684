"""The registered queries of this subpackage and their SQL."""

from __future__ import annotations

from turnwise.llm.pieces import op6_piece_codec
from turnwise.llm import quality
from turnwise.llm.toxicity import op2_toxicity
from turnwise.llm.pii import op1_personal_data
from turnwise.llm.warc import op3_warc_round_trip
from turnwise.llm.html_text import op8_main_text
from turnwise.llm.lines import op7_fuzzy_lines
from turnwise.llm.packing import op4_packed_ids
from turnwise.llm.leaks import op9_benchmark_leaks
from turnwise.llm.simhash import op10_simhash_components

QUERIES = {
    "op9_benchmark_leaks": op9_benchmark_leaks,
    "op4_packed_ids": op4_packed_ids,
    "op7_fuzzy_lines": op7_fuzzy_lines,
    "op8_main_text": op8_main_text,
    "op3_warc_round_trip": op3_warc_round_trip,
    "op1_personal_data": op1_personal_data,
    "op2_toxicity": op2_toxicity,
    "op5_quality_ledger": quality.op5_quality_ledger,
    "op6_piece_codec": op6_piece_codec,
    "op10_simhash_components": op10_simhash_components,
    "quality_ablation": quality.ablation_report,
}

ORACLES: dict[str, str] = {
    "op5_quality_ledger": quality.ORACLE,
    "quality_ablation": quality.ABLATION_ORACLE,
}
