"""Registered queries of the training-data operators and, where SQL can express them, their oracles."""

from __future__ import annotations

from levelgraph.llm.decontamination import op9_decontamination
from levelgraph.llm.licences import op8_licences
from levelgraph.llm.line_quality import op7_line_quality
from levelgraph.llm.mixing import op2_source_mix
from levelgraph.llm.near_duplicates import op1_near_duplicates
from levelgraph.llm.oracles import ORACLES
from levelgraph.llm.pii import op10_personal_data
from levelgraph.llm.quality_rules import op6_quality_rules
from levelgraph.llm.token_counts import op4_token_counts
from levelgraph.llm.token_output import op3_token_output
from levelgraph.llm.toxicity import op5_toxicity

QUERIES = {
    "op1_near_duplicates": op1_near_duplicates,
    "op2_source_mix": op2_source_mix,
    "op3_token_output": op3_token_output,
    "op4_token_counts": op4_token_counts,
    "op5_toxicity": op5_toxicity,
    "op6_quality_rules": op6_quality_rules,
    "op7_line_quality": op7_line_quality,
    "op8_licences": op8_licences,
    "op9_decontamination": op9_decontamination,
    "op10_personal_data": op10_personal_data,
}

__all__ = ["ORACLES", "QUERIES"]
