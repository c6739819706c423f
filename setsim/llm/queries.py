"""Queries of this subpackage, by the names under which the entry module registers them."""

from __future__ import annotations

from setsim.llm.decontaminate import op2_decontaminate
from setsim.llm.embeddings import op4_embeddings
from setsim.llm.html import op10_html
from setsim.llm.language import op6_language
from setsim.llm.lines import op9_line_dedup
from setsim.llm.near_duplicates import op3_near_duplicates
from setsim.llm.oracles import ORACLES
from setsim.llm.packing import op8_packing
from setsim.llm.quality import op5_quality
from setsim.llm.sharding import op1_sharding
from setsim.llm.tokens import op7_token_counts

__all__ = ["ORACLES", "QUERIES"]

QUERIES = {
    "op1_sharding": op1_sharding,
    "op2_decontaminate": op2_decontaminate,
    "op3_near_duplicates": op3_near_duplicates,
    "op4_embeddings": op4_embeddings,
    "op5_quality": op5_quality,
    "op6_language": op6_language,
    "op7_token_counts": op7_token_counts,
    "op8_packing": op8_packing,
    "op9_line_dedup": op9_line_dedup,
    "op10_html": op10_html,
}
