"""Registered queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from rankjoin.llm.bpe import op1_byte_bpe
from rankjoin.llm.chat import OP3_SQL, op3_chat_format
from rankjoin.llm.html import op4_main_text
from rankjoin.llm.lines import op5_line_dedup
from rankjoin.llm.mixing import op10_source_mix
from rankjoin.llm.neighbours import measure_recall, op7_collision_search
from rankjoin.llm.quality import op8_quality_rules
from rankjoin.llm.simhash import op6_simhash
from rankjoin.llm.toxicity import op2_toxicity
from rankjoin.llm.wavelet import op9_wavelet_ids

QUERIES = {f.__name__: f for f in (op1_byte_bpe, op2_toxicity, op3_chat_format, op4_main_text, op5_line_dedup, op6_simhash, op7_collision_search, op8_quality_rules, op9_wavelet_ids, op10_source_mix)}
QUERIES["recall_collision_search"] = measure_recall
ORACLE_SQL = {"op3_chat_format": OP3_SQL}
