"""The queries of the training-data operators and their SQL, where SQL can express them."""

from __future__ import annotations

from tablevec.llm.chat_format import OP3_SQL, op3_chat_formatting
from tablevec.llm.decontamination import op8_benchmark_decontamination
from tablevec.llm.exact_search import OP2_SQL, op2_exact_top_k
from tablevec.llm.language_id import op4_language_id
from tablevec.llm.lm_scoring import op6_lm_scoring
from tablevec.llm.near_duplicates import op10_minhash_forest
from tablevec.llm.packing import op5_best_fit_packing
from tablevec.llm.sharding import op7_sharding
from tablevec.llm.token_counts import op9_token_counts
from tablevec.llm.toxicity import op1_toxicity

QUERIES = {f.__name__: f for f in (op1_toxicity, op2_exact_top_k, op3_chat_formatting, op4_language_id, op5_best_fit_packing, op6_lm_scoring, op7_sharding, op8_benchmark_decontamination, op9_token_counts, op10_minhash_forest)}
ORACLES: dict[str, str] = {"op2_exact_top_k": OP2_SQL, "op3_chat_formatting": OP3_SQL}
