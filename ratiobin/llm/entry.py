"""Queries of the training-data operators."""

from __future__ import annotations

from ratiobin.llm import revisits
from ratiobin.llm.decontam import op9_winnowing
from ratiobin.llm.edit_counts import op5_edit_counts
from ratiobin.llm.language_model import op2_backoff_lm
from ratiobin.llm.nn_descent import op1_nn_descent
from ratiobin.llm.packing import op10_packing
from ratiobin.llm.resampling import op6_resampling
from ratiobin.llm.revisits import op4_revisits
from ratiobin.llm.secrets import op7_secrets
from ratiobin.llm.simhash import op8_simhash
from ratiobin.llm.toxicity import op3_toxicity

QUERIES = {
    "op1_nn_descent": op1_nn_descent,
    "op2_backoff_lm": op2_backoff_lm,
    "op3_toxicity": op3_toxicity,
    "op4_revisits": op4_revisits,
    "op5_edit_counts": op5_edit_counts,
    "op6_resampling": op6_resampling,
    "op7_secrets": op7_secrets,
    "op8_simhash": op8_simhash,
    "op9_winnowing": op9_winnowing,
    "op10_packing": op10_packing,
}

ORACLE_SQL: dict[str, str] = {"op4_revisits": revisits.SQL}
