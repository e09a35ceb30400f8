"""Queries and SQL twins of the training-data operators."""

from __future__ import annotations

from . import ball_tree, chat_trees, exact_dedup
from .ball_tree import op2_exact_top_k
from .chat_trees import op8_chat_formatting
from .class_lm import op6_class_lm
from .exact_dedup import op10_exact_dedup
from .packing import op5_best_fit_packing
from .pii import op3_pii_surrogates
from .sentence_pieces import op9_sentence_pieces
from .simhash import op4_simhash_near_dedup
from .substring_dedup import op1_substring_dedup
from .toxicity import op7_toxicity

QUERIES = {
    "op1_substring_dedup": op1_substring_dedup,
    "op10_exact_dedup": op10_exact_dedup,
    "op2_exact_top_k": op2_exact_top_k,
    "op3_pii_surrogates": op3_pii_surrogates,
    "op4_simhash_near_dedup": op4_simhash_near_dedup,
    "op5_best_fit_packing": op5_best_fit_packing,
    "op6_class_lm": op6_class_lm,
    "op7_toxicity": op7_toxicity,
    "op8_chat_formatting": op8_chat_formatting,
    "op9_sentence_pieces": op9_sentence_pieces,
}

#: DuckDB twins, for the operators that SQL can express on whole tables.
SQL: dict[str, str] = {"op2_exact_top_k": ball_tree.SQL, "op10_exact_dedup": exact_dedup.SQL, "op8_chat_formatting": chat_trees.SQL}
