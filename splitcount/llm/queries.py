"""Registered queries of the training-data operators and their DuckDB counterparts."""

from __future__ import annotations

from splitcount.llm.bestfit_packing import op5_bestfit_packing
from splitcount.llm.language_mix import op2_language_mix
from splitcount.llm.line_dedup import OP6_SQL, op6_line_dedup
from splitcount.llm.piece_dropout import op8_piece_dropout
from splitcount.llm.quality_rules import op1_quality_rules
from splitcount.llm.secret_scan import op3_secret_scan
from splitcount.llm.simhash_dedup import op9_simhash_dedup
from splitcount.llm.token_counts import op7_token_counts
from splitcount.llm.topk_search import OP4_SQL, op4_topk_search
from splitcount.llm.toxicity import op10_toxicity

QUERIES = {
    "op1_quality_rules": op1_quality_rules,
    "op2_language_mix": op2_language_mix,
    "op3_secret_scan": op3_secret_scan,
    "op4_topk_search": op4_topk_search,
    "op5_bestfit_packing": op5_bestfit_packing,
    "op6_line_dedup": op6_line_dedup,
    "op7_token_counts": op7_token_counts,
    "op8_piece_dropout": op8_piece_dropout,
    "op9_simhash_dedup": op9_simhash_dedup,
    "op10_toxicity": op10_toxicity,
}

ORACLES: dict[str, str] = {
    "op4_topk_search": OP4_SQL,
    "op6_line_dedup": OP6_SQL,
}
