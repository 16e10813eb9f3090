"""Queries and SQL of this subpackage, by name."""

from __future__ import annotations

from .byte_bpe import op1_byte_bpe
from .exact_dedup import OP2_SQL, op2_exact_dedup
from .packing import op7_best_fit_packing
from .quality import op4_quality
from .search import op8_topk_search
from .sharding import op9_sharding
from .simhash import op5_simhash
from .token_files import op6_token_files
from .toxicity import op10_toxicity
from .url_filter import OP3_SQL, op3_url_filter

QUERIES = {
    "op1_byte_bpe": op1_byte_bpe,
    "op2_exact_dedup": op2_exact_dedup,
    "op3_url_filter": op3_url_filter,
    "op4_quality": op4_quality,
    "op5_simhash": op5_simhash,
    "op6_token_files": op6_token_files,
    "op7_best_fit_packing": op7_best_fit_packing,
    "op8_topk_search": op8_topk_search,
    "op9_sharding": op9_sharding,
    "op10_toxicity": op10_toxicity,
}
ORACLES = {"op2_exact_dedup": OP2_SQL, "op3_url_filter": OP3_SQL}
