"""Queries of the training-data operators and their DuckDB equivalents."""

from __future__ import annotations

from .bpe import op5_byte_bpe
from .exact_dedup import OP2_SQL, op2_exact_dedup
from .mixing import OP1_SQL, op1_mixing
from .near_dedup import op7_near_dedup
from .neighbours import op9_nearest
from .quality import op4_quality
from .secrets import op10_secret_scan
from .sharding import op8_sharding
from .substring import op6_substring_dedup
from .toxicity import op3_toxicity

QUERIES = [op1_mixing, op2_exact_dedup, op3_toxicity, op4_quality, op5_byte_bpe, op6_substring_dedup, op7_near_dedup, op8_sharding, op9_nearest, op10_secret_scan]
ORACLES = {"op1_mixing": OP1_SQL, "op2_exact_dedup": OP2_SQL}


def queries():
    return {f.__name__: f for f in QUERIES}


def oracle_sql():
    return dict(ORACLES)
