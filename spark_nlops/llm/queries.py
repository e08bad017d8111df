"""Driver queries of the training-data operators and the SQL that recomputes them."""

from __future__ import annotations

from .bpe import op2_byte_bpe
from .langid import op6_language_id
from .preference import OP8_SQL, op8_preference_format
from .simhash import op3_simhash_near_dedup
from .suffix_dedup import OP5_SQL, op5_suffix_dedup
from .tiling import op10_benchmark_tiling
from .token_scan import op4_token_counts
from .toxicity import op1_toxicity
from .url_rules import OP9_SQL, op9_url_rules
from .wav_media import op7_wav_fingerprints

QUERIES = {
    "op1_toxicity": op1_toxicity,
    "op2_byte_bpe": op2_byte_bpe,
    "op3_simhash_near_dedup": op3_simhash_near_dedup,
    "op4_token_counts": op4_token_counts,
    "op5_suffix_dedup": op5_suffix_dedup,
    "op6_language_id": op6_language_id,
    "op7_wav_fingerprints": op7_wav_fingerprints,
    "op8_preference_format": op8_preference_format,
    "op9_url_rules": op9_url_rules,
    "op10_benchmark_tiling": op10_benchmark_tiling,
}

ORACLE_SQL = {
    "op5_suffix_dedup": OP5_SQL,
    "op8_preference_format": OP8_SQL,
    "op9_url_rules": OP9_SQL,
}
