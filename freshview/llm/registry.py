"""Queries of the training-data operators and, where SQL can express them, their DuckDB SQL."""

from __future__ import annotations

from .avi_clips import op6_avi_clips
from .byte_bpe import op7_byte_bpe
from .decontaminate import ORACLE_SQL as OP5_SQL
from .decontaminate import op5_decontamination
from .kd_shards import op10_kd_shards
from .language import op8_language_id
from .ngram_join import ORACLE_SQL as OP2_SQL
from .ngram_join import op2_ngram_join
from .page_text import op1_page_text
from .piece_counts import op3_token_counts
from .preferences import op9_preference_pairs
from .secrets import op4_secret_scan


def queries() -> dict:
    return {
        "op7_byte_bpe": op7_byte_bpe,
        "op5_decontamination": op5_decontamination,
        "op8_language_id": op8_language_id,
        "op2_ngram_join": op2_ngram_join,
        "op10_kd_shards": op10_kd_shards,
        "op1_page_text": op1_page_text,
        "op6_avi_clips": op6_avi_clips,
        "op3_token_counts": op3_token_counts,
        "op9_preference_pairs": op9_preference_pairs,
        "op4_secret_scan": op4_secret_scan,
    }


def oracle_sql() -> dict:
    return {"op2_ngram_join": OP2_SQL, "op5_decontamination": OP5_SQL}
