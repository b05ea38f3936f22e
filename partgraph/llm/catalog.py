"""Digest queries of the operators and their SQL."""

from __future__ import annotations

from .bpe import op5_byte_bpe
from .html_blocks import op7_block_lstm
from .jaccard_join import op2_chosen_path_join
from .line_dedup import op8_segment_edit_lines
from .neighbours import op9_nn_descent
from .packing import op6_genetic_packing
from .quality import op3_adaptive_quality
from .sharding import op4_jump_shards
from .substring_dedup import op1_fm_substrings
from .toxicity import op10_nnpu_toxicity


def queries() -> dict:
    return {
        "op1_fm_substrings": op1_fm_substrings,
        "op2_chosen_path_join": op2_chosen_path_join,
        "op3_adaptive_quality": op3_adaptive_quality,
        "op4_jump_shards": op4_jump_shards,
        "op5_byte_bpe": op5_byte_bpe,
        "op6_genetic_packing": op6_genetic_packing,
        "op7_block_lstm": op7_block_lstm,
        "op8_segment_edit_lines": op8_segment_edit_lines,
        "op9_nn_descent": op9_nn_descent,
        "op10_nnpu_toxicity": op10_nnpu_toxicity,
    }


def oracle_sql() -> dict[str, str]:
    return {}
