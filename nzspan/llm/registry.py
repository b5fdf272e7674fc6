"""The queries of this subpackage and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import edit_counts, hidden_markov, mixing, pieces, simhash, spots, suffixes, token_files, topk, toxicity


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_mixing": mixing.op1_mixing,
        "op2_token_files": token_files.op2_token_files,
        "op3_edit_counts": edit_counts.op3_edit_counts,
        "op4_pieces": pieces.op4_pieces,
        "op5_simhash": simhash.op5_simhash,
        "op6_spots": spots.op6_spots,
        "op7_toxicity": toxicity.op7_toxicity,
        "op8_topk": topk.op8_topk,
        "op9_hidden_markov": hidden_markov.op9_hidden_markov,
        "op10_suffixes": suffixes.op10_suffixes,
    }


def oracle_sql() -> dict[str, str]:
    return {"op8_topk": topk.OP8_SQL}
