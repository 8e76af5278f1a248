"""The queries of this subpackage, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from pivotgrove.llm.bilinear_lm import op2_log_bilinear_scores
from pivotgrove.llm.bpe_transducer import op9_bpe_transducer
from pivotgrove.llm.multi_index import op5_inverted_multi_index
from pivotgrove.llm.occurrence_join import op7_occurrence_join
from pivotgrove.llm.overlap_counts import op4_overlap_token_counts
from pivotgrove.llm.packing import op3_concatenate_and_cut
from pivotgrove.llm.private_data import op1_bootstrapped_private_data
from pivotgrove.llm.scaled_sketch import op10_scaled_fingerprints
from pivotgrove.llm.secrets import op8_secret_ownership
from pivotgrove.llm.toxicity import op6_factorisation_machine

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_bootstrapped_private_data": op1_bootstrapped_private_data,
    "op2_log_bilinear_scores": op2_log_bilinear_scores,
    "op3_concatenate_and_cut": op3_concatenate_and_cut,
    "op4_overlap_token_counts": op4_overlap_token_counts,
    "op5_inverted_multi_index": op5_inverted_multi_index,
    "op6_factorisation_machine": op6_factorisation_machine,
    "op7_occurrence_join": op7_occurrence_join,
    "op8_secret_ownership": op8_secret_ownership,
    "op9_bpe_transducer": op9_bpe_transducer,
    "op10_scaled_fingerprints": op10_scaled_fingerprints,
}

ORACLES: dict[str, str] = {}
