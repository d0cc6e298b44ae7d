"""The driver's queries of this folder: one for each operator, and the pipeline."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from proxembed.llm.audio import op6_audio_features
from proxembed.llm.html_text import op5_tree_scoring
from proxembed.llm.line_dedup import op9_line_dedup
from proxembed.llm.multi_index import op10_multi_index
from proxembed.llm.oracles import oracle_sql
from proxembed.llm.packing import op3_best_fit_packing
from proxembed.llm.parity_join import op4_parity_join
from proxembed.llm.secret_scan import op2_secret_ledger
from proxembed.llm.subword import op7_streaming_viterbi
from proxembed.llm.toxicity import op8_ordinal_toxicity
from proxembed.llm.warc import op1_warc_segments


__all__ = ["oracle_sql", "queries"]


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    import corpus_pipeline

    return {
        "op1_warc_segments": op1_warc_segments,
        "op2_secret_ledger": op2_secret_ledger,
        "op3_best_fit_packing": op3_best_fit_packing,
        "op4_parity_join": op4_parity_join,
        "op5_tree_scoring": op5_tree_scoring,
        "op6_audio_features": op6_audio_features,
        "op7_streaming_viterbi": op7_streaming_viterbi,
        "op8_ordinal_toxicity": op8_ordinal_toxicity,
        "op9_line_dedup": op9_line_dedup,
        "op10_multi_index": op10_multi_index,
        "pipeline": corpus_pipeline.run,
    }
