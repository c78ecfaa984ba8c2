"""Named queries of the training-data operators, and their SQL where it can say them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

import corpus_pipeline
from reuse_engine.llm.chat_format import OP7_SQL, op7_chat_formatting
from reuse_engine.llm.decontaminate import OP1_SQL, op1_benchmark_decontamination
from reuse_engine.llm.html_extract import op4_html_extraction
from reuse_engine.llm.jaccard_join import OP2_SQL, op2_ngram_jaccard_join
from reuse_engine.llm.language_id import op8_language_id
from reuse_engine.llm.line_dedup import OP5_SQL, op5_line_dedup
from reuse_engine.llm.piece_codec import op6_sentencepiece_codec
from reuse_engine.llm.quality_gam import op10_quality_classifier
from reuse_engine.llm.quality_rules import BASE_SQL, op3_quality_rules, quality_base_measures
from reuse_engine.llm.warc import OP9_SQL, op9_warc


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_benchmark_decontamination": op1_benchmark_decontamination,
        "op2_ngram_jaccard_join": op2_ngram_jaccard_join,
        "op3_quality_rules": op3_quality_rules,
        "op4_html_extraction": op4_html_extraction,
        "op5_line_dedup": op5_line_dedup,
        "op6_sentencepiece_codec": op6_sentencepiece_codec,
        "op7_chat_formatting": op7_chat_formatting,
        "op8_language_id": op8_language_id,
        "op9_warc": op9_warc,
        "op10_quality_classifier": op10_quality_classifier,
        "quality_base_measures": quality_base_measures,
        "pipeline": corpus_pipeline.run,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op1_benchmark_decontamination": OP1_SQL,
        "op2_ngram_jaccard_join": OP2_SQL,
        "op5_line_dedup": OP5_SQL,
        "op7_chat_formatting": OP7_SQL,
        "op9_warc": OP9_SQL,
        "quality_base_measures": BASE_SQL,
    }
