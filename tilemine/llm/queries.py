"""The queries of the text operators and their SQL, by name."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from tilemine.llm import decontaminate, html, language, lines, pieces, quality, simhash, substrings, tokens, warc

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        lines.op1_line_dedup, decontaminate.op2_decontamination, simhash.op3_simhash_near_dedup, html.op4_html_extraction, warc.op5_warc_normaliser,
        language.op6_language_id, pieces.op7_sentencepiece_round_trip, quality.op8_quality_rules, tokens.op9_token_counts, substrings.op10_substring_dedup,
    )
}

#: No SQL: op3 (fingerprints), op4 (trained tree), op6 (trained model), op7 and op9 (tokenizers).
SQL = {"op1_line_dedup": lines.SQL, "op2_decontamination": decontaminate.SQL, "op5_warc_normaliser": warc.SQL, "op8_quality_rules": quality.SQL, "op10_substring_dedup": substrings.SQL}
