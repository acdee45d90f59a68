"""Queries of the text operators and of the pipeline."""

from __future__ import annotations

import corpus_pipeline
from peakgroups.llm import decontaminate, language, licenses, linededup, mixing, quality, simhash, tokens, urls, warc


def queries() -> dict:
    return {
        "op1_decontaminate": decontaminate.op1_decontaminate,
        "op2_simhash": simhash.op2_simhash,
        "op3_line_dedup": linededup.op3_line_dedup,
        "op4_license_scan": licenses.op4_license_scan,
        "op5_warc": warc.op5_warc,
        "op6_quality_rules": quality.op6_quality_rules,
        "op7_token_counts": tokens.op7_token_counts,
        "op8_language_id": language.op8_language_id,
        "op9_url_filter": urls.op9_url_filter,
        "op10_mix_sources": mixing.op10_mix_sources,
        "pipeline": corpus_pipeline.run,
    }


def oracle_sql() -> dict:
    return {"op1_decontaminate": decontaminate.OP1_SQL, "op3_line_dedup": linededup.OP3_SQL, "op5_warc": warc.OP5_SQL, "op6_quality_rules": quality.OP6_SQL, "op9_url_filter": urls.OP9_SQL, "op10_mix_sources": mixing.OP10_SQL}
