"""Registered queries of the training-data operators, and their SQL."""

from __future__ import annotations

import corpus_pipeline

from . import chat_format, exact_dedup, mixing, neural_lm, packing, quality_rules, simhash, token_files, toxicity, warc


def queries():
    return {
        "op1_warc_index": warc.op1_warc_index,
        "op2_chat_format": chat_format.op2_chat_format,
        "op3_quality_rules": quality_rules.op3_quality_rules,
        "op4_toxicity": toxicity.op4_toxicity,
        "op5_simhash": simhash.op5_simhash,
        "op6_best_fit_packing": packing.op6_best_fit_packing,
        "op7_neural_lm": neural_lm.op7_neural_lm,
        "op8_curriculum_mixing": mixing.op8_curriculum_mixing,
        "op9_exact_dedup": exact_dedup.op9_exact_dedup,
        "op10_token_files": token_files.op10_token_files,
        "pipeline": corpus_pipeline.run,
    }


def oracle_sql():
    return {
        "op1_warc_index": warc.ORACLE_SQL,
        "op3_quality_rules": quality_rules.ORACLE_SQL,
        "op8_curriculum_mixing": mixing.ORACLE_SQL,
        "op9_exact_dedup": exact_dedup.ORACLE_SQL,
    }
