"""Queries of the operators and their SQL twins."""

from __future__ import annotations

from distinct_bounds.llm import bpe, exact, language, mixing, ngram_join, personal, quality, rules, toxicity, warc


def queries():
    return {
        "op1_quality": quality.op1_quality,
        "op2_bpe": bpe.op2_bpe,
        "op3_rules": rules.op3_rules,
        "op4_toxicity": toxicity.op4_toxicity,
        "op5_ngram_join": ngram_join.op5_ngram_join,
        "op6_personal": personal.op6_personal,
        "op7_language": language.op7_language,
        "op8_warc": warc.op8_warc,
        "op9_exact": exact.op9_exact,
        "op10_mixing": mixing.op10_mixing,
    }


def oracle_sql():
    return {"op5_ngram_join": ngram_join.OP5_SQL, "op8_warc": warc.OP8_SQL, "op9_exact": exact.OP9_SQL}
