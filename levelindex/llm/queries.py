"""The registered queries of this subpackage: each applies one operator to its whole table."""

from __future__ import annotations

from levelindex.llm.common import table
from levelindex.llm.pfair_mix import ORACLE


def op1_mil_quality(spark, sf_dir):
    from levelindex.llm.mil_quality import quality_scores

    return quality_scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op2_crf_toxicity(spark, sf_dir):
    from levelindex.llm.crf_toxicity import toxicity_scores

    return toxicity_scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op3_hmm_lm(spark, sf_dir):
    from levelindex.llm.hmm_lm import hmm_scores

    return hmm_scores(table(spark, sf_dir, "documents"))


def op4_decontaminate(spark, sf_dir):
    from levelindex.llm.decontaminate import leaks

    return leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op5_multi_index_hash(spark, sf_dir):
    from levelindex.llm.multi_index_hash import nearest

    return nearest(table(spark, sf_dir, "embeddings"))


def op6_html_main_text(spark, sf_dir):
    from levelindex.llm.html_main_text import extract

    return extract(table(spark, sf_dir, "pages"))


def op7_token_counts(spark, sf_dir):
    from levelindex.llm.token_counts import token_counts

    return token_counts(table(spark, sf_dir, "documents"))


def op8_suffix_dedup(spark, sf_dir):
    from levelindex.llm.suffix_dedup import repeated_bytes

    return repeated_bytes(table(spark, sf_dir, "documents"))


def op9_pfair_mix(spark, sf_dir):
    from levelindex.llm.pfair_mix import mix

    return mix(table(spark, sf_dir, "documents"))


def op10_simhash_gray(spark, sf_dir):
    from levelindex.llm.simhash_gray import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_mil_quality, op2_crf_toxicity, op3_hmm_lm, op4_decontaminate, op5_multi_index_hash, op6_html_main_text, op7_token_counts, op8_suffix_dedup, op9_pfair_mix, op10_simhash_gray)}

ORACLE_SQL: dict[str, str] = {"op9_pfair_mix": ORACLE}
