"""Queries and SQL of the corpus operators."""

from __future__ import annotations

from . import chat, decontaminate, htmltext, langid, media, mixing, neardup, pii, suffixdedup, toxicity


def pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries():
    return {
        "op1_mixing": mixing.op1_mixing,
        "op2_prob_minhash": neardup.op2_prob_minhash,
        "op3_suffix_dedup": suffixdedup.op3_suffix_dedup,
        "op4_html_main_text": htmltext.op4_html_main_text,
        "op5_language_id": langid.op5_language_id,
        "op6_media_columns": media.op6_media_columns,
        "op7_chat_format": chat.op7_chat_format,
        "op8_toxicity": toxicity.op8_toxicity,
        "op9_pii_surrogates": pii.op9_pii_surrogates,
        "op10_decontaminate": decontaminate.op10_decontaminate,
        "pipeline": pipeline,
    }


def oracle_sql():
    return {"op3_suffix_dedup": suffixdedup.OP3_SQL, "op7_chat_format": chat.OP7_SQL, "op10_decontaminate": decontaminate.OP10_SQL}
