"""A corpus through five operators: toxicity, near-duplicates, decontamination, PII, mixing.

Each stage takes (spark, docs, sf_dir) and returns what it keeps with the columns of
documents; the last adds the mixing columns. Stages work on all their predecessor kept.
Null texts and ids, empty tables and extra columns follow the operators' own rules.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from lattica.llm import decontaminate, mixing, neardup, pii, toxicity
from lattica.llm.common import DOC_COLUMNS, materialize, release, table


def drop_toxic(spark, docs, sf_dir):
    """Documents whose toxicity score is below one half."""
    model = toxicity.learn(docs, table(spark, sf_dir, "labels", "doc_id", "toxic"))
    return toxicity.score(docs, model).where("score < 0.5").select(*DOC_COLUMNS)


def drop_near_copies(spark, docs, sf_dir):
    """The first document of every near-duplicate class."""
    return neardup.keep_first(docs).select(*DOC_COLUMNS)


def drop_leaks(spark, docs, sf_dir):
    """Documents without a benchmark passage."""
    return decontaminate.judge(docs, table(spark, sf_dir, "benchmark", "item_id", "text")).where(~F.col("contaminated")).select(*DOC_COLUMNS)


def hide_personal_data(spark, docs, sf_dir):
    """All documents, with surrogates for personal data."""
    out = pii.replace(docs, pii.session_key(spark))
    size = F.when(F.col("n_entities") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))
    return out.withColumn("n_chars", size).select(*DOC_COLUMNS)


def mix_sources(spark, docs, sf_dir):
    """All documents with their memberships, rate and number of repeats in the target mixture."""
    return mixing.mix(docs, mixing.domains_of(table(spark, sf_dir, "labels", "doc_id", "quality", "toxic")))


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_copies),
    ("decontamination", drop_leaks),
    ("pii", hide_personal_data),
    ("mixing", mix_sources),
]

#: Two stages fit models and one draws keyed surrogates; the tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark, sf_dir):
    docs = table(spark, sf_dir, "documents", *DOC_COLUMNS)
    for name, stage in STAGES:
        before, docs = docs, materialize(stage(spark, docs, sf_dir), f"stage-{name}")
        release(before)  # scratch of the stage before; the input has none
    return docs
