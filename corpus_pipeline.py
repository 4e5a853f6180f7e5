"""Corpus pipeline: language ID, quality rules, near duplicates, decontamination, mixing.

Each stage takes (spark, docs, sf_dir) and works on all that its predecessor kept; all but the
last return the columns of documents. The pipeline can't be expressed as SQL as a whole (trained model,
concentration steps, connected components); it is tested against a brute-force version.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangebound.llm import decontaminate, jaccard_join, langid, mixing, quality_rules
from rangebound.llm.common import aside, materialise, table

#: Least posterior of a language.
LEAST_POSTERIOR = 0.5


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops texts of no language, and those whose language is in doubt."""
    docs, back = aside(docs, ("lang_pred", "lang_score"))
    found = langid.predict(docs, langid.fit(docs))
    return back(found.where((F.col("lang_pred") != langid.UNDETERMINED) & (F.col("lang_score") >= LEAST_POSTERIOR)).select(*docs.columns))


def rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops what the base rules or the outlier rule reject."""
    whole = docs.select(F.struct("*").alias("doc"), "text", "lang", "source")
    return quality_rules.judge(whole, carry=("doc",)).where("kept").select("doc.*")


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the smallest id of each component of 5-word-shingle Jaccard 0.8; rows that share an id stay together."""
    found = jaccard_join.groups(docs, jaccard_join.JoinConfig(words=5, percent=80))
    extra = materialise(found.where("id != component_id").select("id").distinct())
    return jaccard_join.without(docs, extra)


def benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that cover half of a benchmark item's words or more."""
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The training order: a row for each time a document is read."""
    return mixing.mix(docs)


STAGES = [
    ("language ID", language_id),
    ("quality rules", rules),
    ("near duplicates", near_duplicates),
    ("benchmark decontamination", benchmark_leaks),
    ("mixing", mixed),
]

#: No SQL: see above.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = materialise(docs)
    return docs
