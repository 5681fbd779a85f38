"""The corpus pipeline: quality, line de-duplication, near duplicates, decontamination, packing.

Each stage reads what its predecessor kept, as Parquet, and all but the last return the columns of ``documents``, whatever
further columns those have and whatever their names.  Every stage takes an empty table, and gives one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgreason.llm import decontaminate, linededup, neardup, ordinal, packing
from kgreason.llm.common import materialize, renamed_back, table


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose probability of the top grade reaches the bound; the model learns from the labelled ones among docs.

    Null and empty texts score by the thresholds alone, very long ones as a whole; repeated rows and equal texts share a verdict; null ids train nothing and are scored like others.
    """
    model = ordinal.train(docs, table(spark, sf_dir, "labels"))
    return renamed_back(ordinal.score(docs, model).where("quality_kept"), docs.columns)


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with their kept lines and ``n_chars``, where they have it, counted anew; none goes, an emptied one and a null text stay as an empty text.

    Rows repeating an id count as one holder and keep the same lines; rows without an id hold nothing and lose every repeated line.
    """
    out = renamed_back(linededup.dedup_lines(docs), docs.columns)
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near duplicates: the smallest doc_id, a row without an id only where none has one.

    Rows without words are in no group and stay, repeated or not; of repeated rows with words one stays.
    """
    return neardup.drop_near_duplicates(docs)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows without any window of the benchmark in their own text, whether they have an id or share it; null and empty texts stay."""
    return decontaminate.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each piece of each row stands in the training sequences; a null or empty text is its end id alone, long ones are cut, repeated rows are packed each."""
    return packing.pack_documents(docs, with_ids=False)


STAGES = [
    ("quality_classifier", quality_stage),
    ("line_dedup", line_stage),
    ("minhash_near_dedup", near_duplicate_stage),
    ("benchmark_decontamination", decontamination_stage),
    ("best_fit_packing", packing_stage),
]

#: The first stage is a trained model, which SQL does not express; tests run the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
