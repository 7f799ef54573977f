"""A training corpus from raw documents: quality, near duplicates, benchmark leaks, mixture, token files.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and reread as the docs of
the next one. All but the last return the columns of documents; the last returns what the token files hold per document.

Rows that are equal in all columns count as copies of each other; a document without any word is not a duplicate of
anything else. Columns beside those that a stage needs pass through it whatever their names are. Documents that the mixture repeats are repeated rows. Empty tables give empty tables.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from simsearch.llm import common, decontaminate, jaccard, mixing, quality, repair

#: SQL cannot express the fitted classifier of the first stage; tests/llm/test_tables.py compares the stages with a brute-force version.
ORACLE_SQL = None


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose lines are likely good by the chain model fitted on the labels."""
    model = quality.fit_quality(docs, common.table(spark, sf_dir, "labels"))
    safe, names = common.sealed(docs, "doc_id", "text")
    return quality.score_documents(safe, model).where("quality_score >= 0.5").drop("quality_score").toDF(*names)


def keep_one_of_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents linked by five-word shingles at a similarity of 0.8 or more, the one with the smallest id."""
    safe, names = common.sealed(docs, "doc_id", "text")
    return jaccard.one_of_each(safe, n=5, percent=80).toDF(*names)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no window of a benchmark item."""
    safe, names = common.sealed(docs, "doc_id", "text")
    found = decontaminate.find_leaks(safe, common.table(spark, sf_dir, "benchmark").select("item_id", "text"), keep_text=True)
    return found.where(F.size("hit") == 0).select(*safe.columns).toDF(*names)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mixture takes them; weights 1, 2, 3 over the sources, three repetitions at most."""
    safe, names = common.sealed(docs, "doc_id", "text", "source")
    return mixing.repeat(mixing.mix_documents(safe)).toDF(*names)


def write_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token shards of all that is left, read back."""
    return repair.round_trip(docs, repair.default_tokenizer())


STAGES = [("quality", keep_good), ("near_duplicates", keep_one_of_group), ("decontamination", drop_leaks), ("mixture", mix_sources), ("tokens", write_tokens)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.documents(spark, sf_dir)
    for name, stage in STAGES:
        before, old = common.written_so_far(), docs
        docs = common.materialize(stage(spark, docs, sf_dir), f"stage-{name}")
        common.sweep(docs, before)
        common.discard(old)
    return docs
