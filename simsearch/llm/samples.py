"""Bounded samples of labelled documents to fit classifiers on."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, *, rows: int, fold: int = 1) -> list[tuple[str, int]]:
    """(text, label) of at most ``rows`` labelled documents outside the held-out fold, in a fixed order.

    The labels to use are those with the smallest hashes of their ids, so the sample does not depend on
    partitions. At most ``rows`` ids are broadcast to the scan of docs; only the chosen texts are shuffled. Of several texts
    with one id the first in order of their hashes is used; null texts count as empty."""
    chosen = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull()).where(common.crc_mod(F.col("doc_id"), 3) != fold)
    chosen = chosen.groupBy("doc_id").agg(F.max(label).cast("int").alias("y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    text = F.coalesce(F.col("text"), F.lit(""))
    found = docs.select("doc_id", text.alias("text")).join(F.broadcast(chosen), "doc_id")
    found = found.groupBy("doc_id", "y").agg(F.min_by("text", F.struct(F.xxhash64("text"), "text")).alias("text")).toPandas()
    found = found.sort_values("doc_id", kind="stable")
    return list(zip(found["text"].tolist(), found["y"].tolist()))
