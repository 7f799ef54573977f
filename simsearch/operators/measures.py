"""Closeness, spread and their balance for result sets (qid, id, s, dist)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def pair_distances(rows: DataFrame, known: DataFrame | None = None) -> DataFrame:
    """(qid, i, j, d) for i < j among the rows of a query; rows are candidates, never the corpus.

    known: distances of this form that hold all pairs of rows already; theirs are looked up, none is worked out."""
    if known is not None:
        kept = known.join(rows.select("qid", F.col("id").alias("i")), ["qid", "i"], "left_semi")
        return kept.join(rows.select("qid", F.col("id").alias("j")), ["qid", "j"], "left_semi").select("qid", "i", "j", "d")
    a = rows.select("qid", F.col("id").alias("i"), F.col("s").alias("x"))
    b = rows.select("qid", F.col("id").alias("j"), F.col("s").alias("y"))
    return a.join(b, "qid").where("i < j").select("qid", "i", "j", F.levenshtein("x", "y").alias("d"))


def mean_query_distance(results: DataFrame) -> DataFrame:
    return results.groupBy("qid").agg(F.avg("dist").alias("mean_query_distance"))


def mean_pair_distance(results: DataFrame, known: DataFrame | None = None) -> DataFrame:
    """Over unordered pairs; 0 for a single result."""
    pairs = pair_distances(results, known).groupBy("qid").agg(F.avg("d").alias("p"))
    return results.select("qid").distinct().join(pairs, "qid", "left").select("qid", F.coalesce("p", F.lit(0.0)).alias("mean_pair_distance"))


def balance_score(results: DataFrame, lam: float, known: DataFrame | None = None) -> DataFrame:
    """lam x spread - (1 - lam) x distance."""
    return mean_query_distance(results).join(mean_pair_distance(results, known), "qid").withColumn("balance_score", F.lit(lam) * F.col("mean_pair_distance") - F.lit(1 - lam) * F.col("mean_query_distance"))


def score_card(results: DataFrame, lam: float, kmin: int, kmax: int, queries: DataFrame | None = None, known: DataFrame | None = None) -> DataFrame:
    """Per query: count, whether it is in range, closeness, spread, balance; queries without results count 0.

    Results are at most kmax per query; they are kept while the measures are taken, so a method runs once."""
    results = results.select("qid", "id", "s", "dist").persist()
    counts = results.groupBy("qid").agg(F.count(F.lit(1)).alias("result_count"))
    card = counts.join(balance_score(results, lam, known), "qid")
    if queries is not None:
        card = queries.select("qid").join(card, "qid", "left").withColumn("result_count", F.coalesce("result_count", F.lit(0)))
    return card.withColumn("in_range", F.col("result_count").between(kmin, kmax))


def suggest_lambda(corpus, queries, method, goal_of, grid, target_spread: float, known: DataFrame | None = None) -> DataFrame:
    """(lam, spread, distance, chosen): the smallest weight of the grid whose mean spread reaches the target.

    Results are kept while they are measured, so the method runs once per weight."""
    out = None
    for lam in grid:
        results = method(corpus, queries, goal_of(lam)).select("qid", "id", "s", "dist").persist()
        row = balance_score(results, lam, known).agg(F.avg("mean_pair_distance").alias("spread"), F.avg("mean_query_distance").alias("distance")).select(F.lit(float(lam)).alias("lam"), "spread", "distance")
        out = row if out is None else out.union(row)
    out = out.persist()  # one row per weight, read for the rows and for the choice
    best = out.where(F.col("spread") >= target_spread).agg(F.min("lam").alias("best"))
    return out.crossJoin(F.broadcast(best)).select("lam", "spread", "distance", (F.col("lam") == F.col("best")).alias("chosen"))
