"""Relax, then rank candidates by their total distance to the other candidates."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.goal import Goal
from .measures import pair_distances
from .relax import relax


def contribution(cands: DataFrame, known: DataFrame | None = None) -> DataFrame:
    """(qid, id, contrib): total distance to all other candidates of the query. known: as in ``pair_distances``."""
    pairs = pair_distances(cands, known)
    both = pairs.select("qid", F.explode(F.array("i", "j")).alias("id"), "d")
    sums = both.groupBy("qid", "id").agg(F.sum("d").alias("contrib"))
    return cands.join(sums, ["qid", "id"], "left").withColumn("contrib", F.coalesce("contrib", F.lit(0)).cast("long"))


def cut_off(contrib: DataFrame, *, sample_share: float = 0.25, cut_factor: float = 0.75) -> DataFrame:
    """(qid, cut): factor times the mean total over a sample that is fixed by the md5 of ids; a share of 1 takes all."""
    if not (0 < sample_share <= 1 and 0.5 < cut_factor < 1):
        raise ValueError("need 0 < sample_share <= 1 and 0.5 < cut_factor < 1")
    w = Window.partitionBy("qid")
    picked = contrib.withColumn("r", F.row_number().over(w.orderBy(F.md5(F.col("id").cast("string")), "id"))).withColumn("m", F.count(F.lit(1)).over(w))
    picked = picked.where(F.col("r") <= F.ceil(F.lit(sample_share) * F.col("m")))
    return picked.groupBy("qid").agg((F.lit(cut_factor) * F.avg("contrib")).alias("cut"))


def rank_by(scored: DataFrame, score: str, goal: Goal, *, pruned=None, quota_base: str = "before", backfill: bool = True, keep_exact: bool = False) -> DataFrame:
    """The highest scores per query: as many as the goal's share of the candidates.

    quota_base: share of all candidates or of those not pruned. backfill: pruned ones fill up to kmin."""
    w = Window.partitionBy("qid")
    rows = scored.withColumn("pruned", F.lit(False) if pruned is None else pruned)
    if keep_exact:
        rows = rows.withColumn("pruned", F.col("pruned") & (F.col("dist") > 0))
    base = F.count(F.lit(1)).over(w) if quota_base == "before" else F.sum((~F.col("pruned")).cast("long")).over(w)
    n = goal.share_of(base)
    first = F.when(F.col("dist") == 0, 0).otherwise(1) if keep_exact else F.lit(0)
    rows = rows.withColumn("n", n).withColumn("rank", F.row_number().over(w.orderBy("pruned", first, F.col(score).desc(), "id")))
    allowed = ~F.col("pruned") | (F.col("rank") <= goal.kmin) if backfill else ~F.col("pruned")
    return rows.where((F.col("rank") <= F.col("n")) & allowed).drop("n")


def relax_rank(corpus: DataFrame, queries: DataFrame, goal: Goal, *, sample_share: float | None = 0.25, cut_factor: float = 0.75, quota_base: str = "before", backfill: bool = True, keep_exact: bool = False, candidates: DataFrame | None = None, known: DataFrame | None = None, **options) -> DataFrame:
    """(qid, id, s, dist, contrib, rank, pruned). sample_share=None: no pruning; 1.0: exact cut-off."""
    cands = relax(corpus, queries, goal, **options) if candidates is None else candidates
    scored = contribution(cands.select("qid", "id", "s", "dist"), known)
    pruned = F.lit(False)
    if sample_share is not None:
        scored = scored.join(F.broadcast(cut_off(scored, sample_share=sample_share, cut_factor=cut_factor)), "qid")
        pruned = F.col("contrib") < F.col("cut")
    out = rank_by(scored, "contrib", goal, pruned=pruned, quota_base=quota_base, backfill=backfill, keep_exact=keep_exact)
    return out.select("qid", "id", "s", "dist", "contrib", "rank", "pruned")


def relax_medoid(corpus: DataFrame, queries: DataFrame, goal: Goal, **options) -> DataFrame:
    """A fast centre in place of a consensus: the candidate with the least total distance; the farthest from it stay."""
    cands = contribution(relax(corpus, queries, goal, **options).select("qid", "id", "s", "dist"))
    w = Window.partitionBy("qid").orderBy("contrib", "id")
    centre = F.first("s").over(w)
    scored = cands.withColumn("to_centre", F.levenshtein(F.col("s"), centre))
    return rank_by(scored, "to_centre", goal).select("qid", "id", "s", "dist", "to_centre", "rank")
