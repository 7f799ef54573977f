"""Relax, align all candidates, build a consensus, and keep those farthest from it."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import alignment as kernel
from ..plans.goal import Goal
from .measures import balance_score, pair_distances
from .rank import rank_by
from .relax import relax


def _packed(cands: DataFrame) -> DataFrame:
    """One row per query: at most the cap's number of candidates and their pair distances."""
    rows = cands.groupBy("qid").agg(F.sort_array(F.collect_list(F.struct("id", "s"))).alias("c"))
    pairs = pair_distances(cands).groupBy("qid").agg(F.collect_list(F.struct("i", "j", "d")).alias("p"))
    return rows.join(pairs, "qid", "left")


def _tree(row, linkage):
    ids = [c["id"] for c in row.c]
    return ids, kernel.guide_tree(ids, {(p["i"], p["j"]): p["d"] for p in (row.p if row.p is not None else [])}, linkage)


def guide_tree(cands: DataFrame, linkage: str = "wpgma") -> DataFrame:
    """(qid, step, left, right, height)."""

    def run(frames):
        for frame in frames:
            out = [(row.qid, i + 1, a, b, h) for row in frame.itertuples() for i, (a, b, h) in enumerate(_tree(row, linkage)[1])]
            yield pd.DataFrame(out, columns=["qid", "step", "left", "right", "height"])

    return _packed(cands).mapInPandas(run, "qid int, step int, left long, right long, height double")


def substitution_matrix(cands: DataFrame, *, linkage: str = "wpgma", groups: int = 1, **score) -> DataFrame:
    """(qid, profile, id, aligned, motif_votes, motif_plain): rows of equal length per profile, and its consensus."""

    def run(frames):
        for frame in frames:
            out = []
            for row in frame.itertuples():
                ids, tree = _tree(row, linkage)
                strings = {c["id"]: c["s"] for c in row.c}
                for n, (members, rows) in enumerate(kernel.align_along(ids, strings, tree, min(groups, len(ids)), **score)):
                    votes, plain = kernel.motif(rows), kernel.motif(rows, gap_votes=False)
                    out += [(row.qid, n, i, kernel.shown(r), votes, plain) for i, r in zip(members, rows)]
            yield pd.DataFrame(out, columns=["qid", "profile", "id", "aligned", "motif_votes", "motif_plain"])

    return _packed(cands).mapInPandas(run, "qid int, profile int, id long, aligned string, motif_votes string, motif_plain string")


def motif_sql(aligned: DataFrame, *, gap_votes: bool = True, gap: str = "-") -> DataFrame:
    """(qid, motif) from aligned rows (qid, id, aligned) by column votes, as aggregates."""
    cells = aligned.select("qid", F.posexplode(F.split("aligned", "")).alias("pos", "ch"))
    if not gap_votes:
        cells = cells.where(F.col("ch") != gap)
    votes = cells.groupBy("qid", "pos", "ch").count()
    w = Window.partitionBy("qid", "pos").orderBy(F.col("count").desc(), F.col("ch") == gap, "ch")
    won = votes.withColumn("r", F.row_number().over(w)).where((F.col("r") == 1) & (F.col("ch") != gap))
    return won.groupBy("qid").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("pos", "ch"))), lambda x: x["ch"]), "").alias("motif"))


def sum_of_pairs_sql(aligned: DataFrame, *, match=1, mismatch=0, gap=-1, gapgap=0, sign: str = "-") -> DataFrame:
    """(qid, i, j, score) of all pairs of aligned rows, as far as both reach.

    Rows meet whole, by query, and a pair is scored from its two strings: a cell per place and row would be joined with every
    other of its place. The rows are sorted on the executors also where they look small enough for the driver to hold."""
    rows = aligned.where(F.length("aligned") > 0)
    a, b = rows.select("qid", F.col("id").alias("i"), F.col("aligned").alias("x")), rows.select("qid", F.col("id").alias("j"), F.col("aligned").alias("y"))

    def cost(x, y):
        c = F.when(x.isNull() | y.isNull(), 0).when((x == sign) & (y == sign), gapgap).when((x == sign) | (y == sign), gap).when(x == y, match).otherwise(mismatch)
        return c.cast("double")

    score = F.aggregate(F.zip_with(F.split("x", ""), F.split("y", ""), cost), F.lit(0.0), lambda s, c: s + c)
    pairs = a.hint("merge").join(b, (a["qid"] == b["qid"]) & (F.col("i") < F.col("j"))).select(a["qid"], "i", "j", score.alias("score"))
    return pairs.groupBy("qid", "i", "j").agg(F.sum("score").cast("long").alias("score"))


def rank_by_motif(cands: DataFrame, matrix: DataFrame, goal: Goal, gap_votes: bool = True) -> DataFrame:
    """With several profiles a string's score is its distance to the nearest consensus."""
    motifs = matrix.select("qid", "profile", F.col("motif_votes" if gap_votes else "motif_plain").alias("motif")).distinct()
    far = cands.join(motifs, "qid").groupBy("qid", "id", "s", "dist").agg(F.min(F.levenshtein("s", "motif")).alias("motif_dist"))
    return rank_by(far, "motif_dist", goal).select("qid", "id", "s", "dist", "motif_dist", "rank")


def relax_align(corpus: DataFrame, queries: DataFrame, goal: Goal, *, linkage: str = "wpgma", gap_votes: bool = True, profiles: int | str = 1, most_profiles: int = 4, candidates: DataFrame | None = None, score: dict | None = None, **options) -> DataFrame:
    """(qid, id, s, dist, motif_dist, rank). profiles='auto': for each query as many as give the best balance."""
    cands = relax(corpus, queries, goal, **options) if candidates is None else candidates
    cands = cands.select("qid", "id", "s", "dist").persist()
    of = lambda p: rank_by_motif(cands, substitution_matrix(cands, linkage=linkage, groups=p, **(score or {})), goal, gap_votes)
    if profiles != "auto":
        return of(profiles)
    tried = [of(p).withColumn("p", F.lit(p)).persist() for p in range(1, most_profiles + 1)]
    scores = None
    for t in tried:
        s = balance_score(t, goal.lam).join(t.select("qid", "p").distinct(), "qid").select("qid", "p", "balance_score")
        scores = s if scores is None else scores.union(s)
    best = scores.groupBy("qid").agg(F.max(F.struct("balance_score", (-F.col("p")).alias("m"))).alias("b")).select("qid", (-F.col("b.m")).alias("p"))
    every = tried[0]
    for t in tried[1:]:
        every = every.union(t)
    return every.join(F.broadcast(best), ["qid", "p"]).select("qid", "id", "s", "dist", "motif_dist", "rank")
