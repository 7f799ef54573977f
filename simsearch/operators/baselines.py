"""Baselines over a range search without relaxation, exact optimum for small inputs, random answer."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import edits
from ..functions.alignment import distance
from ..plans.goal import Goal
from .relax import LONG, long_scan, range_scan


def _per_query(cands: DataFrame, pick) -> DataFrame:
    """pick(list of (id, s, dist) in order of (dist, id)) -> chosen ids, for the candidates of each query in one group."""

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values(["dist", "id"])
        chosen = pick(list(zip(frame["id"].tolist(), frame["s"].tolist(), frame["dist"].tolist())))
        out = frame.set_index("id").loc[chosen].reset_index()
        out["rank"] = range(1, len(out) + 1)
        return out[["qid", "id", "s", "dist", "rank"]]

    return cands.select("qid", "id", "s", "dist").groupBy("qid").applyInPandas(run, "qid int, id long, s string, dist int, rank int")


def all_within(corpus: DataFrame, queries: DataFrame, eps: int) -> DataFrame:
    """All strings under eps: the farthest ones are those that a spread-seeking baseline picks."""
    longest = queries.agg(F.max(F.length("q"))).first()[0] or 0
    if longest > LONG:
        return long_scan(corpus, queries, eps - 1).where(F.col("dist") < eps)
    return range_scan(corpus, queries, eps - 1)


class _Pairs:
    def __init__(self, rows):
        self.rows, self.memo = rows, {}

    def __call__(self, i: int, j: int) -> int:
        key = (i, j) if i < j else (j, i)
        if key not in self.memo:
            self.memo[key] = distance(self.rows[i][1], self.rows[j][1])
        return self.memo[key]


def _balance(lam, n, pairs, near):
    """The objective of n members with these sums of distances, to each other and to the query; of numbers or arrays."""
    return lam * (2 * pairs / (n * (n - 1)) if n > 1 else 0.0) - (1 - lam) * near / n


def _score(lam, rows, d, members) -> float:
    return _balance(lam, len(members), sum(d(i, j) for i, j in combinations(members, 2)), sum(rows[i][2] for i in members))


def swap_baseline(corpus: DataFrame, queries: DataFrame, *, k: int = 25, lam: float = 0.5, eps: int = 40, max_drop: int | None = None, gain: str = "spread", candidates: DataFrame | None = None) -> DataFrame:
    """Start with the k nearest; each farther string replaces the member of least spread if that raises the gain.

    Strings are looked at in blocks: their distances to all members at once, the first that raises the gain, the distances to
    it of those behind it, and so on. Blocks grow, as most replacements are among the first strings."""

    def pick(rows):
        s, strings = list(range(min(k, len(rows)))), [r[1] for r in rows]
        dist = np.array([r[2] for r in rows], np.int64)
        first = edits.Texts(strings[: len(s)])
        inner = np.array([first.distances(strings[i]) for i in s], np.int64).reshape(len(s), len(s))
        total, n, begin, size = inner.sum(1), len(s), len(s), 256
        while begin < len(rows):
            texts, near = edits.Texts(strings[begin : begin + size]), dist[begin : begin + size]
            to = np.array([texts.distances(strings[i]) for i in s])
            sums, at = to.sum(0), 0
            allowed = near - dist[0] <= max_drop if max_drop is not None else np.ones(len(near), bool)
            while True:
                w = min(range(n), key=lambda x: (total[x], -dist[s[x]], -rows[s[x]][0]))
                new = sums[at:] - to[w, at:]
                if gain == "spread":
                    better = new > total[w]
                else:
                    pairs, close = int(total.sum()) // 2, int(dist[s].sum())
                    better = _balance(lam, n, pairs - total[w] + new, close - dist[s[w]] + near[at:]) - _balance(lam, n, pairs, close) > 0
                found = np.flatnonzero(better & allowed[at:])
                if not len(found):
                    break
                at += int(found[0])
                column = to[:, at].copy()
                column[w] = 0
                total += column - inner[w]
                total[w] = column.sum()
                inner[w], inner[:, w] = column, column
                s[w] = begin + at
                other = texts.distances(strings[s[w]])
                sums += other - to[w]
                to[w] = other
                at += 1
            begin, size = begin + size, min(2 * size, edits.BLOCK)
        return [rows[i][0] for i in s]

    return _per_query(all_within(corpus, queries, eps) if candidates is None else candidates, pick)


def multipass_greedy(corpus: DataFrame, queries: DataFrame, *, k: int = 25, lam: float = 0.5, eps: int = 40, passes: int = 1, candidates: DataFrame | None = None) -> DataFrame:
    """k passes over all candidates; each adds the one with the best objective. Further passes try replacements."""

    def pick(rows):
        s, strings = [0] if rows else [], [r[1] for r in rows]
        dist, texts = np.array([r[2] for r in rows], np.int64), edits.Texts(strings)
        far, near, pairs = np.zeros(len(rows), np.int64), rows[0][2] if rows else 0, 0  # far: to all members
        inside = np.zeros(len(rows), bool)
        inside[s] = True
        while s and len(s) < min(k, len(rows)):
            far += texts.distances(strings[s[-1]])
            n = len(s) + 1
            gain = lam * 2 * (pairs + far) / (n * (n - 1)) - (1 - lam) * (near + dist) / n
            gain[inside] = -np.inf
            best = int(np.argmax(gain))  # of equals the first in the order of (dist, id)
            pairs, near = pairs + int(far[best]), near + rows[best][2]
            s.append(best)
            inside[best] = True
        if s and passes > 1:
            far += texts.distances(strings[s[-1]])
        for _ in range(passes - 1):
            for at in range(len(s)):
                own = texts.distances(strings[s[at]])
                rest, close = pairs - int(far[s[at]]), near - rows[s[at]][2]
                score = _balance(lam, len(s), rest + far - own, close + dist)
                score[inside] = -np.inf
                best = min(np.flatnonzero(score == score.max()).tolist(), key=lambda i: rows[i][0])
                if score[best] > _balance(lam, len(s), pairs, near) + 1e-12:
                    pairs, near = rest + int(far[best] - own[best]), close + rows[best][2]
                    far += texts.distances(strings[best]) - own
                    inside[s[at]], inside[best] = False, True
                    s[at] = best
        return [rows[i][0] for i in s]

    return _per_query(all_within(corpus, queries, eps) if candidates is None else candidates, pick)


def exact_best(cands: DataFrame, goal: Goal, most: int = 18) -> DataFrame:
    """The subset of allowed size with the best balance, by enumeration; for at most ``most`` candidates."""

    def pick(rows):
        if len(rows) > most:
            raise ValueError(f"enumeration takes at most {most} candidates")
        d, best = _Pairs(rows), (float("-inf"), ())
        for n in range(min(goal.kmin, len(rows)), min(goal.kmax, len(rows)) + 1):
            for s in combinations(range(len(rows)), n):
                x = _score(goal.lam, rows, d, s)
                if x > best[0] + 1e-12:
                    best = (x, s)
        return [rows[i][0] for i in best[1]]

    return _per_query(cands, pick)


def random_subset(cands: DataFrame, k: int, seed: int = 1) -> DataFrame:
    w = Window.partitionBy("qid").orderBy(F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("id").cast("string"))), "id")
    return cands.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("qid", "id", "s", "dist", "rank")


def choose_method(*, changing: bool, strings: int, quality_first: bool) -> str:
    """Changing data: ranking needs nothing built. Large and fixed: walk over clusters. Else quality: alignment."""
    if changing:
        return "relax_rank"
    if quality_first and strings < 1_000_000:
        return "relax_align"
    return "cluster_walk" if strings >= 50_000 else "relax_align"
