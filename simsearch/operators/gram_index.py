"""Inverted lists of grams: build, append, probe with a count bound, verify.

Each insertion, deletion or substitution touches at most n padded grams, so strings within distance e share at
least length + n - 1 - n*e of the query's grams, as multisets. Where that bound is not above 0 the index
knows nothing about strings without a common gram, and the search scans instead."""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import edits
from ..functions.strings import numbered_grams
from .relax import range_scan, small


def postings(corpus: DataFrame, n: int = 2, pad: bool = True) -> DataFrame:
    """(gram, occ, id, len)."""
    return numbered_grams(corpus, ["id", "len"], "s", n, pad).select("gram", "occ", "id", "len")


def probe(lists: DataFrame, queries: DataFrame, eps: int, n: int = 2, *, mode: str = "bag") -> DataFrame:
    """(qid, id, common) of strings that pass the count bound for a distance below eps (strict).

    bag: grams counted with their numbers, nothing is lost. set: distinct grams, bounded by the query's distinct
    grams, which loses nothing either but lets more through."""
    reach = eps - 1
    small(queries)  # refuses more than a batch; a query has as many grams as characters
    q = numbered_grams(queries.select("qid", "q", F.length("q").alias("qlen")), ["qid", "qlen"], "q", n)
    if mode == "set":
        q, lists = q.where("occ = 1"), lists.where("occ = 1")
        sizes = q.groupBy("qid").agg(F.count(F.lit(1)).alias("size"))
    else:
        sizes = q.select("qid", (F.col("qlen") + n - 1).cast("long").alias("size")).distinct()
    hits = lists.join(F.broadcast(q), ["gram", "occ"]).where(F.abs(F.col("len") - F.col("qlen")) <= reach)
    common = hits.groupBy("qid", "id").agg(F.count(F.lit(1)).alias("common"))
    return common.join(F.broadcast(sizes), "qid").where(F.col("common") >= F.col("size") - n * reach).select("qid", "id", "common")


def vacuous(eps: int, n: int = 2):
    """True for query lengths that the count bound says nothing about."""
    return F.length("q") + (n - 1) - n * (eps - 1) <= 0


class GramIndex:
    """Postings stored as Parquet in ranges of grams, beside the strings they belong to."""

    def __init__(self, corpus: DataFrame, lists: DataFrame, n: int = 2):
        self.corpus, self.lists, self.n = corpus, lists, n

    @classmethod
    def build(cls, corpus: DataFrame, path: str, n: int = 2, ranges: int | None = None) -> GramIndex:
        corpus.write.parquet(f"{path}/strings")
        spark = corpus.sparkSession
        kept = spark.read.schema(corpus.schema).parquet(f"{path}/strings")
        lists = postings(kept, n)
        dealt = lists.repartitionByRange(ranges, "gram", "len") if ranges else lists.repartitionByRange("gram", "len")
        dealt.sortWithinPartitions("gram", "len").write.parquet(f"{path}/postings")
        return cls.open(spark, path, n)

    @classmethod
    def open(cls, spark: SparkSession, path: str, n: int = 2) -> GramIndex:
        return cls(spark.read.parquet(f"{path}/strings"), spark.read.parquet(f"{path}/postings"), n)

    def append(self, batch: DataFrame, path: str) -> GramIndex:
        """New strings become more files; nothing is rewritten."""
        batch.select("id", "s", "len").write.mode("append").parquet(f"{path}/strings")
        postings(batch, self.n).sortWithinPartitions("gram", "len").write.mode("append").parquet(f"{path}/postings")
        return self.open(batch.sparkSession, path, self.n)

    def range_search(self, queries: DataFrame, eps: int, *, mode: str = "bag") -> DataFrame:
        """(qid, id, s, len, dist) with dist < eps: by the lists where they help, by a scan for the other queries."""
        near, far = queries.where(~vacuous(eps, self.n)), queries.where(vacuous(eps, self.n))
        cands = probe(self.lists, near, eps, self.n, mode=mode)
        found = verify(self.corpus, cands, near, eps)
        return found.unionByName(range_scan(self.corpus, far, eps - 1))

    def blind(self, eps: int):
        """Queries about which the count bound says nothing."""
        return vacuous(eps, self.n)

    def postings_read(self, queries: DataFrame, eps: int) -> int:
        """Postings that a probe for the queries reads, after the length band."""
        q = numbered_grams(queries.select("qid", "q", F.length("q").alias("qlen")), ["qid", "qlen"], "q", self.n)
        return self.lists.join(F.broadcast(q), ["gram", "occ"]).where(F.abs(F.col("len") - F.col("qlen")) < eps).count()

    def explain_engine(self, queries: DataFrame, eps: int) -> DataFrame:
        return queries.select("qid", F.when(vacuous(eps, self.n), "scan").otherwise("index").alias("engine"))


def verify(corpus: DataFrame, cands: DataFrame, queries: DataFrame, eps: int) -> DataFrame:
    rows = corpus.join(cands.select("qid", "id"), "id").join(small(queries.select("qid", "q")), "qid")
    near = rows.select("qid", "id", "s", "len", F.explode(F.array(F.levenshtein("s", "q", eps - 1))).alias("dist"))
    return near.where("dist >= 0")


def similarity_self_join(corpus: DataFrame, eps: int, *, left_out: str = "0-9", block: int = 8192) -> DataFrame:
    """(i, j, dist) of all pairs with i < j and dist < eps.

    With some letters (``left_out``, a class of a regular expression) taken out of both, two strings are no farther apart than
    before. Many strings are equal then: such classes are compared first, and only strings of two near classes are compared whole.
    Strings are dealt in order of their classes into blocks of about ``block``, and every two blocks meet in one task."""
    limit = eps - 1
    rows = corpus.select("id", "s").where("id is not null and s is not null").distinct()
    seen = rows.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("id").alias("ids")).first()
    blocks = max(-(-seen.n // block), min(8, -(-seen.n // 256)), 1)

    def run(batches):
        held: list = []  # the rows of one cell
        for batch in batches:
            cell = batch.column("cell").to_numpy()
            edges = [0, *(np.flatnonzero(np.diff(cell)) + 1).tolist(), len(cell)]
            for first, last in zip(edges[:-1], edges[1:]):
                if held and last > first and held[0].column("cell")[0].as_py() != cell[first]:
                    yield from _near_pairs(pa.Table.from_batches(held), limit, left_out)
                    held = []
                held += [batch.slice(first, last - first)] if last > first else []
        if held:
            yield from _near_pairs(pa.Table.from_batches(held), limit, left_out)

    # the block is taken from the partition, whatever number of partitions there is
    dealt = rows.repartitionByRange(blocks, F.regexp_replace("s", f"[{left_out}]", ""), "s").select("id", "s", F.pmod(F.spark_partition_id(), F.lit(blocks)).alias("own"))
    both = F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), lambda x: F.greatest(x, F.col("own")) * (F.greatest(x, F.col("own")) + 1) / 2 + F.least(x, F.col("own")))
    cells = dealt.select("id", "s", "own", F.explode(both.cast("array<int>")).alias("cell"))
    met = cells.repartitionById(min(blocks * (blocks + 1) // 2, 4096), "cell").sortWithinPartitions("cell", "own")
    out = met.mapInArrow(run, "i long, j long, dist int")
    return out if seen.ids == seen.n else out.distinct()


def _classes(strings: list[str], left_out: str) -> tuple[list[str], np.ndarray, np.ndarray, np.ndarray]:
    """Distinct strings without the letters, an order of the strings by them, and where in it each begins and how many it has."""
    taken = re.compile(f"[{left_out}]")
    names, number = np.unique(np.array([taken.sub("", s) for s in strings], object), return_inverse=True)
    many = np.bincount(number, minlength=len(names))
    return names.tolist(), np.argsort(number, kind="stable"), np.cumsum(many) - many, many


def _products(rows: np.ndarray, cols: np.ndarray, most: int):
    """All (which, place in its rows, place in its cols), where the x-th product has rows[x] times cols[x] of them."""
    end = np.cumsum(rows * cols)
    for first in range(0, int(end[-1]) if len(end) else 0, most):
        at = np.arange(first, min(first + most, int(end[-1])))
        which = np.searchsorted(end, at, "right")
        yield which, *np.divmod(at - (end - rows * cols)[which], cols[which])


def _near_pairs(held: pa.Table, limit: int, left_out: str):
    """Pairs of the strings of two blocks, or of one with itself."""
    own, cell = held.column("own").to_numpy(), held.column("cell")[0].as_py()
    parts = [held.filter(pa.array(own == x)) for x in np.unique(own)]
    same = cell == own[0] * (own[0] + 3) // 2
    if len(parts) == 1 and not same:  # the other block is empty
        return
    sides = []
    for part in parts:
        names, order, begin, many = _classes(part.column("s").to_pylist(), left_out)
        part = part.take(pa.array(order))
        sides.append((part.column("id").to_numpy(), part.column("s").to_pylist(), names, begin, many))
    letters = edits.letters_of([s for side in sides for s in side[1]])
    whole, short = [edits.Rows(side[1], letters) for side in sides], [edits.Rows(side[2], letters) for side in sides]
    (ids, _, _, begin, many), (ids_b, _, _, begin_b, many_b) = sides[0], sides[-1]

    def near(a, b, i, j):
        at = np.flatnonzero(np.abs(a.size[i] - b.size[j]) <= limit)
        dist = edits.pair_distances(a, b, i[at], j[at])
        return at[dist <= limit], dist[dist <= limit]

    for _, c, d in _products(np.array([len(many)]), np.array([len(many_b)]), edits.PAIRS):
        c, d = (c[c <= d], d[c <= d]) if same else (c, d)
        found, _ = near(short[0], short[-1], c, d)
        c, d = c[found], d[found]
        for which, x, y in _products(many[c], many_b[d], edits.PAIRS):
            i, j = begin[c[which]] + x, begin_b[d[which]] + y
            i, j = (i[i < j], j[i < j]) if same else (i, j)
            found, dist = near(whole[0], whole[-1], i, j)
            i, j = ids[i[found]], ids_b[j[found]]
            apart = i != j
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(i, j)[apart]), pa.array(np.maximum(i, j)[apart]), pa.array(dist[apart].astype(np.int32))], names=["i", "j", "dist"])
