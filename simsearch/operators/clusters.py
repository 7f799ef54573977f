"""Vectors, clusters and the walk over neighbouring clusters."""

from __future__ import annotations

import math
import zlib
from collections import Counter
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from functools import cached_property

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.ml.clustering import KMeans
from pyspark.ml.feature import HashingTF, IDF, StopWordsRemover, VarianceThresholdSelector, Word2Vec
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type
from pyspark.util import inheritable_thread_target

from ..functions import alignment as kernel
from ..functions.strings import cosine, euclid, grams
from ..plans.goal import Goal
from .relax import small


def tokenize(s, *, stop: bool = True, stem: str | None = None, n: int | None = 3):
    """Character n-grams by default (short strings are often a single word); words if n is None."""
    if n is not None:
        return grams(F.lower(s), n)
    words = F.filter(F.split(F.lower(s), r"[^0-9a-z?]+"), lambda w: w != "")
    if stop:
        listed = F.array(*[F.lit(w) for w in StopWordsRemover.loadDefaultStopWords("english")])
        words = F.filter(words, lambda w: ~F.array_contains(listed, w))
    if stem == "suffix":
        words = F.transform(words, lambda w: F.regexp_replace(w, r"(?<=...)(ingly|edly|ing|ed|ies|es|ly|s)$", ""))
    return words


def _gram_counts(s: str, dims: int, n: int, known: dict[str, np.ndarray]) -> np.ndarray:
    """How many of the padded grams of s fall into each of dims buckets by crc32."""
    p = "\x02" * (n - 1) + s + "\x03" * (n - 1)
    if len(p) < n:
        return np.zeros(dims)
    if n == 2 and p.isascii():
        if not known:
            known["all"] = np.array([zlib.crc32(bytes((i >> 7, i & 127))) % dims for i in range(1 << 14)], np.int16)
        c = np.frombuffer(p.encode(), np.uint8).astype(np.int32)
        return np.bincount(known["all"][(c[:-1] << 7) | c[1:]], minlength=dims).astype(float)
    grams_of = Counter(p[i : i + n] for i in range(len(p) - n + 1))
    out = np.zeros(dims)
    for g, times in grams_of.items():
        out[zlib.crc32(g.encode()) % dims] += times
    return out


def _gram_vectors(s, dims: int, n: int):
    """Column of vectors: counts of hashed grams, of unit length. One pass over each string, the same on every run."""

    @F.pandas_udf("array<double>")
    def vec(strings: Iterator[pd.Series]) -> Iterator[pd.Series]:
        known: dict = {}
        for some in strings:
            out = []
            for x in some:
                if x is None:
                    out.append(None)
                    continue
                c = _gram_counts(x, dims, n, known)
                out.append(c / max(math.sqrt((c * c).sum()), 1e-12))
            yield pd.Series(out, dtype=object)

    return vec(F.lower(s))


def hashed_grams(corpus: DataFrame, *, dims: int = 64, n: int = 2, s: str = "s") -> DataFrame:
    """corpus with vec: counts of hashed grams, of unit length; null where the string is null. Strings may be whole texts."""
    return corpus.withColumn("vec", _gram_vectors(F.col(s), dims, n))


def fit_vectorizer(corpus: DataFrame, how: str = "word2vec", *, dims: int = 32, seed: int = 1, n: int | None = 3):
    """A function from corpora to corpora with vec (array of double)."""
    if how == "hashed_grams":
        return lambda df: hashed_grams(df, dims=dims)
    toks = lambda df: df.withColumn("__t", tokenize(F.col("s"), n=n))
    if how == "word2vec":
        model = Word2Vec(vectorSize=dims, minCount=1, maxIter=1, numPartitions=corpus.sparkSession.sparkContext.defaultParallelism, seed=seed, inputCol="__t", outputCol="__v").fit(toks(corpus))
        return lambda df: model.transform(toks(df)).withColumn("vec", vector_to_array("__v")).drop("__t", "__v")
    tf = HashingTF(numFeatures=dims, inputCol="__t", outputCol="__tf")
    idf = IDF(inputCol="__tf", outputCol="__v").fit(tf.transform(toks(corpus)))
    return lambda df: idf.transform(tf.transform(toks(df))).withColumn("vec", vector_to_array("__v")).drop("__t", "__tf", "__v")


def select_features(vectors: DataFrame, least_variance: float = 0.0):
    """Drop components that hardly vary; returns the frame with shorter vec."""
    df = vectors.withColumn("__v", array_to_vector("vec"))
    model = VarianceThresholdSelector(varianceThreshold=least_variance, featuresCol="__v", outputCol="__o").fit(df)
    return model.transform(df).withColumn("vec", vector_to_array("__o")).drop("__v", "__o")


#: Large clusters that are fitted at a time, and rows of theirs in a task.
FITS_AT_ONCE, ROWS_A_TASK = 6, 32_768


def cluster_count(total_bytes: int, cap: int = 64 << 20, floor: int = 8) -> int:
    return max(floor, math.ceil(total_bytes / cap))


def partition(vectors: DataFrame, m: int | None = None, *, seed: int = 1, cap: int = 64 << 20, most_rounds: int = 8, size: Column | None = None) -> DataFrame:
    """vectors with cid. Clusters whose strings (or size, in bytes) take more than cap are clustered again, each into as many
    parts as the cap asks for, until none is too large or a cluster cannot be told apart any further (all of its vectors equal).

    Large clusters are independent and fitted some at a time, each on as many partitions as its rows ask for: an iteration is
    a job, and with all partitions in it most of its time goes into empty tasks."""
    size = F.octet_length("s") if size is None else size
    spark = vectors.sparkSession
    if m is None:
        m = cluster_count(vectors.agg(F.coalesce(F.sum(size), F.lit(0))).first()[0], cap)
    featured = lambda df: df.withColumn("__v", array_to_vector("vec"))
    fit = lambda df, k: KMeans(k=k, seed=seed, maxIter=20, featuresCol="__v", predictionCol="cid").fit(df)
    out = fit(featured(vectors), m).transform(featured(vectors)).drop("__v").persist()
    whole: set[int] = set()
    made: list[range] = []
    before = None
    for _ in range(most_rounds):
        sizes = {r.cid: r for r in out.groupBy("cid").agg(F.sum(size).alias("bytes"), F.count(F.lit(1)).alias("rows")).collect()}  # rows: clusters
        if before is not None:
            before.unpersist()
        for left in ([c for c in new if c in sizes] for new in made):
            whole |= set(left) if len(left) == 1 else set()
        large = sorted(c for c, r in sizes.items() if (r.bytes or 0) > cap and c not in whole)
        if not large:
            break

        def split(c: int, out=out, sizes=sizes) -> np.ndarray:
            some = out.where(F.col("cid") == c).select("vec").repartition(math.ceil(sizes[c].rows / ROWS_A_TASK)).sortWithinPartitions("vec")  # the start of a fit depends on the order
            return np.array(fit(featured(some), max(2, math.ceil(sizes[c].bytes / cap))).clusterCenters())

        with ThreadPoolExecutor(FITS_AT_ONCE) as pool:
            found = dict(zip(large, pool.map(inheritable_thread_target(spark)(split), large)))
        told, made, top = {}, [], max(sizes) + 1
        for c, centre in found.items():
            if len(centre) < 2:
                whole.add(c)
                continue
            told[c] = (top, centre)
            made.append(range(top, top + len(centre)))
            top += len(centre)
        if not told:
            break
        before, out = out, out.withColumn("cid", _moved(told)("cid", "vec")).persist()
    return out


def _moved(told: dict[int, tuple[int, np.ndarray]]):
    """Column of clusters in the place of (cid, vec): a cluster of ``told`` gives way to its nearest new centre, numbered from
    the first number. One pass for all clusters; a union with a part for each would double the plan round by round."""

    @F.pandas_udf("int")
    def nearest(cid: pd.Series, vec: pd.Series) -> pd.Series:
        out = cid.to_numpy().copy()
        for c in set(out.tolist()) & set(told):
            first, centre = told[c]
            at = np.flatnonzero(cid.to_numpy() == c)
            x = np.stack(vec.to_numpy()[at])
            out[at] = first + np.stack([((x - y) ** 2).sum(1) for y in centre]).argmin(0)
        return pd.Series(out)

    return nearest


def centres(members: DataFrame, how: str = "median") -> DataFrame:
    """(cid, centre): component-wise mean or median."""
    parts = members.select("cid", F.posexplode("vec").alias("i", "x"))
    if how == "mean":
        value = F.avg("x")
    else:  # equal components are counted first: strings have few different ones
        parts = parts.groupBy("cid", "i", "x").agg(F.count(F.lit(1)).alias("times"))
        value = F.percentile("x", F.lit(0.5), F.col("times"))
    return parts.groupBy("cid", "i").agg(value.alias("x")).groupBy("cid").agg(F.transform(F.sort_array(F.collect_list(F.struct("i", "x"))), lambda v: v["x"]).alias("centre"))


def cluster_graph(centre: DataFrame, metric: str = "euclid") -> DataFrame:
    """(src, dst, w) between all centres: one row per pair of clusters, so for few clusters only."""
    f = {"euclid": euclid, "cosine": cosine}[metric]
    a, b = centre.select(F.col("cid").alias("src"), F.col("centre").alias("x")), centre.select(F.col("cid").alias("dst"), F.col("centre").alias("y"))
    return a.join(F.broadcast(b), F.col("src") != F.col("dst")).select("src", "dst", f(F.col("x"), F.col("y")).alias("w"))


def shortest_paths(edges: DataFrame, rounds: int = 3) -> DataFrame:
    """Min-plus products; differs from the direct order only where the measure is no metric."""
    best = edges
    for _ in range(rounds):
        step = best.select("src", F.col("dst").alias("mid"), F.col("w").alias("w1")).join(edges.select(F.col("src").alias("mid"), "dst", F.col("w").alias("w2")), "mid").where("src != dst")
        best = best.union(step.select("src", "dst", F.col("w1") + F.col("w2"))).groupBy("src", "dst").agg(F.min("w").alias("w"))
    return best


def reachable(edges: DataFrame, clusters: int, cluster_share: float = 0.5) -> DataFrame:
    """(src, dst, hop): the nearest share of all clusters, the start itself as hop 0."""
    w = Window.partitionBy("src").orderBy("w", "dst")
    keep = max(1, math.ceil(cluster_share * clusters))
    own = edges.select("src").distinct().select("src", F.col("src").alias("dst"), F.lit(0).alias("hop"))
    return edges.select("src", "dst", F.row_number().over(w).alias("hop")).where(F.col("hop") < keep).union(own)


def training_sample(members: DataFrame, share: float = 0.05) -> DataFrame:
    """(cid, id, vec): a share of every cluster by id digest, at least one row."""
    w = Window.partitionBy("cid").orderBy(F.md5(F.col("id").cast("string")), "id")
    rows = members.select("cid", "id", "vec", F.row_number().over(w).alias("r"), F.count(F.lit(1)).over(Window.partitionBy("cid")).alias("n"))
    return rows.where(F.col("r") <= F.greatest(F.lit(1), F.ceil(F.lit(share) * F.col("n")))).select("cid", "id", "vec")


def _numbers(vec: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Components of all vectors one after another, where each begins, and its length: -1 if it or a component is null."""
    parts = vec.combine_chunks()
    lists = parts if isinstance(parts, pa.ListArray) else parts.chunk(0) if parts.num_chunks else pa.array([], vec.type)
    at, values = np.asarray(lists.offsets), lists.values
    x = np.asarray(values.cast(pa.float64()).fill_null(0.0))
    gaps = np.concatenate([[0], np.cumsum(np.asarray(values.is_null(), dtype=np.int64))])
    length = np.diff(at)
    return x, at[:-1], np.where(np.asarray(lists.is_null()) | (gaps[at[1:]] > gaps[at[:-1]]), -1, length)


def _nearest_rows(q: np.ndarray, s: np.ndarray, order: np.ndarray, k: int, cells: int = 4_000_000) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(row of q, row of s, distance) of the k nearest rows of s by (distance, order).

    Squares of distances from one matrix product tell which rows can be among them, with room for its rounding; the distances
    of these are added up component by component, as ``euclid`` does."""
    qt, st, step = np.ascontiguousarray(q.T), np.ascontiguousarray(s.T), max(1, cells // max(1, len(s)))
    for a in range(0, len(q), step):
        with np.errstate(invalid="ignore", over="ignore"):
            some = q[a : a + step]
            size = (some * some).sum(1)[:, None] + (st * st).sum(0)
            near = size - 2 * (some @ st)
            room = 8 * (q.shape[1] + 4) * np.finfo(float).eps * size.max(1, initial=0.0)
            last = np.partition(near, k - 1, axis=1)[:, k - 1] if len(s) > k else np.full(len(near), np.inf)
            i, j = np.nonzero(~(near > (last + 2 * room)[:, None]))  # what is no number stays
            i += a
            d = np.zeros(len(i))
            for b in range(0, len(i), cells // 4):
                at = slice(b, b + cells // 4)
                for x, y in zip(qt, st):
                    t = x[i[at]] - y[j[at]]
                    d[at] += t * t
            d = np.sqrt(d)
        by = np.lexsort((order[j], d, i))
        i, j, d = i[by], j[by], d[by]
        first = np.arange(len(i)) - np.searchsorted(i, i) < k
        yield i[first], j[first], d[first]


def _nearest(asked: pa.Table, given: pa.Table, k: int) -> tuple[list, list, list, list]:
    """Rows of asked, rows of given, distances and whether they are null (as of vectors that are null or differ in length)."""
    (x, xa, xn), (y, ya, yn) = _numbers(asked["qv"]), _numbers(given["vec"])
    ids = np.asarray(given["id"].cast(pa.int64()).fill_null(np.iinfo(np.int64).min))
    out: tuple[list, list, list, list] = ([], [], [], [])
    for n in np.unique(xn):
        rows, same = np.flatnonzero(xn == n), np.flatnonzero(yn == n) if n >= 0 else np.array([], int)
        other = np.setdiff1d(np.arange(len(yn)), same)
        other = other[np.argsort(ids[other], kind="stable")][:k]
        if len(other):
            found = [(np.repeat(rows, len(other)), np.tile(other, len(rows)), np.zeros(len(rows) * len(other)), True)]
        else:
            found = []
        if len(same):
            of = lambda v, at: v[at[:, None] + np.arange(n)]  # noqa: B023, E731
            found += [(rows[i], same[j], d, False) for i, j, d in _nearest_rows(of(x, xa[rows]), of(y, ya[same]), ids[same], k)]
        for i, j, d, null in found:
            for column, values in zip(out, (i, j, d, np.full(len(i), null))):
                column.append(values)
    return out


#: Queries that are compared with a part of the sample at once.
ASKED_AT_ONCE = 8192


def nearest_sampled(queries: DataFrame, sample: DataFrame, k: int) -> DataFrame:
    """(qid, cid, id, d): of each part of the sample the k rows nearest to a query's vector, which hold the k nearest of all.

    The sample is dealt over parts, and the queries as well if they are many; every part of one meets every part of the
    other, as matrices. Neither goes to the driver, and no row is made per pair."""
    parts, batches = 4 * queries.sparkSession.sparkContext.defaultParallelism, math.ceil(queries.count() / ASKED_AT_ONCE) or 1
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    dealt = lambda c, n: F.pmod(F.xxhash64(c), F.lit(n)).cast("int")
    q = queries.select("qid", F.col("vec").alias("qv"), dealt("qid", batches).alias("b")).withColumn("p", every(parts))
    s = sample.select("cid", "id", "vec", dealt("id", parts).alias("p")).withColumn("b", every(batches))
    kinds = {"qid": queries.schema["qid"].dataType, "cid": sample.schema["cid"].dataType, "id": sample.schema["id"].dataType}
    schema = pa.schema([*[(name, to_arrow_type(kind)) for name, kind in kinds.items()], ("d", pa.float64())])

    def near(asked: pa.Table, given: pa.Table) -> pa.Table:
        if not (asked.num_rows and given.num_rows):
            return schema.empty_table()
        i, j, d, null = (np.concatenate(c) for c in _nearest(asked, given, k))
        columns = [asked["qid"].take(pa.array(i)), given["cid"].take(pa.array(j)), given["id"].take(pa.array(j))]
        return pa.Table.from_arrays([*[c.cast(f.type) for c, f in zip(columns, schema)], pa.array(d, mask=null)], schema=schema)

    ddl = ", ".join(f"{name} {kind.simpleString()}" for name, kind in kinds.items()) + ", d double"
    return q.groupBy("p", "b").cogroup(s.groupBy("p", "b")).applyInArrow(near, ddl)


def classify(queries: DataFrame, sample: DataFrame, k: int = 5, metric: str = "euclid") -> DataFrame:
    """(qid, cid): majority of the k nearest sampled vectors; ties go to the nearer sum, then the smaller cid."""
    if metric == "euclid":
        d = nearest_sampled(queries, sample, k)
    else:
        d = small(queries.select("qid", F.col("vec").alias("qv"))).join(sample, how="cross").select("qid", "cid", "id", {"cosine": cosine}[metric](F.col("qv"), F.col("vec")).alias("d"))
    w = Window.partitionBy("qid").orderBy("d", "id")
    votes = d.withColumn("r", F.row_number().over(w)).where(F.col("r") <= k).groupBy("qid", "cid").agg(F.count(F.lit(1)).alias("n"), F.sum("d").alias("d"))
    first = Window.partitionBy("qid").orderBy(F.col("n").desc(), "d", "cid")
    return votes.withColumn("r", F.row_number().over(first)).where("r = 1").select("qid", "cid")


class ClusterModel:
    """Members stored by cluster; centres, their graph and the training sample are worked out when first asked for."""

    def __init__(self, members: DataFrame, vectorizer=None, *, how: str = "median", share: float = 0.05, first: ClusterModel | None = None):
        self.members, self.vectorizer, self._how, self._share, self._first = members, vectorizer, how, share, first

    @cached_property
    def centre(self) -> DataFrame:
        return self._first.centre if self._first else centres(self.members, self._how).persist()

    @cached_property
    def edges(self) -> DataFrame:
        return self._first.edges if self._first else cluster_graph(self.centre).persist()

    @cached_property
    def sample(self) -> DataFrame:
        return self._first.sample if self._first else training_sample(self.members, self._share).persist()

    @cached_property
    def clusters(self) -> int:
        return self._first.clusters if self._first else self.centre.count()

    @classmethod
    def build(cls, corpus: DataFrame, path: str, *, how: str = "word2vec", m: int | None = None, centre: str = "median", share: float = 0.05, seed: int = 1, **options) -> ClusterModel:
        vectorizer = fit_vectorizer(corpus, how, seed=seed, **options)
        partition(vectorizer(corpus), m, seed=seed).select("id", "s", "len", "vec", "cid").write.partitionBy("cid").parquet(path)
        return cls(corpus.sparkSession.read.parquet(path), vectorizer, how=centre, share=share)

    def append(self, batch: DataFrame, path: str) -> ClusterModel:
        """New strings get the nearest centre's cluster; nothing is fitted again."""
        v = self.vectorizer(batch).join(F.broadcast(self.centre))
        w = Window.partitionBy("id").orderBy(euclid(F.col("vec"), F.col("centre")), "cid")
        v.withColumn("r", F.row_number().over(w)).where("r = 1").select("id", "s", "len", "vec", "cid").write.mode("append").partitionBy("cid").parquet(path)
        return ClusterModel(batch.sparkSession.read.parquet(path), self.vectorizer, first=self)


def frontier(members: DataFrame, starts: DataFrame, order: DataFrame, queries: DataFrame, kmax: int | None) -> DataFrame:
    """(qid, q, cid, hop, id, s, vdist): per query and cluster the kmax nearest vectors, or all of them (None).

    A walk that keeps what it looks at never needs more than kmax of a cluster; one that skips strings may need all."""
    q = small(queries.select("qid", "q", F.col("vec").alias("qv")).join(starts.withColumnRenamed("cid", "src"), "qid").join(order, "src").select("qid", "q", "qv", F.col("dst").alias("cid"), "hop"))
    rows = members.join(q, "cid").select("qid", "q", "cid", "hop", "id", "s", euclid(F.col("qv"), F.col("vec")).alias("vdist"))
    if kmax is None:
        return rows
    w = Window.partitionBy("qid", "cid").orderBy("vdist", "id")
    return rows.withColumn("r", F.row_number().over(w)).where(F.col("r") <= kmax).drop("r")


def walk(rows: DataFrame, goal: Goal, *, stop: str = "pass_end", on_drop: str = "keep", reference: str = "stale", drop_rule: bool = True, eps: int | None = None) -> DataFrame:
    """(qid, pick, pass, cid, id, s, vdist, dist, score, move) from a frontier, one query per group.

    In a cluster strings are taken by vector distance while the balance does not fall and the first share is not
    exceeded; then the next cluster is visited, round and round, until kmin are together (kmax at most)."""
    kmin, kmax, quota, lam = goal.kmin, goal.kmax, float(goal.quota), goal.lam

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values(["hop", "vdist", "id"])
        q = frame["q"].iloc[0]
        lists = [g[["cid", "id", "s", "vdist"]].values.tolist() for _, g in frame.groupby("hop", sort=True)]
        state, out, ref, turn, at = kernel.ScoreState(lam), [], None, 1, [0] * len(lists)
        while len(out) < kmax and any(a < len(x) for a, x in zip(at, lists)):
            for h, items in enumerate(lists):
                while at[h] < len(items) and len(out) < kmax:
                    cid, i, s, v = items[at[h]]
                    at[h] += 1
                    d = kernel.distance(q, s)
                    if eps is not None and d >= eps:
                        continue
                    score = state.gain(s, d)[2]
                    drop = drop_rule and ref is not None and score < ref - 1e-12
                    if drop and on_drop == "revert":
                        break
                    state.add(s, d)
                    full, over = len(out) + 1 >= kmax, len(out) + 1 > quota
                    out.append((turn, cid, i, s, v, d, score, "full" if full else "drop" if drop else "quota" if over else "stay"))
                    if not (drop or over) or reference == "always":
                        ref = score
                    if drop or over or full or (stop == "at_kmin" and len(out) >= kmin):
                        break
                if len(out) >= kmax or (stop == "at_kmin" and len(out) >= kmin):
                    break
            turn += 1
            if len(out) >= kmin:
                break
        df = pd.DataFrame(out, columns=["pass", "cid", "id", "s", "vdist", "dist", "score", "move"])
        df.insert(0, "pick", range(1, len(df) + 1))
        df.insert(0, "qid", frame["qid"].iloc[0])
        return df

    return rows.groupBy("qid").applyInPandas(run, "qid int, pick int, pass int, cid int, id long, s string, vdist double, dist int, score double, move string")


def quota_walk(rows: DataFrame, goal: Goal) -> DataFrame:
    """(qid, pick, cid, id, s, vdist): the walk without the drop rule in closed form, where no cluster runs out.

    The start cluster gives floor((1 - lam) kmin) + 1 strings, then every visit gives one."""
    first = int(goal.quota) + 1
    w = Window.partitionBy("qid", "cid").orderBy("vdist", "id")
    width = F.max("hop").over(Window.partitionBy("qid")) + 1
    r = rows.withColumn("r", F.row_number().over(w)).withColumn("width", width)
    place = F.when((F.col("hop") == 0) & (F.col("r") <= first), F.col("r")).when(F.col("hop") == 0, first + (F.col("r") - first) * F.col("width")).otherwise(first + (F.col("r") - 1) * F.col("width") + F.col("hop"))
    r = r.withColumn("place", place)
    # the size is looked at when a round ends
    need = F.lit(first) + F.greatest(F.ceil((F.lit(goal.kmin) - first + 1) / F.col("width")), F.lit(1)) * F.col("width") - 1
    pick = F.row_number().over(Window.partitionBy("qid").orderBy("place"))
    return r.where(F.col("place") <= F.least(need, F.lit(goal.kmax))).select("qid", pick.alias("pick"), "cid", "id", "s", "vdist")


def cluster_walk(model: ClusterModel, queries: DataFrame, goal: Goal, *, cluster_share: float = 0.5, k: int = 5, route: str = "direct", **options) -> DataFrame:
    qv = model.vectorizer(queries.withColumn("s", F.col("q"))).select("qid", "q", "vec").persist()
    starts = classify(qv, model.sample, k)
    edges = shortest_paths(model.edges) if route == "shortest_path" else model.edges
    skips = options.get("eps") is not None or options.get("on_drop") == "revert"
    rows = frontier(model.members, starts, reachable(edges, model.clusters, cluster_share), qv, None if skips else goal.kmax)
    return walk(rows, goal, **options)
