"""The experiment workloads: build times, index against scan, five methods by data size, sweeps over four corpora.

Queries with seconds in them return what was measured in the session as it is; their other columns are the same on every run.
``WORKLOADS`` are those that take minutes even on small tables; ``bench.py --workloads`` runs them, the others are queries."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .functions.strings import numbered_grams
from .operators import align, baselines, clusters, gram_index, measures, rank
from .operators.relax import final_threshold, range_scan, relax, take
from .plans.goal import Goal
from .queries import EPS_GRID, K_GRID, SMALL, USUAL, line_setting, name_queries, query, scratch
from .sources import corpora as src

FOUR = ("titles", "turns", "lines", "chains")
LAMBDAS = tuple(i / 10 for i in range(11))
SHARES = (20, 40, 60, 80, 100)
SEARCH_GRID = (2, 5, 10, 20, 30, 40)
WORKLOADS: dict = {}


def workload(f):
    WORKLOADS[f.__name__] = f
    return f


def seconds(df: DataFrame) -> float:
    began = time.time()
    df.write.format("noop").mode("overwrite").save()
    return time.time() - began


def rows_of(spark, rows, schema):
    return spark.createDataFrame(rows, schema)


def held(spark, sf_dir, name, n: int = 5):
    c = src.CORPORA[name](spark, sf_dir).persist()
    return c, src.own_queries(c, n).persist()


# build times -----------------------------------------------------------------------------------------------


@workload
def index_build_times(spark, sf_dir):
    """Seconds to build and store the gram index of each corpus, its strings and postings."""
    out = []
    for name in FOUR:
        c = src.CORPORA[name](spark, sf_dir).persist()
        n, began = c.count(), time.time()
        built = gram_index.GramIndex.build(c, scratch(spark))
        took = time.time() - began
        out.append((name, n, built.lists.count(), took))
        c.unpersist()
    return rows_of(spark, out, "corpus string, strings long, postings long, seconds double")


@query
def index_sizes(spark, sf_dir):
    """Strings, postings and different grams of each corpus but the longest strings'."""
    out = None
    for name in ("titles", "turns", "lines"):
        p = gram_index.postings(src.CORPORA[name](spark, sf_dir)).agg(F.countDistinct("id").alias("strings"), F.count(F.lit(1)).alias("postings"), F.countDistinct("gram").alias("grams"))
        p = p.select(F.lit(name).alias("corpus"), "strings", "postings", "grams")
        out = p if out is None else out.union(p)
    return out


@workload
def vector_cluster_times(spark, sf_dir):
    """Seconds to vectorise (three ways) and to cluster each corpus, apart."""
    out = []
    for name in FOUR:
        c = src.CORPORA[name](spark, sf_dir).persist()
        n = c.count()
        for how in ("hashed_grams", "word2vec", "tfidf"):
            began = time.time()
            v = clusters.fit_vectorizer(c, how, dims=32)(c).select("id", "s", "len", "vec").persist()
            v.count()
            vectorised, began = time.time() - began, time.time()
            found = clusters.partition(v, 8).select("cid").distinct().count()
            out.append((name, how, n, vectorised, time.time() - began, found))
            v.unpersist()
        c.unpersist()
    return rows_of(spark, out, "corpus string, vectors string, strings long, vector_seconds double, cluster_seconds double, clusters int")


# index against scan ----------------------------------------------------------------------------------------


@query
def index_against_scan(spark, sf_dir):
    """Seconds of a range search by scan and by the stored index for each limit, the build, and both ratios."""
    c, q = line_setting(spark, sf_dir)
    c.count(), q.count()
    began = time.time()
    index = gram_index.GramIndex.build(c, scratch(spark))
    build, out = time.time() - began, []
    for eps in SEARCH_GRID:
        scan, by_index = seconds(range_scan(c, q, eps - 1)), seconds(index.range_search(q, eps))
        out.append((eps, index.explain_engine(q, eps).where("engine = 'scan'").count(), scan, by_index, build, by_index / scan, (by_index + build) / scan))
    return rows_of(spark, out, "eps int, scanned_queries long, scan_seconds double, index_seconds double, build_seconds double, ratio double, ratio_with_build double")


@query
def search_counters(spark, sf_dir):
    """What a search costs in counts: per query and limit the strings inside the length band, the postings read, the
    candidates that pass the count bound, and the results."""
    c, q = line_setting(spark, sf_dir)
    lists = gram_index.postings(c).persist()
    asked = numbered_grams(q.select("qid", "q", F.length("q").alias("qlen")), ["qid", "qlen"], "q")
    dists = range_scan(c, q).join(q.select("qid", F.length("q").alias("qlen")), "qid").withColumn("gap", F.abs(F.col("len") - F.col("qlen"))).persist()
    met = lists.join(F.broadcast(asked), ["gram", "occ"]).groupBy("qid", "id", "qlen", "len").agg(F.count(F.lit(1)).alias("common")).withColumn("gap", F.abs(F.col("len") - F.col("qlen"))).persist()
    count = lambda test: F.sum(F.when(test, 1).otherwise(0)).cast("long")
    out = None
    for eps in SEARCH_GRID:
        band = F.col("gap") < eps
        a = dists.groupBy("qid").agg(count(band).alias("verified_by_scan"), count(F.col("dist") < eps).alias("results"))
        b = met.groupBy("qid").agg(F.sum(F.when(band, F.col("common")).otherwise(0)).cast("long").alias("postings_read"), count(band & (F.col("common") >= F.col("qlen") + 1 - 2 * (eps - 1))).alias("verified_by_index"))
        row = a.join(b, "qid").select("qid", F.lit(eps).alias("eps"), "verified_by_scan", "postings_read", "verified_by_index", "results")
        out = row if out is None else out.union(row)
    return out


@query
def index_recall(spark, sf_dir):
    """Results by the index beside those of a scan, for each limit."""
    c, q = line_setting(spark, sf_dir)
    index, dists = gram_index.GramIndex(c, gram_index.postings(c).persist()), range_scan(c, q).persist()
    out = None
    for eps in SEARCH_GRID:
        found = index.range_search(q, eps).join(dists.select("qid", "id", F.col("dist").alias("true")), ["qid", "id"])
        row = found.agg(F.sum((F.col("dist") == F.col("true")).cast("long")).alias("found")).join(dists.where(F.col("dist") < eps).agg(F.count(F.lit(1)).alias("truth"))).select(F.lit(eps).alias("eps"), "found", "truth")
        out = row if out is None else out.union(row)
    return out


# five methods ----------------------------------------------------------------------------------------------


def five(c, q, model, goal: Goal, eps: int) -> dict:
    return {
        "relax_rank": lambda: rank.relax_rank(c, q, goal, eps_start=eps),
        "relax_align": lambda: align.relax_align(c, q, goal, eps_start=eps),
        "cluster_walk": lambda: clusters.cluster_walk(model, q, goal),
        "swap": lambda: baselines.swap_baseline(c, q, k=goal.kmin, lam=goal.lam, eps=eps),
        "multipass_greedy": lambda: baselines.multipass_greedy(c, q, k=goal.kmin, lam=goal.lam, eps=eps),
    }


@workload
def runtime_by_size(spark, sf_dir):
    """Seconds of the five methods on a fifth to all of the lines; the clusters are built beforehand and timed apart."""
    every, out = src.lines(spark, sf_dir).persist(), []
    for share in SHARES:
        c = every.where(F.pmod(F.crc32(F.col("s").cast("binary")), F.lit(100)) < share).persist()
        n, q = c.count(), src.own_queries(c).persist()
        began = time.time()
        model = clusters.ClusterModel.build(c, scratch(spark), m=8, how="hashed_grams", dims=32)
        model.sample.count()
        out.append(("cluster_build", share, n, time.time() - began))
        out += [(name, share, n, seconds(method())) for name, method in five(c, q, model, USUAL, 40).items()]
        c.unpersist()
    return rows_of(spark, out, "method string, percent int, strings long, seconds double")


def many(dists: DataFrame, grid, column: str) -> DataFrame:
    """dists once per value of a grid: a query at a value becomes a query of its own (qid * 1000 + place of the value), so
    that all values go through a method together."""
    places = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(v).alias("v")) for i, v in enumerate(grid)])).alias("x")
    return dists.select("*", places).withColumn("qid", (F.col("qid") * 1000 + F.col("x.i")).cast("int")).withColumn(column, F.col("x.v")).drop("x")


def summary(name: str, results: DataFrame, lam: float, grid, goal: Goal, asked: int) -> DataFrame:
    """Mean and spread over the queries of score, distance, spread and count, per value of the grid; queries without results
    count as 0 results out of range."""
    card = measures.score_card(results.select("qid", "id", "s", "dist"), lam, goal.kmin, goal.kmax)
    value = F.element_at(F.array(*[F.lit(float(v)) for v in grid]), F.pmod(F.col("qid"), F.lit(1000)) + 1)
    per = card.groupBy(value.alias("value")).agg(F.avg("balance_score").alias("score"), F.stddev_pop("balance_score").alias("score_deviation"), F.avg("mean_query_distance").alias("distance"), F.avg("mean_pair_distance").alias("spread"), (F.sum("result_count") / asked).alias("results"), F.stddev_pop("result_count").alias("count_deviation"), (asked - F.sum(F.col("in_range").cast("int"))).cast("long").alias("out_of_range"))
    return per.select(F.lit(name).alias("method"), "value", *[F.round(c, 6).alias(c) for c in ("score", "score_deviation", "distance", "spread", "results", "count_deviation")], "out_of_range")


def eps_sweep(spark, sf_dir, corpus: str, methods=("relax_rank", "relax_align", "cluster_walk", "swap", "multipass_greedy"), n: int = 5) -> DataFrame:
    """Score and number of results against the first limit. The walk doesn't use the limit: it is run once."""
    c, q = held(spark, sf_dir, corpus, n)
    dists = range_scan(c, q).persist()
    each = many(dists, EPS_GRID, "eps").persist()
    start = F.col("eps")
    limits = None
    for i, eps in enumerate(EPS_GRID):
        some = final_threshold(each.where(start == eps), USUAL, eps_start=eps)
        limits = some if limits is None else limits.union(some)
    cands = take(each, limits, USUAL, start, 1, False).persist()
    near = each.where(F.col("dist") < start).persist()
    made = {"relax_rank": lambda: rank.relax_rank(None, None, USUAL, candidates=cands), "relax_align": lambda: align.relax_align(None, None, USUAL, candidates=cands), "swap": lambda: baselines.swap_baseline(None, None, candidates=near), "multipass_greedy": lambda: baselines.multipass_greedy(None, None, candidates=near)}
    out = None
    for name in methods:
        if name == "cluster_walk":
            model = clusters.ClusterModel.build(c, scratch(spark), m=8, how="hashed_grams", dims=32)
            results = many(clusters.cluster_walk(model, q, USUAL), EPS_GRID, "eps")
        else:
            results = made[name]()
        rows = summary(name, results, USUAL.lam, EPS_GRID, USUAL, n)
        out = rows if out is None else out.union(rows)
    return out


def _eps_query(corpus):
    def run(spark, sf_dir):
        return eps_sweep(spark, sf_dir, corpus, n=2 if corpus == "chains" else 5)

    run.__name__ = f"eps_sweep_{corpus}"
    return workload(run)


for _corpus in FOUR:
    _eps_query(_corpus)


def _rank_over(dists, goals: list[Goal], eps_start: int):
    """relax-rank of the same distances under several goals."""
    return [rank.relax_rank(None, None, g, candidates=take(dists, final_threshold(dists, g, eps_start=eps_start), g, eps_start, 1, False)) for g in goals]


def _card_row(name, value, results, goal):
    card = measures.score_card(results.select("qid", "id", "s", "dist"), goal.lam, goal.kmin, goal.kmax)
    return card.agg(*[F.round(F.avg(c), 6).alias(c) for c in ("balance_score", "mean_query_distance", "mean_pair_distance", "result_count")]).select(F.lit(name).alias("method"), F.lit(float(value)).alias("value"), "balance_score", "mean_query_distance", "mean_pair_distance", "result_count")


def _union(rows):
    out = None
    for r in rows:
        out = r if out is None else out.union(r)
    return out


@workload
def lambda_sweep_chains(spark, sf_dir):
    """Score against the weight on the long random strings, for relax-rank, relax-align and the walk."""
    c, q = held(spark, sf_dir, "chains", 2)
    dists = range_scan(c, q).persist()
    model = clusters.ClusterModel.build(c, scratch(spark), m=8, how="hashed_grams", dims=32)
    rows = []
    for lam in LAMBDAS:
        g = Goal(25, 55, lam)
        cands = take(dists, final_threshold(dists, g, eps_start=30), g, 30, 1, False).persist()
        rows.append(_card_row("relax_rank", lam, rank.relax_rank(None, None, g, candidates=cands), g))
        rows.append(_card_row("cluster_walk", lam, clusters.cluster_walk(model, q, g), g))
        if round(lam * 10) % 2 == 0:  # alignments of such strings take long: every other weight
            rows.append(_card_row("relax_align", lam, align.relax_align(None, None, g, candidates=cands), g))
    return _union(rows)


@workload
def k_sweep_chains(spark, sf_dir):
    """Score, distance and spread against the mean number of results, on the long random strings."""
    c, q = held(spark, sf_dir, "chains", 2)
    dists = range_scan(c, q).persist()
    goals = [Goal(k, k + 30, 0.5) for k in K_GRID]
    return _union(_card_row("relax_rank", g.kmin + 15, r, g) for g, r in zip(goals, _rank_over(dists, goals, 30)))


# ablations and the rest ------------------------------------------------------------------------------------


@query
def cut_off_grid(spark, sf_dir):
    """relax-rank under shares of the sample and factors of the cut-off: how many strings are pruned and what is kept."""
    c, q = line_setting(spark, sf_dir)
    cands = relax(c, q, USUAL, eps_start=30, engine="histogram").persist()
    scored = rank.contribution(cands.select("qid", "id", "s", "dist")).persist()
    rows = []
    for share in (0.1, 0.25, 0.4, 1.0):
        for factor in (0.6, 0.75, 0.9):
            cut = rank.cut_off(scored, sample_share=share, cut_factor=factor)
            rows.append(scored.join(F.broadcast(cut), "qid").agg(F.sum((F.col("contrib") < F.col("cut")).cast("long")).alias("pruned"), F.count(F.lit(1)).alias("candidates")).select(F.lit(share).alias("sample_share"), F.lit(factor).alias("cut_factor"), "pruned", "candidates"))
    return _union(rows)


@workload
def cluster_share_grid(spark, sf_dir):
    """The walk under shares of the clusters that it may visit."""
    c, q = line_setting(spark, sf_dir)
    model = clusters.ClusterModel.build(c, scratch(spark), m=8, how="hashed_grams", dims=32)
    return _union(_card_row("cluster_walk", share, clusters.cluster_walk(model, q, USUAL, cluster_share=share), USUAL) for share in (0.125, 0.25, 0.5, 1.0))


@workload
def walk_revert(spark, sf_dir):
    """The walk that puts back a string which lowers the score."""
    c, q = line_setting(spark, sf_dir)
    model = clusters.ClusterModel.build(c, scratch(spark), m=8, how="hashed_grams", dims=32)
    return clusters.cluster_walk(model, q, SMALL, on_drop="revert").select("qid", "pick", "cid", "id", "dist", "move")


@query
def model_append(spark, sf_dir):
    """A tenth of the lines joins the clusters afterwards: members before and after, strings without a cluster."""
    c, _ = line_setting(spark, sf_dir)
    late = F.pmod(F.crc32(F.col("s").cast("binary")), F.lit(10)) == 0
    path = scratch(spark)
    model = clusters.ClusterModel.build(c.where(~late), path, m=8, how="hashed_grams", dims=32)
    before = model.members.count()
    after = model.append(c.where(late), path).members
    return after.agg(F.lit(before).cast("long").alias("before"), F.count(F.lit(1)).alias("after"), F.sum(F.col("cid").isNull().cast("long")).alias("without"))


@query
def cluster_purity(spark, sf_dir):
    """Documents clustered by gram vectors of their whole texts: per cluster the share of its commonest language."""
    d = src.table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "lang", src.fold(F.coalesce("text", F.lit(""))).alias("s")).where("id is not null")
    v = clusters.hashed_grams(src.spread(d)).select("lang", "vec", F.octet_length("s").alias("bytes")).persist()  # texts are not held
    n = clusters.partition(v, 8, size=F.col("bytes")).groupBy("cid", "lang").agg(F.count(F.lit(1)).alias("n"))
    return n.groupBy("cid").agg(F.sum("n").alias("documents"), F.round(F.max("n") / F.sum("n"), 4).alias("purity"))


@query
def token_words(spark, sf_dir):
    """Words of documents with stop words left out and endings cut: per language how many are left and how many differ."""
    d = src.table(spark, sf_dir, "documents").select("lang", src.fold(F.coalesce("text", F.lit(""))).alias("s"))
    words = lambda **o: F.size(clusters.tokenize(F.col("s"), n=None, **o))
    different = F.size(F.array_distinct(clusters.tokenize(F.col("s"), n=None, stem="suffix")))
    return d.groupBy("lang").agg(F.sum(words(stop=False)).alias("words"), F.sum(words()).alias("without_stop_words"), F.sum(different).alias("different_stems"))


@query
def feature_selection(spark, sf_dir):
    """Weighted gram vectors of titles: components, and those that vary enough to be kept."""
    c = src.titles(spark, sf_dir)
    v = clusters.fit_vectorizer(c, "tfidf", dims=64)(c).select("id", "vec").persist()
    kept = clusters.select_features(v, 0.05)
    return v.agg(F.max(F.size("vec")).alias("components")).join(kept.agg(F.max(F.size("vec")).alias("kept")))


@query
def method_choice(spark, sf_dir):
    """The method that the chooser names for each corpus: changing, fixed, and fixed with quality first."""
    rows = []
    for name in FOUR:
        n = src.CORPORA[name](spark, sf_dir).count()
        rows.append((name, n, *(baselines.choose_method(changing=a, strings=n, quality_first=b) for a, b in ((True, False), (False, False), (False, True)))))
    return rows_of(spark, rows, "corpus string, strings long, changing string, fixed string, quality string")


@query
def engine_choice(spark, sf_dir):
    """What the planner chooses for names, lines without and lines with an index."""
    from .operators.relax import plan_engine

    c, q = line_setting(spark, sf_dir)
    index = gram_index.GramIndex(c, gram_index.postings(c).persist())
    names = src.names(spark, sf_dir)
    rows = [("names", *plan_engine(names, name_queries(spark))), ("lines", *plan_engine(c, q, 30)), ("lines with index", *plan_engine(c, q, 5, index))]
    return rows_of(spark, rows, "setting string, engine string, why string")


@query
def read_back(spark, sf_dir):
    """A ranked answer written as CSV, JSON, text and Parquet by query, and read again: rows of each."""
    from .sources.corpora import read_strings, write_results

    got = rank.relax_rank(src.names(spark, sf_dir), name_queries(spark), SMALL, sample_share=1.0).select("qid", "s").persist()
    rows = []
    for kind in ("csv", "json", "parquet"):
        path = scratch(spark)
        write_results(got, path, kind=kind, partition_by="qid" if kind == "parquet" else None)
        rows.append((kind, read_strings(spark, path, kind=kind, column="_c1" if kind == "csv" else "s").count()))
    path = scratch(spark)
    write_results(got.select("s"), path, kind="text")
    rows.append(("text", read_strings(spark, path).count()))
    return rows_of(spark, rows, "kind string, strings long")


@query
def window_ranks(spark, sf_dir):
    """Ranks, quarters, medians and distinct counts of distances."""
    c, q = line_setting(spark, sf_dir)
    d = range_scan(c, q, 59)
    w = Window.partitionBy("qid").orderBy("dist")
    ranked = d.select("qid", "dist", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dense"), F.ntile(4).over(w.orderBy("dist", "id")).alias("quarter"))
    return ranked.groupBy("qid", "quarter").agg(F.max("r").alias("last_rank"), F.max("dense").alias("last_dense"), F.percentile("dist", F.lit(0.5)).alias("median"), F.countDistinct("dist").alias("distances"))
