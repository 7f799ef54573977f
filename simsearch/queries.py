"""Every method, variant, baseline, measure and workload as a query (spark, sf_dir) -> DataFrame, by name."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import sqlapi
from .functions import strings as fs
from .operators import align, baselines, clusters, gram_index, measures, rank
from .operators.relax import cap, final_threshold, nearest, range_scan, relax, relax_if_empty, take
from .plans.goal import Goal, GoalGrid
from .sources import corpora as src
from .streaming import upkeep

SMALL, USUAL = Goal(5, 8, 0.5), Goal(25, 55, 0.5)
EPS_GRID = (5, 10, 20, 30, 40, 60, 80)
K_GRID = tuple(range(5, 70, 10))
QUERIES: dict = {}


def query(f):
    QUERIES[f.__name__] = f
    return f


def scratch(spark: SparkSession) -> str:
    """A folder for built indexes: in the shared folder of the cluster, a temporary one only in local runs."""
    shared = spark.conf.get("spark.checkpoint.dir", None)
    if shared:
        import uuid

        return f"{shared}/simsearch-{uuid.uuid4().hex}"
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    return f"file://{tempfile.mkdtemp(prefix='simsearch-')}"


def ring(spark) -> DataFrame:
    return src.literal_queries(spark, ["small ring"])


def name_queries(spark) -> DataFrame:
    return src.literal_queries(spark, ["small ring", "cold bolt", "smal wigdet"])


def rounded(df: DataFrame, *cols: str, places: int = 6) -> DataFrame:
    return df.withColumns({c: F.round(c, places) for c in cols})


def line_setting(spark, sf_dir):
    c = src.lines(spark, sf_dir).persist()
    return c, src.own_queries(c).persist()


# corpora ---------------------------------------------------------------------------------------------------


def _corpus(name):
    def run(spark, sf_dir):
        return src.CORPORA[name](spark, sf_dir)

    run.__name__ = f"corpus_{name}"
    return query(run)


for _name in src.CORPORA:
    _corpus(_name)


@query
def corpus_stats(spark, sf_dir):
    out = None
    for name in ("names", "urls", "titles", "lines"):
        row = src.CORPORA[name](spark, sf_dir).agg(F.count(F.lit(1)).alias("n"), F.min("len").alias("shortest"), F.max("len").alias("longest"), F.round(F.avg("len"), 6).alias("mean")).select(F.lit(name).alias("corpus"), "n", "shortest", "longest", "mean")
        out = row if out is None else out.union(row)
    return out


@query
def queries_typo(spark, sf_dir):
    return src.typo_queries(src.names(spark, sf_dir))


# distances, grams, index -----------------------------------------------------------------------------------


@query
def edit_distance_scan(spark, sf_dir):
    return range_scan(src.names(spark, sf_dir), name_queries(spark)).select("qid", "id", "dist")


@query
def bounded_scan(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    return range_scan(c, q, 39).select("qid", "id", "dist")


@query
def length_band_scan(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    return c.join(F.broadcast(q), F.abs(F.col("len") - F.length("q")) < 10).groupBy("qid").agg(F.count(F.lit(1)).alias("n"))


@query
def hamming_cells(spark, sf_dir):
    """Every client whose id is divisible by 100 against all of the same length."""
    c = src.clients(spark, sf_dir)
    words = [f"w{n}" for n in range(fs.PACKED // 7)]
    met = (F.col("i") != F.col("j")) & (F.col("l") == F.col("len"))

    def pairs(some, cells, d):
        """Pairs of equal length: the few asked strings to all nodes, the others dealt out, as some MB make very many pairs."""
        a = some.where("id % 100 = 0").select(F.col("id").alias("i"), F.col("len").alias("l"), *[F.col(x).alias(f"{x}_i") for x in cells])
        b = some.select(F.col("id").alias("j"), "len", *cells).repartition(8 * spark.sparkContext.defaultParallelism, "j")
        return b.join(F.broadcast(a), met).select("i", "j", d.alias("d"))

    # clients are folded to ASCII; longer strings go character by character, apart, as that is not compiled
    short = c.where(F.col("len") <= fs.PACKED).select("id", "len", *fs.packed(F.col("s")))
    fast = pairs(short, words, fs.packed_hamming([F.col(f"{w}_i") for w in words], [F.col(w) for w in words]))
    return fast.union(pairs(c.where(F.col("len") > fs.PACKED), ["s"], fs.hamming(F.col("s_i"), F.col("s"))))


@query
def metrics_other(spark, sf_dir):
    c = src.names(spark, sf_dir).join(F.broadcast(ring(spark)))
    return rounded(c.select("id", fs.normalised_edit(F.col("s"), F.col("q")).alias("norm_edit"), fs.gram_jaccard_distance(F.col("s"), F.col("q")).alias("jaccard_gram")), "norm_edit", "jaccard_gram")


@query
def grams_padded(spark, sf_dir):
    return fs.numbered_grams(src.names(spark, sf_dir), ["id"], "s").select("id", F.translate("gram", "\x02\x03", "^$").alias("gram"), "occ")


@query
def grams_unpadded(spark, sf_dir):
    return fs.numbered_grams(src.names(spark, sf_dir), ["id"], "s", pad=False)


@query
def postings(spark, sf_dir):
    p = gram_index.postings(src.lines(spark, sf_dir))
    return p.groupBy("gram", "occ").agg(F.count(F.lit(1)).alias("n"), F.sum("len").alias("chars")).select(F.translate("gram", "\x02\x03", "^$").alias("gram"), "occ", "n", "chars")


@query
def posting_lengths(spark, sf_dir):
    p = gram_index.postings(src.titles(spark, sf_dir)).groupBy("gram").agg(F.countDistinct("id").alias("strings"))
    return p.groupBy("strings").agg(F.count(F.lit(1)).alias("grams"))


@query
def gram_probe(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    return gram_index.probe(gram_index.postings(c), q, 20)


@query
def gram_probe_set(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    return gram_index.probe(gram_index.postings(c), q, 10, mode="set")


@query
def index_range_search(spark, sf_dir):
    """Built and stored index; limit 40 makes the bound empty for short queries, which are scanned."""
    c, q = line_setting(spark, sf_dir)
    return gram_index.GramIndex.build(c, scratch(spark)).range_search(q, 40).select("qid", "id", "dist")


@query
def index_engine(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    return gram_index.GramIndex(c, gram_index.postings(c)).explain_engine(q, 40)


@query
def edit_selfjoin(spark, sf_dir):
    return gram_index.similarity_self_join(src.urls(spark, sf_dir), 6)


# relaxation ------------------------------------------------------------------------------------------------


def _relaxed(df):
    return df.select("qid", "id", "dist", "round", "eps_final", "exhausted")


@query
def relax_names(spark, sf_dir):
    return _relaxed(relax(src.names(spark, sf_dir), ring(spark), SMALL))


@query
def relax_batch(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    return _relaxed(relax(c, q, USUAL, eps_start=30, engine="histogram"))


@query
def relax_auto(spark, sf_dir):
    """Engine by the planner's rule."""
    c, q = line_setting(spark, sf_dir)
    return _relaxed(relax(c, q, USUAL, eps_start=30))


@query
def relax_max_rounds(spark, sf_dir):
    return _relaxed(relax(src.names(spark, sf_dir), name_queries(spark), SMALL, max_rounds=4))


@query
def relax_gallop(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    return _relaxed(relax(c, q, USUAL, eps_start=30, engine="gallop"))


@query
def relax_index(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    return _relaxed(relax(c, q, USUAL, eps_start=5, engine="index", index=gram_index.GramIndex(c, gram_index.postings(c).persist())))


@query
def relax_rounds(spark, sf_dir):
    return _relaxed(relax(src.names(spark, sf_dir), name_queries(spark), SMALL, engine="rounds"))


@query
def relax_arrival(spark, sf_dir):
    return _relaxed(relax(src.names(spark, sf_dir), name_queries(spark), SMALL, eps_start=4, step=3, tie_order="arrival"))


@query
def relax_inclusive(spark, sf_dir):
    return _relaxed(relax(src.names(spark, sf_dir), name_queries(spark), SMALL, inclusive=True))


@query
def relax_step(spark, sf_dir):
    return _relaxed(relax(src.names(spark, sf_dir), name_queries(spark), SMALL, eps_start=2, step=4))


@query
def relax_exhausted(spark, sf_dir):
    return _relaxed(relax(src.names(spark, sf_dir), ring(spark), Goal(60, 100, 0.5)))


@query
def relax_if_empty_names(spark, sf_dir):
    return relax_if_empty(src.names(spark, sf_dir), name_queries(spark), 1).select("qid", "id", "dist", "eps_final")


@query
def nearest_k(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    return nearest(c, q, 25).select("qid", "id", "dist", "rank")


@query
def relax_chains(spark, sf_dir):
    """Long random strings, all of them: the nearest others are some 210 edits away."""
    c = src.chains(spark, sf_dir).persist()
    return _relaxed(relax(c, src.own_queries(c, 1).persist(), USUAL, eps_start=30, engine="gallop"))


# ranking ---------------------------------------------------------------------------------------------------


def _small_cands(spark, sf_dir):
    return relax(src.names(spark, sf_dir), name_queries(spark), SMALL)


@query
def pair_distances(spark, sf_dir):
    return measures.pair_distances(_small_cands(spark, sf_dir))


@query
def contribution(spark, sf_dir):
    return rank.contribution(_small_cands(spark, sf_dir)).select("qid", "id", "contrib")


@query
def cut_off_sampled(spark, sf_dir):
    return rounded(rank.cut_off(rank.contribution(_small_cands(spark, sf_dir))), "cut")


@query
def cut_off_exact(spark, sf_dir):
    return rounded(rank.cut_off(rank.contribution(_small_cands(spark, sf_dir)), sample_share=1.0), "cut")


def _ranked(df):
    return df.select("qid", "id", "dist", "contrib", "rank", "pruned")


@query
def relax_rank(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    return _ranked(rank.relax_rank(c, q, USUAL, eps_start=30))


@query
def relax_rank_names(spark, sf_dir):
    return _ranked(rank.relax_rank(src.names(spark, sf_dir), name_queries(spark), SMALL, sample_share=1.0))


@query
def relax_rank_noprune(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    return _ranked(rank.relax_rank(c, q, USUAL, eps_start=30, sample_share=None))


@query
def relax_rank_literal(spark, sf_dir):
    """Pruned strings stay out even if too few are left."""
    return _ranked(rank.relax_rank(src.names(spark, sf_dir), name_queries(spark), SMALL, sample_share=1.0, cut_factor=0.99, backfill=False))


@query
def relax_rank_after(spark, sf_dir):
    return _ranked(rank.relax_rank(src.names(spark, sf_dir), name_queries(spark), SMALL, sample_share=1.0, cut_factor=0.95, quota_base="after"))


@query
def relax_rank_exact_kept(spark, sf_dir):
    return _ranked(rank.relax_rank(src.names(spark, sf_dir), name_queries(spark), SMALL, sample_share=1.0, keep_exact=True))


@query
def relax_medoid(spark, sf_dir):
    return rank.relax_medoid(src.names(spark, sf_dir), name_queries(spark), SMALL).select("qid", "id", "dist", "to_centre", "rank")


# measures and sweeps ---------------------------------------------------------------------------------------


@query
def measures_relax_rank(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    card = measures.score_card(rank.relax_rank(c, q, USUAL, eps_start=30), 0.5, 25, 55, q)
    return rounded(card, "mean_query_distance", "mean_pair_distance", "balance_score")


@query
def score_identity(spark, sf_dir):
    """lam (spread + distance) - distance, the other way to write the balance."""
    c, q = line_setting(spark, sf_dir)
    b = measures.balance_score(nearest(c, q, 25), 0.3)
    other = F.lit(0.3) * (F.col("mean_pair_distance") + F.col("mean_query_distance")) - F.col("mean_query_distance")
    return b.select("qid", (F.abs(other - F.col("balance_score")) < 1e-9).alias("same"))


def _means():
    of = {"score": "balance_score", "distance": "mean_query_distance", "spread": "mean_pair_distance", "results": "result_count"}
    return [*[F.round(F.avg(c), 6).alias(name) for name, c in of.items()], F.sum((~F.col("in_range")).cast("int")).cast("long").alias("out_of_range")]


def _sweep_rows(parts):
    out = None
    for label, value, df in parts:
        row = df.agg(*_means()).select(F.lit(label).alias("method"), F.lit(float(value)).alias("value"), "score", "distance", "spread", "results", "out_of_range")
        out = row if out is None else out.union(row)
    return out


def _nearest_known(dists, goals):
    """The first candidates by (distance, id) of the goal that keeps most, which hold those of every goal, and their pair
    distances: the corpus is read once, and no distance is worked out twice."""
    near = cap(dists, max(goals, key=lambda g: g.most), ["dist", "id"]).persist()
    return near, measures.pair_distances(near).persist()


def _rank_of(dists, goal, eps_start, known=None, **options):
    """relax-rank from distances that are there already."""
    cands = take(dists, final_threshold(dists, goal, eps_start=eps_start), goal, eps_start, 1, False)
    return rank.relax_rank(None, None, goal, candidates=cands, known=known, **options)


def _rank_sweep(dists, goals, values, eps_start):
    """Means over the queries of relax-rank's measures under several goals, all goals in one plan."""
    near, known = _nearest_known(dists, goals)
    grid = GoalGrid(goals)
    near, known = grid.over(near), grid.over(known)
    card = measures.score_card(_rank_of(near, grid, eps_start, known), grid.lam, grid.kmin, grid.kmax, known=known)
    value = grid.pick([float(v) for v in values]).alias("value")
    return card.groupBy(value).agg(*_means()).select(F.lit("relax_rank").alias("method"), "value", "score", "distance", "spread", "results", "out_of_range")


@query
def lambda_sweep(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    goals = [Goal(25, 55, lam) for lam in (0.0, 0.2, 0.4, 0.6, 0.8, 1.0)]
    return _rank_sweep(range_scan(c, q), goals, [g.lam for g in goals], 30)


@query
def k_sweep(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    goals = [Goal(k, k + 30, 0.5) for k in K_GRID]
    return _rank_sweep(range_scan(c, q), goals, [g.kmin + 15 for g in goals], 30)


@query
def eps_sweep_counts(spark, sf_dir):
    """Results against the first limit: a plain range search against relax-rank."""
    c, q = line_setting(spark, sf_dir)
    dists = range_scan(c, q).persist()
    near, known = _nearest_known(dists, [USUAL])
    out = None
    for eps in EPS_GRID:
        plain = dists.where(F.col("dist") < eps).groupBy("qid").agg(F.least(F.count(F.lit(1)), F.lit(25)).alias("n")).select(F.lit("range_k").alias("method"), "qid", "n")
        ours = _rank_of(near, USUAL, eps, known).groupBy("qid").agg(F.count(F.lit(1)).alias("n")).select(F.lit("relax_rank").alias("method"), "qid", "n")
        rows = q.select("qid").crossJoin(F.broadcast(spark.createDataFrame([("range_k",), ("relax_rank",)], "method string"))).join(plain.union(ours), ["method", "qid"], "left").select(F.lit(eps).alias("eps"), "method", "qid", F.coalesce("n", F.lit(0)).cast("long").alias("n"))
        out = rows if out is None else out.union(rows)
    return out


def _method_card(c, q):
    ours = rank.relax_rank(c, q, USUAL, eps_start=30).select("qid", "id", "s", "dist").withColumn("method", F.lit("relax_rank"))
    return ours.union(nearest(c, q, 25).select("qid", "id", "s", "dist").withColumn("method", F.lit("nearest")))


@query
def measures_cube(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    rows = _method_card(c, q)
    return rows.cube("method", "qid").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("dist"), 6).alias("distance"), F.round(F.stddev_pop("dist"), 6).alias("stability"))


@query
def rollup_measures(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    return _method_card(c, q).rollup("method", "qid").agg(F.min("dist").alias("lowest"), F.max("dist").alias("highest"), F.countDistinct("id").alias("ids"))


@query
def overlap_methods(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    a, b = rank.relax_rank(c, q, USUAL, eps_start=30).select("qid", "id"), nearest(c, q, 25).select("qid", "id")
    both, only = a.intersect(b).withColumn("part", F.lit("both")), a.exceptAll(b).withColumn("part", F.lit("relax_rank"))
    return both.union(only).union(b.exceptAll(a).withColumn("part", F.lit("nearest"))).groupBy("qid", "part").agg(F.count(F.lit(1)).alias("n"))


@query
def suggest_lambda(spark, sf_dir):
    c, q = src.names(spark, sf_dir), name_queries(spark)
    near, known = _nearest_known(range_scan(c, q), [Goal(5, 8, 1.0)])
    return rounded(measures.suggest_lambda(c, q, lambda a, b, g: _rank_of(near, g, 1, known, sample_share=None), lambda lam: Goal(5, 8, lam), (0.0, 0.25, 0.5, 0.75, 1.0), 6.0, known), "spread", "distance")


# alignment -------------------------------------------------------------------------------------------------

def _aligned(spark, sf_dir):
    """Client names as aligned rows, ten neighbouring keys a group, their zeros as gaps."""
    key = F.col("c_custkey")
    return src.table(spark, sf_dir, "customer").select(F.floor(key / 10).cast("long").alias("qid"), key.cast("long").alias("id"), F.translate("c_name", "0", "-").alias("aligned"))


@query
def sum_of_pairs(spark, sf_dir):
    return align.sum_of_pairs_sql(_aligned(spark, sf_dir))


@query
def motif_fixed(spark, sf_dir):
    return align.motif_sql(_aligned(spark, sf_dir))


@query
def motif_nogap(spark, sf_dir):
    return align.motif_sql(_aligned(spark, sf_dir), gap_votes=False)


@query
def udaf_motif(spark, sf_dir):
    return _aligned(spark, sf_dir).groupBy("qid").agg(sqlapi.motif_of("aligned").alias("motif")).where("motif <> ''")


@query
def guide_tree(spark, sf_dir):
    return align.guide_tree(_small_cands(spark, sf_dir))


@query
def guide_tree_upgma(spark, sf_dir):
    return align.guide_tree(_small_cands(spark, sf_dir), "upgma")


@query
def substitution_matrix(spark, sf_dir):
    return align.substitution_matrix(_small_cands(spark, sf_dir))


@query
def relax_align(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    return align.relax_align(c, q, USUAL, eps_start=30).select("qid", "id", "dist", "motif_dist", "rank")


@query
def relax_align_names(spark, sf_dir):
    return align.relax_align(src.names(spark, sf_dir), name_queries(spark), SMALL).select("qid", "id", "dist", "motif_dist", "rank")


@query
def relax_align_multi(spark, sf_dir):
    return align.relax_align(src.names(spark, sf_dir), name_queries(spark), SMALL, profiles="auto").select("qid", "id", "dist", "motif_dist", "rank")


# vectors, clusters, walk -----------------------------------------------------------------------------------


@query
def token_segments(spark, sf_dir):
    d = src.table(spark, sf_dir, "documents").select("doc_id", src.fold(F.col("text")).alias("s"))
    return d.select("doc_id", F.size(clusters.tokenize(F.col("s"), stop=False, n=None)).alias("words"))


@query
def hashed_vectors(spark, sf_dir):
    v = clusters.hashed_grams(src.names(spark, sf_dir), dims=16)
    return v.select("id", F.posexplode("vec").alias("i", "x")).where("x > 0").select("id", F.col("i").alias("component"), F.round("x", 6).alias("x"))


def _embedded(spark, sf_dir):
    e = src.table(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"), F.col("label").alias("cid"))


@query
def knn_embeddings(spark, sf_dir):
    e = _embedded(spark, sf_dir)
    q = e.where("id % 100 = 0").select(F.col("id").alias("qid"), F.col("vec").alias("qv"))
    d = e.join(F.broadcast(q), F.col("id") != F.col("qid")).select("qid", "id", fs.euclid(F.col("qv"), F.col("vec")).alias("d"))
    w = Window.partitionBy("qid").orderBy("d", "id")
    return d.withColumn("rank", F.row_number().over(w)).where("rank <= 5").select("qid", "id", "rank")


@query
def centre_graph(spark, sf_dir):
    return rounded(clusters.cluster_graph(clusters.centres(_embedded(spark, sf_dir), "mean")), "w", places=4)


@query
def centre_median(spark, sf_dir):
    c = clusters.centres(_embedded(spark, sf_dir))
    return c.select("cid", F.posexplode("centre").alias("component", "x")).select("cid", "component", F.round("x", 5).alias("x"))


@query
def reachable(spark, sf_dir):
    return clusters.reachable(clusters.cluster_graph(clusters.centres(_embedded(spark, sf_dir), "mean")), 10)


@query
def training_sample(spark, sf_dir):
    return clusters.training_sample(_embedded(spark, sf_dir)).select("cid", "id")


@query
def knn_classes(spark, sf_dir):
    e = _embedded(spark, sf_dir)
    return clusters.classify(e.where("id % 100 = 0").select(F.col("id").alias("qid"), "vec"), clusters.training_sample(e))


@query
def knn_accuracy(spark, sf_dir):
    """Language of every hundredth document from a sampled twentieth of all, by hashed gram vectors of whole texts: per language
    how many were asked and how many were right."""
    d = src.table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "lang", src.fold(F.coalesce("text", F.lit(""))).alias("s")).where("id is not null")
    langs = d.select(F.coalesce("lang", F.lit("")).alias("l")).distinct().select("l", F.dense_rank().over(Window.partitionBy(F.lit(0)).orderBy("l")).alias("cid"))
    v = clusters.hashed_grams(src.spread(d)).drop("s").join(F.broadcast(langs), F.coalesce("lang", F.lit("")) == F.col("l")).drop("l").persist()
    got = clusters.classify(v.select(F.col("id").alias("qid"), "vec").where("qid % 100 = 0"), clusters.training_sample(v, 0.05), 5)
    truth = v.select(F.col("id").alias("qid"), "lang", F.col("cid").alias("true_cid"))
    return got.join(truth, "qid").groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("cid") == F.col("true_cid")).cast("long")).alias("right"))


def _word_clusters(spark, sf_dir):
    """Names clustered by their second word, in order of the word's distance from 'ring'."""
    c = src.names(spark, sf_dir).withColumn("w", F.regexp_extract("s", r"^\S+ (.*)$", 1))
    order = F.dense_rank().over(Window.partitionBy(F.lit(0)).orderBy(F.levenshtein("w", F.lit("ring")), "w")) - 1
    return c.withColumn("hop", order).select(F.lit(1).alias("qid"), F.lit("small ring").alias("q"), F.col("hop").alias("cid"), "hop", "id", "s", F.levenshtein("s", F.lit("small ring")).cast("double").alias("vdist")).where("hop < 4")  # the nearest clusters, as a walk keeps them


@query
def word_walk(spark, sf_dir):
    return rounded(clusters.walk(_word_clusters(spark, sf_dir), SMALL), "score").drop("s")


@query
def quota_walk(spark, sf_dir):
    return clusters.quota_walk(_word_clusters(spark, sf_dir), SMALL).select("qid", "pick", "cid", "id")


@query
def word_walk_quota_only(spark, sf_dir):
    return rounded(clusters.walk(_word_clusters(spark, sf_dir), Goal(10, 16, 0.2), drop_rule=False), "score").drop("s")


def _model(spark, c, **options):
    return clusters.ClusterModel.build(c, scratch(spark), m=8, **options)


@query
def cluster_walk(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    return clusters.cluster_walk(_model(spark, c, how="hashed_grams", dims=32), q, USUAL).select("qid", "pick", "cid", "id", "dist", F.round("score", 6).alias("score"), "move")


@query
def word2vec_clusters(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    return clusters.cluster_walk(_model(spark, c, how="word2vec", dims=16), q, USUAL, route="shortest_path").groupBy("qid").agg(F.count(F.lit(1)).alias("n"))


@query
def cluster_sizes(spark, sf_dir):
    c, _ = line_setting(spark, sf_dir)
    return _model(spark, c, how="hashed_grams", dims=32).members.groupBy("cid").agg(F.count(F.lit(1)).alias("n"), F.sum(F.octet_length("s")).alias("bytes"))


# baselines -------------------------------------------------------------------------------------------------


@query
def swap_baseline(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    return baselines.swap_baseline(c, q, eps=50).select("qid", "id", "dist", "rank")


@query
def multipass_greedy(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    return baselines.multipass_greedy(c, q, eps=50).select("qid", "id", "dist", "rank")


@query
def exact_best(spark, sf_dir):
    best = baselines.exact_best(relax(src.names(spark, sf_dir), ring(spark), SMALL), SMALL)
    return rounded(measures.balance_score(best, 0.5), "mean_query_distance", "mean_pair_distance", "balance_score").select("qid", "balance_score")


@query
def optimality_ratio(spark, sf_dir):
    cands = _small_cands(spark, sf_dir).persist()
    best = measures.balance_score(baselines.exact_best(cands, SMALL), 0.5).select("qid", F.col("balance_score").alias("best"))
    ours = measures.balance_score(rank.relax_rank(None, None, SMALL, candidates=cands), 0.5)
    return ours.join(best, "qid").select("qid", (F.col("balance_score") <= F.col("best") + 1e-9).alias("bounded"), F.round(F.col("best") - F.col("balance_score"), 6).alias("loss"))


@query
def random_subset(spark, sf_dir):
    return baselines.random_subset(_small_cands(spark, sf_dir), 5).select("qid", "id", "rank")


@query
def five_methods(spark, sf_dir):
    """Closeness, spread, balance and number of results of all five methods on lines, first limit 40."""
    c, q = line_setting(spark, sf_dir)
    model = _model(spark, c, how="hashed_grams", dims=32)
    # two methods start from the same candidates, and both baselines from the same strings under the limit
    cands = relax(c, q, USUAL, eps_start=40).persist()
    within = baselines.all_within(c, q, 40).persist()
    by = {"relax_rank": rank.relax_rank(c, q, USUAL, candidates=cands), "relax_align": align.relax_align(c, q, USUAL, candidates=cands), "cluster_walk": clusters.cluster_walk(model, q, USUAL), "swap": baselines.swap_baseline(c, q, candidates=within), "multipass_greedy": baselines.multipass_greedy(c, q, candidates=within)}
    return _sweep_rows((name, 40, measures.score_card(df.select("qid", "id", "s", "dist"), 0.5, 25, 55)) for name, df in by.items())


# around the methods ----------------------------------------------------------------------------------------


@query
def join_labels(spark, sf_dir):
    d, lab = src.table(spark, sf_dir, "documents").select("doc_id", "lang"), src.table(spark, sf_dir, "labels").where("quality = 1").select("doc_id")
    return d.join(lab, "doc_id").groupBy("lang").agg(F.count(F.lit(1)).alias("n"))


@query
def join_sales(spark, sf_dir):
    """Catalogue browsing: quantity sold of the varied answer to 'small ring'."""
    got = rank.relax_rank(src.names(spark, sf_dir), ring(spark), SMALL, sample_share=1.0).select("s")
    p, li = src.table(spark, sf_dir, "part").select("p_partkey", "p_name", "p_brand"), src.table(spark, sf_dir, "lineitem").select("l_partkey", "l_quantity")
    parts = p.join(F.broadcast(got), F.col("p_name") == F.col("s"), "left_semi")
    return li.join(parts, F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.count(F.lit(1)).alias("lines"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@query
def semi_taken(spark, sf_dir):
    c = src.names(spark, sf_dir)
    return c.join(_small_cands(spark, sf_dir).select("id"), "id", "left_semi").select("id", "s")


@query
def anti_missing(spark, sf_dir):
    c = src.names(spark, sf_dir)
    return c.join(_small_cands(spark, sf_dir).select("id"), "id", "left_anti").select("id", "s")


@query
def count_with_zero(spark, sf_dir):
    c, q = src.names(spark, sf_dir), src.literal_queries(spark, ["small ring", "zzzzzzzzzzzz"])
    n = range_scan(c, q, 2).groupBy("qid").agg(F.count(F.lit(1)).alias("n"))
    return q.select("qid").join(n, "qid", "left").select("qid", F.coalesce("n", F.lit(0)).alias("n"))


@query
def asof_version(spark, sf_dir):
    """For every purchase the last view of the user before it."""
    e = src.table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    at = e.where("event_type = 'purchase'").select("event_id", "user_id", F.col("ts").alias("t"))
    before = e.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), "user_id", "ts")
    return at.join(before, "user_id").where("ts <= t").groupBy("event_id").agg(F.max_by("view_id", F.struct("ts", "view_id")).alias("view_id"))


@query
def win_running_count(spark, sf_dir):
    c, q = line_setting(spark, sf_dir)
    counts = range_scan(c, q).groupBy("qid", "dist").agg(F.count(F.lit(1)).alias("n"))
    w = Window.partitionBy("qid").orderBy("dist")
    return counts.select("qid", "dist", "n", F.sum("n").over(w).alias("running"), (F.col("n") - F.coalesce(F.lag("n").over(w), F.lit(0))).alias("change"))


@query
def fn_surface(spark, sf_dir):
    e = src.table(spark, sf_dir, "events")
    return e.groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k"), F.round(F.avg(F.abs("value")), 6).alias("size"), F.date_format(F.max("ts"), "yyyy-MM-dd").alias("last_day"))


@query
def udtf_grams(spark, sf_dir):
    sqlapi.register(spark)
    src.names(spark, sf_dir).createOrReplaceTempView("simsearch_names")
    return spark.sql("SELECT id, translate(gram, chr(2) || chr(3), '^$') AS gram, occ FROM simsearch_names, LATERAL gram_table(s, 2)")


@query
def sql_relax(spark, sf_dir):
    src.names(spark, sf_dir).createOrReplaceTempView("simsearch_names")
    return sqlapi.relax_sql(spark, "simsearch_names", "small ring", SMALL.least, SMALL.most).select("id", "dist")


@query
def udf_distance(spark, sf_dir):
    c = src.names(spark, sf_dir).join(F.broadcast(ring(spark)))
    return c.select("id", sqlapi.arrow_distance("s", "q").alias("dist"))


@query
def stream_append(spark, sf_dir):
    """A tenth of the lines arrives as files after the index was built; the answer equals that over all lines."""
    c, q = line_setting(spark, sf_dir)
    late = F.pmod(F.crc32(F.col("s").cast("binary")), F.lit(10)) == 0
    base = scratch(spark)
    gram_index.GramIndex.build(c.where(~late), f"{base}/index")
    c.where(late).write.parquet(f"{base}/new")
    built = gram_index.GramIndex.open(spark, f"{base}/index")
    upkeep.append_stream(spark, f"{base}/new", c.schema, lambda batch, _: built.append(batch, f"{base}/index") and None, f"{base}/progress")
    return gram_index.GramIndex.open(spark, f"{base}/index").range_search(q, 40).select("qid", "id", "dist")


@query
def stream_tumbling(spark, sf_dir):
    return upkeep.tumbling(spark, sf_dir)


@query
def stream_sliding(spark, sf_dir):
    return upkeep.sliding(spark, sf_dir)


@query
def stream_session(spark, sf_dir):
    return upkeep.sessions(spark, sf_dir, scratch(spark))


@query
def stream_dedup(spark, sf_dir):
    return upkeep.deduplicated(spark, sf_dir, scratch(spark))
