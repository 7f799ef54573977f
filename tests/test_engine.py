"""Worked examples, literal loops against closed forms, and edge cases of the search engine."""

import pytest
from pyspark.sql import functions as F

from simsearch.functions import alignment as al
from simsearch.operators import baselines, clusters, gram_index, measures, rank
from simsearch.operators.relax import final_threshold, range_scan, relax, take
from simsearch.plans.goal import Goal, GoalGrid
from simsearch.queries import QUERIES, SMALL
from simsearch.sources import corpora as src

SF = "/root/testdata/sf0.01"


def corpus(spark, strings):
    return src.as_corpus(spark.createDataFrame(list(enumerate(strings)), "i long, x string"), F.col("i"), F.col("x"))


def test_goal_sizes_are_decimal():
    g = Goal(25, 55, 0.5)
    assert (g.least, g.most, g.share(40), g.quota) == (38, 82, 26, 12.5)
    assert (SMALL.least, SMALL.most, SMALL.share(8)) == (8, 12, 5)
    assert Goal(3, 3, 0.5).least <= Goal(3, 3, 0.5).most
    with pytest.raises(ValueError):
        Goal(5, 4)


def test_names_example(spark):
    names, q = src.names(spark, SF), src.literal_queries(spark, ["small ring"])
    cands = relax(names, q, SMALL).persist()
    assert {r.eps_final for r in cands.collect()} == {5} and cands.count() == 8
    contrib = {r.id: r.contrib for r in rank.contribution(cands.select("qid", "id", "s", "dist")).collect()}
    assert contrib == {0: 27, 175: 34, 4: 39, 5: 37, 19: 40, 45: 44, 64: 44, 177: 37}
    got = rank.relax_rank(names, q, SMALL, sample_share=1.0)
    assert [r.id for r in got.orderBy("rank").collect()] == [45, 64, 19, 4, 5]
    assert measures.balance_score(got, 0.5).first().balance_score == pytest.approx(1.2)
    best = baselines.exact_best(cands, SMALL)
    assert measures.balance_score(best, 0.5).first().balance_score == pytest.approx(1.2)


def test_guide_tree_and_alignment():
    ids = [0, 4, 5, 19, 45, 64, 175, 177]
    words = {0: "small ring", 175: "small rod", 4: "small gizmo", 5: "small bolt", 19: "small widget", 45: "cold ring", 64: "old ring", 177: "small gear"}
    d = {(a, b): al.distance(words[a], words[b]) for a in ids for b in ids if a < b}
    assert [round(h, 4) for _, _, h in al.guide_tree(ids, d)] == [1, 3, 3.5, 4.0, 4.375, 4.9375, 7.8438]
    import numpy as np

    rows = np.array([[al.GAP if c == "-" else ord(c) for c in s] for s in ("---gttag", "acag---g", "-cagttag")])
    assert al.sum_of_pairs(rows) == -1
    assert (al.motif(rows), al.motif(rows, gap_votes=False)) == ("cagttag", "acagttag")
    for members, aligned in al.align_along(ids, words, al.guide_tree(ids, d)):
        assert {al.shown(r).replace("-", "") for r in aligned} == set(words.values()) and len({len(r) for r in aligned}) == 1


def test_walk_example(spark):
    got = QUERIES["word_walk"](spark, SF).orderBy("pick").collect()
    assert [(r.id, r.score) for r in got] == [(0, 0.0), (45, 1.0), (64, 0.166667), (175, 0.791667), (5, 0.95), (177, 0.983333)]
    only = QUERIES["word_walk_quota_only"](spark, SF).orderBy("pick").collect()
    assert [r.id for r in only] == [0, 45, 64, 13, 41, 59, 74, 154, 175, 5, 177]
    assert only[-1].score == pytest.approx(-2.090909)


@pytest.mark.parametrize("options", [{}, {"step": 3, "eps_start": 2}, {"inclusive": True}, {"tie_order": "arrival", "step": 2}])
def test_loop_and_closed_form_agree(spark, options):
    names, q = src.names(spark, SF), src.literal_queries(spark, ["small ring", "x", ""])
    key = lambda df: sorted((r.qid, r.id, r.dist, r.eps_final, r.exhausted) for r in df.collect())
    want = key(relax(names, q, SMALL, engine="rounds", **options))
    assert key(relax(names, q, SMALL, **options)) == want
    assert key(relax(names, q, SMALL, engine="gallop", **options)) == want


def test_gram_filter_loses_nothing(spark):
    c = corpus(spark, ["abab", "abba", "baba", "ab", "a", "", "aaaa", "abababab", "bbbb", "ababa"])
    q = src.literal_queries(spark, ["abab", "a", ""])
    index = gram_index.GramIndex(c, gram_index.postings(c).persist())
    for eps in (1, 2, 3, 6):
        want = {(r.qid, r.id, r.dist) for r in range_scan(c, q, eps - 1).collect()}
        for mode in ("bag", "set"):
            assert {(r.qid, r.id, r.dist) for r in index.range_search(q, eps, mode=mode).collect()} == want


def test_edges(spark):
    q = src.literal_queries(spark, ["abc"])
    assert relax(corpus(spark, []), q, SMALL).count() == 0
    one = relax(corpus(spark, ["abd"]), q, SMALL).collect()
    assert len(one) == 1 and one[0].exhausted
    assert corpus(spark, ["x"] * 10 + [None]).count() == 1
    assert rank.relax_rank(corpus(spark, ["abd"]), q, SMALL).count() == 1
    assert relax(corpus(spark, ["é"]), q, SMALL).first().s == "?"


def test_plans(spark):
    plan = range_scan(src.names(spark, SF), src.literal_queries(spark, ["small ring"]), 5)._jdf.queryExecution().toString()
    physical = plan.split("== Physical Plan ==")[1]
    assert "BroadcastNestedLoopJoin" in physical and "CartesianProduct" not in physical
    assert physical.count("levenshtein(") == 1


def test_vectors(spark):
    v = clusters.hashed_grams(corpus(spark, ["small ring", "old bolt"]), dims=16).collect()
    assert all(abs(sum(x * x for x in r.vec) - 1) < 1e-9 for r in v)


def test_baselines_look_at_all_strings_under_the_limit(spark):
    c = corpus(spark, [f"a{i:03d}" for i in range(450)] + ["zzzzzzzzzzzz"])
    q = src.literal_queries(spark, ["a000"])
    for method in (baselines.swap_baseline, baselines.multipass_greedy):
        got = method(c, q, k=3, eps=20).collect()
        assert len(got) == 3 and 450 in {r.id for r in got}


def test_doubled_limits_reach_the_threshold_on_the_grid(spark):
    """With a step above 1 the final threshold may lie beyond the first limit that holds enough strings."""
    c = corpus(spark, [f"abcdefgh{i}" for i in range(8)] + [f"abcd{x * 5}" for x in "XYZ"])
    q = src.literal_queries(spark, ["abcdefgh_"])
    rows = lambda engine: sorted((r.id, r.dist, r.eps_final) for r in relax(c, q, Goal(5, 8, 0.5), step=10, engine=engine).collect())
    assert len(rows("rounds")) == 11 and rows("gallop") == rows("histogram") == rows("auto") == rows("rounds")


def test_goals_in_one_plan(spark):
    """A grid of goals gives each goal the results that it has alone, ties and too few strings included."""
    words = ["ring", "rings", "bring", "king", "rang", "rung", "string", "wing", "rig", "ringer", "r", "zzzzzzzzzz"]
    corpus = spark.createDataFrame([(i, w, len(w)) for i, w in enumerate(words)], "id long, s string, len int")
    queries = spark.createDataFrame([(1, "ring"), (2, "zzzz")], "qid int, q string")
    goals = [Goal(2, 4, 0.0), Goal(3, 5, 0.5), Goal(20, 30, 1.0)]
    dists, grid = range_scan(corpus, queries).persist(), GoalGrid(goals)

    def ranked(rows, goal):
        cands = take(rows, final_threshold(rows, goal, eps_start=2), goal, 2, 1, False)
        return sorted(tuple(r) for r in rank.relax_rank(None, None, goal, candidates=cands).select("qid", "id", "contrib", "rank", "pruned").collect())

    together = ranked(grid.over(dists), grid)
    alone = sorted((q * GoalGrid.PLACES + i, *rest) for i, g in enumerate(goals) for q, *rest in ranked(dists, g))
    assert together == alone and len({q for q, *_ in alone}) == 6


def test_streams_give_files(spark):
    """Sessions and deduplication leave nothing in the driver, and agree with the same aggregates of the table."""
    e = spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    by = e.groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")
    kinds = e.groupBy("event_type").agg(F.countDistinct("event_id").alias("n"))
    for name, want in (("stream_session", by), ("stream_dedup", kinds)):
        got = QUERIES[name](spark, SF)
        assert got.inputFiles()
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_vectors_of_long_texts(spark):
    """A text of 400,000 characters takes one pass; the quadratic way over its grams took minutes."""
    import time
    import zlib

    text = "ab cd" * 80_000
    began = time.time()
    vec = clusters.hashed_grams(spark.createDataFrame([(1, text), (2, ""), (3, "Äx")], "id long, s string"), dims=16).orderBy("id").collect()
    assert time.time() - began < 30
    for row in vec:
        p, count = f"\x02{row.s.lower()}\x03", [0] * 16
        for i in range(len(p) - 1):
            count[zlib.crc32(p[i : i + 2].encode()) % 16] += 1
        assert row.vec == pytest.approx([c / sum(x * x for x in count) ** 0.5 for c in count])


def test_cluster_model_works_out_parts_when_asked(spark, tmp_path):
    lines = src.lines(spark, SF).limit(200).persist()
    model = clusters.ClusterModel.build(lines, f"file://{tmp_path}/m", m=3, how="hashed_grams", dims=8)
    assert not {"centre", "edges", "sample", "clusters"} & set(vars(model))
    assert (model.clusters, model.edges.count()) == (3, 6)
    want = model.members.select("cid", F.posexplode("vec").alias("i", "x")).groupBy("cid", "i").agg(F.percentile("x", F.lit(0.5)).alias("x"))
    got = model.centre.select("cid", F.posexplode("centre").alias("i", "x"))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_repeated_documents_count_once_each(spark, tmp_path):
    """Rows with one id stay rows, also where the text is null."""
    import simsearch.experiments  # noqa: F401

    rows = [(1, "aa bb", "en"), (1, "aa bb", "en"), (2, "zz", "de"), (3, "yy zz", "de"), (4, None, None), *[(i, f"t{i}", "fr") for i in range(5, 12)]]
    spark.createDataFrame(rows, "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    assert sum(r.documents for r in QUERIES["cluster_purity"](spark, str(tmp_path)).collect()) == len(rows)


def test_packed_hamming(spark):
    from simsearch.functions import strings as fs

    pairs = [("abc", "abd"), ("", ""), ("Customer#000000010", "Customer#000000201"), ("x" * 28, "y" * 28), ("\x7f~\x01", "\x00\x7f\x01"), ("é", "e"), ("a" * 29, "a" * 29)]
    df = spark.createDataFrame(pairs, "x string, y string")
    got = df.select("x", "y", fs.packed_hamming(fs.packed(F.col("x")), fs.packed(F.col("y"))).alias("d")).collect()
    assert [r.d for r in got] == [None if len(x) > 28 or not x.isascii() else sum(a != b for a, b in zip(x, y)) for x, y in pairs]


def test_hamming_cells_of_short_and_long_names(spark, tmp_path):
    names = {0: "abc", 1: "abd", 2: "xy", 100: "é" + "b" * 30, 101: "?" + "b" * 29 + "c", 200: None, 300: "ab?"}
    spark.createDataFrame(list(names.items()), "c_custkey long, c_name string").write.parquet(f"{tmp_path}/customer.parquet")
    got = QUERIES["hamming_cells"](spark, str(tmp_path))
    assert sorted(map(tuple, got.collect())) == [(0, 1, 1), (0, 300, 1), (100, 101, 1), (300, 0, 1), (300, 1, 1)]
    assert "bit_count" in got._jdf.queryExecution().toString()


def test_aligned_rows_come_from_customers(spark, tmp_path):
    """Rows of unequal length vote as far as they reach; both motifs agree, null names do not count."""
    rows = [(10, "a0c"), (11, "abcd"), (12, "xb0d"), (20, None), (30, "00")]
    spark.createDataFrame(rows, "c_custkey long, c_name string").write.parquet(f"{tmp_path}/customer.parquet")
    at = str(tmp_path)
    assert [tuple(r) for r in QUERIES["motif_fixed"](spark, at).collect()] == [(1, "abcd")]
    assert [tuple(r) for r in QUERIES["udaf_motif"](spark, at).collect()] == [(1, "abcd")]
    assert [tuple(r) for r in QUERIES["motif_nogap"](spark, at).collect()] == [(1, "abcd")]
    assert sorted(map(tuple, QUERIES["sum_of_pairs"](spark, at).collect())) == [(1, 10, 11, 1), (1, 10, 12, -2), (1, 11, 12, 1)]


def test_bit_parallel_distances():
    """Words of 64 places, empty strings, letters beyond one byte: as the table, row by row, says."""
    import random

    from simsearch.functions.alignment import distance
    from simsearch.functions.edits import Texts

    draw = random.Random(5)
    for letters in ("ab", "0123456789abcdef", "aé一\U0001F600b"):
        strings = ["".join(draw.choices(letters, k=n)) for n in (0, 1, 2, 33, 63, 64, 65, 127, 128, 129, 200, 64)]
        texts = Texts(strings)
        for p in [*strings, "zq" + strings[3]]:
            assert texts.distances(p).tolist() == [distance(s, p) for s in strings]
    assert Texts([]).distances("ab").tolist() == []


def test_long_strings_are_compared_once_in_doubled_limits(spark, monkeypatch):
    """Rows of all engines agree for long strings; an earlier limit's strings are not compared again, and no task gives more
    than the nearest candidates (before, each limit scanned all of its band anew and kept every row under it)."""
    from simsearch.operators import relax as module

    strings = [("0123456789abcdef" * 40)[i % 16 :][: 150 + 7 * i] + "x" * (i % 5) for i in range(60)]
    c, q = corpus(spark, strings), src.literal_queries(spark, [strings[20] + "yy", strings[0], "b" * 400])
    seen = []
    scan = module.long_scan
    monkeypatch.setattr(module, "long_scan", lambda *a: seen.append(a[2:4]) or scan(*a))
    for goal in (Goal(3, 4, 0.5), Goal(25, 30, 0.5), Goal(80, 90, 0.5)):
        rows = lambda engine: sorted(tuple(r) for r in relax(c, q, goal, eps_start=4, step=3, engine=engine).collect())
        assert rows("gallop") == rows("histogram")
    assert seen and all(low == -1 or low < high for high, low in seen)
    kept = scan(c, q, 1000, -1, 2).where("qid = 1")
    assert kept.count() <= 2 * c.rdd.getNumPartitions()


def test_baselines_compare_many_strings_at_once(spark):
    """The members that the definitions give, pair by pair; 4,000 strings under the limit, which took minutes one pair at a time."""
    import random
    import time
    from itertools import combinations

    draw = random.Random(7)
    words = sorted({"".join(draw.choices("abcdef", k=draw.randint(60, 90))) for _ in range(4000)})
    c, q = corpus(spark, words), src.literal_queries(spark, ["abcdef" * 12])
    began = time.time()
    for method in (baselines.swap_baseline, baselines.multipass_greedy):
        assert len(method(c, q, eps=90).collect()) == 25
    assert time.time() - began < 60
    few = range_scan(c.where("id < 40"), q, 90).persist()
    rows = [tuple(r) for r in few.orderBy("dist", "id").select("id", "s", "dist").collect()]
    d = lambda x, y: al.distance(x[1], y[1])
    s = rows[:5]
    for x in rows[5:]:
        spread = {y: sum(d(y, z) for z in s) for y in s}
        w = min(s, key=lambda y: (spread[y], -y[2], -y[0]))
        if sum(d(x, z) for z in s if z != w) > spread[w]:
            s[s.index(w)] = x
    assert [r.id for r in baselines.swap_baseline(None, None, k=5, candidates=few).orderBy("rank").collect()] == [x[0] for x in s]
    s = rows[:1]
    while len(s) < 5:
        value = lambda t: 0.5 * 2 * sum(d(x, y) for x, y in combinations(t, 2)) / (len(t) * (len(t) - 1)) - 0.5 * sum(x[2] for x in t) / len(t)
        s.append(max((x for x in rows if x not in s), key=lambda x: (value([*s, x]), -x[2], -x[0])))
    assert [r.id for r in baselines.multipass_greedy(None, None, k=5, candidates=few).orderBy("rank").collect()] == [x[0] for x in s]


def test_self_join_finds_all_near_pairs(spark, monkeypatch):
    """Blocks, classes, digits alone, long strings, equal strings and ids: the pairs that the table of cells gives. 12,000 strings
    with numbers in them, whose pairs took minutes cell by cell."""
    import random
    import time

    draw = random.Random(11)
    some = ["", "7", "123456", "12x45", "x" * 64 + "1", "x" * 66, "x" * 69 + "22", "aé一\U0001F600b1", "aé一b", *("".join(draw.choices("ab01", k=draw.randint(0, 9))) for _ in range(150))]
    some += [s[:3] + "9" + s[4:] for s in some[:80]]
    rows = [(n, s) for n, s in enumerate(some)] + [(3, "123457"), (500, None), (None, "12")]
    c = spark.createDataFrame(rows, "id long, s string").withColumn("len", F.length("s"))
    kept = sorted({r for r in rows if None not in r})
    for eps, block in ((3, 40), (6, 8192), (0, 40)):
        want = sorted({(a, b, al.distance(x, y)) for a, x in kept for b, y in kept if a < b and al.distance(x, y) < eps})
        assert sorted(map(tuple, gram_index.similarity_self_join(c, eps, block=block).collect())) == want
    assert gram_index.similarity_self_join(c.where("false"), 6).collect() == []
    by_range, more = type(c).repartitionByRange, lambda self, n, *cols: by_range(self, n + 30, *cols)
    monkeypatch.setattr(type(c), "repartitionByRange", more)  # more partitions than blocks lose nothing
    assert sorted(map(tuple, gram_index.similarity_self_join(c, 3, block=40).collect())) == sorted({(a, b, al.distance(x, y)) for a, x in kept for b, y in kept if a < b and al.distance(x, y) < 3})
    monkeypatch.undo()
    began = time.time()
    urls = corpus(spark, [f"https://{draw.choice(['tion', 'there', 'blog.able'])}.example.org/{n}/list" for n in range(10_000, 70_000, 5)])
    found = gram_index.similarity_self_join(urls, 4)
    assert found.count() == found.select("i", "j").distinct().count() > 1_000_000
    assert time.time() - began < 60


def test_five_methods_share_their_candidates(spark, monkeypatch):
    """Two methods start from one relaxation and both baselines from one scan (before, each made its own), and lines are
    compared bit-parallel (before, cell by cell up to 150 characters)."""
    from simsearch import queries
    from simsearch.operators import align, baselines, rank, relax

    made, scan = [], baselines.all_within

    def own(*_, **__):
        raise AssertionError("a method made its own candidates")

    monkeypatch.setattr(rank, "relax", own)
    monkeypatch.setattr(align, "relax", own)
    monkeypatch.setattr(baselines, "all_within", lambda *a: made.append(scan(*a)) or made[-1])
    monkeypatch.setattr(queries, "_model", lambda *_, **__: None)
    monkeypatch.setattr(queries.clusters, "cluster_walk", lambda model, q, goal: q.select("qid", F.lit(1).alias("id"), F.col("q").alias("s"), F.lit(0).alias("dist")))
    queries.QUERIES["five_methods"](spark, "/root/testdata/sf0.001")
    assert len(made) == 1 and "levenshtein" not in made[0]._jdf.queryExecution().toString()
    c, q = queries.line_setting(spark, "/root/testdata/sf0.001")
    rows = lambda df: sorted((r.qid, r.id, r.dist) for r in df.select("qid", "id", "dist").collect())
    assert rows(scan(c, q, 60)) == rows(relax.range_scan(c, q, 59)) != []


def test_pairs_of_rows_are_neither_cells_nor_broadcast(spark):
    """Rows meet whole and on the executors (before, a cell per place and row was sent to the driver and joined); rows of one id
    add up, rows of unequal length count as far as both reach, empty ones have no pairs."""
    from simsearch.operators import align

    rows = [(1, 1, "a-c"), (1, 2, "ab"), (1, 2, "x--d"), (1, 3, "é\U0001F600c"), (1, 4, ""), (1, 5, None), (2, 1, "--"), (2, 9, "--"), (None, 1, "a"), (None, 2, "a")]
    aligned = spark.createDataFrame(rows, "qid long, id long, aligned string")
    cell = lambda x, y, s: s[3] if x == y == "-" else s[2] if "-" in (x, y) else s[0] if x == y else s[1]
    for s in ((1, 0, -1, 0), (2.5, -1, -3, 0.5)):
        want: dict = {}
        for q, i, x in rows:
            for r, j, y in rows:
                if q == r is not None and i < j and x and y:
                    want[q, i, j] = want.get((q, i, j), 0) + sum(cell(a, b, s) for a, b in zip(x, y))
        got = align.sum_of_pairs_sql(aligned, match=s[0], mismatch=s[1], gap=s[2], gapgap=s[3])
        assert sorted(map(tuple, got.collect())) == sorted((*k, int(v)) for k, v in want.items())
    plan = got._jdf.queryExecution().toString()
    assert "posexplode" not in plan and "Broadcast" not in plan


def test_many_queries_are_classified_without_a_row_per_pair(spark, monkeypatch):
    """The rows that the expressions give, with equal, null, short and unusual vectors, in one batch and in several; 12,000 queries
    against 6,000 vectors, which were refused (above 10,000) and took a row per pair."""
    import random
    import time

    from pyspark.sql import Window

    from simsearch.functions.strings import euclid

    draw, nan, inf = random.Random(3), float("nan"), float("inf")
    vec = lambda: [draw.randint(0, 2) / 3 for _ in range(4)]
    given = [(draw.randint(1, 3), i, vec()) for i in range(200)] + [(1, 900, None), (2, 901, [1.0, None, 0.0, 0.0]), (3, 902, [nan, 0.0, 0.0, 0.0]), (1, 903, [inf, 0.0, 0.0, 0.0]), (2, 904, [1.0, 2.0]), (3, 905, []), (1, -5, [1e200, 1.0, 1.0, 1.0])]
    asked = [(i, vec()) for i in range(30)] + [(100, None), (101, [1.0, 2.0]), (102, [nan, 0.0, 0.0, 0.0]), (103, [inf, 0.0, 0.0, 0.0]), (104, [0.1, None, 0.0, 0.0]), (105, []), (106, [1e200, 0.0, 0.0, 0.0]), (5, vec())]
    s, q = spark.createDataFrame(given, "cid int, id long, vec array<double>"), spark.createDataFrame(asked, "qid int, vec array<double>")
    w = Window.partitionBy("qid").orderBy("d", "id")
    first = lambda df, k: sorted(repr((r.qid, r.r, r.id, r.cid, r.d)) for r in df.withColumn("r", F.row_number().over(w)).where(F.col("r") <= k).collect())
    for few, at_once, k in ((given, 8192, 5), (given[:200], 10, 7), (given[:2], 10, 3)):
        monkeypatch.setattr(clusters, "ASKED_AT_ONCE", at_once)
        part = s.where(F.col("id").isin([i for _, i, _ in few]))
        pairs = q.withColumnRenamed("vec", "qv").crossJoin(part).select("qid", "cid", "id", euclid(F.col("qv"), F.col("vec")).alias("d"))
        assert first(clusters.nearest_sampled(q, part, k), k) == first(pairs, k)
    monkeypatch.undo()
    of = lambda n: F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: F.pmod(F.xxhash64("id", i), F.lit(n)) / n)
    began = time.time()
    many = spark.range(12_000).select(F.col("id").alias("qid"), of(1000).alias("vec"))
    got = clusters.classify(many, spark.range(6_000).select((F.col("id") % 4).cast("int").alias("cid"), "id", of(1000).alias("vec")))
    assert got.count() == 12_000 and time.time() - began < 60
    plan = got._jdf.queryExecution().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan


def test_large_clusters_are_split_in_one_pass_a_round(spark):
    """No cluster stays above the cap but one whose vectors are all equal, and the plan has no part per cluster (before, a union
    with one doubled it round by round); members go to the nearest centre and none is lost."""
    import random

    draw = random.Random(2)
    rows = [(i, [draw.gauss(c, 0.4), draw.gauss(-c, 0.4)], "x" * 100) for i, c in enumerate([0, 0, 0, 0, 5, 9] * 60)] + [(1000 + i, [50.0, 50.0], "y" * 200) for i in range(60)]
    df = spark.createDataFrame(rows, "id long, vec array<double>, s string")
    got = clusters.partition(df, 2, cap=6000)
    by = {}
    for r in got.collect():
        by.setdefault(r.cid, []).append(r)
    assert sorted(r.id for some in by.values() for r in some) == [i for i, _, _ in rows]
    large = [some for some in by.values() if sum(len(r.s) for r in some) > 6000]
    assert [sorted(r.id for r in some) for some in large] == [list(range(1000, 1060))] and len(by) > 6
    assert "Union" not in got._jdf.queryExecution().toString()
    lean = clusters.partition(df.select("vec", F.octet_length("s").alias("bytes")), 2, cap=6000, size=F.col("bytes"))
    assert lean.count() == len(rows) and "s" not in lean.columns
