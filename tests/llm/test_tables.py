"""Every operator on whole small tables: clashing columns, empty tables, repeated rows, and the pipeline against brute force."""

import random
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from simsearch.llm import common, decontaminate, encoding, jaccard, mixing, pitman_yor, quality, repair, rules, separators, suffixes, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
CLASHES = ("quality_score", "hit", "items", "n_words", "s", "uid", "__row", "held_out", "n", "cls", "start", "g", "kept", "d2", "file", "expected_severity", "l_sig", "a")


def table(spark, n=60, seed=1):
    rng = random.Random(seed)
    rows = []
    for i in range(n):
        words = [rng.choice(["alpha", "beta", "gamma", "delta", "omega"]) + str(rng.randint(0, 40)) for _ in range(rng.randint(12, 90))]
        text = "# $ % " * 30 if i % 5 == 4 else "\n".join([" ".join(words[:40]) + ".", " ".join(words[40:])])
        rows.append((i, text, "en", rng.choice(["web", "books", None]), len(text)))
    rows += [(i + 500, rows[i][1] + " end", "en", "web", 1) for i in (0, 1, 2)] + [rows[3], rows[3]]
    rows += [(700, None, None, None, None), (701, "", "en", "web", 0), (None, "a null id with some words in it", "en", "web", 3), (702, rows[6][1] + " one two three four five six seven eight nine ten", "en", "web", 3)]
    return rows


def clashing(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).withColumns({c: F.lit("clash") for c in CLASHES})


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    rows, path = table(spark), tmp_path_factory.mktemp("sf")
    clashing(spark, rows).coalesce(2).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame([(i, int(i % 5 != 4), int(i % 7 == 0)) for i in range(60)], "doc_id long, quality int, toxic int").coalesce(1).write.parquet(f"{path}/labels.parquet")
    spark.createDataFrame([(1, "one two three four five six seven eight nine ten"), (2, None)], "item_id long, text string").coalesce(1).write.parquet(f"{path}/benchmark.parquet")
    return str(path), rows


def words3(text, n):
    w = (text or "").lower().split()
    return {tuple(w[i : i + min(n, len(w))]) for i in range(max(1, len(w) - n + 1))} if w else set()


def test_pipeline_matches_brute_force_stage_by_stage(spark, folder):
    path, rows = folder
    key = lambda df: Counter((r.doc_id, r.text) for r in df.collect())
    docs = common.documents(spark, path)
    names = docs.columns
    good = corpus_pipeline.keep_good(spark, docs, path)
    chain = quality.fit_quality(docs, common.table(spark, path, "labels"))
    want = Counter((r[0], r[1]) for r in rows if quality.score_texts([(r[1] or "").encode()], chain)[0] >= 0.5)
    assert key(good) == want and good.columns == names
    assert not any(i is not None and i < 60 and i % 5 == 4 for i, _ in want) and sum(want.values()) > 40
    docs = common.materialize(good, "test")
    one = corpus_pipeline.keep_one_of_group(spark, docs, path)
    left = sorted(set(want), key=lambda x: (x[0] is None, x[0] or 0))
    sets = [words3(t, 5) for _, t in left]
    label = list(range(len(left)))
    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            if a and 100 * len(a & b) >= 80 * len(a | b):
                old, new = max(label[i], label[j]), min(label[i], label[j])
                label = [new if x == old else x for x in label]
    want = Counter(left[i] for i in range(len(left)) if label[i] == i)
    assert key(one) == want and one.columns == names and len(want) < len(left)
    docs = common.materialize(one, "test")
    clean = corpus_pipeline.drop_leaks(spark, docs, path)
    item = "one two three four five six seven eight nine ten"
    want = Counter(x for x in want if item not in (x[1] or ""))
    assert key(clean) == want and clean.columns == names
    docs = common.materialize(clean, "test")
    mixed = corpus_pipeline.mix_sources(spark, docs, path)
    taken = {(r.doc_id, r.text): r["__mix_copies"] for r in mixing.mix_documents(docs).collect()}
    assert key(mixed) == Counter({k: n for k, n in taken.items() if n}) and mixed.columns == names
    docs = common.materialize(mixed, "test")
    t = encoding.Encoder(repair.default_tokenizer()).tokenizer
    ids = lambda x: [*t.encode(x or "", add_special_tokens=False).ids, 2]
    want = Counter((i, len(ids(x)), zlib.crc32(np.array(ids(x), "<u4").tobytes())) for (i, x), n in key(docs).items() for _ in range(n))
    assert Counter((r.doc_id, r.n_tokens, r.ids_crc32) for r in corpus_pipeline.write_tokens(spark, docs, path).collect()) == want
    whole = corpus_pipeline.run(spark, path)
    assert Counter((r.doc_id, r.n_tokens, r.ids_crc32) for r in whole.collect()) == want


def test_queries_take_clashing_columns_and_repeated_rows(spark, folder):
    path, rows = folder
    from simsearch.llm.queries import QUERIES

    for name, query in QUERIES.items():
        got = query(spark, path).collect()
        assert Counter(r.doc_id for r in got) == Counter(r[0] for r in rows), name


def test_operators_take_empty_tables(spark):
    docs = spark.createDataFrame([], SCHEMA)
    path = common.shared_dir(spark).removeprefix("file://") + "/empty"
    docs.write.mode("overwrite").parquet(f"{path}/documents.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.mode("overwrite").parquet(f"{path}/labels.parquet")
    spark.createDataFrame([], "item_id long, text string").write.mode("overwrite").parquet(f"{path}/benchmark.parquet")
    for query in (suffixes.op1_repeated_strings, quality.op2_line_quality, decontaminate.op3_decontaminate, pitman_yor.op4_pitman_yor, mixing.op5_source_mixture, repair.op6_token_shards, rules.op7_robust_rules, jaccard.op8_shingle_join, separators.op9_separator_scan, toxicity.op10_toxicity, corpus_pipeline.run):
        assert query(spark, path).count() == 0, query.__name__


def test_held_out_accuracy(spark, folder):
    path, _ = folder
    labels = {r.doc_id: r.quality for r in common.table(spark, path, "labels").collect()}
    got = [r for r in quality.op2_line_quality(spark, path).collect() if r.held_out and r.doc_id in labels]
    assert len(got) > 10 and all(r.predicted == labels[r.doc_id] for r in got)


def test_separator_query_equals_the_tokenizer(spark, folder):
    path, rows = folder
    t = encoding.Encoder(repair.default_tokenizer(), specials_as_text=True).tokenizer
    want = Counter((r[0], len(t.encode(r[1] or "", add_special_tokens=False).ids)) for r in rows)
    assert Counter((r.doc_id, r.n_tokens) for r in separators.op9_separator_scan(spark, path).collect()) == want


def test_language_model_base_and_total(spark, folder):
    path, rows = folder
    held = lambda i: zlib.crc32(str("" if i is None else i).encode()) % 10 == 0
    tokens = lambda x: [*(x or "").lower().split(), "\0"]
    counts = Counter(w for r in rows if not held(r[0]) for w in tokens(r[1]))
    n, v = sum(counts.values()), len(counts)
    want = Counter((r[0], len(tokens(r[1])), sum(counts[w] > 0 for w in tokens(r[1])), round(float(sum(np.log10((counts[w] + 0.1) / (n + 0.1 * (v + 1))) for w in tokens(r[1]))), 6)) for r in rows)
    assert Counter((r.doc_id, r.n_tokens, r.n_known, round(r.base_score, 6)) for r in pitman_yor.op4_pitman_yor(spark, path).collect()) == want
