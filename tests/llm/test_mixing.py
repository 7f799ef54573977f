import random
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from simsearch.llm import mixing


def test_water_fill_by_hand():
    assert mixing.water_fill([100, 100, 100], [1, 2, 3], 300, 3) == [50, 100, 150]
    # the third is clamped at 3 x 10, the rest shares what is left by weight
    assert mixing.water_fill([100, 100, 10], [1, 2, 3], 210, 3) == [60, 120, 30]


@pytest.mark.parametrize("seed", range(6))
def test_targets_and_taken(spark, seed):
    rng = random.Random(seed)
    names = [None, "a", "b", "ä", "Z", "zz"][: rng.randint(1, 6)]
    rows = [(i, rng.choice([None, "", "  "]) if rng.random() < 0.1 else " ".join("w" * rng.randint(1, 30)), s := names[int(rng.random() ** 3 * len(names))], rng.random()) for i in range(120)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, __extra double")
    got = mixing.mix_documents(docs).collect()
    assert len(got) == len(rows)
    size = {r[0]: len((r[1] or "").split()) for r in rows}
    by = defaultdict(int)
    for i, _, s, _ in rows:
        by[s] += size[i]
    order = sorted((s for s in by if s is not None)) + [s for s in by if s is None]
    want = dict(zip(order, mixing.water_fill([by[s] for s in order], [1 + k % 3 for k in range(len(order))], sum(by.values()), 3)))
    taken, largest = defaultdict(int), defaultdict(int)
    for r in got:
        assert r["__mix_size"] == size[r.doc_id] and r["__mix_source_size"] == by[r.source]
        assert r["__mix_target"] == pytest.approx(want[r.source]) and 0 <= r["__mix_copies"] <= 3
        taken[r.source] += r["__mix_copies"] * r["__mix_size"]
        largest[r.source] = max(largest[r.source], r["__mix_size"])
    for s in by:
        assert abs(taken[s] - want[s]) <= largest[s]
    assert sum(want.values()) == pytest.approx(sum(by.values()))
    again = {r.doc_id: r["__mix_copies"] for r in mixing.mix_documents(docs.repartition(7)).collect()}
    assert again == {r.doc_id: r["__mix_copies"] for r in got}


def test_empty_and_repeat(spark):
    empty = spark.createDataFrame([], "doc_id long, text string, source string")
    assert mixing.repeat(mixing.mix_documents(empty)).count() == 0
    docs = spark.createDataFrame([(1, "a b", "s"), (1, "a b", "s"), (2, "c", "t"), (3, None, "t")], "doc_id long, text string, source string")
    out = mixing.repeat(mixing.mix_documents(docs))
    assert out.columns == ["doc_id", "text", "source"]
    assert out.groupBy("doc_id").count().agg(F.max("count")).first()[0] <= 6
