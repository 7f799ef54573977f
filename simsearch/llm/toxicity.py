"""Toxicity severity by cumulative-link ordinal regression on sparse text features.

P(grade <= j) = sigmoid(threshold_j - w.x): one weight vector for all thresholds, which stay in order. Features are
words and beginnings of words (4 to 6 bytes; they join inflected forms) with dampened counts; a long text keeps
the weight of the few words that matter. Labels are only toxic or
not, so grades of toxic training documents come from how many words they hold that set toxic documents apart:
grade 1 to 3 by thirds of that number, grade 0 for documents that are not toxic. The result is the expected
grade and the probability of each.

The fit uses a bounded sample of labelled documents (``rows``) and the ``features`` words that tell the labels
apart best; every document is scored, whole.

Defined cases: null and empty texts have no features and get the model's base expectation; without both labels
in the sample the weights are zero and every text gets the same value; words that were not selected count for
nothing; equal texts get equal values; ids may repeat or be null.
"""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .samples import labelled_sample

_BEGIN = (4, 5, 6)
_WORD = re.compile(rb"[0-9a-z\x80-\xff]+")


@dataclass
class Ordinal:
    places: dict[bytes, int]
    weights: np.ndarray
    thresholds: np.ndarray


def sigmoid(z):
    return 0.5 * (1 + np.tanh(0.5 * z))


def words(text: bytes) -> list[bytes]:
    return _WORD.findall(text.lower())


def bag_of(text: bytes) -> Counter:
    """Counts of words, and of beginnings as b'^...' (not of words that are no longer)."""
    out = Counter(words(text))
    for w, n in list(out.items()):
        for k in _BEGIN:
            if len(w) > k:
                out[b"^" + w[:k]] += n
    return out


def sparse(bags: list[dict[bytes, int]], places: dict[bytes, int]):
    """Row, column, value of the known words."""
    row, col, val = [], [], []
    for i, bag in enumerate(bags):
        for w in bag.keys() & places.keys():
            row.append(i)
            col.append(places[w])
            val.append(bag[w])
    return np.array(row, np.int64), np.array(col, np.int64), 1 + np.log(np.array(val, float)) if val else np.zeros(0)


def select_words(bags, y, most: int, least_df: int = 3, least_z: float = 3.0) -> tuple[list[bytes], Counter]:
    """The words that toxic documents have more often than others, the surest first (signed root of chi-square)."""
    bad, good = Counter(), Counter()
    for bag, t in zip(bags, y):
        (bad if t else good).update(bag.keys())
    n1, n0 = max(1, sum(y)), max(1, len(y) - sum(y))
    z = {}
    for w in bad.keys() | good.keys():
        a, b = bad[w], good[w]
        if a + b >= least_df:
            p = (a + b) / (n1 + n0)
            z[w] = (a / n1 - b / n0) / np.sqrt(max(p * (1 - p), 1e-12) * (1 / n1 + 1 / n0))
    best = sorted((w for w in z if z[w] >= least_z), key=lambda w: (-z[w], w))[:most]
    return best, Counter({w: z[w] for w in best})


def grades(bags, y, z: Counter, levels: int, strong: float = 5.0) -> np.ndarray:
    marks = {w for w, v in z.items() if v >= strong}
    number = np.array([sum(1 + np.log(n) for w, n in bag.items() if w in marks) for bag in bags])
    toxic = np.array(y, bool)
    out = np.zeros(len(y), int)
    if toxic.any():
        cuts = np.quantile(number[toxic], np.arange(1, levels) / levels)
        out[toxic] = 1 + np.searchsorted(cuts, number[toxic], "right")
    return out


def fit(samples: list[tuple[str, int]], *, features: int = 2000, levels: int = 3, steps: int = 300, rate: float = 0.1, ridge: float = 0.1) -> Ordinal:
    """Penalised maximum likelihood by Adam; thresholds are a first value and positive gaps."""
    y = [int(t > 0) for _, t in samples]
    if len(set(y)) < 2:
        return Ordinal({}, np.zeros(0), np.arange(levels, dtype=float))
    chosen, z = select_words((bag_of(t.encode()) for t, _ in samples), y, features)
    places = {w: i for i, w in enumerate(chosen)}
    # a second pass keeps only the chosen words, so memory holds one bag at a time and the words' frequencies
    bags = [{w: n for w, n in bag_of(t.encode()).items() if w in places} for t, _ in samples]
    grade = grades(bags, y, z, levels)
    row, col, val = sparse(bags, places)
    # a word counts in proportion to how surely it tells the labels apart, so the ridge holds doubtful words down
    scale = np.array([z[w] for w in chosen]) / max(z.values(), default=1)
    val = val * scale[col]
    n, k = len(bags), levels
    p = np.concatenate((np.zeros(len(chosen)), [np.log((n - sum(y)) / sum(y))], np.full(k - 1, 0.0)))
    m, v = np.zeros_like(p), np.zeros_like(p)
    each = np.arange(n)
    for step in range(1, steps + 1):
        w, gaps = p[: len(chosen)], np.exp(p[len(chosen) + 1 :])
        cut = p[len(chosen)] + np.concatenate(([0], np.cumsum(gaps)))
        line = np.bincount(row, val * w[col], minlength=n)
        below = sigmoid(cut[None] - line[:, None])
        full = np.concatenate((np.zeros((n, 1)), below, np.ones((n, 1))), 1)
        slope = full * (1 - full)
        prob = np.maximum(full[each, grade + 1] - full[each, grade], 1e-12)
        up, down = slope[each, grade + 1] / prob, slope[each, grade] / prob
        by_cut = np.bincount(np.minimum(grade, k), up * (grade < k), minlength=k + 1)[:k] - np.bincount(np.maximum(grade - 1, 0), down * (grade > 0), minlength=k + 1)[:k]
        later = np.cumsum(by_cut[::-1])[::-1]
        g = np.concatenate((np.bincount(col, val * (down - up)[row], minlength=len(chosen)) - ridge * w, [later[0]], later[1:] * gaps - 0.01 * p[len(chosen) + 1 :]))
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g**2
        p = p + rate * (1 - step / (steps + 1)) * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-9)
    return Ordinal(places, p[: len(chosen)] * scale, p[len(chosen)] + np.concatenate(([0], np.cumsum(np.exp(p[len(chosen) + 1 :])))))


def above(texts: list[bytes], model: Ordinal) -> np.ndarray:
    """P(grade > j) for every text and threshold."""
    line = np.zeros(len(texts))
    places = model.places
    begin = [(k, {w[1:] for w in places if w[:1] == b"^" and len(w) == k + 1}) for k in _BEGIN]
    for i, t in enumerate(texts):
        n: Counter = Counter()
        for w, c in Counter(words(t)).items():
            if w in places:
                n[w] += c
            for k, known in begin:
                if w[:k] in known and len(w) > k:
                    n[b"^" + w[:k]] += c
        if n:
            line[i] = sum(model.weights[places[w]] * (1 + np.log(c)) for w, c in n.items())
    return sigmoid(line[:, None] - model.thresholds[None])


def score_documents(docs: DataFrame, model: Ordinal, *, batch_bytes: int = 4 << 20) -> DataFrame:
    """docs without text, with expected_severity and grade_probabilities."""
    sent = docs.sparkSession.sparkContext.broadcast(model)
    kept = [f for f in docs.schema if f.name != "text"]

    def run(batches):
        for batch in common.by_bytes(batches, lambda b: [len(v or "") for v in b.column("text").to_pylist()], batch_bytes):
            over = above(common.utf8(batch.column("text").to_pylist()), sent.value)
            edges = np.concatenate((np.ones((len(over), 1)), over, np.zeros((len(over), 1))), 1)
            probs = list(edges[:, :-1] - edges[:, 1:])
            yield pa.RecordBatch.from_arrays([*(batch.column(f.name) for f in kept), pa.array(over.sum(1)), pa.array(probs, pa.list_(pa.float64()))], names=[*(f.name for f in kept), "expected_severity", "grade_probabilities"])

    kinds = "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in kept)
    return docs.mapInArrow(run, f"{kinds}expected_severity double, grade_probabilities array<double>")


def op10_toxicity(spark: SparkSession, sf_dir: str, *, rows: int = 6_000) -> DataFrame:
    """doc_id, held_out, expected_severity (0 to 3), toxic_probability (P(grade > 0)), grade (most likely), toxic (P >= 0.5)."""
    docs = common.documents(spark, sf_dir).select("doc_id", "text")
    model = fit(labelled_sample(docs, common.table(spark, sf_dir, "labels"), "toxic", rows=rows))
    scored = score_documents(docs, model)
    probs = F.col("grade_probabilities")
    p = 1 - F.element_at(probs, 1)
    return scored.select("doc_id", (common.crc_mod(F.col("doc_id"), 3) == 1).alias("held_out"), "expected_severity", p.alias("toxic_probability"), (F.array_position(probs, F.array_max(probs)) - 1).cast("int").alias("grade"), (p >= 0.5).alias("toxic"))


ORACLE: dict[str, str] = {}
