"""Quality of documents by a linear-chain conditional random field over their lines.

Every line is a node with two states, good and bad. A line's potential is linear in features of its own
characters and words and of the lines before and after it; neighbouring lines are tied by transition weights. The weights
maximise the likelihood of labelled documents, all of whose lines carry the document's label. Forward-backward
gives each line's probability of being good; the document's score is their mean, weighted by line length.

The fit uses a bounded sample of labelled documents (``rows``); every document is scored, whole. A long text's features are
made piece by piece, three numbers a line are kept, and its chain is worked through in blocks side by side: a block's
transfer from the line before it is a 2 x 2 matrix, so after one pass over all blocks at once and one over the matrices a last
pass gives every line's messages exactly.

Defined cases: null and empty texts are one empty line and get the score of such a line; a table of labels with
one class or no row gives the score 0.5 shifted by nothing (weights zero); equal documents get equal scores;
ids may repeat or be null. Columns beside doc_id and text are not read for a score.
"""

from __future__ import annotations

from dataclasses import dataclass
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .samples import labelled_sample

# classes of bytes
_LOWER, _UPPER, _DIGIT, _BLANK, _SYMBOL, _STOP, _POINT, _HIGH, _REST = range(9)
_CLASS = np.full(256, _REST, np.int64)
_CLASS[0x61:0x7B], _CLASS[0x41:0x5B], _CLASS[0x30:0x3A], _CLASS[0x80:] = _LOWER, _UPPER, _DIGIT, _HIGH
_CLASS[[9, 10, 11, 12, 13, 32]] = _BLANK
for _chars, _c in (("#*$%&|<>", _SYMBOL), (".!?", _STOP), (",;:'\"()-", _POINT)):
    _CLASS[[ord(x) for x in _chars]] = _c
N_OWN = 19


def lines_of(texts: list[bytes], seen: set[bytes] | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Features of every line of every text, characters per line, lines per text.

    seen: lines that came before in the text, where texts are pieces of one."""
    data = b"\n".join(texts) + b"\n"
    raw = np.frombuffer(data, np.uint8)
    ends = np.flatnonzero(raw == 10)
    starts = np.concatenate(([0], ends[:-1] + 1))
    n = len(ends)
    per_text = np.array([t.count(b"\n") + 1 for t in texts], np.int64)
    kind = _CLASS[raw]
    line = np.repeat(np.arange(n), ends - starts + 1)
    counts = np.bincount(line * 9 + kind, minlength=9 * n).reshape(n, 9).astype(np.float64)
    counts[:, _BLANK] -= 1  # the line's end
    length = (ends - starts).astype(np.float64)
    blank = kind == _BLANK
    before, after = np.concatenate(([True], blank[:-1])), np.concatenate((blank[1:], [True]))
    begins = ~blank & before
    words = np.bincount(line[begins], minlength=n).astype(np.float64)
    marked = np.bincount(line[(kind == _SYMBOL) & after], minlength=n)  # words that end in a symbol
    alone = np.bincount(line[(kind == _SYMBOL) & before & after], minlength=n)  # symbols that stand alone
    again, twice, fresh = np.zeros(n), np.zeros(n), np.zeros(n)
    at = 0
    for text in texts:
        earlier = set() if seen is None else seen
        for part in text.split(b"\n"):
            found = part.split()
            if found:
                again[at] = part in earlier
                twice[at] = sum(map(eq, found, found[1:]))
                fresh[at] = len(set(found))
                earlier.add(part)
            at += 1
    size, per_word = np.maximum(length, 1), np.maximum(words, 1)
    last = np.where(length > 0, raw[np.maximum(ends - 1, 0)], 32)
    x = np.stack((np.ones(n), np.log1p(length) / 6, np.log1p(words) / 4, counts[:, _SYMBOL] / size * 5, np.minimum(counts[:, _SYMBOL] / per_word, 2), marked / per_word, alone / per_word * 2, counts[:, _DIGIT] / size * 3, counts[:, _UPPER] / size * 3, counts[:, _POINT] / size * 5, counts[:, _STOP] / size * 5, counts[:, _HIGH] / size, counts[:, _REST] / size * 5, np.minimum((size - counts[:, _BLANK]) / per_word, 40) / 10, again, twice / per_word, 1 - fresh / per_word, np.isin(last, (0x2E, 0x21, 0x3F)), words < 4), 1)
    return x, length, per_text


def with_neighbours(x: np.ndarray, per_text: np.ndarray) -> np.ndarray:
    """Own features, those of the line before and after (zero outside the text), and of the text's edges."""
    n = len(x)
    first = np.zeros(n, bool)
    begin = np.cumsum(per_text) - per_text
    first[begin] = True
    last = np.zeros(n, bool)
    last[np.cumsum(per_text) - 1] = True
    before, after = np.zeros_like(x), np.zeros_like(x)
    before[1:], after[:-1] = x[:-1], x[1:]
    before[first], after[last] = 0, 0
    return np.concatenate((x, before, after, first[:, None], last[:, None]), 1)


@dataclass
class Chain:
    weights: np.ndarray  # of the features, for good against bad
    moves: np.ndarray  # 2 x 2 transition weights; state 1 is good


def marginals(unary: np.ndarray, moves: np.ndarray, per_text: np.ndarray):
    """P(good) of every line, expected transitions summed over texts, and log normalisers.

    unary: score of good against bad. Texts are stepped through together, the longest first, so that those still
    running are always a prefix."""
    order = np.argsort(-per_text, kind="stable")
    length, begin = per_text[order], (np.cumsum(per_text) - per_text)[order]
    steps = int(length[0]) if len(length) else 0
    alive = np.searchsorted(-length, -np.arange(steps), "left")  # texts with more than t lines
    u = np.stack((np.zeros(len(unary)), unary), 1)
    forward = np.empty((len(unary), 2))
    if steps:
        forward[begin] = u[begin]
    for t in range(1, steps):
        at = begin[: alive[t]] + t
        forward[at] = np.logaddexp(forward[at - 1][:, :1] + moves[0], forward[at - 1][:, 1:] + moves[1]) + u[at]
    backward = np.zeros((len(unary), 2))
    pairs = np.zeros((2, 2))
    end = begin + length - 1
    total = np.logaddexp(forward[end, 0], forward[end, 1]) if steps else np.zeros(0)
    for t in range(steps - 1, 0, -1):
        at = begin[: alive[t]] + t
        coming = u[at] + backward[at]
        reach = moves[None] + coming[:, None, :]
        backward[at - 1] = np.logaddexp(reach[:, :, 0], reach[:, :, 1])
        pairs += np.exp(forward[at - 1][:, :, None] + reach - total[: alive[t], None, None]).sum(0)
    score = forward + backward
    good = np.exp(score[:, 1] - np.logaddexp(score[:, 0], score[:, 1]))
    normal = np.empty(len(per_text))
    normal[order] = total
    return good, pairs, normal


def fit(samples: list[tuple[str, int]], *, steps: int = 100, rate: float = 0.15, ridge: float = 2.0) -> Chain:
    """Maximum likelihood with a ridge, by Adam on the whole sample."""
    width = 3 * N_OWN + 2
    weights, moves = np.zeros(width), np.zeros((2, 2))
    if len({y for _, y in samples}) < 2:
        return Chain(weights, moves)
    made, group, size = [], [], 0
    for text in [*common.utf8(t for t, _ in samples), None]:  # features are made for some texts at a time, to hold little beside them
        if group and (text is None or size > 1 << 20):
            made.append(lines_of(group))
            group, size = [], 0
        if text is not None:
            group.append(text)
            size += len(text)
    own, per_text = (np.concatenate([m[i] for m in made]) for i in (0, 2))
    del made
    x = with_neighbours(own, per_text)
    y = np.repeat(np.array([y for _, y in samples], float), per_text)
    told = np.zeros((2, 2))
    for state in (0, 1):
        told[state, state] = sum(n - 1 for (_, s), n in zip(samples, per_text.tolist()) if s == state)
    params, m, v = np.zeros(width + 4), np.zeros(width + 4), np.zeros(width + 4)
    for step in range(1, steps + 1):
        good, pairs, _ = marginals(x @ params[:width], params[width:].reshape(2, 2), per_text)
        slope = np.concatenate((x.T @ (y - good), (told - pairs).ravel())) - ridge * params
        m, v = 0.9 * m + 0.1 * slope, 0.99 * v + 0.01 * slope**2
        params = params + rate * (1 - step / (steps + 1)) * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-9)
    return Chain(params[:width], params[width:].reshape(2, 2))


def parts_of_scores(texts: list[bytes], chain: Chain, seen: set[bytes] | None = None):
    """What a line's features add to its own score, to that of the next and to that of the line before; and lines' sizes."""
    own, length, per_text = lines_of(texts, seen)
    return *(own @ chain.weights[i * N_OWN : (i + 1) * N_OWN] for i in range(3)), length, per_text


def scores_of_lines(own, to_next, to_last, per_text: np.ndarray, chain: Chain) -> np.ndarray:
    end = np.cumsum(per_text)
    first, last = np.zeros(len(own), bool), np.zeros(len(own), bool)
    first[end - per_text], last[end - 1] = True, True
    u = own + first * chain.weights[3 * N_OWN] + last * chain.weights[3 * N_OWN + 1]
    u[1:] += np.where(first[1:], 0, to_next[:-1])
    u[:-1] += np.where(last[:-1], 0, to_last[1:])
    return u


def marginals_of_long(u: np.ndarray, moves: np.ndarray) -> np.ndarray:
    """P(good) of every line of one text, in blocks side by side; log odds of messages are carried."""
    n = len(u)
    size = max(2, int(n**0.5))
    count = n // size
    block, tail = u[: count * size].reshape(count, size), u[count * size :]
    ahead = lambda f: np.logaddexp(moves[0, 1], moves[1, 1] + f) - np.logaddexp(moves[0, 0], moves[1, 0] + f)
    back = lambda x: np.logaddexp(moves[1, 0], moves[1, 1] + x) - np.logaddexp(moves[0, 0], moves[0, 1] + x)
    # transfer[k, s, t]: from state s of the line before block k to state t of its last line
    transfer = np.broadcast_to(moves, (count, 2, 2)).copy()
    transfer[:, :, 1] += block[:, :1]
    for t in range(1, size):
        transfer = np.logaddexp(transfer[:, :, :1] + moves[0], transfer[:, :, 1:] + moves[1])
        transfer[:, :, 1] += block[:, t, None]
    into, out = np.zeros(count), np.zeros(count)  # log odds of the line before a block; messages back to its last line
    odds = block[0, 0]
    for t in range(1, size):
        odds = block[0, t] + ahead(odds)
    for k in range(1, count):
        into[k] = odds
        ends = np.logaddexp(transfer[k, 0], odds + transfer[k, 1])
        odds = ends[1] - ends[0]
    forward, backward = np.empty(n), np.zeros(n)
    for t, x in enumerate(tail.tolist(), count * size):
        odds = forward[t] = x + ahead(odds)
    for t in range(n - 2, count * size - 1, -1):
        backward[t] = back(u[t + 1] + backward[t + 1])
    if len(tail):
        out[-1] = back(tail[0] + backward[count * size])
    for k in range(count - 1, 0, -1):
        begins = np.logaddexp(transfer[k, :, 0], transfer[k, :, 1] + out[k])
        out[k - 1] = begins[1] - begins[0]
    f, b = forward[: count * size].reshape(count, size), backward[: count * size].reshape(count, size)
    f[:, 0] = block[:, 0] + np.where(np.arange(count) > 0, ahead(into), 0)
    b[:, -1] = out
    for t in range(1, size):
        f[:, t] = block[:, t] + ahead(f[:, t - 1])
        b[:, size - 1 - t] = back(block[:, size - t] + b[:, size - t])
    return 1 / (1 + np.exp(-np.clip(forward + backward, -700, 700)))


def score_long(text: bytes, chain: Chain, piece: int = 1 << 20) -> float:
    """The score of one text whose features are too many to be held at once."""
    seen: set[bytes] = set()
    found, begin = [], 0
    while begin <= len(text):
        end = text.find(b"\n", begin + piece)
        end = len(text) if end < 0 else end
        found.append(parts_of_scores([text[begin:end]], chain, seen)[:4])
        begin = end + 1
    own, to_next, to_last, length = (np.concatenate(x) for x in zip(*found))
    u = scores_of_lines(own, to_next, to_last, np.array([len(own)]), chain)
    good = marginals_of_long(u, chain.moves) if len(u) > 8 else marginals(u, chain.moves, np.array([len(u)]))[0]
    return float(np.average(good, weights=length if length.any() else None))


def score_texts(texts: list[bytes], chain: Chain, *, most_lines: int = 2_000, most_bytes: int = 1 << 20) -> np.ndarray:
    long = np.array([len(t) > most_bytes or t.count(b"\n") >= most_lines for t in texts], bool)
    out = np.zeros(len(texts))
    for i in np.flatnonzero(long).tolist():
        out[i] = score_long(texts[i], chain)
    rest = [t for t, x in zip(texts, long) if not x]
    if rest:
        own, to_next, to_last, length, per_text = parts_of_scores(rest, chain)
        good, _, _ = marginals(scores_of_lines(own, to_next, to_last, per_text, chain), chain.moves, per_text)
        text = np.repeat(np.arange(len(rest)), per_text)
        weight = length + (np.bincount(text, length) == 0)[text]
        out[~long] = np.bincount(text, weight * good) / np.bincount(text, weight)
    return np.clip(out, 0, 1)


def score_documents(docs: DataFrame, chain: Chain, *, batch_bytes: int = 4 << 20) -> DataFrame:
    """docs with a column quality_score; all other columns pass through, one that came in under that name is replaced."""
    docs = common.without(docs, "quality_score")
    model = docs.sparkSession.sparkContext.broadcast(chain)
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)

    def run(batches):
        common.give_back()
        for batch in common.by_bytes(batches, lambda b: [len(v or "") for v in b.column("text").to_pylist()], batch_bytes):
            scores = score_texts(common.utf8(batch.column("text").to_pylist()), model.value)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(scores, pa.float64())], names=[*batch.schema.names, "quality_score"])

    return docs.mapInArrow(run, f"{kinds}, quality_score double")


def fit_quality(docs: DataFrame, labels: DataFrame, *, rows: int = 4000) -> Chain:
    return fit(labelled_sample(docs, labels, "quality", rows=rows))


def op2_line_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.documents(spark, sf_dir).select("doc_id", "text")
    scored = score_documents(docs, fit_quality(docs, common.table(spark, sf_dir, "labels")))
    score = F.col("quality_score")
    return scored.select("doc_id", (common.crc_mod(F.col("doc_id"), 3) == 1).alias("held_out"), score.alias("score"), (score >= 0.5).cast("int").alias("predicted"))


ORACLE: dict[str, str] = {}
