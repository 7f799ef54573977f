"""Benchmark decontamination by winnowing.

Words are runs of digits, letters and non-ASCII characters after lower-casing A-Z. Every k consecutive words
have a hash; of each t-k+1 neighbouring hashes the smallest (the rightmost of equals) is kept as a fingerprint. Two
texts that share t words in a row share a fingerprint of that stretch, so joining fingerprints finds every
document that holds a window of t words of a benchmark item. The hits are then extended: word runs of the
document are compared with the items' own words, which also removes hash collisions.

Items with fewer than t words are a single window of their own length; they are fingerprinted with the
shortest such length as k where that is below the usual one.

The benchmark is the small side by nature, but its size is not trusted: it is cut into blocks of a bounded
number of words, each block is a broadcast of bounded size, and results of the blocks are united per document.

Defined cases: null and empty texts have no words and no hits; an item without words is never found; items
with a null id are ignored; equal items are all reported; repeated documents each get their row; empty tables
give zero hits or no rows. Columns beside doc_id and text are not read.
"""

from __future__ import annotations

from collections import defaultdict
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

_WORD = np.zeros(256, bool)
_WORD[0x30:0x3A] = _WORD[0x61:0x7B] = _WORD[0x80:] = True
_BASE, _K1, _K2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93), np.uint64(0xA0761D6478BD642F)
_BATCH = 4 << 20


def words_of(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Begin and end of every word in lower-cased UTF-8."""
    inside = np.zeros(len(data) + 2, np.int8)
    inside[1:-1] = _WORD[np.frombuffer(data, np.uint8)]
    step = np.diff(inside)
    return np.flatnonzero(step == 1), np.flatnonzero(step == -1)


def word_hashes(data: bytes, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of every word: two sums of its bytes, weighted by place within the word, mixed.

    Only a filter: what it lets through is compared word by word."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    with np.errstate(over="ignore"):
        raw = np.frombuffer(data, np.uint8).astype(np.uint64)
        sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum(common.mix64(np.arange(256, dtype=np.uint64) * _BASE + _K1)[raw.astype(np.intp)], dtype=np.uint64)))
        place = np.concatenate((np.zeros(1, np.uint64), np.cumsum(raw * np.arange(1, len(raw) + 1, dtype=np.uint64), dtype=np.uint64)))
        plain = np.concatenate((np.zeros(1, np.uint64), np.cumsum(raw, dtype=np.uint64)))
        moment = place[ends] - place[starts] - starts.astype(np.uint64) * (plain[ends] - plain[starts])
        return common.mix64((sums[ends] - sums[starts]) * _K2 + moment * _BASE + (ends - starts).astype(np.uint64))


def gram_hashes(words: np.ndarray, k: int) -> np.ndarray:
    if len(words) < k:
        return np.zeros(0, np.uint64)
    with np.errstate(over="ignore"):
        out = np.zeros(len(words) - k + 1, np.uint64)
        for i in range(k):
            out = out * _BASE + words[i : len(words) - k + 1 + i]
        return common.mix64(out)


def winnow(hashes: np.ndarray, window: int) -> np.ndarray:
    """Places of the kept hashes: the rightmost minimum of every window."""
    n = len(hashes)
    if n == 0:
        return np.zeros(0, np.int64)
    window = min(window, n)
    best = np.arange(n - window + 1)
    for i in range(1, window):
        other = np.arange(i, n - window + 1 + i)
        best = np.where(hashes[other] <= hashes[best], other, best)
    return best[common.run_starts(best)]


@dataclass
class Block:
    """Fingerprints and words of some items, as the executors get them."""

    lengths: list[int]  # window lengths that occur
    k: int
    t: int
    prints: np.ndarray  # sorted fingerprints
    windows: dict[tuple[bytes, ...], list[int]]  # window of words -> places in ids
    ids: list[str]


def make_block(items: list[tuple[str, bytes]], t: int, k: int) -> Block:
    windows: dict[tuple[bytes, ...], list[int]] = defaultdict(list)
    prints, ids, split = [], [], []
    for item_id, text in items:
        data = text.lower()
        s, e = words_of(data)
        if len(s):
            ids.append(item_id)
            split.append((data, s, e))
    k = min([k, *(len(s) for _, s, _ in split)])
    for n, (data, s, e) in enumerate(split):
        word = [data[a:b] for a, b in zip(s.tolist(), e.tolist())]
        size = min(t, len(word))
        for i in range(len(word) - size + 1):
            at = windows[tuple(word[i : i + size])]
            if not at or at[-1] != n:
                at.append(n)
        hashes = gram_hashes(word_hashes(data, s, e), k)
        # items shorter than t are looked for by all of their grams, longer ones by their winnowed ones
        prints.append(hashes[winnow(hashes, t - k + 1)] if len(word) >= t else hashes)
    return Block(sorted({len(w) for w in windows}), k, t, np.unique(np.concatenate(prints)) if prints else np.zeros(0, np.uint64), dict(windows), ids)


def hits_of(data: bytes, block: Block) -> tuple[int, np.ndarray, set[int]]:
    """Words of a text, which of them are hit, and the items found."""
    data = data.lower()
    s, e = words_of(data)
    n = len(s)
    hit = np.zeros(n, bool)
    found: set[int] = set()
    if n == 0 or not len(block.prints):
        return n, hit, found
    hashes = gram_hashes(word_hashes(data, s, e), block.k)
    if not len(hashes):
        return n, hit, found
    # winnowed places serve the windows of t words; shorter items need every place
    at = winnow(hashes, block.t - block.k + 1) if block.lengths[0] >= block.t else np.arange(len(hashes))
    where = np.searchsorted(block.prints, hashes[at])
    where[where == len(block.prints)] = 0
    seeds = at[block.prints[where] == hashes[at]]
    if not len(seeds):
        return n, hit, found
    tried: dict[int, set[int]] = {size: set() for size in block.lengths}
    cut = lambda a, b: tuple(data[x:y] for x, y in zip(s[a:b].tolist(), e[a:b].tolist()))
    for seed in seeds.tolist():
        for size in block.lengths:
            for begin in range(max(0, seed + block.k - size), min(seed, n - size) + 1):
                if begin not in tried[size]:
                    tried[size].add(begin)
                    items = block.windows.get(cut(begin, begin + size))
                    if items:
                        hit[begin : begin + size] = True
                        found.update(items)
    return n, hit, found


_OUT = "n_words long, hit array<int>, items array<string>"


def find_leaks(docs: DataFrame, benchmark: DataFrame, *, t: int = 10, k: int = 5, block_words: int = 2_000_000, keep_text: bool = False) -> DataFrame:
    """Per row of docs: its columns (text only if wanted), n_words, hit (places of hit words), items (ids as strings, sorted).

    Columns that came in under the names n_words, hit or items are replaced."""
    spark = docs.sparkSession
    docs = common.without(docs, "n_words", "hit", "items", "__row")
    items = benchmark.where(F.col("item_id").isNotNull()).select(F.col("item_id").cast("string").alias("i"), F.coalesce("text", F.lit("")).alias("t"))
    size = items.agg(F.coalesce(F.sum(F.length("t")), F.lit(0))).first()[0]
    n_blocks = 1 + size // (block_words * 5)
    if n_blocks > 1:  # equal rows are told apart by a number, written once so that every block sees the same
        docs = common.materialize(docs.withColumn("__row", F.monotonically_increasing_id()), "numbered-texts")
    results = []
    for n in range(n_blocks):
        rows = items.where(F.pmod(F.xxhash64("i"), F.lit(n_blocks)) == n).collect() if n_blocks > 1 else items.collect()  # a block of bounded size
        block = spark.sparkContext.broadcast(make_block([(r.i, r.t.encode()) for r in rows], t, k))
        results.append(_scan(docs, block, keep_text))
    if len(results) == 1:
        return results[0]
    keys = [c for c in docs.columns if keep_text or c != "text"]
    union = results[0]
    for r in results[1:]:
        union = union.unionByName(r)
    firsts = [F.first(c).alias(c) for c in keys if c != "__row"]
    return union.groupBy("__row").agg(*firsts, F.first("n_words").alias("n_words"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("hit")))).alias("hit"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items")).drop("__row")


def _scan(docs: DataFrame, block, keep_text: bool) -> DataFrame:
    kept = [c for c in docs.columns if keep_text or c != "text"]
    fields = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in kept)

    def run(batches):
        b = block.value
        for batch in common.by_bytes(batches, lambda x: [len(v) if v else 0 for v in x.column("text").cast(pa.large_binary()).to_pylist()], _BATCH):
            texts = batch.column("text").cast(pa.large_binary()).to_pylist()
            n_words, hits, items = [], [], []
            for data in texts:
                n, hit, found = hits_of(data or b"", b)
                n_words.append(n)
                hits.append(np.flatnonzero(hit).astype(np.int32))
                items.append(sorted({b.ids[i] for i in found}))
            columns = [batch.column(c) for c in kept]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(n_words, pa.int64()), pa.array(hits, pa.list_(pa.int32())), pa.array(items, pa.list_(pa.string()))], names=[*kept, "n_words", "hit", "items"])

    return docs.mapInArrow(run, f"{fields}{', ' if fields else ''}{_OUT}")


def op3_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.documents(spark, sf_dir).select("doc_id", "text")
    found = find_leaks(docs, common.table(spark, sf_dir, "benchmark").select("item_id", "text"))
    hit = F.size("hit").cast("long")
    return found.select("doc_id", "n_words", hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"), (hit > 0).alias("contaminated"))


ORACLE = {
    "op3_decontaminate": r"""
WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
bw AS (SELECT DISTINCT item_id, least(10, len(w)) AS n, array_to_string(w[i:i + least(10, len(w)) - 1], ' ') AS g
       FROM b, unnest(range(1, greatest(len(w) - 10, 0) + 2)) AS u(i) WHERE len(w) > 0),
ns AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT doc_id, n, i, array_to_string(w[i:i + n - 1], ' ') AS g FROM d, ns, unnest(range(1, len(w) - n + 2)) AS u(i) WHERE len(w) >= n),
h AS (SELECT dw.doc_id, dw.n, dw.i, bw.item_id FROM dw JOIN bw USING (n, g)),
p AS (SELECT doc_id, count(DISTINCT j) AS n_hit FROM (SELECT DISTINCT doc_id, n, i FROM h), unnest(range(i, i + n)) AS v(j) GROUP BY doc_id),
q AS (SELECT doc_id, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS items FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS s FROM h) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
  sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN p USING (doc_id) LEFT JOIN q USING (doc_id)""",
}
