"""Token-ID output compressed by Re-Pair grammars.

Documents are ordered by id over the whole table, encoded, closed with an end id and cut into shards of a
bounded number of ids. In each shard the most frequent neighbouring ids are replaced by new symbols, again
and again, until no pair is frequent enough. Pairs never reach over the end of a document, so each document keeps a
symbol range of its own. A shard is one row of a Parquet table: ids of its documents, symbols and tokens of each
document, the rules in order, the expansion length of every rule, and the symbols.

All pairs that are frequent in a pass become rules together, instead of one at a time; of overlapping occurrences the
left one is taken. Expansion lengths make it possible to find and decode a span without decoding what precedes it.

Defined cases: null and empty texts are an end id alone; a null doc_id sorts first; rows with equal ids are
ordered by text; a text longer than a shard is a shard of its own, whole; an empty table gives no shards. Extra columns are not
written, whatever their names.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common
from .encoding import encoder_alone

_CELL_BITS = 18


def _cells(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        return ((left * np.uint32(0x9E3779B1)) ^ (right * np.uint32(0x85EBCA77) + (left >> np.uint32(7)))) * np.uint32(0xC2B2AE3D) >> np.uint32(32 - _CELL_BITS)


def frequent_pairs(x: np.ndarray, at: np.ndarray, least: int):
    """Places of pairs to replace, their pair numbers, and the pairs, of all pairs that begin at one of the places ``at`` and do
    so ``least`` times or more. Counts are exact: the pairs are sorted."""
    left, right = x[at], x[at + 1]
    key = left.astype(np.uint64) << np.uint64(32) | right
    ordered = np.sort(key)
    first = common.run_starts(ordered)
    pairs = ordered[first][np.diff(np.append(first, len(ordered))) >= least]
    if not len(pairs):
        return at[:0], at[:0], pairs
    # the number of a pair is looked up by a hash cell; pairs that share a cell with another are searched for
    table = np.full(1 << _CELL_BITS, -1, np.int32)
    own = _cells((pairs >> np.uint64(32)).astype(np.uint32), pairs.astype(np.uint32))
    table[own] = np.arange(len(pairs), dtype=np.int32)
    cell = _cells(left, right)
    number = table[cell]
    found = (number >= 0) & (pairs[number] == key)
    shared = np.zeros(1 << _CELL_BITS, bool)
    shared[own[table[own] != np.arange(len(pairs))]] = True
    rest = np.flatnonzero(shared[cell] & ~found)
    if len(rest):
        place = np.minimum(np.searchsorted(pairs, key[rest]), len(pairs) - 1)
        same = pairs[place] == key[rest]
        number[rest[same]], found[rest[same]] = place[same], True
    at, number = at[found], number[found]
    # of overlapping occurrences take every other one, from the left
    begins = np.flatnonzero(np.concatenate(([True], np.diff(at) != 1)))
    place = np.arange(len(at)) - np.repeat(begins, np.diff(np.append(begins, len(at))))
    at, number = at[place % 2 == 0], number[place % 2 == 0]
    used = np.bincount(number, minlength=len(pairs)) > 0
    return at, (np.cumsum(used) - 1)[number], pairs[used]


def compress(x: np.ndarray, ends: np.ndarray, first_rule: int, *, least: int = 16):
    """Symbols, new document ends, rules (left, right) and expansion lengths of the rules.

    ends: places of the last symbols of documents, where no pair begins. After a pass only pairs with one of its new symbols
    can have become frequent, so each pass looks at fewer places, until no pair is found."""
    x = x.astype(np.uint32)
    last = np.zeros(len(x), bool)
    last[ends] = True
    if len(x):
        last[-1] = True
    rules: list[np.ndarray] = []
    n_rules, fresh = 0, 0  # symbols from ``fresh`` on are new
    while True:
        new = x >= fresh
        new[:-1] |= new[1:].copy()
        at, number, pairs = frequent_pairs(x, np.flatnonzero(new & ~last), least)
        if not len(pairs):
            break
        fresh = first_rule + n_rules
        x[at] = (fresh + number).astype(np.uint32)
        last[at] = last[at + 1]
        keep = np.ones(len(x), bool)
        keep[at + 1] = False
        x, last = x[keep], last[keep]
        rules.append(np.stack((pairs >> np.uint64(32), pairs & np.uint64(0xFFFFFFFF)), 1).astype(np.uint32))
        n_rules += len(pairs)
    table = np.concatenate(rules) if rules else np.zeros((0, 2), np.uint32)
    return x, np.flatnonzero(last), table, lengths_of(table, first_rule)


def lengths_of(rules: np.ndarray, first_rule: int) -> np.ndarray:
    """Tokens that every rule stands for: rules of rules get their lengths once their parts have them."""
    out = np.zeros(len(rules), np.int64)
    inner, part = rules >= first_rule, np.maximum(rules.astype(np.int64) - first_rule, 0)
    while (out == 0).any():
        size = np.where(inner, out[part], 1)
        out = np.where((size > 0).all(1), size.sum(1), 0)
    return out.astype(np.int32)


class Grammar:
    """Rules made ready to decode: the expansion of every rule, one after another."""

    def __init__(self, rules: np.ndarray, lengths: np.ndarray, first_rule: int):
        self.first, self.lengths = first_rule, lengths.astype(np.int64)
        self.begin = np.concatenate(([0], np.cumsum(self.lengths)))
        flat = rules.ravel().astype(np.uint32)
        while True:  # all rules at once, one level deeper each time
            inner = flat >= first_rule
            if not inner.any():
                break
            place = np.cumsum(1 + inner) - 1 - inner
            out = np.empty(len(flat) + int(inner.sum()), np.uint32)
            out[place[~inner]] = flat[~inner]
            of = flat[inner].astype(np.int64) - first_rule
            out[place[inner]], out[place[inner] + 1] = rules[of, 0], rules[of, 1]
            flat = out
        self.flat = flat

    def sizes(self, symbols: np.ndarray) -> np.ndarray:
        if not len(self.lengths):
            return np.ones(len(symbols), np.int64)
        return np.where(symbols >= self.first, self.lengths[np.maximum(symbols.astype(np.int64) - self.first, 0)], 1)

    def expand(self, symbols: np.ndarray) -> np.ndarray:
        if not len(self.lengths) or not len(symbols):
            return symbols.astype(np.uint32)
        size = self.sizes(symbols)
        end = np.cumsum(size)
        out = np.empty(end[-1], np.uint32)
        rule = symbols >= self.first
        out[(end - size)[~rule]] = symbols[~rule]
        n = size[rule]
        source = np.repeat(self.begin[symbols[rule].astype(np.int64) - self.first], n)
        within = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        out[np.repeat((end - size)[rule], n) + within] = self.flat[source + within]
        return out

    def span(self, symbols: np.ndarray, begin: int, end: int) -> np.ndarray:
        """Tokens begin..end of the expansion, decoding only the symbols that reach into it."""
        stop = np.cumsum(self.sizes(symbols))
        first, last = np.searchsorted(stop, begin, "right"), np.searchsorted(stop, end, "left") + 1
        skipped = int(stop[first - 1]) if first else 0
        return self.expand(symbols[first:last])[begin - skipped : end - skipped]


SHARD = "part int, shard int, first_rule int, width int, doc_ids binary, doc_symbols binary, doc_tokens binary, rules binary, rule_lengths binary, symbols binary, n_tokens long"


def shard_row(part: int, shard: int, doc_ids: list, encoded: list[bytes], end_id: int, first_rule: int, **options) -> dict:
    """One row of the file format from the encoded documents of a shard."""
    tail = np.array([end_id], "<u4").tobytes()
    x = np.frombuffer(tail.join([*encoded, b""]), "<u4")
    tokens = np.array([len(e) // 4 + 1 for e in encoded], np.int64)
    symbols, ends, rules, lengths = compress(x, np.cumsum(tokens) - 1, first_rule, **options)
    width = 2 if first_rule + len(rules) <= 1 << 16 else 4
    ids = np.array([np.iinfo(np.int64).min if i is None else i for i in doc_ids], "<i8")
    return {"part": part, "shard": shard, "first_rule": first_rule, "width": width, "doc_ids": ids.tobytes(), "doc_symbols": np.diff(ends, prepend=-1).astype("<i4").tobytes(), "doc_tokens": tokens.astype("<i4").tobytes(), "rules": rules.astype("<u4").tobytes(), "rule_lengths": lengths.astype("<i4").tobytes(), "symbols": symbols.astype(f"<u{width}").tobytes(), "n_tokens": int(tokens.sum())}


def read_shard(row: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, Grammar]:
    """Ids, symbols per document, tokens per document, symbols, grammar."""
    grammar = Grammar(np.frombuffer(row["rules"], "<u4").reshape(-1, 2), np.frombuffer(row["rule_lengths"], "<i4"), row["first_rule"])
    return np.frombuffer(row["doc_ids"], "<i8"), np.frombuffer(row["doc_symbols"], "<i4"), np.frombuffer(row["doc_tokens"], "<i4"), np.frombuffer(row["symbols"], f"<u{row['width']}"), grammar


def write_shards(docs: DataFrame, path: str, tokenizer: str, *, end_id: int = 2, first_rule: int | None = None, shard_tokens: int = 1 << 20, **options) -> None:
    """Encode docs (doc_id, text) in ascending order of doc_id and write the shards as Parquet under path."""

    def run(batches):
        from pyspark import TaskContext

        enc = encoder_alone(tokenizer)
        base = max(enc.tokenizer.get_vocab_size(), end_id + 1) if first_rule is None else first_rule
        part, shard, ids, encoded, held = TaskContext.get().partitionId(), 0, [], [], 0

        def flush():
            return pa.RecordBatch.from_pylist([shard_row(part, shard, ids, encoded, end_id, base, **options)], schema)

        for batch in batches:
            for piece in common.by_bytes([batch], lambda x: pc.binary_length(x.column("text")).fill_null(0).to_pylist(), 4 << 20):
                texts = [t or "" for t in piece.column("text").to_pylist()]
                for i, e in zip(piece.column("doc_id").to_pylist(), enc.encode(texts)):
                    if held and held + len(e) // 4 >= shard_tokens:
                        yield flush()
                        shard, ids, encoded, held = shard + 1, [], [], 0
                    ids.append(i)
                    encoded.append(e)
                    held += len(e) // 4 + 1
        if ids:
            yield flush()

    fields = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary()}
    schema = pa.schema([(n, fields[t]) for n, t in (f.split() for f in SHARD.split(", "))])
    ordered = docs.select("doc_id", "text").repartitionByRange(F.col("doc_id")).sortWithinPartitions("doc_id", "text")
    ordered.mapInArrow(run, SHARD).write.parquet(path)


def read_documents(shards: DataFrame) -> DataFrame:
    """Per document, from the shards: doc_id, part, shard, at (ids before it in its shard), n_tokens, ids_crc32."""

    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                ids, per_symbols, per_tokens, symbols, grammar = read_shard(row)
                data, stop = grammar.expand(symbols).astype("<u4").tobytes(), np.cumsum(per_tokens.astype(np.int64))
                begin = stop - per_tokens
                crc = [zlib.crc32(data[a * 4 : b * 4]) for a, b in zip(begin.tolist(), stop.tolist())]
                ids = pa.array([None if i == np.iinfo(np.int64).min else i for i in ids.tolist()], pa.int64())
                n = len(ids)
                yield pa.RecordBatch.from_arrays([ids, pa.array([row["part"]] * n, pa.int32()), pa.array([row["shard"]] * n, pa.int32()), pa.array(begin, pa.int64()), pa.array(per_tokens.astype(np.int64)), pa.array(crc, pa.int64())], names=["doc_id", "part", "shard", "at", "n_tokens", "ids_crc32"])

    return shards.mapInArrow(run, "doc_id long, part int, shard int, at long, n_tokens long, ids_crc32 long")


def shard_starts(shards: DataFrame) -> DataFrame:
    """Ids before each shard. Sums within a part, then over parts: no window holds more than the shards of one part
    or one row per part."""
    sizes = shards.select("part", "shard", "n_tokens")
    within = Window.partitionBy("part").orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    parts = sizes.groupBy("part").agg(F.sum("n_tokens").alias("n"))
    over = Window.partitionBy(F.lit(0)).orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    parts = parts.select(F.col("part").alias("p"), F.coalesce(F.sum("n").over(over), F.lit(0)).alias("before_part"))
    sizes = sizes.withColumn("before", F.coalesce(F.sum("n_tokens").over(within), F.lit(0)))
    return sizes.join(parts, F.col("part") == F.col("p")).select("part", "shard", (F.col("before") + F.col("before_part")).alias("base"))


def round_trip(docs: DataFrame, tokenizer: str, *, end_id: int = 2, **options) -> DataFrame:
    """Write docs, read the files back and return what they hold per document."""
    import uuid

    spark = docs.sparkSession
    path = f"{common.shared_dir(spark)}/token-shards-{uuid.uuid4().hex}"
    write_shards(docs, path, tokenizer, end_id=end_id, **options)
    fields = [f.split() for f in SHARD.split(", ")]
    shards = spark.read.schema(", ".join(f"{n} {t}" for n, t in fields)).parquet(path)
    starts = shard_starts(shards)
    return read_documents(shards).join(starts, ["part", "shard"]).select("doc_id", (F.col("base") + F.col("at")).alias("start"), "n_tokens", "ids_crc32")


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op6_token_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return round_trip(common.documents(spark, sf_dir), default_tokenizer())


ORACLE: dict[str, str] = {}
