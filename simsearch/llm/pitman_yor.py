"""Language-model scores by a hierarchical Pitman-Yor model.

Words are dishes. Every word before (or the text's begin) is a context with a restaurant of its own, and all of them have
the same parent, the restaurant without context, whose own base is uniform over the known words and one unknown word.
Tables that a dish has in a context are customers of the parent. Seating is sampled by Gibbs sweeps: all customers of a
dish in a restaurant leave and come back one by one, with the other dishes' tables as they are. Between sweeps only
totals are exchanged (tables per context, tables per word, tables of the parent), so (word, context) pairs are independent
within a sweep and are worked on in parallel. The predictive probability is averaged over the samples.

Seating flips one coin per customer, for many dishes at once; beyond 67 million customers it draws the waiting time to the next
new table from its closed form, so a word with a billion customers costs as many steps as it has tables. A pair that was seen once has one table whatever
is drawn: such pairs enter the totals once and only the others are swept.

How rows are held. Words are named by 64 bits of a 128-bit digest (a clash is detected and stops the query) and known words
get numbers, small ones for frequent words. Texts are read once: each stretch of texts becomes a chunk with its own small
vocabulary and its texts as codes of it. The pairs of a chunk are dealt over buckets by a hash of both words, so no context
and no word is hot; what a chunk sends to a bucket is one packed row. There are as many buckets as the tokens need, about
``per_bucket`` each. A bucket asks for totals once per word and context that it holds. To score, every chunk is sent what the
buckets know of its own pairs. Tables of a step are deleted once the next is written.

Defined cases: null and empty texts are the end token alone. Unknown words get the parent's unknown mass; after a context
that was not trained on, the parent decides. With no training text every count is 0 and probabilities are uniform over the
one unknown word (score 0). Equal rows are scored alike and count as often as they are there. Ids may repeat or be null.
A text is never cut: one longer than a chunk closes the chunk that it is in. More than 2^32 distinct words stop the query. Of the table only doc_id and
text are read, so other columns may have any name.
"""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

END = b""  # no word is empty
BEGIN = b" "  # no word has a space


def names_of(words: list[bytes]) -> np.ndarray:
    """Two 64-bit numbers per word: its name, and what tells a clash of names."""
    return np.frombuffer(b"".join(hashlib.blake2b(w, digest_size=16).digest() for w in words), "<i8").reshape(-1, 2)


def pack(numbers: np.ndarray) -> bytes:
    """Whole numbers from 0 to 2^32 - 1 as four planes of bytes, deflated."""
    return zlib.compress(np.ascontiguousarray(numbers.astype("<u4").view(np.uint8).reshape(-1, 4).T).tobytes(), 3)


def unpack(packed: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(zlib.decompress(packed), np.uint8).reshape(4, -1).T).view("<u4").ravel()


def pack_keys(keys: np.ndarray) -> tuple[bytes, bytes]:
    """Ascending keys (context in the upper half, word in the lower): steps of the contexts, and the words."""
    return pack(np.diff(keys >> np.uint64(32), prepend=np.uint64(0))), pack(keys & np.uint64(0xFFFFFFFF))


def unpack_keys(steps: bytes, words: bytes) -> np.ndarray:
    return (np.cumsum(unpack(steps).astype(np.uint64), dtype=np.uint64) << np.uint64(32)) | unpack(words).astype(np.uint64)


def batch_of(schema: pa.Schema, size: int, /, **columns) -> pa.RecordBatch:
    """A batch of that many rows; columns that are not given are null."""
    return pa.RecordBatch.from_arrays([pa.array(columns[f.name], f.type) if f.name in columns else pa.nulls(size, f.type) for f in schema], schema=schema)


def groups(batches, by: str):
    """(value, table) of each run of rows with the same value of ``by``; runs may go over several batches."""
    now, held = None, []
    for batch in batches:
        ids = batch.column(by).to_numpy(zero_copy_only=False)
        edges = [*common.run_starts(ids).tolist(), len(ids)]
        for a, b in zip(edges[:-1], edges[1:]):
            if held and ids[a] != now:
                yield now, pa.Table.from_batches(held)
                held = []
            now = ids[a]
            held.append(batch.slice(a, b - a))
    if held:
        yield now, pa.Table.from_batches(held)


def united(first: DataFrame, second: DataFrame) -> DataFrame:
    return first.unionByName(second, allowMissingColumns=True)


def chunks(docs: DataFrame, chunk_bytes: int = 24 << 20) -> DataFrame:
    """One written table with two kinds of rows. Word rows, one per word of a chunk: chunk, code, id, proof, n (training
    count), followers (tokens of training texts that come after it); the text's begin is the last of them. Document
    rows, one per stretch of documents: chunk, code (their order), ids, held_out, sizes, words (codes of all their tokens)."""
    schema = pa.schema([("chunk", pa.int64()), ("code", pa.int32()), ("id", pa.int64()), ("proof", pa.int64()), ("n", pa.int64()), ("followers", pa.int64()), ("ids", pa.list_(pa.int64())), ("held_out", pa.list_(pa.bool_())), ("sizes", pa.list_(pa.int64())), ("words", pa.binary())])

    def run(batches):
        from pyspark import TaskContext

        part, serial, size = TaskContext.get().partitionId(), 0, 0
        codes: dict[bytes, int] = {}
        held: list = []  # per document: id, held_out, word codes

        def close():
            chunk, names, begin = (part << 32) + serial, names_of([*codes, BEGIN]), len(codes)
            trained = [x for x in held if not x[1]]
            n = np.bincount(np.concatenate([x[2] for x in trained]), minlength=begin + 1) if trained else np.zeros(begin + 1, np.int64)
            followers = n.copy()
            followers[begin] = len(trained)
            if END in codes:
                followers[codes[END]] = 0
            for a in range(0, len(names), 100_000):
                w = names[a : a + 100_000]
                yield batch_of(schema, len(w), chunk=np.full(len(w), chunk), code=np.arange(a, a + len(w), dtype=np.int32), id=w[:, 0].copy(), proof=w[:, 1].copy(), n=n[a : a + len(w)], followers=followers[a : a + len(w)])
            for a in range(0, len(held), 2000):
                h = held[a : a + 2000]
                yield batch_of(schema, 1, chunk=[chunk], code=[a], ids=[[x[0] for x in h]], held_out=[[x[1] for x in h]], sizes=[[len(x[2]) for x in h]], words=[pack(np.concatenate([x[2] for x in h]))])

        for batch in common.by_bytes(batches, lambda b: [len(v or "") for v in b.column("text").to_pylist()], 2 << 20):
            for doc_id, out, text in zip(batch.column("doc_id").to_pylist(), batch.column("held_out").to_pylist(), common.utf8(batch.column("text").to_pylist())):
                tokens = text.lower().split()
                tokens.append(END)
                for w in tokens:
                    if w not in codes:
                        codes[w] = len(codes)
                held.append((doc_id, out, np.fromiter(map(codes.__getitem__, tokens), np.int64, len(tokens)).astype(np.uint32)))
                size += len(text) + 64
            if size >= chunk_bytes:
                yield from close()
                codes, held, size = {}, [], 0
                serial += 1
        if held:
            yield from close()

    marked = docs.select("doc_id", "text", (common.crc_mod(F.col("doc_id"), 10) == 0).alias("held_out"))
    return common.materialize(marked.mapInArrow(run, "chunk long, code int, id long, proof long, n long, followers long, ids array<long>, held_out array<boolean>, sizes array<long>, words binary"), "lm-chunks")


def word_rows(parts: DataFrame) -> DataFrame:
    return parts.where(F.col("proof").isNotNull()).select("chunk", "code", "id", "proof", "n", "followers")


def text_rows(parts: DataFrame) -> DataFrame:
    return parts.where(F.col("words").isNotNull()).select("chunk", F.col("code").alias("at"), "ids", "held_out", "sizes", "words")


def numbered(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct keys in order, and each key's place among them; fewer and smaller arrays than ``np.unique`` makes."""
    order = np.argsort(keys)
    ordered = keys[order]
    new = np.ones(len(keys), bool)
    new[1:] = ordered[1:] != ordered[:-1]
    distinct, number = ordered[new], np.empty(len(keys), np.int32)
    del ordered
    number[order] = np.cumsum(new, dtype=np.int32) - np.int32(1)
    return distinct, number


class Texts:
    """The texts of one chunk as pairs. word, ctx: the chunk's codes of its distinct pairs. number: the pair of each
    token. sizes, ids, held_out: per document. known: pairs of known words; keys: theirs, in numbers of the model, with
    ``bucket``, in the order in which they are sent."""

    def __init__(self, rows: pa.Table, numbers: np.ndarray, buckets: int):
        rows = rows.sort_by("at")
        self.ids, self.held_out, self.sizes = (np.concatenate([np.array(x, dtype=object) for x in rows.column(c).to_pylist()]) for c in ("ids", "held_out", "sizes"))
        self.sizes = self.sizes.astype(np.int64)
        flat = np.concatenate([unpack(x) for x in rows.column("words").to_pylist()])
        begin = len(numbers) - 1
        self.begins = np.cumsum(self.sizes) - self.sizes
        pairs = flat * np.int64(begin + 1)  # the words' codes, then those before them
        flat[1:] = flat[:-1].copy()
        flat[self.begins] = begin
        pairs += flat
        del flat
        pairs, self.number = numbered(pairs)
        self.word, self.ctx = np.divmod(pairs, begin + 1)
        known = np.flatnonzero((numbers[self.word] >= 0) & (numbers[self.ctx] >= 0))
        keys = (numbers[self.ctx[known]].astype(np.uint64) << np.uint64(32)) | numbers[self.word[known]].astype(np.uint64)
        bucket = (common.mix64(keys) % np.uint64(buckets)).astype(np.int64)
        order = np.lexsort((keys, bucket))
        self.known, self.keys, self.bucket = known[order], keys[order], bucket[order]

    def counts(self) -> np.ndarray:
        """Training counts of the known pairs."""
        trained = np.repeat(~self.held_out.astype(bool), self.sizes)
        return np.bincount(self.number[trained], minlength=len(self.word))[self.known]


def numbers_of(rows: pa.Table) -> np.ndarray:
    """The model's numbers of a chunk's codes, -1 for words that it does not know."""
    numbers = np.empty(len(rows), np.int64)
    numbers[rows.column("code").to_numpy()] = rows.column("g").combine_chunks().fill_null(-1).to_numpy()
    return numbers


def log_gamma(x: np.ndarray) -> np.ndarray:
    """Stirling's series after shifting small arguments up."""
    shift = np.zeros_like(x)
    y = x.copy()
    for _ in range(8):
        low = y < 8
        shift[low] += np.log(y[low])
        y[low] += 1
    r = 1 / y
    return (y - 0.5) * np.log(y) - y + 0.9189385332046727 + r * (1 / 12 - r * r * (1 / 360 - r * r / 1260)) - shift


class Draws:
    """Uniform draws that depend on the key of a place and on how often it was asked for, not on how rows are dealt."""

    def __init__(self, keys: np.ndarray, seed: int, number: int):
        self.keys, self.turn = common.mix64(keys + np.uint64((seed << 20) + number)), 0

    def at(self, places: np.ndarray) -> np.ndarray:
        self.turn += 1
        with np.errstate(over="ignore"):
            x = common.mix64(self.keys[places] + np.uint64(self.turn) * np.uint64(0x9E3779B97F4A7C15))
        return ((x >> np.uint64(11)).astype(float) + 0.5) * 2.0**-53

    def random_at(self, places: np.ndarray, turns: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            x = common.mix64(self.keys[places] + (turns.astype(np.uint64) << np.uint64(20)) * np.uint64(0x9E3779B97F4A7C15))
        return ((x >> np.uint64(11)).astype(float) + 0.5) * 2.0**-53


def seat_by_coins(customers: np.ndarray, push: np.ndarray, discount: float, rng, at: np.ndarray, block: int = 1 << 21) -> np.ndarray:
    """Tables of the dishes ``at``, one coin per customer, all customers of a block of dishes at once.

    Customer m + 1 opens a table where the tables so far exceed a number that its coin fixes in advance. The tables before
    each customer are the least solution of that; starting from one table, repeated running sums climb to it."""
    out = np.ones(len(at), np.int64)
    large = customers[at] > block
    for i in np.flatnonzero(large):  # one dish, stretch by stretch
        for a in range(1, int(customers[at[i]]), block):
            m = np.arange(a, min(a + block, int(customers[at[i]])))
            u = rng.random_at(np.full(len(m), at[i]), m) if isinstance(rng, Draws) else rng.random(len(m))
            need, tables = (m - push[at[i]] * (1 - u) / u) / discount, np.full(len(m), float(out[i]))
            while True:
                opened = need < tables
                now = out[i] + np.cumsum(opened) - opened
                if (now == tables).all():
                    break
                tables = now
            out[i] += opened.sum()
    if large.any():
        out[~large] = seat_by_coins(customers, push, discount, rng, at[~large], block)
        return out
    ends = np.cumsum(customers[at] - 1)
    begin = 0
    while begin < len(at):
        base = ends[begin - 1] if begin else 0
        end = max(begin + 1, int(np.searchsorted(ends, base + block, "right")))
        here = np.arange(begin, end)
        size = customers[at[here]] - 1
        first = np.cumsum(size) - size
        of = np.repeat(at[here], size)
        m = np.arange(len(of)) - np.repeat(first, size) + 1
        u = rng.random_at(of, m) if isinstance(rng, Draws) else rng.random(len(of))
        need = (m - push[of] * (1 - u) / u) / discount
        tables = np.ones(len(of))
        while len(here):
            opened = need < tables
            sums = np.cumsum(opened)
            now = 1.0 + (sums - opened) - np.repeat(sums[first] - opened[first], size)
            out[here] = 1 + np.add.reduceat(opened.astype(np.int64), first)
            moving = np.maximum.reduceat(now != tables, first)
            keep = np.repeat(moving, size)
            here, size, need, tables = here[moving], size[moving], need[keep], now[keep]
            first = np.cumsum(size) - size
        begin = end
    return out


def seat(customers: np.ndarray, push: np.ndarray, discount: float, rng, coins: int = 1 << 26) -> np.ndarray:
    """Tables of each dish after all its customers have come in one by one.

    push: (strength + discount * tables of the restaurant) * parent's probability of the dish. With t tables and m seated
    customers the next one opens a table with odds push / (m - discount * t). The chance that none of the next
    ones does is a ratio of gamma functions; a uniform draw is turned into the number of customers until one does. Dishes of up
    to ``coins`` customers are seated by one coin each instead, which is faster and has the same distribution."""
    tables = (customers > 0).astype(np.int64)
    few = np.flatnonzero((customers > 1) & (customers <= coins)) if discount > 0 else np.zeros(0, np.int64)
    tables[few] = seat_by_coins(customers, push, discount, rng, few)
    at = np.flatnonzero(customers > (coins if discount > 0 else 1))
    seated = np.ones(len(at))
    while len(at):
        n, a = customers[at].astype(float), np.maximum(push[at], 1e-300)
        base = seated - discount * tables[at]
        draw = np.log(rng.at(at) if isinstance(rng, Draws) else rng.random(len(at)))
        whole = lambda j: log_gamma(base + j) - log_gamma(base) - log_gamma(base + j + a) + log_gamma(base + a)
        left = n - seated
        end = whole(left)
        more = end < draw  # some of the remaining customers opens a table
        at, seated, base, draw, a, left = at[more], seated[more], base[more], draw[more], a[more], left[more]
        low, high = np.zeros(len(at)), left.copy()
        while True:
            open_ = high - low > 1
            if not open_.any():
                break
            middle = np.floor((low + high) / 2)
            under = log_gamma(base + middle) - log_gamma(base) - log_gamma(base + middle + a) + log_gamma(base + a) < draw
            high = np.where(open_ & under, middle, high)
            low = np.where(open_ & ~under, middle, low)
        tables[at] += 1
        seated = seated + high
        go = seated < customers[at]
        at, seated = at[go], seated[go]
    return tables


class Model:
    """Written tables of a fitted model. codes: chunk, code, g (the word's number). blocks: what chunks sent to buckets.
    seating: per bucket the packed pairs seen more than once with tables t (last sweep) and total (over the samples).
    words: g, id, n, followers (its customers as a context), p<j> (the parent's probability), k<j> (its tables as a context)."""

    def __init__(self, strength: float, discount: float, samples: int):
        self.strength, self.discount, self.samples = strength, discount, samples
        self.codes = self.blocks = self.seating = self.words = None
        self.known = self.tokens = 0
        self.buckets = 1
        self.unknown: list[float] = []  # the parent's probability of the unknown word, per sample


def number_words(parts: DataFrame, m: Model, per_part: int = 100_000) -> DataFrame:
    """id, g, n, followers of the words of training texts and of the text's begin. Numbers are dealt within parts by falling
    counts, so frequent words have small ones."""
    counted = word_rows(parts).groupBy("id").agg(F.sum("n").alias("n"), F.sum("followers").alias("followers"), (F.min("proof") != F.max("proof")).alias("clash"))
    counted = common.materialize(counted.where("n > 0 or followers > 0 or clash"), "lm-counted")
    first = counted.agg(F.count(F.lit(1)).alias("rows"), F.count_if(F.col("n") > 0).alias("known"), F.sum("n").alias("tokens"), F.max("clash").alias("clash")).first()
    if first.clash:
        raise ValueError("two words have the same 64-bit name")
    spread = first.rows // per_part + 1
    m.known, m.tokens = first.known, first.tokens or 0
    part = F.pmod(F.col("id"), F.lit(spread))
    rank = F.row_number().over(Window.partitionBy(part).orderBy(F.desc(F.col("n") + F.col("followers")), "id"))
    numbered = common.materialize(counted.select("id", ((rank - 1) * spread + part).cast("long").alias("g"), "n", "followers"), "lm-numbered")
    if (numbered.agg(F.max("g")).first()[0] or 0) >= 1 << 32:
        raise ValueError("more than 2^32 words")
    common.discard(counted)
    return numbered


def send_pairs(parts: DataFrame, m: Model) -> DataFrame:
    """Per chunk and bucket one row: bucket, chunk, steps and dishes (packed keys), n (packed training counts)."""
    buckets = m.buckets
    schema = pa.schema([("bucket", pa.int64()), ("chunk", pa.int64()), ("steps", pa.binary()), ("dishes", pa.binary()), ("n", pa.binary())])

    def run(words: pa.Table, rows: pa.Table) -> pa.Table:
        texts = Texts(rows, numbers_of(words), buckets)
        n, edges, out = texts.counts(), [*common.run_starts(texts.bucket).tolist(), len(texts.bucket)], []
        for a, b in zip(edges[:-1], edges[1:]):
            steps, dishes = pack_keys(texts.keys[a:b])
            out.append(batch_of(schema, 1, bucket=texts.bucket[a : a + 1], chunk=rows.column("chunk")[:1].to_pylist(), steps=[steps], dishes=[dishes], n=[pack(n[a:b])]))
        return pa.Table.from_batches(out, schema)

    both = m.codes.groupBy("chunk").cogroup(text_rows(parts).groupBy("chunk"))
    return common.materialize(both.applyInArrow(run, "bucket long, chunk long, steps binary, dishes binary, n binary"), "lm-blocks")


def merged(rows: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Ascending keys of a bucket's trained pairs, and their counts over all chunks."""
    keys, n = [], []
    for steps, dishes, count in zip(*(rows.column(c).to_pylist() for c in ("steps", "dishes", "n"))):
        here = unpack(count)
        keys.append(unpack_keys(steps, dishes)[here > 0])
        n.append(here[here > 0].astype(np.int64))
    keys, n = np.concatenate(keys), np.concatenate(n)
    order = np.argsort(keys)
    keys, n = keys[order], n[order]
    first = common.run_starts(keys)
    return keys[first], np.add.reduceat(n, first) if len(first) else n


STATE = "bucket long, steps binary, dishes binary, n binary, t binary, total binary, g long, as_ctx long, as_word long, asked boolean"
STATE_SCHEMA = pa.schema([("bucket", pa.int64()), ("steps", pa.binary()), ("dishes", pa.binary()), ("n", pa.binary()), ("t", pa.binary()), ("total", pa.binary()), ("g", pa.int64()), ("as_ctx", pa.int64()), ("as_word", pa.int64()), ("asked", pa.bool_())])


def state_rows(bucket: int, keys: np.ndarray, n: np.ndarray, t: np.ndarray, total: np.ndarray, sums: dict[str, np.ndarray], asked: np.ndarray | None):
    """One row with the packed pairs of a bucket, then one per word number with the tables it adds as context and as word."""
    steps, dishes = pack_keys(keys)
    yield batch_of(STATE_SCHEMA, 1, bucket=[bucket], steps=[steps], dishes=[dishes], n=[pack(n)], t=[pack(t)], total=[pack(total)])
    size = len(sums["g"])
    for a in range(0, size, 100_000):
        b = min(size, a + 100_000)
        more = {} if asked is None else {"asked": asked[a:b]}
        yield batch_of(STATE_SCHEMA, b - a, bucket=np.full(b - a, bucket), **{c: v[a:b] for c, v in sums.items()}, **more)


def tables_by_word(keys: np.ndarray, t: np.ndarray) -> dict[str, np.ndarray]:
    ctx, word = (keys >> np.uint64(32)).astype(np.int64), (keys & np.uint64(0xFFFFFFFF)).astype(np.int64)
    g, at = np.unique(np.concatenate((ctx, word)), return_inverse=True)
    count = lambda which: np.bincount(which, weights=t, minlength=len(g)).astype(np.int64)
    return {"g": g, "as_ctx": count(at[: len(keys)]), "as_word": count(at[len(keys) :])}


def first_seating(blocks: DataFrame) -> DataFrame:
    """Every pair at one table. The packed rows hold the pairs seen more than once; the sums count all pairs seen once."""

    def run(batches):
        for bucket, rows in groups(batches, "bucket"):
            keys, n = merged(rows)
            more = n > 1
            sums = tables_by_word(keys, n == 1)
            asked = np.isin(sums["g"], tables_by_word(keys[more], n[more])["g"])
            one = np.ones(int(more.sum()), np.int64)
            yield from state_rows(bucket, keys[more], n[more], one, 0 * one, sums, asked)

    dealt = blocks.repartition("bucket").sortWithinPartitions("bucket")
    return common.materialize(dealt.mapInArrow(run, STATE), "lm-seating")


def sweep_pairs(state: DataFrame, answers: DataFrame, m: Model, seed: int, number: int, keep: bool) -> DataFrame:
    """Seat the packed pairs anew. answers: bucket, g, p (the parent's probability), pull (of the context)."""
    discount = m.discount
    packed = state.where("steps is not null").select("bucket", "steps", "dishes", "n", "t", "total")
    both = united(packed, answers).repartition("bucket").sortWithinPartitions("bucket")

    def run(batches):
        for bucket, rows in groups(batches, "bucket"):
            told = rows.filter(rows.column("p").is_valid()).sort_by("g")
            g, p, pull = (told.column(c).to_numpy() for c in ("g", "p", "pull"))
            row = rows.filter(rows.column("steps").is_valid()).to_pylist()[0]
            keys, n, total = unpack_keys(row["steps"], row["dishes"]), unpack(row["n"]).astype(np.int64), unpack(row["total"]).astype(np.int64)
            ctx, word = (keys >> np.uint64(32)).astype(np.int64), (keys & np.uint64(0xFFFFFFFF)).astype(np.int64)
            t = seat(n, pull[np.searchsorted(g, ctx)] * p[np.searchsorted(g, word)], discount, Draws(common.mix64(keys), seed, number))
            yield from state_rows(bucket, keys, n, t, total + t * keep, tables_by_word(keys, t), None)

    return common.materialize(both.mapInArrow(run, STATE), "lm-seating")


def seat_parent(rows: DataFrame, discount: float, seed: int, number: int) -> DataFrame:
    """rows with r, the tables of each word in the parent, drawn anew; customers are ``tables``, the column push goes."""
    keep = [c for c in rows.columns if c != "push"]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema if f.name != "push")

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            value = lambda c: batch.column(c).to_numpy(zero_copy_only=False)
            r = seat(value("tables"), value("push"), discount, Draws(value("id").view(np.uint64), seed, number))
            yield pa.RecordBatch.from_arrays([pa.array(r) if c == "r" else batch.column(c) for c in keep], names=keep)

    return rows.mapInArrow(run, schema)


def fit(parts: DataFrame, *, burn_in: int = 1, samples: int = 2, strength: float = 1.0, discount: float = 0.5, seed: int = 1, per_bucket: int = 2_000_000) -> Model:
    """Count all pairs, seat them, sweep, and keep the seatings of the last sweeps."""
    m, s, d = Model(strength, discount, samples), strength, discount
    numbered = number_words(parts, m)
    m.buckets = m.tokens // per_bucket + 1
    m.codes = common.materialize(word_rows(parts).select("chunk", "code", "id").join(numbered.select("id", "g"), "id", "left").select("chunk", "code", "g"), "lm-codes")
    common.release(parts.sparkSession)
    m.blocks = send_pairs(parts, m)
    common.release(parts.sparkSession)
    state = first_seating(m.blocks)
    sums = state.where("g is not null").groupBy("g").agg(F.sum("as_ctx").alias("once_ctx"), F.sum("as_word").alias("once_word"))
    zero = lambda c: F.coalesce(c, F.lit(0)).alias(c)
    # pairs seen more than once start with one table each
    packed = state.where("steps is not null").select("bucket", "steps", "dishes", "t")

    def start(batches):
        for batch in batches:
            for row in batch.to_pylist():
                found = tables_by_word(unpack_keys(row["steps"], row["dishes"]), unpack(row["t"]))
                yield pa.RecordBatch.from_arrays([pa.array(found[c]) for c in ("g", "as_ctx", "as_word")], names=["g", "as_ctx", "as_word"])

    begun = packed.mapInArrow(start, "g long, as_ctx long, as_word long").groupBy("g").agg(F.sum("as_ctx").alias("as_ctx"), F.sum("as_word").alias("as_word"))
    base = numbered.join(sums, "g", "left").select("g", "id", "n", "followers", zero("once_ctx"), zero("once_word"))

    def with_tables(words, found):
        filled = words.join(found, "g", "left")
        kept = [c for c in words.columns if c not in ("ctx_tables", "tables", "r")]
        r = F.col("r") if "r" in words.columns else (F.col("n") > 0).cast("long").alias("r")
        plus = lambda a, b, c: (F.col(a) + F.coalesce(b, F.lit(0))).alias(c)
        return filled.select(*kept, plus("once_ctx", "as_ctx", "ctx_tables"), plus("once_word", "as_word", "tables"), r)

    words = common.materialize(with_tables(base, begun), "lm-parent")
    requests = common.materialize(state.where("asked").select("bucket", "g"), "lm-requests")
    state_now = common.materialize(state.where("steps is not null"), "lm-seating")
    common.discard(state, numbered)
    state = state_now

    def totals():
        row = words.agg(F.coalesce(F.sum("tables"), F.lit(0)).alias("t"), F.coalesce(F.sum("r"), F.lit(0)).alias("r")).first()
        return row.t, row.r

    def parent(t, r):
        return (F.greatest(F.col("tables") - d * F.col("r"), F.lit(0.0)) + (s + d * r) / (m.known + 1)) / (s + t)

    t_all, r_all = totals()
    for number in range(1, burn_in + samples + 1):
        told = requests.join(words.select("g", parent(t_all, r_all).alias("p"), (s + d * F.col("ctx_tables")).alias("pull")), "g").select("bucket", "g", "p", "pull")
        after = sweep_pairs(state, told, m, seed, number, number > burn_in)
        common.discard(state)
        state = after
        found = state.where("g is not null").groupBy("g").agg(F.sum("as_ctx").alias("as_ctx"), F.sum("as_word").alias("as_word"))
        filled = with_tables(words, found).withColumn("push", F.lit((s + d * r_all) / (m.known + 1)))
        after = common.materialize(seat_parent(filled, d, seed, number), "lm-parent")
        common.discard(words)
        words = after
        t_all, r_all = totals()
        if number > burn_in:
            j, u = number - burn_in - 1, (s + d * r_all) / (m.known + 1) / (s + t_all)
            # the text's begin is a context but no word
            p = F.when(F.col("n") > 0, parent(t_all, r_all)).otherwise(F.lit(u))
            after = common.materialize(words.withColumn(f"p{j}", p).withColumn(f"k{j}", F.col("ctx_tables")), "lm-parent")
            common.discard(words)
            words = after
            m.unknown.append(u)
    common.discard(requests)
    m.seating, m.words = state, words
    return m


def answers(m: Model) -> DataFrame:
    """Per block: chunk, bucket, n and total (packed), the training count of each of its pairs and its tables over all samples."""
    schema, samples = pa.schema([("chunk", pa.int64()), ("bucket", pa.int64()), ("n", pa.binary()), ("total", pa.binary())]), m.samples
    packed = m.seating.where("steps is not null").select("bucket", F.col("steps").alias("s"), F.col("dishes").alias("w"), "total")
    both = united(m.blocks, packed).repartition("bucket").sortWithinPartitions("bucket")

    def run(batches):
        for bucket, rows in groups(batches, "bucket"):
            blocks = rows.filter(rows.column("chunk").is_valid())
            keys, n = merged(blocks)
            state = rows.filter(rows.column("s").is_valid()).to_pylist()[0]
            total = np.full(len(keys), samples)
            total[np.searchsorted(keys, unpack_keys(state["s"], state["w"]))] = unpack(state["total"])
            for chunk, steps, dishes in zip(*(blocks.column(c).to_pylist() for c in ("chunk", "steps", "dishes"))):
                asked = unpack_keys(steps, dishes)
                at = np.minimum(np.searchsorted(keys, asked), max(len(keys) - 1, 0))
                there = keys[at] == asked if len(keys) else np.zeros(len(asked), bool)
                take = lambda v: np.where(there, v[at], 0) if len(keys) else np.zeros(len(asked), np.int64)
                yield batch_of(schema, 1, chunk=[chunk], bucket=[bucket], n=[pack(take(n))], total=[pack(take(total))])

    return common.materialize(both.mapInArrow(run, "chunk long, bucket long, n binary, total binary"), "lm-answers")


def score_chunks(parts: DataFrame, found: DataFrame, m: Model) -> DataFrame:
    """Per document: doc_id, held_out, n_tokens, n_known, base_score, score."""
    strength, discount, known, total, js, buckets, unknown = m.strength, m.discount, m.known, m.tokens, range(m.samples), m.buckets, m.unknown
    facts = ["followers", *[f"{k}{j}" for j in js for k in ("p", "k")]]
    asked = m.codes.join(m.words.select("g", F.col("n").alias("c"), *facts), "g", "left")
    schema = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64())])

    def run(of_words: pa.Table, rows: pa.Table) -> pa.Table:
        texts = Texts(rows.filter(rows.column("words").is_valid()), numbers_of(of_words), buckets)
        of_words = of_words.sort_by("code")
        value = lambda c, missing=0: of_words.column(c).combine_chunks().fill_null(missing).to_numpy()
        told = rows.filter(rows.column("bucket").is_valid()).sort_by("bucket")
        own = np.zeros(len(texts.word))
        if len(told):
            n, tables = (np.concatenate([unpack(x) for x in told.column(c).to_pylist()]) for c in ("n", "total"))
            own[texts.known] = n - discount * tables / len(js)
        for j in js:
            own += (strength + discount * value(f"k{j}")[texts.ctx]) * value(f"p{j}", unknown[j])[texts.word] / len(js)
        lp = np.log10(own / (strength + value("followers")[texts.ctx]))
        c, number = value("c"), texts.number
        base = np.log10((c + 0.1) / (total + 0.1 * (known + 1)))
        sums = [np.add.reduceat(v[number], texts.begins) for v in ((c > 0).astype(np.int64)[texts.word], base[texts.word], lp)]
        return pa.Table.from_batches([batch_of(schema, len(texts.ids), doc_id=texts.ids.tolist(), held_out=texts.held_out.tolist(), n_tokens=texts.sizes, n_known=sums[0], base_score=sums[1], score=sums[2])])

    both = asked.groupBy("chunk").cogroup(united(text_rows(parts), found).groupBy("chunk"))
    return both.applyInArrow(run, "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, score double")


def op4_pitman_yor(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = chunks(common.documents(spark, sf_dir).select("doc_id", "text"))
    m = fit(parts)
    found = answers(m)
    common.discard(m.blocks, m.seating)
    scored = score_chunks(parts, found, m)
    return scored.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(m.tokens).cast("long").alias("train_tokens"), "base_score", "score")


def perplexity(scored: DataFrame) -> DataFrame:
    """Per word perplexity of held-out and training texts, of the model and of the base."""
    of = lambda c: F.pow(F.lit(10.0), -F.sum(c) / F.sum("n_tokens"))
    return scored.groupBy("held_out").agg(of("score").alias("perplexity"), of("base_score").alias("base_perplexity"))


ORACLE: dict[str, str] = {}
