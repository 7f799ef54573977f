"""Similarity join of documents on word shingles by PartEnum signatures.

Sets are sorted into bands of sizes such that a set can only be similar to sets of its own or the next band. For each
band a bound on the size of the symmetric difference follows from the similarity. The domain of shingles is cut into
groups, so many that similar sets differ at most ``spared`` times in one of them; each group is cut into ``parts``, and every
choice of parts that leaves ``spared`` of them out makes a signature. Similar sets agree on at least one, so no link is lost.
With the usual 3 parts of which one is spared a set has about 1.5 signatures per allowed difference; more parts and more
spared ones make signatures of more shingles, hence fewer chance meetings, and more of them: for corpora far larger than this.

Equal sets are one class, found by a 128-bit digest, and only classes take part in the join. Classes that share a signature
are first compared with the smallest of them; those comparisons make components. Only classes which then still lie in
different components are compared with each other, as only they can change the components. Sizes and parity bitmaps
(the xor of two bitmaps never has more bits than the sets have differences) drop pairs without error; the rest
is decided on the sets themselves.

A signature that very many classes share is no single task's burden: classes of one task that share it are tied to the
smallest of them there, and only that one goes on under the signature.

Defined cases: null and empty texts, and texts without words, have an empty set and are alone. Texts with fewer words
than a shingle are one shingle, unlike any other length. A null doc_id takes part and gets the smallest id of its
component. Equal rows are one class. Texts are worked on in pieces of some MB, a longer one on its own, whole. Columns beside
doc_id and text are not read. An empty table gives no rows.
"""

from __future__ import annotations

from itertools import combinations
from math import floor

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .components import components

_B = 0x9E3779B97F4A7C15 | 1
_BI = pow(_B, -1, 1 << 64)
_BLANK = np.zeros(256, bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True
_CODE = common.mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95))
_powers: dict[str, np.ndarray] = {}
BITMAPS = 16
#: Bytes of text that are worked on at once: arrays of some 60 bytes a byte are made of them.
_PIECE = 1 << 20


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse, up to n."""
    if not len(_powers) or len(_powers["up"]) < n:
        size = max(n, 1 << 20)
        with np.errstate(over="ignore"):
            for name, base in (("up", _B), ("down", _BI)):
                x = np.full(size, base, np.uint64)
                x[0] = 1
                _powers[name] = np.cumprod(x, dtype=np.uint64)
    return _powers["up"], _powers["down"]


def word_hashes(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Begins of the words between white space, and their 64-bit hashes: polynomials in the bytes' random codes, mixed."""
    raw = np.frombuffer(data, np.uint8)
    inside = np.zeros(len(raw) + 2, np.int8)
    inside[1:-1] = ~_BLANK[raw]
    step = np.diff(inside)
    starts, ends = np.flatnonzero(step == 1), np.flatnonzero(step == -1)
    up, down = powers(len(raw) + 1)
    with np.errstate(over="ignore"):
        sums = np.zeros(len(raw) + 1, np.uint64)
        np.cumsum(_CODE[raw] * up[: len(raw)], dtype=np.uint64, out=sums[1:])
        return starts, common.mix64((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(np.uint64))


def _windows(words: np.ndarray, at: np.ndarray, size: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        out = np.full(len(at), size, np.uint64) * np.uint64(0x2545F4914F6CDD1D)
        for i in range(size):
            out = common.mix64(out * np.uint64(0x9FB21C651E98DF25) + words[at + i])
    return out


class Sets:
    """Sorted distinct hashes of the shingles of several texts, one after another; edges: where each text's begin and end."""

    def __init__(self, texts: list[bytes], n: int):
        starts, words = word_hashes(b"\n".join([*texts, b""]).lower())
        stop = np.cumsum(np.array([len(t) + 1 for t in texts], np.int64))
        count = np.diff(np.searchsorted(starts, stop), prepend=0)
        first = np.cumsum(count) - count
        size = np.where(count >= n, count - n + 1, np.minimum(count, 1))
        edges = np.concatenate(([0], np.cumsum(size)))
        at = np.repeat(first - edges[:-1], size) + np.arange(edges[-1])
        full = np.repeat(count >= n, size)
        found = np.empty(edges[-1], np.uint64)
        found[full] = _windows(words, at[full], n)
        for i in np.flatnonzero((count > 0) & (count < n)).tolist():  # a text of fewer words is one shingle
            found[edges[i]] = _windows(words, first[i : i + 1], int(count[i]))[0]
        for x, y in zip(edges[:-1].tolist(), edges[1:].tolist()):
            found[x:y].sort()
        new = np.ones(len(found), bool)
        new[1:] = found[1:] != found[:-1]
        new[edges[:-1][size > 0]] = True
        self.hashes, self.edges = found[new], np.concatenate(([0], np.cumsum(new)))[edges]
        self.size = np.diff(self.edges)
        self.of = np.repeat(np.arange(len(texts)), self.size)

    def __getitem__(self, i: int) -> np.ndarray:
        return self.hashes[self.edges[i] : self.edges[i + 1]]

    def sums(self, values: np.ndarray) -> np.ndarray:
        """Sums modulo 2^64 of a value per hash."""
        total = np.zeros(len(values) + 1, np.uint64)
        with np.errstate(over="ignore"):
            np.cumsum(values, dtype=np.uint64, out=total[1:])
            return total[self.edges[1:]] - total[self.edges[:-1]]

    def digests(self) -> tuple[np.ndarray, np.ndarray]:
        """Two 64-bit halves of every set's digest."""
        return tuple(self.sums(common.mix64(self.hashes ^ np.uint64(x))).view(np.int64) for x in (0, 0xA5A5A5A5A5A5A5A5))

    def parities(self) -> np.ndarray:
        """Parity bitmaps, one row of 64-bit numbers per set."""
        bit = (common.mix64(self.hashes ^ np.uint64(0x1234567)) % np.uint64(64 * BITMAPS)).astype(np.int64)
        bits = np.bincount(self.of * (64 * BITMAPS) + bit, minlength=len(self.size) * 64 * BITMAPS) & 1
        return np.packbits(bits.astype(np.uint8), bitorder="little").view(np.int64).reshape(-1, BITMAPS)


def histogram(hashes: np.ndarray, cells: int = 1024) -> bytes:
    """How many hashes fall into each cell, 255 at most: the differences of two histograms never add up to more than the
    sets have differences. Unlike parities they tell large sets apart."""
    cell = (common.mix64(hashes ^ np.uint64(0x7654321)) % np.uint64(cells)).astype(np.int64)
    return np.minimum(np.bincount(cell, minlength=cells), 255).astype(np.uint8).tobytes()


def shingles(text: bytes, n: int) -> np.ndarray:
    return Sets([text], n).hashes


class Bands:
    """Bands of set sizes for a similarity in per cent, and what differences they allow."""

    def __init__(self, percent: int, parts: int = 3, spared: int = 1):
        if not 0 < spared < parts:
            raise ValueError("need 0 < spared < parts")
        self.percent, self.parts, self.spared = percent, parts, spared
        self.last: list[int] = []  # largest size of each band

    def bands(self, sizes: np.ndarray) -> np.ndarray:
        while not self.last or self.last[-1] < sizes.max(initial=1):
            first = self.last[-1] + 1 if self.last else 1
            self.last.append(first * 100 // self.percent)
        return np.searchsorted(self.last, sizes)

    def differences(self, band: int) -> int:
        while len(self.last) <= band:
            self.bands(np.array([self.last[-1] + 1 if self.last else 1]))
        return floor((100 - self.percent) * 2 * self.last[band] / (100 + self.percent))

    def signatures(self, sets: Sets, chosen: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Signatures of the chosen sets in the instance of their own band and in that of the next, and whose they are."""
        own = self.bands(sets.size)
        low, high = ((sets.hashes & np.uint64(0xFFFFFFFF)).astype(np.float64), (sets.hashes >> np.uint64(32)).astype(np.float64))
        spread = common.mix64(sets.hashes ^ np.uint64(0x5851F42D4C957F2D))
        chosen = chosen & (sets.size > 0)
        out, whose = [], []
        for instance in (own, own + 1):
            allowed = np.array([self.differences(i) for i in range(int(instance.max(initial=0)) + 1)], np.int64)[instance]
            # without any difference only equal sets are similar, which are one class already
            groups = np.where(chosen & (allowed > 0), allowed // (self.spared + 1) + 1, 0)
            cells = groups * self.parts
            base, use = np.cumsum(cells) - cells, groups[sets.of] > 0
            of = sets.of[use]
            cell = base[of] + (spread[use] % cells[of].astype(np.uint64)).astype(np.int64)
            # sums of 32-bit halves are exact in doubles
            a, b = (np.bincount(cell, w[use], cells.sum()).astype(np.uint64) for w in (low, high))
            mine = np.repeat(np.arange(len(groups)), groups)
            number = (np.arange(len(mine)) - np.repeat(np.cumsum(groups) - groups, groups)).astype(np.uint64)
            band = instance[mine].astype(np.uint64)
            with np.errstate(over="ignore"):
                whole = common.mix64(common.mix64(a + np.repeat(band, self.parts)) * np.uint64(_B) + b).reshape(-1, self.parts)
                for n, kept in enumerate(combinations(range(self.parts), self.parts - self.spared)):
                    sig = (number << np.uint64(8)) + (band << np.uint64(40)) + np.uint64(n)
                    for part in kept:
                        sig = common.mix64(sig * np.uint64(_B) + whole[:, part])
                    out.append(sig)
                    whose.append(mine)
        return np.concatenate(out).view(np.int64), np.concatenate(whose)


def pieces(batches):
    """Batches of bounded text and of at most some thousand rows (bitmaps are made for all rows of a piece)."""
    common.give_back()
    return common.by_bytes(batches, lambda b: [max(n, _PIECE >> 10) for n in pc.binary_length(b.column("text")).fill_null(0).to_pylist()], _PIECE)


def text_key():
    """64 bits by which rows of one id are told apart."""
    return F.xxhash64(F.col("text").isNull(), F.col("text"))


def profiles(docs: DataFrame, n: int) -> DataFrame:
    """Per row: doc_id, t (key of its text), n, the digest of its set, the set's parity bitmaps."""

    def run(batches):
        for batch in pieces(batches):
            sets = Sets(common.utf8(batch.column("text").to_pylist()), n)
            bits = sets.parities()
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").cast(pa.int64()), batch.column("t"), pa.array(sets.size), *map(pa.array, sets.digests()), *(pa.array(np.ascontiguousarray(bits[:, i])) for i in range(BITMAPS))], names=["doc_id", "t", "n", "d1", "d2", *(f"p{i}" for i in range(BITMAPS))])

    return docs.select("doc_id", "text", text_key().alias("t")).mapInArrow(run, "doc_id long, t long, n long, d1 long, d2 long, " + ", ".join(f"p{i} long" for i in range(BITMAPS)))


_PAIRS = "sig long, cls long, low long"


def _shared(sig, cls, low) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(sig), pa.array(cls), pa.array(low)], names=["sig", "cls", "low"])


def signature_rows(docs: DataFrame, n: int, bands: Bands, part: int, slices: int, flush_rows: int = 1_000_000) -> DataFrame:
    """(sig, cls, low) of the signatures in one of several slices of their values; cls is a class by its digest's first half.

    Among the rows that a task holds at a time, classes that share a signature are tied to the smallest of them (low) already;
    only that one goes on alone (low is null), to meet those of other tasks."""

    def run(batches):
        seen: set = set()
        held, size = [], 0

        def flush():
            sig, cls = (np.concatenate(x) for x in zip(*held))
            order = np.lexsort((cls, sig))
            sig, cls = sig[order], cls[order]
            first = common.run_starts(sig)
            many = np.diff(np.append(first, len(sig)))
            yield pa.RecordBatch.from_arrays([pa.array(sig[first]), pa.array(cls[first]), pa.nulls(len(first), pa.int64())], names=["sig", "cls", "low"])
            several = np.repeat(many > 1, many)
            yield _shared(sig[several], cls[several], np.repeat(cls[first], many)[several])

        for batch in pieces(batches):
            sets = Sets(common.utf8(batch.column("text").to_pylist()), n)
            names = sets.digests()[0]
            fresh = np.zeros(len(names), bool)
            for i, name in enumerate(names.tolist()):
                if name not in seen:  # a copy in the same task adds nothing
                    seen.add(name)
                    fresh[i] = True
            sig, whose = bands.signatures(sets, fresh)
            if slices > 1:
                mine = sig.view(np.uint64) % np.uint64(slices) == part
                sig, whose = sig[mine], whose[mine]
            held.append((sig, names[whose]))
            size += len(sig)
            if size >= flush_rows:
                yield from flush()
                held, size = [], 0
            if len(seen) > 200_000:
                seen.clear()
        if size:
            yield from flush()
        held.clear()
        common.give_back()

    return docs.select("text").mapInArrow(run, _PAIRS)


def members(rows: DataFrame) -> DataFrame:
    """(sig, cls, low) of signatures that several classes have, from ``signature_rows``: one shuffle, then one pass over
    the rows in order. Rows that were tied before are dealt out evenly."""

    def run(batches):
        alone = np.zeros((2, 0), np.int64)  # the last signature, if it had one class so far
        known = None  # the last signature and its smallest class, if it had several
        common.give_back()
        for batch in batches:
            tied = batch.column("low").is_valid().to_numpy(zero_copy_only=False)
            sig, cls = (batch.column(c).to_numpy() for c in ("sig", "cls"))
            if tied.any():
                yield _shared(sig[tied], cls[tied], batch.column("low").filter(pa.array(tied)).to_numpy())
            sig, cls = np.concatenate((alone[0], sig[~tied])), np.concatenate((alone[1], cls[~tied]))
            if not len(sig):
                continue
            new = np.ones(len(sig), bool)
            new[1:] = (sig[1:] != sig[:-1]) | (cls[1:] != cls[:-1])
            sig, cls = sig[new], cls[new]
            first = common.run_starts(sig)
            many = np.diff(np.append(first, len(sig)))
            low, several = cls[first].copy(), many > 1
            if known and sig[0] == known[0]:
                low[0], several[0] = known[1], True
            keep = np.repeat(several, many)
            yield _shared(sig[keep], cls[keep], np.repeat(low, many)[keep])
            alone = np.zeros((2, 0), np.int64) if several[-1] else np.stack((sig[-1:], cls[-1:]))
            known = (sig[-1], low[-1]) if several[-1] else None

    key = F.when(F.col("low").isNull(), F.col("sig")).otherwise(F.xxhash64("sig", "cls"))
    return rows.repartition(key).sortWithinPartitions("sig", "cls").mapInArrow(run, _PAIRS)


def sided(rows: DataFrame, side: str) -> DataFrame:
    return rows.select(*[F.col(c).alias(f"{side}_{c}") for c in rows.columns])


def may_be_similar(percent: int):
    """Of two sides l_ and r_: true unless sizes or parity bitmaps prove that the sets are not similar."""
    differ = sum((F.bit_count(F.col(f"l_p{i}").bitwiseXOR(F.col(f"r_p{i}"))) for i in range(1, BITMAPS)), F.bit_count(F.col("l_p0").bitwiseXOR(F.col("r_p0"))))
    sizes = F.least("l_n", "r_n") * 100 >= F.greatest("l_n", "r_n") * percent
    return sizes & (differ * (100 + percent) <= (F.col("l_n") + F.col("r_n")) * (100 - percent))


def similar_pairs(pairs: DataFrame, classes: DataFrame, docs: DataFrame, n: int, percent: int) -> DataFrame:
    """Those of pairs (a, b) of classes whose sets are similar, by their whole sets.

    Sizes and parity bitmaps first, then histograms: all only drop pairs that cannot be similar."""
    small = classes.select("cls", "n", *[f"p{i}" for i in range(BITMAPS)])
    both = pairs.join(sided(small, "l"), F.col("a") == F.col("l_cls")).join(sided(small, "r"), F.col("b") == F.col("r_cls")).where(may_be_similar(percent))
    both = common.materialize(both.select("a", "b"), "pairs")
    wanted = common.materialize(both.select(F.col("a").alias("cls")).union(both.select("b")).distinct().join(classes.select("cls", "rep"), "cls"), "wanted")

    def sets(batches):
        for batch in pieces(batches):
            found = Sets(common.utf8(batch.column("text").to_pylist()), n)
            yield pa.RecordBatch.from_arrays([pa.array(found.digests()[0]), pa.array(found.size), pa.array([histogram(found[i]) for i in range(batch.num_rows)], pa.binary()), pa.array([found[i].astype("<u8").tobytes() for i in range(batch.num_rows)], pa.binary())], names=["cls", "n", "h", "s"])

    # ids may repeat or be null: a set's own digest says of which class it is
    texts = docs.select("doc_id", "text").join(wanted.select("rep").distinct(), F.col("doc_id").eqNullSafe(F.col("rep")), "left_semi").select("text")
    found = texts.mapInArrow(sets, "cls long, n long, h binary, s binary").join(wanted.select("cls"), "cls", "left_semi")
    held = common.materialize(found.dropDuplicates(["cls"]), "sets")

    def near(m, n, x, y):
        x, y = np.frombuffer(x.as_buffer(), np.uint8), np.frombuffer(y.as_buffer(), np.uint8)
        return int(np.abs(x.astype(np.int16) - y).sum()) * (100 + percent) <= (m + n) * (100 - percent)

    def similar(m, n, x, y):
        inter = len(np.intersect1d(np.frombuffer(x.as_buffer(), "<u8"), np.frombuffer(y.as_buffer(), "<u8"), assume_unique=True))
        return 100 * inter >= percent * (m + n - inter)

    def those(some: DataFrame, value: str, test) -> DataFrame:
        def run(batches):
            common.give_back()
            for batch in batches:
                rows = zip(batch.column("m").to_pylist(), batch.column("n").to_pylist(), batch.column("x"), batch.column("y"))
                mask = pa.array([test(*r) for r in rows], pa.bool_())
                yield pa.RecordBatch.from_arrays([batch.column("a").filter(mask), batch.column("b").filter(mask)], names=["a", "b"])

        left, right = held.select(F.col("cls").alias("a"), F.col("n").alias("m"), F.col(value).alias("x")), held.select(F.col("cls").alias("b"), "n", F.col(value).alias("y"))
        return some.join(left, "a").join(right, "b").select("a", "b", "m", "n", "x", "y").mapInArrow(run, "a long, b long")

    close = common.materialize(those(both, "h", near), "close")
    out = common.materialize(those(close, "s", similar), "similar")
    common.discard(both, wanted, held, close)
    return out


def shared_signatures(docs: DataFrame, n: int, bands: Bands, slices: int) -> list[DataFrame]:
    """Tables (sig, cls, low) of signatures that several classes have; low is the smallest of those that met.

    A lower similarity needs more signatures. They are worked on in slices of their values, made anew from the texts for
    each, so that the shuffle of only one slice lies on disk at a time."""
    out = []
    for part in range(slices):
        out.append(common.materialize(members(signature_rows(docs, n, bands, part, slices)), "members"))
        common.release(docs.sparkSession)
    return out


def link_classes(docs: DataFrame, *, n: int = 5, percent: int = 80, parts: int = 3, spared: int = 1, slices: int | None = None) -> tuple[DataFrame, DataFrame]:
    """Rows (doc_id, n, cls) and components (node, component) of the classes, for one link relation."""
    slices = slices or (1 if percent >= 90 else 3)
    rows = common.materialize(profiles(docs, n), "profiles")
    classes = common.materialize(rows.where("n > 0").groupBy(F.col("d1").alias("cls")).agg(F.min("doc_id").alias("rep"), F.first("n").alias("n"), *[F.first(f"p{i}").alias(f"p{i}") for i in range(BITMAPS)]), "classes")
    # the second half of the digest must agree as well; a clash of first halves would make classes meaningless
    clash = rows.where("n > 0").groupBy("d1").agg(F.min("d2").alias("x"), F.max("d2").alias("y")).where("x != y").limit(1).count()
    if clash:
        raise RuntimeError("two different sets have the same 64-bit digest")
    tables = shared_signatures(docs, n, Bands(percent, parts, spared), slices)
    shared = tables[0]
    for t in tables[1:]:
        shared = shared.union(t)
    stars = common.materialize(shared.where("cls != low").select(F.col("low").alias("a"), F.col("cls").alias("b")).distinct(), "stars")
    links = similar_pairs(stars, classes, docs, n, percent)
    found = components(links)
    marked = shared.join(found, F.col("cls") == F.col("node"), "left").select("sig", "cls", F.coalesce("component", "cls").alias("comp"))
    open_ = marked.groupBy("sig").agg(F.min("comp").alias("x"), F.max("comp").alias("y")).where("x != y").select("sig")
    rest = common.materialize(marked.join(open_, "sig").distinct(), "open")
    # compared inside the join: of classes that share a signature by chance or by a common passage nothing is emitted
    bits = classes.select(F.col("cls").alias("k"), "n", *[f"p{i}" for i in range(BITMAPS)])
    fitted = common.materialize(rest.join(bits, F.col("cls") == F.col("k")).drop("k"), "open")
    common.discard(rest, found, *tables)
    left, right = sided(fitted, "l"), sided(fitted, "r")
    pair = (F.col("l_sig") == F.col("r_sig")) & (F.col("l_cls") < F.col("r_cls")) & (F.col("l_comp") != F.col("r_comp"))
    across = left.join(right, pair & may_be_similar(percent)).select(F.col("l_cls").alias("a"), F.col("r_cls").alias("b")).distinct()
    more = similar_pairs(across.join(stars, ["a", "b"], "left_anti"), classes, docs, n, percent)
    out = components(links.union(more))
    common.discard(fitted, stars, links, more, classes)
    return rows, out


def near_duplicates(docs: DataFrame, *, n: int = 5, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id): the smallest doc_id that can be reached by links of similar sets."""
    rows, found = link_classes(docs, n=n, percent=percent)
    full = rows.where("n > 0").join(found, F.col("d1") == F.col("node"), "left").select("doc_id", "n", F.coalesce("component", "d1").alias("c"))
    least = full.groupBy("c").agg(F.min("doc_id").alias("component_id"))
    alone = rows.where("n = 0").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id"))
    return full.join(least, "c").select("doc_id", F.col("n").alias("n_shingles"), "component_id").union(alone)


def one_of_each(docs: DataFrame, *, n: int = 5, percent: int = 80) -> DataFrame:
    """Rows of docs, one of each group of similar texts: that with the smallest doc_id (null last), of those with equal ids
    the one with the smallest key of its text. Texts without words are similar to nothing; only equal ones of one id are one."""
    rows, found = link_classes(docs.select("doc_id", "text"), n=n, percent=percent)
    full = rows.where("n > 0").join(found, F.col("d1") == F.col("node"), "left").select("doc_id", "t", F.coalesce("component", "d1").alias("c"))
    first = full.groupBy("c").agg(F.min(F.struct(F.col("doc_id").isNull().alias("x"), "doc_id", "t")).alias("k")).select("k.doc_id", "k.t")
    chosen = first.union(rows.where("n = 0").select("doc_id", "t")).distinct()
    chosen = common.materialize(chosen.select(F.col("doc_id").alias("__id"), F.col("t").alias("__t")), "kept")
    common.discard(rows, found)
    same = F.col("doc_id").eqNullSafe(F.col("__id")) & (F.col("__key") == F.col("__t"))
    return docs.withColumn("__key", text_key()).join(chosen, same, "left_semi").dropDuplicates(["doc_id", "__key"]).drop("__key")


def op8_shingle_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(common.documents(spark, sf_dir).select("doc_id", "text"), n=3, percent=90)


ORACLE = {
    "op8_shingle_join": r"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS MATERIALIZED (SELECT DISTINCT doc_id, array_to_string(w[i:i + least(3, len(w)) - 1], ' ') AS g
      FROM d, unnest(range(1, greatest(len(w) - 3, 0) + 2)) AS u(i) WHERE len(w) > 0),
n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS i FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS MATERIALIZED (SELECT x, y FROM p JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * i >= 90 * (a.n + b.n - i)),
e AS MATERIALIZED (SELECT x, y FROM l UNION SELECT y, x FROM l UNION SELECT doc_id, doc_id FROM d),
r AS (SELECT x, y FROM e UNION SELECT r.x, e.y FROM r JOIN e ON r.y = e.x)
SELECT d.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, min(r.y) AS component_id
FROM d LEFT JOIN n USING (doc_id) JOIN r ON r.x = d.doc_id GROUP BY d.doc_id, n.n""",
}
