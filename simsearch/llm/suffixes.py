"""Removal of long repeated strings by common-prefix interval trees over anchored suffixes.

A string of ``short`` bytes or more holds an anchor: of the k-byte pieces of its first ``short`` bytes the one whose hash is
smallest (the rightmost of equals). Equal strings have the same anchor at the same offset, so only occurrences of anchors
with equal pieces can repeat each other, and only suffixes that begin at anchors need sorting. An occurrence's context is what
strings of ``length`` bytes over the anchor can reach: ``length`` bytes to the right of its begin, ``short - k`` to the left.
Anchors whose piece occurs once, which most do, are left out before anything else is done.

Contexts that occur twice are repeated as a whole; that is a count per context (named by the digests of piece and context,
128 bits together). For the different contexts of an anchor an enhanced suffix array is made: suffixes in order with the
lengths of common prefixes. A stack scan gives the intervals of the prefix tree. Within an interval the left sides are
sorted and scanned the same way: a group of occurrences whose left sides part at one length and whose right sides part at
another is a maximal repeat. Groups are reported with all of their occurrences; from them follow the bytes that repeated
strings of ``length`` bytes cover, which are removed, and those that repeated strings of ``short`` bytes cover, which are counted.

An anchor with very many different contexts is split without loss: strings over it begin 0 to short-k bytes before it;
each half of that range has a longer core that equal strings share, and the occurrences are dealt by the digest of their
core. Halving ends at single begins, where the core is the string and a count decides.

Defined cases: null and empty texts have no bytes; texts shorter than ``short`` have no repeats. Matches never reach
over a text's end. Equal rows are different texts, so all of their strings repeat. Cuts may split characters: what
is left is bytes. Null ids are kept. A long text is read in stretches of some MB that overlap. Columns beside doc_id and text
are not read. An empty table gives no rows.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

PIECE_BITS = 6  # pieces of 64 bytes
K = 1 << PIECE_BITS
_CODES = common.mix64(np.arange(7, 263, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
_LOW = np.uint64((1 << 24) - 1)
_STRETCH = 1 << 22


def rolling(raw: np.ndarray) -> np.ndarray:
    """A hash of every K bytes, by doubling."""
    with np.errstate(over="ignore"):
        h = _CODES[raw]
        factor, size = 0x9FB21C651E98DF25, 1
        for _ in range(PIECE_BITS):
            h = h[:-size] * np.uint64(factor) + h[size:]
            factor, size = factor * factor & ((1 << 64) - 1) | 1, size * 2
        return common.mix64(h)


def sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    n = len(x) - w + 1
    blocks = np.full(-(-len(x) // w) * w, np.iinfo(np.uint64).max, np.uint64)
    blocks[: len(x)] = x
    blocks = blocks.reshape(-1, w)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    behind = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(behind[:n], ahead[w - 1 : w - 1 + n])


def anchors(data: bytes, length: int) -> list[int]:
    """Places of the anchors of all strings of the length (the shorter of the two), in order."""
    raw = np.frombuffer(data, np.uint8)
    out: list[int] = []
    for begin in range(0, max(0, len(raw) - length + 1), _STRETCH):
        stretch = raw[begin : begin + _STRETCH + length - 1]
        if len(stretch) < length:
            break
        h = rolling(stretch)
        at = np.arange(len(h), dtype=np.uint64)
        low = sliding_min((h & ~_LOW) | (_LOW - at), length - K + 1)
        found = _LOW - (low & _LOW)
        found = found[common.run_starts(found)].astype(np.int64) + begin
        out += [p for p in found.tolist() if not out or p > out[-1]]
    return out


def anchor_rows(docs: DataFrame, length: int, short: int) -> DataFrame:
    """(h, c, doc_id, uid, pos, nl, nr): anchor digest, context digest, where, and bytes of context on both sides."""

    def run(batches):
        for batch in common.by_bytes(batches, lambda b: [len(v or "") for v in b.column("text").to_pylist()], 4 << 20):
            columns: list[list] = [[] for _ in range(7)]
            for doc_id, uid, data in zip(batch.column("doc_id").to_pylist(), batch.column("uid").to_pylist(), common.utf8(batch.column("text").to_pylist())):
                n = len(data)
                if n < short:
                    continue
                for p in anchors(data, short):
                    nl, nr = min(p, short - K), min(n - p, length)
                    h, c = xxhash.xxh3_64_intdigest(data[p : p + K]), xxhash.xxh3_64_intdigest(data[p - nl : p + nr], nl)
                    for column, v in zip(columns, (h, c, doc_id, uid, p, nl, nr)):
                        column.append(v)
            digests = [pa.array(np.array(x, np.uint64).view(np.int64)) for x in columns[:2]]
            rest = [pa.array(x, t) for x, t in zip(columns[2:], (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32()))]
            yield pa.RecordBatch.from_arrays([*digests, *rest], names=["h", "c", "doc_id", "uid", "pos", "nl", "nr"])

    return docs.mapInArrow(run, "h long, c long, doc_id long, uid long, pos long, nl int, nr int")


def common_prefix(a: bytes, b: bytes) -> int:
    n = min(len(a), len(b))
    return n - ((int.from_bytes(a[:n], "big") ^ int.from_bytes(b[:n], "big")).bit_length() + 7) // 8


def intervals(lcp: list[int]):
    """(common length, first, last) of all inner nodes of the prefix tree over a sorted list, by a stack scan.

    lcp[i] is the common length of entries i and i + 1."""
    stack: list[tuple[int, int]] = []
    for i, x in enumerate([*lcp, -1]):
        begin = i
        while stack and stack[-1][0] > x:
            size, begin = stack.pop()
            yield size, begin, i
        if x >= 0 and (not stack or stack[-1][0] < x):
            stack.append((x, begin))


def repeat_groups(lefts: list[bytes], rights: list[bytes], least: int, from_: int = 0, to: int = 1 << 30):
    """Maximal repeats of at least ``least`` bytes that begin from_ to to-1 bytes before the anchor:
    (bytes left, bytes right, members)."""
    order = sorted(range(len(rights)), key=rights.__getitem__)
    lcp = [common_prefix(rights[a], rights[b]) for a, b in zip(order, order[1:])]
    mirror = [x[::-1] for x in lefts]
    for right, first, last in intervals(lcp):
        if right + min(to - 1, 1 << 30) < least:
            continue
        members = sorted(range(first, last + 1), key=lambda i: mirror[order[i]])
        sides = [mirror[order[i]] for i in members]
        for left, a, b in intervals([common_prefix(x, y) for x, y in zip(sides, sides[1:])]):
            if left + right < least or left < from_:
                continue
            group = members[a : b + 1]
            # their right sides must part here, too, or a deeper interval reports them
            if min(lcp[min(group) : max(group)]) == right:
                yield left, right, [order[i] for i in group]


def _span(left: int, right: int, least: int, from_: int, to: int):
    """Bytes around the anchor that strings beginning from_ to to-1 bytes before it cover, if any."""
    low, high = max(least - right, from_), min(left, to - 1)
    return (-high, least - low) if low <= high else None


_SPAN = "h long, c long, kind int, lo int, hi int"


def group_spans(rows: DataFrame, sizes: dict[int, int]) -> DataFrame:
    """(h, c, kind, lo, hi) for groups of rows (g, h, c, left, right, d0, d1), each group within one task.

    sizes: for each kind of result the bytes of its strings."""

    def run(batches):
        key, rows_of = None, []
        out: list[list] = [[], [], [], [], []]

        def close():
            if len(rows_of) < 2:
                return
            lefts, rights, d0, d1 = [r[2] for r in rows_of], [r[3] for r in rows_of], rows_of[0][4], rows_of[0][5]
            # every stretch holds the anchor, so what covers a member is one stretch
            best: dict[tuple[int, int], tuple[int, int]] = {}
            for left, right, members in repeat_groups(lefts, rights, min(sizes.values()), d0, d1):
                for kind, size in sizes.items():
                    s = _span(left, right, size, d0, d1) if left + right >= size else None
                    if s:
                        for m in members:
                            lo, hi = best.get((kind, m), s)
                            best[kind, m] = (min(lo, s[0]), max(hi, s[1]))
            for (kind, m), (lo, hi) in best.items():
                for column, v in zip(out, (rows_of[m][0], rows_of[m][1], kind, lo, hi)):
                    column.append(v)

        def flush():
            types = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32())
            batch = pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(out, types)], names=["h", "c", "kind", "lo", "hi"])
            for x in out:
                x.clear()
            return batch

        for batch in batches:
            columns = [batch.column(c).to_pylist() for c in ("g", "h", "c", "left", "right", "d0", "d1")]
            for row in zip(*columns):
                if row[0] != key:
                    close()
                    key, rows_of = row[0], []
                rows_of.append(row[1:])
            if len(out[0]) > 20_000:
                yield flush()
        close()
        yield flush()

    ordered = rows.repartition("g").sortWithinPartitions("g")
    return ordered.select("g", "h", "c", "left", "right", "d0", "d1").mapInArrow(run, _SPAN)


def halves(rows: DataFrame, length: int) -> DataFrame:
    """Rows (g, h, c, n, left, right, d0, d1) dealt by the cores of both halves of d0..d1."""
    middle = F.floor((F.col("d0") + F.col("d1")) / 2).cast("int")
    both = rows.withColumn("band", F.explode(F.array(F.struct(F.col("d0").alias("x"), middle.alias("y")), F.struct(middle.alias("x"), F.col("d1").alias("y")))))
    both = both.withColumns({"d0": F.col("band.x"), "d1": F.col("band.y")}).drop("band").where("d0 < d1")
    nl, nr = F.length("left"), F.length("right")
    both = both.where((nl >= F.col("d0")) & (nr >= length - F.col("d1") + 1))
    part = lambda l, r: F.concat(F.expr(f"substring(left, length(left) - ({l}) + 1, ({l}))"), F.expr(f"substring(right, 1, ({r}))"))
    core, whole = part("d0", f"{length} - d1 + 1"), part("least(length(left), d1 - 1)", f"least(length(right), {length} - d0)")
    # two digests for the group, so that 64 bits of chance do not join strangers; members are compared byte by byte
    return both.withColumns({"g": F.xxhash64("g", "d0", "d1", core), "f": F.xxhash64(F.least(nl, F.col("d1") - 1), whole), "f2": F.crc32(whole)})


def repeated_anchors(docs: DataFrame, length: int, short: int) -> DataFrame:
    """Written anchor rows of those anchors whose piece occurs more than once."""
    found = common.materialize(anchor_rows(docs, length, short), "anchors")
    again = common.materialize(found.groupBy("h").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("h"), "pieces")
    out = common.materialize(found.join(again, "h", "left_semi"), "anchors")
    common.discard(found, again)
    return out


def split_spans(rows: DataFrame, kind: int, size: int, most: int) -> list[DataFrame]:
    """Written spans of strings of one size over anchors with very many different contexts."""
    spans, hot, held = [], rows, []
    while hot.limit(1).count():
        dealt = common.materialize(halves(hot, size), "halves")
        same = common.materialize(dealt.groupBy("g", "f", "f2").agg(F.sum("n").alias("n"), F.min(F.struct("h", "c")).alias("k")), "cores")
        nl, nr = F.length("left"), F.length("right")
        twice = dealt.join(same.where("n > 1").select("g", "f", "f2"), ["g", "f", "f2"])
        spans.append(common.materialize(twice.select("h", "c", F.lit(kind).alias("kind"), (-F.least(nl, F.col("d1") - 1)).alias("lo"), F.least(nr, F.lit(size) - F.col("d0")).alias("hi")), "spans"))
        # one row per different context goes on; what it finds holds for its equals, which are covered already
        groups = same.groupBy("g").agg(F.count(F.lit(1)).alias("m"))
        lone = same.join(groups.where("m > 1"), "g").select("g", "f", "f2", "n", "m", "k.h", "k.c")
        rest = common.materialize(dealt.drop("n").join(lone, ["g", "f", "f2", "h", "c"]).drop("f", "f2"), "halves")
        spans.append(common.materialize(group_spans(rest.where(F.col("m") <= most).drop("m"), {kind: size}), "spans"))
        common.discard(dealt, same, *held)
        hot, held = rest.where(F.col("m") > most).drop("m"), [rest]
    common.discard(*held)
    return spans


def repeated_spans(docs: DataFrame, *, length: int = 400, short: int = 256, most: int = 256) -> DataFrame:
    """(doc_id, uid, kind, begin, end): stretches of docs (doc_id, uid, text) that repeated strings cover, of ``length`` bytes
    (kind 0) and of ``short`` bytes (kind 1).

    Stretches may overlap. most: different contexts of an anchor up to which one task sorts them; more are split."""
    spark, sizes = docs.sparkSession, {0: length, 1: short}
    found = repeated_anchors(docs, length, short)
    classes = found.groupBy("h", "c").agg(F.count(F.lit(1)).alias("n"), F.min(F.struct("doc_id", "uid", "pos", "nl", "nr")).alias("rep"))
    classes = common.materialize(classes, "contexts")
    common.release(spark)
    kinds = F.explode(F.array(*[F.struct(F.lit(k).alias("kind"), F.lit(size).alias("size")) for k, size in sizes.items()])).alias("x")
    whole = classes.where("n > 1").select("h", "c", kinds, "rep").where(F.col("rep.nl") + F.col("rep.nr") >= F.col("x.size"))
    whole = whole.select("h", "c", "x.kind", (-F.col("rep.nl")).alias("lo"), F.least(F.col("rep.nr"), F.col("x.size")).alias("hi"))
    open_ = classes.groupBy("h").agg(F.count(F.lit(1)).alias("m"), F.min("n").alias("fewest")).where("m > 1 and fewest = 1").select("h", "m")
    open_ = common.materialize(open_, "open")
    wanted = classes.join(open_, "h").select("h", "c", "n", "m", "rep.*")
    per = wanted.groupBy("doc_id", "uid").agg(F.collect_list(F.struct("h", "c", "n", "m", "pos", "nl", "nr")).alias("x"))  # at most a text's anchors
    fetched = per.withColumnRenamed("doc_id", "i").withColumnRenamed("uid", "u").join(docs, F.col("i").eqNullSafe(F.col("doc_id")) & (F.col("u") == F.col("uid")))
    fetched = fetched.select(F.encode("text", "utf-8").alias("b"), F.explode("x").alias("x"))
    rows = fetched.select(F.col("x.h").alias("g"), "x.h", "x.c", "x.n", "x.m", F.expr("substring(b, cast(x.pos - x.nl + 1 as int), x.nl)").alias("left"), F.expr("substring(b, cast(x.pos + 1 as int), x.nr)").alias("right"), F.lit(0).alias("d0"), F.lit(short - K + 1).alias("d1"))
    rows = common.materialize(rows.dropDuplicates(["h", "c"]), "context-bytes")
    common.discard(open_)
    spans = [common.materialize(group_spans(rows.where(F.col("m") <= most), sizes), "spans")]
    hot = rows.where(F.col("m") > most).drop("m")
    for kind, size in sizes.items():
        spans += split_spans(hot, kind, size, most)
    every = whole
    for s in spans:
        every = every.union(s)
    every = common.materialize(every.groupBy("h", "c", "kind").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi")), "cover")
    common.discard(classes, rows, *spans)
    out = found.join(every, ["h", "c"]).select("doc_id", "uid", "kind", (F.col("pos") + F.col("lo")).alias("begin"), (F.col("pos") + F.col("hi")).alias("end"))
    out = common.materialize(out, "stretches")
    common.discard(found, every)
    return out


def maximal_repeats(docs: DataFrame, *, length: int = 400) -> DataFrame:
    """(repeat, n_bytes, doc_id, begin): maximal repeats around shared anchors, each with all of its occurrences; for
    corpora whose anchors have few different contexts each (those are sorted in one task). A repeat longer than
    ``length`` appears once per anchor in it, cut to the anchor's context."""

    def run(batches):
        key, rows_of = None, []

        def close():
            for i, (left, right, members) in enumerate(repeat_groups([r[1] for r in rows_of], [r[2] for r in rows_of], length)):
                for m in members:
                    yield (f"{key & (1 << 64) - 1:016x}-{i}", left + right, rows_of[m][0], rows_of[m][3] - left)

        def table(rows):
            return pa.RecordBatch.from_arrays([pa.array([r[j] for r in rows], t) for j, t in enumerate((pa.string(), pa.int32(), pa.int64(), pa.int64()))], names=["repeat", "n_bytes", "doc_id", "begin"])

        for batch in batches:
            done = []
            for row in zip(*(batch.column(c).to_pylist() for c in ("h", "doc_id", "left", "right", "pos"))):
                if row[0] != key:
                    done += close()
                    key, rows_of = row[0], []
                rows_of.append(row[1:])
            yield table(done)
        yield table(list(close()) if rows_of else [])

    docs = with_uid(docs)
    found = repeated_anchors(docs, length, length)
    per = found.groupBy(F.col("doc_id").alias("i"), F.col("uid").alias("u")).agg(F.collect_list(F.struct("h", "pos", "nl", "nr")).alias("x"))
    fetched = per.join(docs, F.col("i").eqNullSafe(F.col("doc_id")) & (F.col("u") == F.col("uid"))).select("doc_id", F.encode("text", "utf-8").alias("b"), F.explode("x").alias("x"))
    rows = fetched.select("x.h", "doc_id", F.expr("substring(b, cast(x.pos - x.nl + 1 as int), x.nl)").alias("left"), F.expr("substring(b, cast(x.pos + 1 as int), x.nr)").alias("right"), "x.pos")
    return rows.repartition("h").sortWithinPartitions("h", "doc_id", "pos").mapInArrow(run, "repeat string, n_bytes int, doc_id long, begin long")


def with_uid(docs: DataFrame) -> DataFrame:
    """Equal rows share a uid and get equal stretches; rows that share only the id do not."""
    return docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("uid", F.xxhash64("doc_id", "text"))


def remove_repeats(docs: DataFrame, *, length: int = 400, short: int = 256, keep_bytes: bool = True, **options) -> DataFrame:
    """Per row: doc_id, n_bytes, spans (removed stretches), kept_sha256, if wanted kept (the remaining bytes), and n_short:
    bytes that strings of ``short`` bytes cover which start anywhere else as well; they are counted, not removed."""
    marked = with_uid(docs)
    spans = repeated_spans(marked, length=length, short=short, **options)
    per = spans.groupBy(F.col("doc_id").alias("i"), F.col("uid").alias("u")).agg(F.collect_set(F.struct("kind", "begin", "end")).alias("x"))
    joined = marked.join(per, F.col("i").eqNullSafe(F.col("doc_id")) & (F.col("u") == F.col("uid")), "left").select("doc_id", "text", F.col("x.kind").alias("kind"), F.col("x.begin").alias("begin"), F.col("x.end").alias("end"))

    def merge(stretches):
        merged: list[list[int]] = []
        for a, b in sorted(stretches):
            if merged and a <= merged[-1][1]:
                merged[-1][1] = max(merged[-1][1], b)
            else:
                merged.append([a, b])
        return merged

    def run(batches):
        for batch in common.by_bytes(batches, lambda b: [len(v or "") for v in b.column("text").to_pylist()], 8 << 20):
            ids, sizes, cuts, sums, kept, short_ = batch.column("doc_id"), [], [], [], [], []
            of = [batch.column(c).to_pylist() for c in ("kind", "begin", "end")]
            for data, kind, begin, end in zip(common.utf8(batch.column("text").to_pylist()), *of):
                stretches = list(zip(kind or [], begin or [], end or []))
                merged = merge((a, b) for k, a, b in stretches if k == 0)
                edges = [0, *(x for m in merged for x in m), len(data)]
                left = b"".join(data[a:b] for a, b in zip(edges[::2], edges[1::2]))
                sizes.append(len(data))
                cuts.append([{"begin": a, "end": b} for a, b in merged])
                sums.append(hashlib.sha256(left).hexdigest())
                kept.append(left if keep_bytes else None)
                short_.append(sum(b - a for a, b in merge((a, b) for k, a, b in stretches if k == 1)))
            span = pa.list_(pa.struct([("begin", pa.int64()), ("end", pa.int64())]))
            yield pa.RecordBatch.from_arrays([ids, pa.array(sizes, pa.int64()), pa.array(cuts, span), pa.array(sums), pa.array(kept, pa.binary()), pa.array(short_, pa.int64())], names=["doc_id", "n_bytes", "spans", "kept_sha256", "kept", "n_short"])

    return joined.mapInArrow(run, "doc_id long, n_bytes long, spans array<struct<begin: long, end: long>>, kept_sha256 string, kept binary, n_short long")


def op1_repeated_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Beside the columns asked for n_repeated_256: bytes that 256-byte strings cover which also start anywhere else, from the
    same trees. A passage of some fifty words has fewer than the 400 bytes that are needed to be removed."""
    out = remove_repeats(common.documents(spark, sf_dir).select("doc_id", "text"), keep_bytes=False)
    removed = F.aggregate("spans", F.lit(0).cast("long"), lambda a, s: a + s["end"] - s["begin"])
    return out.select("doc_id", "n_bytes", removed.alias("n_removed"), F.size("spans").cast("long").alias("n_spans"), "kept_sha256", F.col("n_short").alias("n_repeated_256"))


ORACLE: dict[str, str] = {}
