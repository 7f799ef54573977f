"""Distances and grams as column expressions."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_START, _STOP = "\x02", "\x03"


def edit_distance(a: Column, b: Column, limit: int | None = None) -> Column:
    """Null where the distance is above the limit (the bounded form only fills a band)."""
    if limit is None:
        return F.levenshtein(a, b)
    d = F.levenshtein(a, b, limit)
    return F.when(d >= 0, d)


#: Longest ASCII string whose places are compared as whole numbers, seven at a time (sums then stay within a long).
PACKED = 28


def _word(s: Column, i: int) -> Column:
    """Bytes 7i to 7i+6 of an ASCII string as a number, zeros behind its end."""
    return F.conv(F.rpad(F.hex(F.encode(F.substring(s, 7 * i + 1, 7), "UTF-8")), 14, "0"), 16, 10).cast("long")


def packed(s: Column) -> list[Column]:
    """Numbers w0, w1, ... of the first PACKED characters, for ``packed_hamming``; null where the string is no ASCII or longer.
    A frame keeps them per string, so that a pair costs some operations on numbers."""
    fits = (F.length(s) <= PACKED) & (F.octet_length(s) == F.length(s))
    return [F.when(fits, _word(s, i)).alias(f"w{i}") for i in range(PACKED // 7)]


def packed_hamming(a: list[Column], b: list[Column]) -> Column:
    """Different places of two strings of equal length from their numbers; null where one has none."""
    low, high = F.lit(0x7F7F7F7F7F7F7F), F.lit(0x80808080808080)
    out = None
    for x, y in zip(a, b):
        n = F.bit_count((x.bitwiseXOR(y) + low).bitwiseAND(high))  # seven bits and a carry per differing byte
        out = n if out is None else out + n
    return out


def hamming(a: Column, b: Column) -> Column:
    """Different places of two strings of equal length; null for other lengths."""
    cells = F.zip_with(F.split(a, ""), F.split(b, ""), lambda x, y: (x != y).cast("int"))
    return F.when(F.length(a) == F.length(b), F.aggregate(cells, F.lit(0), lambda s, x: s + x))


def grams(s: Column, n: int = 2, pad: bool = True) -> Column:
    """All n-grams in order, of the string with n-1 marks on both sides if padded."""
    p = F.concat(F.lit(_START * (n - 1)), s, F.lit(_STOP * (n - 1))) if pad else s
    return F.when(F.length(p) < n, F.array().cast("array<string>")).otherwise(F.transform(F.sequence(F.lit(1), F.length(p) - n + 1), lambda i: F.substring(p, i, F.lit(n))))


def numbered_grams(df: DataFrame, key: list[str], s: str, n: int = 2, pad: bool = True) -> DataFrame:
    """(key..., gram, occ): the occ-th time the gram is in the string. Equal rows then make a multiset meet.

    Numbered within the row: the grams in order, and for each how far it is from the first of its equals."""
    ordered = F.sort_array(grams(F.col(s), n, pad))
    numbered = F.transform(F.array(ordered), lambda g: F.transform(g, lambda x, i: F.struct(x.alias("gram"), (i - F.array_position(g, x) + 2).cast("int").alias("occ"))))
    return df.select(*key, F.explode(F.element_at(numbered, 1)).alias("x")).select(*key, "x.gram", "x.occ")


def normalised_edit(a: Column, b: Column) -> Column:
    return F.levenshtein(a, b) / F.greatest(F.length(a), F.length(b), F.lit(1))


def gram_jaccard_distance(a: Column, b: Column, n: int = 2) -> Column:
    x, y = F.array_distinct(grams(a, n)), F.array_distinct(grams(b, n))
    return 1 - F.size(F.array_intersect(x, y)) / F.greatest(F.size(F.array_union(x, y)), F.lit(1))


def euclid(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("double") - y) * (x.cast("double") - y)), F.lit(0.0), lambda s, x: s + x))


def cosine(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda u, v: u.cast("double") * v), F.lit(0.0), lambda s, z: s + z)
    return 1 - dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


METRICS: dict[str, Callable[[Column, Column], Column]] = {"edit": edit_distance, "hamming": hamming, "norm_edit": normalised_edit, "jaccard_gram": gram_jaccard_distance, "euclid": euclid, "cosine": cosine}
