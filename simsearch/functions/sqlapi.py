"""SQL surface: grams as a table function, distances and measures by name."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import alignment


@F.udtf(returnType=T.StructType([T.StructField("gram", T.StringType()), T.StructField("occ", T.IntegerType())]))
class GramTable:
    """Padded grams of a string with their numbers, for LATERAL joins."""

    def eval(self, s: str, n: int):
        if s is None:
            return
        p = "\x02" * (n - 1) + s + "\x03" * (n - 1)
        seen: dict[str, int] = {}
        for i in range(len(p) - n + 1):
            g = p[i : i + n]
            seen[g] = seen.get(g, 0) + 1
            yield g, seen[g]


@F.pandas_udf(T.IntegerType())
def arrow_distance(a: pd.Series, b: pd.Series) -> pd.Series:
    """Edit distance outside the JVM, to compare with the built-in."""
    return pd.Series([None if x is None or y is None else alignment.distance(x, y) for x, y in zip(a, b)], dtype="Int32")


@F.pandas_udf(T.StringType())
def motif_of(aligned: pd.Series) -> str:
    """Consensus of aligned rows as an aggregate; a row votes nowhere behind its end."""
    import numpy as np

    strings = [s for s in aligned if s]
    if len({len(s) for s in strings}) == 1:
        return alignment.motif(np.array([[alignment.GAP if c == "-" else ord(c) for c in s] for s in strings]))
    columns = ([s[i] for s in strings if len(s) > i] for i in range(max(map(len, strings), default=0)))
    return "".join(alignment.motif(np.array([[alignment.GAP if c == "-" else ord(c)] for c in col])) for col in columns)


def register(spark: SparkSession) -> None:
    spark.udtf.register("gram_table", GramTable)
    spark.udf.register("arrow_distance", arrow_distance)
    spark.udf.register("motif_of", motif_of)


def relax_sql(spark: SparkSession, corpus_view: str, q: str, least: int, most: int):
    """Relaxation of one query as parameterised SQL over a view (id, s)."""
    text = f"""
      WITH d AS (SELECT id, s, levenshtein(s, :q) AS dist FROM {corpus_view}),
           c AS (SELECT dist, sum(count(*)) OVER (ORDER BY dist) AS n FROM d GROUP BY dist),
           e AS (SELECT min(dist) + 1 AS eps FROM c WHERE n >= :least)
      SELECT id, s, dist FROM d, e WHERE eps IS NULL OR dist < eps ORDER BY dist, id LIMIT {int(most)}"""
    return spark.sql(text, args={"q": q, "least": least})
