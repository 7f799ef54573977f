"""Mixing sources to target weights by capped water-filling.

Every source gets a share of a budget in proportion to its weight. A share above ``max_epochs`` times
what the source holds is clamped there and the excess goes to the sources that still have room, in
proportion to their weights, until none is above. A source then gives whole repetitions of all of its
documents and one fractional repetition: its documents in a seeded order, as far as the rest goes.

Defined cases: a null source is a source of its own, last in order. Null or empty texts have size 0 and are
taken 0 words. Sources without any words get target 0. Equal ids or rows tie by size; equal rows are
interchangeable. An empty table gives an empty result. Extra columns are kept by ``mix_documents``, except those that
begin with the prefix of its own columns, which are replaced. Only sizes of texts take part, whatever their length.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

PATTERN_WORD = r"[^\x20\x09-\x0D]+"
_P = "__mix_"


def word_count(text):
    """Runs of non-white characters: one more than the white runs of the trimmed text."""
    blank = F.translate(F.coalesce(text, F.lit("")), "\t\n\x0b\x0c\r", "     ")
    trimmed = F.trim(F.regexp_replace(blank, " {2,}", " "))
    return F.when(trimmed == "", F.lit(0)).otherwise(F.length(trimmed) - F.length(F.translate(trimmed, " ", "")) + 1).cast("long")


def water_fill(sizes: list[int], weights: list[float], budget: float, max_epochs: float) -> list[float]:
    """Targets for sources of the given sizes; their sum is the budget where the caps allow it."""
    target = [0.0] * len(sizes)
    open_, left = [i for i, n in enumerate(sizes) if n > 0 and weights[i] > 0], float(budget)
    while open_ and left > 0:
        total = sum(weights[i] for i in open_)
        over = [i for i in open_ if left * weights[i] / total > max_epochs * sizes[i]]
        if not over:
            for i in open_:
                target[i] = left * weights[i] / total
            break
        for i in over:
            target[i] = float(max_epochs * sizes[i])
        left -= sum(target[i] for i in over)
        open_ = [i for i in open_ if i not in set(over)]
    return target


def source_targets(sized: DataFrame, *, weights=(1, 2, 3), max_epochs: float = 3.0, budget_share: float = 1.0) -> DataFrame:
    """Per source: size, weight, target. Sources in code-point order, weights repeat in that order.

    Water-filling is done on one row per source with windows: sorted by cap/weight, the clamped sources are a
    prefix, found where the level that the others would get first fits (it only falls from there on). No row of a document takes part."""
    per = sized.groupBy(f"{_P}source").agg(F.sum(f"{_P}size").alias(f"{_P}source_size"))
    whole = Window.partitionBy(F.lit(0))
    order = whole.orderBy(F.col(f"{_P}source").cast("binary").asc_nulls_last())
    values = F.array(*[F.lit(float(w)) for w in weights])
    per = per.withColumn("w", F.element_at(values, (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int")))
    live = (F.col(f"{_P}source_size") > 0) & (F.col("w") > 0)
    per = per.withColumn("cap", F.col(f"{_P}source_size") * F.lit(float(max_epochs))).withColumn("ratio", F.when(live, F.col("cap") / F.col("w")))
    per = per.withColumn("budget", F.sum(f"{_P}source_size").over(whole) * F.lit(float(budget_share)))
    before = whole.orderBy(F.col("ratio").asc_nulls_last(), F.col(f"{_P}source").cast("binary").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    zero = F.lit(0.0)
    per = per.withColumn("level", (F.col("budget") - F.coalesce(F.sum(F.when(F.col("ratio").isNotNull(), F.col("cap"))).over(before), zero)) / (F.sum(F.when(F.col("ratio").isNotNull(), F.col("w"))).over(whole) - F.coalesce(F.sum(F.when(F.col("ratio").isNotNull(), F.col("w"))).over(before), zero)))
    per = per.withColumn("level", F.max(F.when(F.col("ratio").isNotNull() & (F.col("level") <= F.col("ratio")), F.col("level"))).over(whole))
    target = F.when(F.col("ratio").isNull(), zero).when(F.col("level").isNull() | (F.col("ratio") < F.col("level")), F.col("cap")).otherwise(F.col("w") * F.col("level"))
    return per.select(f"{_P}source", f"{_P}source_size", F.col("w").alias(f"{_P}weight"), target.alias(f"{_P}target"))


def source_plan(sized: DataFrame, *, weights=(1, 2, 3), max_epochs: float = 3.0, budget_share: float = 1.0, bucket_digits: int = 3) -> tuple[DataFrame, list[DataFrame]]:
    """One row per source: size, target, whole repetitions, and the last md5 that the fractional one takes; and the written
    tables that it reads.

    The seeded order is by md5. A running sum over a whole source would put a hot source into one task, so
    sums per leading digits of the md5 find the one group of digits where the fraction ends, and only that
    group is ranked row by row."""
    sized = sized.withColumn(f"{_P}bucket", F.substring(f"{_P}key", 1, bucket_digits))
    targets = source_targets(sized, weights=weights, max_epochs=max_epochs, budget_share=budget_share)
    whole = F.when(F.col(f"{_P}source_size") > 0, F.floor(F.col(f"{_P}target") / F.col(f"{_P}source_size"))).otherwise(F.lit(0))
    targets = targets.withColumn(f"{_P}whole", whole.cast("int")).withColumn(f"{_P}need", F.col(f"{_P}target") - F.col(f"{_P}whole") * F.col(f"{_P}source_size"))
    written = common.materialize(targets, "mix-targets")
    targets = written.withColumnRenamed(f"{_P}source", "s")
    here = F.col(f"{_P}source").eqNullSafe(F.col("s"))
    buckets = sized.groupBy(f"{_P}source", f"{_P}bucket").agg(F.sum(f"{_P}size").alias("n"))
    running = Window.partitionBy(f"{_P}source").orderBy(f"{_P}bucket").rowsBetween(Window.unboundedPreceding, -1)
    buckets = buckets.withColumn(f"{_P}before", F.coalesce(F.sum("n").over(running), F.lit(0))).join(targets, here)
    edge = buckets.where((F.col(f"{_P}before") < F.col(f"{_P}need")) & (F.col(f"{_P}before") + F.col("n") > F.col(f"{_P}need")))
    edge = common.materialize(edge.select("s", F.col(f"{_P}bucket").alias("b"), f"{_P}before", f"{_P}need"), "mix-edges")
    inside = sized.join(bounded_broadcast(edge), here & (F.col(f"{_P}bucket") == F.col("b")))
    rank = Window.partitionBy(f"{_P}source").orderBy(f"{_P}key", f"{_P}size").rowsBetween(Window.unboundedPreceding, -1)
    reached = F.col(f"{_P}before") + F.coalesce(F.sum(f"{_P}size").over(rank), F.lit(0)) + F.col(f"{_P}size") / 2
    last = inside.withColumn("r", reached).groupBy(f"{_P}source").agg(F.coalesce(F.max(F.when(F.col("r") <= F.col(f"{_P}need"), F.col(f"{_P}key"))), F.min("b")).alias("last"))
    # without an edge the fraction ends between two groups: none at all, or up to the last group below need
    full = buckets.where(F.col(f"{_P}before") + F.col("n") <= F.col(f"{_P}need")).groupBy("s").agg(F.max(f"{_P}bucket").alias("top"))
    out = targets.join(last, here, "left").drop(f"{_P}source").join(full.withColumnRenamed("s", "s2"), F.col("s").eqNullSafe(F.col("s2")), "left")
    return out.select(F.col("s").alias(f"{_P}s"), f"{_P}source_size", f"{_P}target", f"{_P}whole", F.coalesce("last", F.concat(F.col("top"), F.lit("~")), F.lit("")).alias(f"{_P}last")), [written, edge]


def bounded_broadcast(df: DataFrame, rows: int = 20_000) -> DataFrame:
    """Broadcast a written table if it has few rows; else the planner's join, whose hot keys AQE splits."""
    return F.broadcast(df) if df.count() <= rows else df


def seeded_key(doc_id, seed: str):
    return F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(doc_id.cast("string"), F.lit(""))).cast("binary"))


def mix_documents(docs: DataFrame, *, size=None, weights=(1, 2, 3), max_epochs: float = 3.0, budget_share: float = 1.0, seed: str = "mix", bucket_digits: int = 3) -> DataFrame:
    """docs with __mix_size, __mix_source_size, __mix_target and __mix_copies (how often the document is taken).

    size: the column that measures a document, by default the words of its text. The plan of the sources is
    worked out on ids and numbers and written; the documents themselves are joined to it without a shuffle."""
    docs = docs.drop(*[c for c in docs.columns if c.startswith(_P)])
    slim = docs.select(F.col("source").alias(f"{_P}source"), (word_count(F.col("text")) if size is None else size).alias(f"{_P}size"), seeded_key(F.col("doc_id"), seed).alias(f"{_P}key"))
    slim = common.materialize(slim, "mix-sizes")
    plan, used = source_plan(slim, weights=weights, max_epochs=max_epochs, budget_share=budget_share, bucket_digits=bucket_digits)
    plan = common.materialize(plan, "mix-plan")
    common.discard(slim, *used)
    sized = docs.withColumns({f"{_P}size": word_count(F.col("text")) if size is None else size, f"{_P}key": seeded_key(F.col("doc_id"), seed)})
    joined = sized.join(bounded_broadcast(plan), F.col("source").eqNullSafe(F.col(f"{_P}s")), "left").drop(f"{_P}s")
    copies = F.when(F.col(f"{_P}size") > 0, F.col(f"{_P}whole") + (F.col(f"{_P}key") <= F.col(f"{_P}last")).cast("int")).otherwise(F.lit(0))
    return joined.withColumn(f"{_P}copies", copies.cast("int")).drop(f"{_P}key", f"{_P}whole", f"{_P}last")


def repeat(mixed: DataFrame) -> DataFrame:
    """The mixture itself: every document as often as it is taken, with the columns that came in."""
    rows = mixed.where(F.col(f"{_P}copies") > 0).withColumn(f"{_P}copy", F.explode(F.sequence(F.lit(1), F.col(f"{_P}copies"))))
    return rows.drop(*[c for c in rows.columns if c.startswith(_P)])


def op5_source_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.documents(spark, sf_dir).select("doc_id", "text", "source")
    # sizes once: every later step works on ids and numbers, so the texts are read a single time
    slim = common.materialize(docs.select("doc_id", "source", word_count(F.col("text")).alias("size")), "mix-docs")
    mixed = mix_documents(slim, size=F.col("size"))
    return mixed.select("doc_id", "size", F.col(f"{_P}source_size").alias("source_size"), F.col(f"{_P}target").alias("target"), (F.col("size") * F.col(f"{_P}copies")).alias("taken"))


ORACLE = {
    "op5_source_mixture": r"""
WITH RECURSIVE d AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
w AS (SELECT *, 1.0 + (row_number() OVER (ORDER BY encode(source) ASC NULLS LAST) - 1) % 3 AS w,
             3.0 * source_size AS cap, (SELECT sum(source_size) FROM s) AS budget FROM s),
r AS (SELECT *, cap / w AS ratio,
        (budget - coalesce(sum(cap) OVER o, 0)) / (sum(w) OVER () - coalesce(sum(w) OVER o, 0)) AS level
      FROM w WHERE source_size > 0
      WINDOW o AS (ORDER BY cap / w, encode(source) ASC NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
v AS (SELECT max(level) AS level FROM r WHERE level <= ratio),
t AS (SELECT source, source_size, CAST(CASE WHEN v.level IS NULL OR ratio < v.level THEN cap ELSE w * v.level END AS DOUBLE) AS target FROM r, v),
u AS (SELECT d.doc_id, d.size, s.source_size, coalesce(t.target, 0.0) AS target,
        coalesce(sum(d.size) OVER (PARTITION BY d.source ORDER BY md5('mix:' || CAST(d.doc_id AS VARCHAR)), d.size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before
      FROM d JOIN s ON d.source IS NOT DISTINCT FROM s.source LEFT JOIN t ON d.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target,
  CAST(CASE WHEN size = 0 THEN 0 ELSE size * (floor(target / source_size)
     + CASE WHEN before + size / 2.0 <= target - floor(target / source_size) * source_size THEN 1 ELSE 0 END) END AS BIGINT) AS taken
FROM u""",
}
