"""Quality rules with robust multivariate outliers, in DataFrame expressions only.

Plain rules (words, repeated 5-word windows) fail some documents. For the others a vector of transformed text
statistics is compared with the documents of the same language and source: the minimum covariance determinant
method finds location and scatter of the ``share`` of rows that lie closest together, by concentration steps from two
starts until they settle, then a reweighting step; documents whose Mahalanobis distance is above a chi-square cut-off are
rejected.

All groups are worked on at once by partial aggregates, so a hot source is no single task. Quantiles come from
counts per narrow bin, which are the same however rows are partitioned. Statistics per document are worked out once and
written; later steps read numbers only.

Defined cases: null and empty texts have no words and fail the plain rules. A null language or source is a value of
its own. Sources with fewer than ``least_rows`` rows in a language are pooled per language. Features that do not
vary get a floor of scatter, so no matrix is singular. Equal rows get equal verdicts, ids may repeat or be null. Whole texts are
counted within one row, however long. Columns beside doc_id, text, lang and source are not read. An empty table gives no rows.
"""

from __future__ import annotations

from math import log1p, sqrt

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common
from .mixing import bounded_broadcast

_WHITE = " \t\n\x0b\x0c\r"
FEATURES = ("length", "word_length", "symbols", "dup_lines", "repeats")
#: Chi-square with five degrees of freedom: the median, and the values exceeded with probability 0.025 and 0.001.
_CHI_MEDIAN, _CHI_INNER, _CHI_CUT = 4.351, 12.833, 20.515
#: Least standard deviation of a feature: a tenth for lengths; for shares, such that a text at the usual limit (symbols in 2 % of
#: the characters, that is one in ten words; 30 % repeated lines; 20 % repeated words) lies at the cut-off among texts without any.
FLOORS = (0.1, 0.1, *(log1p(percent) / sqrt(_CHI_CUT) for percent in (2, 30, 20)))


def let(value: Column, body) -> Column:
    """body(value) with value worked out once: a lambda variable keeps the optimizer from copying it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def repeated_words(words: Column, window: int = 5) -> Column:
    """Words inside windows that occur twice or more. Windows are compared by 64-bit hashes within the text."""

    def covered(hashes: Column) -> Column:
        ordered = F.sort_array(F.transform(hashes, lambda x, i: F.struct(x.alias("h"), i.alias("p"))))

        def places(s: Column) -> Column:
            same = lambda e, k: F.coalesce(F.get(s, k)["h"] == e["h"], F.lit(False))
            return F.sort_array(F.transform(F.filter(s, lambda e, k: same(e, k - 1) | same(e, k + 1)), lambda e: e["p"]))

        start = F.struct(F.lit(-window).alias("last"), F.lit(0).alias("n"))
        step = lambda acc, p: F.struct(p.alias("last"), (acc["n"] + F.least(F.lit(window), p - acc["last"])).alias("n"))
        return F.aggregate(let(ordered, places), start, step, lambda acc: acc["n"])

    def of(h: Column) -> Column:
        grams = F.transform(F.sequence(F.lit(0), F.size(h) - window), lambda i: F.xxhash64(*[F.get(h, i + k) for k in range(window)]))
        return F.when(F.size(h) < window, F.lit(0)).otherwise(let(grams, lambda g: F.when(F.size(F.array_distinct(g)) == F.size(g), F.lit(0)).otherwise(covered(g))))

    return let(F.transform(words, lambda w: F.xxhash64(w)), of)


def statistics(docs: DataFrame) -> DataFrame:
    """doc_id, lang, source and the base counts of every whole text."""
    text = F.coalesce(F.col("text"), F.lit(""))
    counted = docs.select("doc_id", "lang", "source", text.alias("text")).select(
        "doc_id", "lang", "source",
        let(F.filter(F.split(F.col("text"), common.SPACE), lambda w: w != ""), lambda w: F.struct(F.size(w).alias("n_words"), repeated_words(w).alias("n_repeat_words"))).alias("w"),
        F.length(F.translate("text", _WHITE, "")).alias("word_chars"),
        (F.length("text") - F.length(F.translate("text", "#*$%&|<>", ""))).alias("n_symbols"),
        let(F.filter(F.split(F.col("text"), "\n"), lambda x: F.translate(x, _WHITE, "") != ""), lambda x: F.struct(F.size(x).alias("n_lines"), (F.size(x) - F.size(F.array_distinct(x))).alias("n_dup_lines"))).alias("l"),
    )
    return counted.select("doc_id", "lang", "source", *[F.col(c).cast("long").alias(c.split(".")[-1]) for c in ("w.n_words", "word_chars", "n_symbols", "l.n_lines", "l.n_dup_lines", "w.n_repeat_words")])


def vectors(stats: DataFrame) -> DataFrame:
    """The transformed statistics, x0 to x4."""
    per_word, per_line = F.greatest("n_words", F.lit(1)), F.greatest("n_lines", F.lit(1))
    x = (F.log1p("n_words"), F.log1p(F.col("word_chars") / per_word), F.log1p(100 * F.col("n_symbols") / F.greatest("word_chars", F.lit(1))), F.log1p(100 * F.col("n_dup_lines") / per_line), F.log1p(100 * F.col("n_repeat_words") / per_word))
    return stats.withColumns({f"x{i}": c for i, c in enumerate(x)})


def group_quantiles(rows: DataFrame, values: dict[str, Column], share: float, width: float) -> DataFrame:
    """Per group g the upper edge of the bin in which the quantile of each value lies."""
    long = rows.select("g", F.explode(F.array(*[F.struct(F.lit(n).alias("name"), F.floor(v / width).alias("bin")) for n, v in values.items()])).alias("v")).select("g", "v.name", "v.bin")
    counts = long.groupBy("g", "name", "bin").count()
    part = Window.partitionBy("g", "name")
    reached = F.sum("count").over(part.orderBy("bin")) >= F.lit(share) * F.sum("count").over(part)
    edges = counts.withColumn("in", reached).where("in").groupBy("g", "name").agg(((F.min("bin") + 1) * width).alias("edge"))
    return edges.groupBy("g").agg(*[F.max(F.when(F.col("name") == n, F.col("edge"))).alias(n) for n in values])


def moments(rows: DataFrame, p: int) -> DataFrame:
    return rows.groupBy("g").agg(*[F.avg(f"x{i}").alias(f"m{i}") for i in range(p)], *[F.covar_pop(f"x{i}", f"x{j}").alias(f"c{i}{j}") for i in range(p) for j in range(i + 1)])


def factor(group: DataFrame, floors) -> DataFrame:
    """Cholesky factor l_ij of the scatter, with the floors added to its diagonal; one small row per group."""
    p = len(floors)
    for i in range(p):
        for j in range(i + 1):
            rest = F.coalesce(F.col(f"c{i}{j}"), F.lit(0.0)) + (F.lit(floors[i] ** 2) if i == j else F.lit(0.0))
            for k in range(j):
                rest = rest - F.col(f"l{i}{k}") * F.col(f"l{j}{k}")
            group = group.withColumn(f"l{i}{j}", F.sqrt(F.greatest(rest, F.lit(1e-12))) if i == j else rest / F.col(f"l{j}{j}"))
    return group.select("g", *[f"m{i}" for i in range(p)], *[f"l{i}{j}" for i in range(p) for j in range(i + 1)])


def distance(p: int) -> list[tuple[str, Column]]:
    """Columns z0.. and d2 by forward substitution."""
    out = []
    for i in range(p):
        rest = F.col(f"x{i}") - F.col(f"m{i}")
        for k in range(i):
            rest = rest - F.col(f"l{i}{k}") * F.col(f"z{k}")
        out.append((f"z{i}", rest / F.col(f"l{i}{i}")))
    return out


def with_distance(rows: DataFrame, group: DataFrame, p: int) -> DataFrame:
    joined = rows.join(bounded_broadcast(group), "g")
    for name, c in distance(p):
        joined = joined.withColumn(name, c)
    return joined.withColumn("d2", sum((F.col(f"z{i}") * F.col(f"z{i}") for i in range(1, p)), F.col("z0") * F.col("z0"))).select(*rows.columns, "d2")


def concentrate(rows: DataFrame, start: DataFrame, *, share: float, most_steps: int, tolerance: float, floors) -> DataFrame:
    """Concentration steps from a start (g, m0.., c00..) until the logarithm of no group's determinant moves by more than
    the tolerance. A written table (g, m0.., l00.., volume) with volume the sum of the logarithms of l_ii."""
    p, volume = len(floors), sum((F.log(f"l{i}{i}") for i in range(1, len(floors))), F.log("l00"))
    keep = lambda df, what: common.materialize(df.coalesce(1), what)
    group = keep(factor(start, floors).withColumn("volume", volume), "mcd-step")
    for _ in range(most_steps):
        near = with_distance(rows, group.drop("volume"), p)
        bound = keep(group_quantiles(near, {"bound": F.log1p("d2")}, share, 0.002), "mcd-bound")
        inner = near.join(bounded_broadcast(bound), "g").where(F.log1p("d2") <= F.col("bound"))
        after = keep(factor(moments(inner, p), floors).withColumn("volume", volume), "mcd-step")
        moved = after.join(group.select("g", F.col("volume").alias("old")), "g").agg(F.max(F.abs(F.col("volume") - F.col("old")))).first()[0]
        common.discard(bound, group)
        group = after
        if moved is None or moved <= tolerance:
            break
    return group


def estimates(rows: DataFrame, *, share: float = 0.75, most_steps: int = 8, tolerance: float = 0.01, floors=FLOORS) -> DataFrame:
    """Location and scatter factor per group g of rows (g, x0..), with the scale of d2: a written table.

    Concentration steps run from two starts, medians with absolute deviations and the moments of all rows; the result with the
    smaller determinant is taken. Rows within the 0.975 value of it give the reweighted estimate."""
    p, keep = len(floors), lambda df, what: common.materialize(df.coalesce(1), what)
    xs = {f"m{i}": F.col(f"x{i}") for i in range(p)}
    centre = keep(group_quantiles(rows, xs, 0.5, 0.005), "mcd-centre")
    off = rows.join(bounded_broadcast(centre), "g")
    spread = group_quantiles(off, {f"s{i}": F.abs(F.col(f"x{i}") - F.col(f"m{i}")) for i in range(p)}, 0.5, 0.005)
    robust = centre.join(spread, "g").select("g", *[f"m{i}" for i in range(p)], *[(F.pow(1.4826 * F.col(f"s{i}"), 2) if i == j else F.lit(0.0)).alias(f"c{i}{j}") for i in range(p) for j in range(i + 1)])
    options = {"share": share, "most_steps": most_steps, "tolerance": tolerance, "floors": floors}
    one, two = concentrate(rows, robust, **options), concentrate(rows, moments(rows, p), **options)
    best = one.unionByName(two).groupBy("g").agg(F.min_by(F.struct(*one.columns), "volume").alias("b")).select("b.*").drop("volume")
    best = keep(best, "mcd-best")
    scale_of = lambda group: keep(group_quantiles(with_distance(rows, group, p), {"middle": F.log1p("d2")}, 0.5, 0.002).select("g", F.greatest(F.expm1("middle") / _CHI_MEDIAN, F.lit(1.0)).alias("scale")), "mcd-scale")
    scale = scale_of(best)
    inner = with_distance(rows, best, p).join(bounded_broadcast(scale), "g").where(F.col("d2") <= _CHI_INNER * F.col("scale"))
    final = keep(factor(moments(inner, p), floors), "mcd-final")
    last = scale_of(final)
    out = keep(final.join(last, "g"), "mcd-groups")
    common.discard(centre, one, two, best, scale, final, last)
    return out


def apply_rules(stats: DataFrame, *, least_rows: int = 50, cut: float = _CHI_CUT, **options) -> DataFrame:
    """stats (a written table) with base_failed, d2 (null where it failed) and kept."""
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    stats = stats.withColumn("base_failed", failed)
    good = stats.where(~F.col("base_failed"))
    sizes = good.groupBy("lang", "source").count().select(F.col("lang").alias("gl"), F.col("source").alias("gs"), (F.col("count") >= least_rows).alias("own"))
    sizes = common.materialize(sizes.coalesce(1), "mcd-sizes")  # one row per language and source
    # quoted, so that null, empty and the pool are different groups
    quote = lambda c: F.coalesce(F.concat(F.lit("="), c), F.lit("null"))
    g = F.concat_ws("\x00", quote(F.col("lang")), F.when(F.col("own"), quote(F.col("source"))).otherwise(F.lit("pool")))
    rows = vectors(good).join(bounded_broadcast(sizes), F.col("lang").eqNullSafe(F.col("gl")) & F.col("source").eqNullSafe(F.col("gs"))).withColumn("g", g).drop("gl", "gs", "own")
    rows = common.materialize(rows, "mcd-rows")
    group = estimates(rows.select("g", *[f"x{i}" for i in range(len(FEATURES))]), **options)
    scale = bounded_broadcast(group.select("g", "scale"))
    judged = with_distance(rows, group.drop("scale"), len(FEATURES)).join(scale, "g").withColumn("d2", F.col("d2") / F.col("scale"))
    judged = judged.select(*stats.columns, "d2", (F.col("d2") <= cut).alias("kept"))
    return judged.unionByName(stats.where("base_failed").withColumns({"d2": F.lit(None).cast("double"), "kept": F.lit(False)}))


def op7_robust_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    stats = common.materialize(statistics(common.documents(spark, sf_dir)), "text-statistics")
    return apply_rules(stats).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.round("d2", 6).alias("distance2"))


ORACLE: dict[str, str] = {}
