"""String corpora corpus(id BIGINT, s STRING, len INT) from the given tables, and query sets.

Characters outside ASCII are folded to '?', one for one, so that every engine measures the same edit distance."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..session import spread


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def fold(s: Column) -> Column:
    return F.regexp_replace(s, r"[^\x00-\x7F]", "?")


def as_corpus(df: DataFrame, id_: Column, s: Column, *, dedupe: bool = True, lower: bool = False, folded: bool = True) -> DataFrame:
    """Null strings go; of equal strings the smallest id stays."""
    s = fold(s) if folded else s
    s = F.lower(s) if lower else s
    out = df.select(id_.cast("long").alias("id"), s.alias("s")).where("s is not null")
    if dedupe:
        out = out.groupBy("s").agg(F.min("id").alias("id"))
    return out.select("id", "s", F.length("s").alias("len"))


def names(spark, sf_dir):
    return as_corpus(table(spark, sf_dir, "part"), F.col("p_partkey"), F.col("p_name"))


def clients(spark, sf_dir):
    return as_corpus(table(spark, sf_dir, "customer"), F.col("c_custkey"), F.col("c_name"))


def urls(spark, sf_dir):
    return as_corpus(table(spark, sf_dir, "pages"), F.col("page_id"), F.col("url"))


def titles(spark, sf_dir):
    title = F.regexp_extract("html", r"<title>(.*?)</title>", 1)
    return as_corpus(spread(table(spark, sf_dir, "pages").select("page_id", "html")), F.col("page_id"), F.when(title != "", title))


def lines(spark, sf_dir):
    """Distinct trimmed lines of documents with 40 to 142 characters; ids in md5 order."""
    text = spread(table(spark, sf_dir, "documents").select("text"))
    line = text.select(F.explode(F.split(fold(F.col("text")), "\n")).alias("x")).select(F.trim("x").alias("s")).where(F.length("s").between(40, 142)).distinct()
    # a running number over everything would be one task: the md5's leading digits are the id
    number = F.conv(F.substring(F.md5("s"), 1, 15), 16, 10).cast("long")
    return line.select(number.alias("id"), "s", F.length("s").alias("len"))


def turns(spark, sf_dir):
    number = F.conv(F.substring(F.md5(F.concat_ws(":", F.col("conv_id").cast("string"), F.col("turn").cast("string"))), 1, 15), 16, 10)
    return as_corpus(spread(table(spark, sf_dir, "conversations").select("conv_id", "turn", "text")), number, F.col("text"))


def chains(spark, sf_dir, orders: DataFrame | None = None):
    """Per order 1 to 17 md5 digests, one after another: long strings of random letters.

    The keys are dealt out, as a few MB of them make many strings."""
    keys = table(spark, sf_dir, "orders").select("o_orderkey") if orders is None else orders
    digest = F.transform(F.sequence(F.lit(0), (F.col("o_orderkey") % 17).cast("int")), lambda i: F.md5(F.concat(F.col("o_orderkey").cast("string"), F.lit("-"), i.cast("string"))))
    dealt = keys.repartition(8 * spark.sparkContext.defaultParallelism)
    return dealt.select(F.col("o_orderkey").alias("id"), F.array_join(digest, "").alias("s")).withColumn("len", F.length("s"))


def passages(spark, sf_dir):
    return as_corpus(table(spark, sf_dir, "benchmark"), F.col("item_id"), F.col("text"))


CORPORA = {f.__name__: f for f in (names, clients, urls, titles, lines, turns, chains, passages)}


def own_queries(corpus: DataFrame, n: int = 5) -> DataFrame:
    """(qid, q): the first strings by md5."""
    first = corpus.orderBy(F.md5("s"), "id").limit(n)
    return first.select(F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(F.md5("s"), "id")).alias("qid"), F.col("s").alias("q"))


def typo_queries(corpus: DataFrame, n: int = 5) -> DataFrame:
    """The same strings with two characters swapped, one dropped and one put in."""
    q = F.col("q")
    swapped = F.concat(F.substring(q, 1, 1), F.substring(q, 3, 1), F.substring(q, 2, 1), F.expr("substring(q, 4)"))
    dropped = F.concat(F.substring(swapped, 1, 3), F.expr("substring(s1, 5)"))
    base = own_queries(corpus, n).withColumn("s1", swapped)
    return base.select("qid", F.concat(F.lit("x"), dropped).alias("q"))


def literal_queries(spark: SparkSession, strings: list[str]) -> DataFrame:
    return spark.createDataFrame([(i + 1, s) for i, s in enumerate(strings)], "qid int, q string")


def read_strings(spark: SparkSession, path: str, *, kind: str = "text", column: str = "value", **options) -> DataFrame:
    """A corpus from text, csv, json or parquet files; ids are hashes of the strings."""
    df = spark.read.options(**options).format(kind).load(path)
    return as_corpus(df, F.xxhash64(column), F.col(column))


def write_results(results: DataFrame, path: str, *, kind: str = "parquet", partition_by: str | None = None) -> None:
    writer = results.write.format(kind)
    (writer.partitionBy(partition_by) if partition_by else writer).save(path)
