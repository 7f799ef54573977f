"""Token counts by a separator scan of flat, unindexed token files.

A token file is a plain run of 16- or 32-bit ids in which an end id closes every document; nothing tells where documents
begin. Files are looked at in blocks of any size. Each block is searched at once for the end id; its row tells how many
ids it holds and where the end ids are. A prefix scan over these rows, in order of blocks, gives the ids and
documents before each block and the place of the last end id before it, which stitches documents that reach over
one or many blocks.

Defined cases: a file without any end id is one unfinished document; ids after the last end id are an unfinished
document; two end ids in a row close an empty document (0 tokens); an empty file has none. Null and empty
texts are written as an end id alone. Nulls among document ids are kept. Equal rows are separate documents.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common
from .encoding import encoder
from .repair import default_tokenizer

_FLAT = "file int, block int, data binary, ids array<long>"


def write_flat(docs: DataFrame, path: str, tokenizer: str, *, end_id: int, width: int = 2, block_ids: int = 1 << 20) -> None:
    """Write docs (doc_id, text) as flat token files: blocks cut without regard to documents, and, apart from
    them, the list of ids in the order of writing (no offsets)."""

    def run(batches):
        from pyspark import TaskContext

        enc, file, block, held = encoder(tokenizer, specials_as_text=True), TaskContext.get().partitionId(), 0, bytearray()
        size, tail = block_ids * width, np.array([end_id], "<u4").tobytes()
        row = lambda n, data, ids: pa.RecordBatch.from_pylist([{"file": file, "block": n, "data": data, "ids": ids}], schema)
        listed = 0
        for batch in batches:
            for piece in common.by_bytes([batch], lambda x: [len(v or "") for v in x.column("text").to_pylist()], 8 << 20):
                encoded = enc.encode([t or "" for t in piece.column("text").to_pylist()])
                held += np.frombuffer(tail.join([*encoded, b""]), "<u4").astype(f"<u{width}").tobytes()
                while len(held) >= size:
                    yield row(block, bytes(held[:size]), None)
                    del held[:size]
                    block += 1
                yield row(listed, None, piece.column("doc_id").to_pylist())
                listed += 1
        if held:
            yield row(block, bytes(held), None)

    schema = pa.schema([("file", pa.int32()), ("block", pa.int32()), ("data", pa.binary()), ("ids", pa.list_(pa.int64()))])
    docs.select("doc_id", "text").mapInArrow(run, _FLAT).write.option("compression", "zstd").parquet(path)


def read_files(spark: SparkSession, path: str, *, block_bytes: int = 1 << 21) -> DataFrame:
    """Blocks (file, block, data) of binary token files that lie in a folder, one after another as they are."""
    files = spark.read.format("binaryFile").load(path).select(F.col("path").alias("file"), "content")
    n = F.greatest(F.lit(1), F.ceil(F.length("content") / F.lit(block_bytes)))
    return files.withColumn("block", F.explode(F.sequence(F.lit(0), (n - 1).cast("int")))).select("file", "block", F.expr(f"substring(content, block * {block_bytes} + 1, {block_bytes})").alias("data"))


def block_rows(blocks: DataFrame, end_id: int, width: int) -> DataFrame:
    """(file, block, n, ends): ids in the block and the places of end ids. One vectorised search per block."""
    kind = blocks.schema["file"].dataType.simpleString()

    def run(batches):
        for batch in batches:
            data = [np.frombuffer(d or b"", f"<u{width}") for d in batch.column("data").to_pylist()]
            ends = [np.flatnonzero(x == end_id).astype(np.int32) for x in data]
            yield pa.RecordBatch.from_arrays([batch.column("file"), batch.column("block"), pa.array([len(x) for x in data], pa.int32()), pa.array(ends, pa.list_(pa.int32()))], names=["file", "block", "n", "ends"])

    return blocks.select("file", "block", "data").mapInArrow(run, f"file {kind}, block int, n int, ends array<int>")


def scan(blocks: DataFrame, end_id: int, *, width: int = 2) -> DataFrame:
    """(file, ordinal, start, n_tokens, complete) of every document; n_tokens does not count the end id."""
    rows = block_rows(blocks, end_id, width)
    before = Window.partitionBy("file").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0))).withColumn("first", F.coalesce(F.sum(F.size("ends")).over(before), F.lit(0)))
    last = F.when(F.size("ends") > 0, F.col("base") + F.element_at("ends", -1))
    rows = rows.withColumn("last", last).withColumn("previous", F.coalesce(F.max("last").over(before), F.lit(-1)))
    docs = rows.select("file", "base", "first", "previous", "ends", F.posexplode("ends").alias("i", "end"))
    start = F.when(F.col("i") == 0, F.col("previous") + 1).otherwise(F.col("base") + F.element_at("ends", F.greatest(F.col("i"), F.lit(1))) + 1)
    done = docs.select("file", (F.col("first") + F.col("i")).alias("ordinal"), start.alias("start"), (F.col("base") + F.col("end") - start).alias("n_tokens"), F.lit(True).alias("complete"))
    open_ = rows.groupBy("file").agg(F.sum("n").alias("n"), F.coalesce(F.max("last"), F.lit(-1)).alias("last"), F.sum(F.size("ends")).alias("ordinal"))
    open_ = open_.where(F.col("n") > F.col("last") + 1).select("file", "ordinal", (F.col("last") + 1).alias("start"), (F.col("n") - F.col("last") - 1).alias("n_tokens"), F.lit(False).alias("complete"))
    return done.unionByName(open_)


def op9_separator_scan(spark: SparkSession, sf_dir: str, *, end_id: int = 50256) -> DataFrame:
    """Write all documents as flat token files, forget where they begin, and count their tokens by the scan.

    Returns doc_id, n_tokens (without the end id), file and start (ids before it in its file)."""
    path = f"{common.shared_dir(spark)}/flat-tokens-{uuid.uuid4().hex}"
    write_flat(common.documents(spark, sf_dir), path, default_tokenizer(), end_id=end_id)
    flat = spark.read.schema(_FLAT).parquet(path)
    found = scan(flat.where(F.col("data").isNotNull()), end_id)
    before = Window.partitionBy("file").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    lists = flat.where(F.col("ids").isNotNull()).select("file", "block", "ids").withColumn("first", F.coalesce(F.sum(F.size("ids")).over(before), F.lit(0)))
    names = lists.select("file", "first", F.posexplode("ids").alias("i", "doc_id")).select("file", (F.col("first") + F.col("i")).alias("ordinal"), "doc_id")
    return names.join(found.where("complete"), ["file", "ordinal"]).select("doc_id", "n_tokens", "file", "start")


ORACLE: dict[str, str] = {}
