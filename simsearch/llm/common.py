"""What the operators share: tables, durable intermediate results, byte-level helpers."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space as the contracts write it: space and the five control characters.
SPACE = r"[\x20\x09-\x0D]+"

_local_dir: str | None = None
_written: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster names in spark.checkpoint.dir; a temporary one only where it is
    unset and everything runs in this process (tests)."""
    global _local_dir
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    current = spark.sparkContext._jsc.sc().getCheckpointDir()
    if current.isDefined():
        return current.get().rstrip("/")
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    if _local_dir is None:
        _local_dir = tempfile.mkdtemp(prefix="simsearch-shared-")
        atexit.register(shutil.rmtree, _local_dir, ignore_errors=True)
    return f"file://{_local_dir}"


def materialize(df: DataFrame, what: str) -> DataFrame:
    """Write df into the shared folder and read it back: cuts lineage and survives lost executors.

    Whoever writes a table deletes it with ``discard`` once its successor is written."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.written_at = path
    _written.append(path)
    return out


def _delete(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(at, True)
    if path in _written:
        _written.remove(path)


def discard(*tables: DataFrame) -> None:
    """Delete written tables that nothing reads any more, and let go of the shuffles that made their successors."""
    for t in tables:
        path = t.__dict__.pop("written_at", None)
        if path:
            _delete(t.sparkSession, path)
    if tables:
        release(tables[0].sparkSession)


def written_so_far() -> set[str]:
    return set(_written)


def sweep(kept: DataFrame, before: set[str]) -> None:
    """Once ``kept`` is written: delete all tables written on the way to it, that is since ``before`` was taken."""
    for path in set(_written) - before - {kept.__dict__.get("written_at")}:
        _delete(kept.sparkSession, path)
    release(kept.sparkSession)


def sealed(docs: DataFrame, *kept: str) -> tuple[DataFrame, list[str]]:
    """docs with all columns but ``kept`` under names that no operator uses, and the old names in order (for ``toDF``)."""
    return docs.toDF(*[c if c in kept else f"__column{i}" for i, c in enumerate(docs.columns)]), docs.columns


def without(docs: DataFrame, *names: str) -> DataFrame:
    """docs less the columns that an operator is about to add: a column that came in under such a name is replaced."""
    return docs.drop(*[c for c in docs.columns if c.lower() in {n.lower() for n in names}])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents")


def crc_mod(column, modulus: int):
    """crc32 of the id as text, modulo: the folds of the contracts. A null id hashes as empty text."""
    return F.pmod(F.crc32(F.coalesce(column.cast("string"), F.lit("")).cast("binary")), F.lit(modulus))


def utf8(texts) -> list[bytes]:
    """UTF-8 of every text, null as empty; lone surrogates cannot come from Arrow strings."""
    return [b"" if t is None else t.encode() for t in texts]


def mix64(x: np.ndarray) -> np.ndarray:
    """Bit mixer for uint64 arrays."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def by_bytes(batches, size_of, limit: int) -> Iterator:
    """Cut each batch so that no piece has much more than limit bytes: long texts stay bounded in memory."""
    for batch in batches:
        sizes = size_of(batch)
        start = total = 0
        for i, n in enumerate(sizes):
            if total and total + n > limit:
                yield batch.slice(start, i - start)
                start, total = i, 0
            total += n
        if start < len(sizes):
            yield batch.slice(start)


def run_starts(keys: np.ndarray) -> np.ndarray:
    """Where each run of equal neighbours begins."""
    if not len(keys):
        return np.zeros(0, np.int64)
    return np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))


def release(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of queries that are over: it does so when the driver's garbage is collected."""
    import gc

    gc.collect()
    spark.sparkContext._jvm.System.gc()


#: What processes hold beyond a task, by owner: a worker that goes on to another operator lets it go.
held_by_process: list[dict] = []


def give_back(keep: dict | None = None) -> None:
    """Forget what this process holds for other operators and return freed memory to the system: a Python worker goes on to the
    next query with what it took for the last one."""
    import ctypes
    import gc

    import pyarrow as pa

    for held in held_by_process:
        if held is not keep:
            held.clear()
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc alone has it
    if trim is not None:
        trim(0)
