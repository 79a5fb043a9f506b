"""Helpers shared by the operators of this subpackage."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Tables up to this many bytes may be broadcast; beyond it the operators shuffle.
BROADCAST_BYTES = 32 << 20


def scratch_dir(spark: SparkSession) -> str:
    """The folder all executors share: the session's checkpoint folder, or with a local master one of our own where none is set."""
    sc = spark.sparkContext
    known = sc._jsc.sc().getCheckpointDir()
    if known.isDefined():
        return known.get()
    named = sc.getConf().get("spark.checkpoint.dir", None)
    if not named and not sc.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="portsweep-"))
    return sc._jsc.sc().getCheckpointDir().get()


def materialize(df: DataFrame, tag: str) -> DataFrame:
    """Write once to the shared folder and read back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = f"{scratch_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def with_columns_only(df: DataFrame, *names: str) -> DataFrame:
    """Only the named columns, so that extra or clashing columns of an input never matter."""
    return df.select(*[F.col(f"`{n}`") for n in names])


#: Column that names a row; an input must not have it.
ROW = "__portsweep_row"


def fresh(columns: list[str], *names: str) -> list[str]:
    """The names, each made longer until no column has it."""
    taken, out = {c.lower() for c in columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def with_rows(docs: DataFrame) -> DataFrame:
    """docs with a distinct ROW in the order of doc_id: doc_id itself, or places in a sorted copy if some are repeated or null."""
    if ROW in docs.columns:
        raise ValueError(f"{ROW} is the name of a column of our own")
    row = F.col("doc_id").cast("bigint")
    n, h = fresh(docs.columns, "n", "h")
    odd = docs.groupBy("doc_id").agg(F.count("*").alias(n)).where((F.col(n) > 1) | F.col("doc_id").isNull()).limit(1).count()
    if not odd:
        return docs.withColumn(ROW, row)
    ordered = docs.withColumn(h, F.xxhash64("text")).repartitionByRange("doc_id", h).sortWithinPartitions("doc_id", h).drop(h)
    return materialize(ordered.withColumn(ROW, F.monotonically_increasing_id()), "rows")


def maybe_broadcast(df: DataFrame, row_bytes: int, rows: int | None = None) -> DataFrame:
    """df marked for broadcasting if its counted rows fit in BROADCAST_BYTES, else unchanged (shuffle join)."""
    rows = df.count() if rows is None else rows
    return F.broadcast(df) if rows * row_bytes <= BROADCAST_BYTES else df


@contextmanager
def batch_rows(spark: SparkSession, rows: int) -> Iterator[None]:
    """Jobs run inside hand this many rows at once to Python workers: for rows that are large."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(rows))
    try:
        yield
    finally:
        spark.conf.set(name, before)


#: What workers keep between tasks: emptied when a worker turns to work that does not use it.
CACHES: list[dict] = []


def drop_caches() -> None:
    for c in CACHES:
        c.clear()
    pa.default_memory_pool().release_unused()


def slices(batches: Iterator[pa.RecordBatch], rows: int = 500) -> Iterator[pa.RecordBatch]:
    """Batches of so many rows at most, so that what is made of one stays small; the worker's caches are dropped first."""
    drop_caches()
    for b in batches:
        for at in range(0, b.num_rows, rows):
            yield b.slice(at, rows)


_K1 = np.uint64(0x9E3779B97F4A7C15)
_K2 = np.uint64(0xBF58476D1CE4E5B9)
_K3 = np.uint64(0x94D049BB133111EB)


def mix64(x: np.ndarray) -> np.ndarray:
    """Bijective 64-bit finaliser on a uint64 array."""
    x = (x ^ (x >> np.uint64(30))) * _K2
    x = (x ^ (x >> np.uint64(27))) * _K3
    return x ^ (x >> np.uint64(31))


def roll(h: np.ndarray, width: int, salt: int = 0) -> np.ndarray:
    """64-bit hash of each run of `width` consecutive entries of h (uint64); empty if there are fewer."""
    n = len(h) - width + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    acc = np.full(n, np.uint64(salt) * _K1 + np.uint64(width), np.uint64)
    for i in range(width):
        acc = mix64(acc * _K1 + h[i : i + n])
    return acc
