"""The loop driver: rounds as jobs, lineage cut after each, one scalar per round on the driver."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_kept: dict[tuple[str, str, str], DataFrame] = {}

#: Trees deeper than this many levels are worked on by doubling, in rounds that grow with the logarithm of the depth.
DEEP = 16

#: Frames of up to this many rows of a few numbers may be sent to every task.
SMALL = 200_000


def ready(spark: SparkSession) -> None:
    """Make sure that a checkpoint folder is set: the session's own, or with a local master a temporary one where it names none."""
    sc = spark.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        named = sc.getConf().get("spark.checkpoint.dir", None)
        if not named and not sc.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="portsweep-"))


def cut(df: DataFrame) -> DataFrame:
    """df computed once and written to the shared checkpoint folder.

    A written table rather than checkpoint(): that computes a frame twice and keeps the constraints that the optimizer has
    found, which grow exponentially with the rounds of a loop over sums.
    """
    spark = df.sparkSession
    ready(spark)
    path = f"{spark.sparkContext._jsc.sc().getCheckpointDir().get()}/cut-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def small(df: DataFrame) -> bool:
    return df.limit(SMALL + 1).count() <= SMALL


def spread(df: DataFrame) -> DataFrame:
    """A written table marked to be sent to every task if it has at most SMALL rows: what it meets then stays where it is."""
    return F.broadcast(df) if small(df) else df


def stamp(spark: SparkSession, folder: str) -> str:
    """Names, sizes and times of the files of a folder of tables: changes when a table does."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    told = []
    for one in fs.listStatus(path):
        inner = fs.listStatus(one.getPath()) if one.isDirectory() else [one]
        told += [f"{f.getPath().toString()}:{f.getLen()}:{f.getModificationTime()}" for f in inner]
    return "|".join(sorted(told))


def keep(name: str, make: Callable[[], DataFrame], spark: SparkSession, mark: str = "") -> DataFrame:
    """What make() gives, computed once per application under this name and mark (such as the stamp of its tables)."""
    key = (spark.sparkContext.applicationId, name, mark)
    if key not in _kept:
        _kept[key] = cut(make())
    return _kept[key]


def forget() -> None:
    """Drop what keep() holds, so that it is computed anew."""
    _kept.clear()


def double(up: DataFrame, rounds: int = 64) -> DataFrame:
    """v, root, hops for up (v, parent; the root's parent is null): pointer doubling, about log2(depth) rounds."""
    ptr = cut(up.select("v", F.coalesce("parent", "v").alias("anc"), F.when(F.col("parent").isNull(), 0).otherwise(1).cast("bigint").alias("hops")))
    for _ in range(rounds):
        a = ptr.select(F.col("v").alias("anc"), F.col("anc").alias("far"), F.col("hops").alias("more"))
        new = cut(ptr.join(a, "anc").select("v", F.col("far").alias("anc"), (F.col("hops") + F.col("more")).alias("hops"), (F.col("more") > 0).alias("moved")))
        ptr = new.drop("moved")
        if new.where("moved").isEmpty():
            break
    return ptr.withColumnRenamed("anc", "root")


def downward(tree: DataFrame, start: Callable[[DataFrame], DataFrame], step: Callable[[DataFrame, DataFrame], DataFrame]) -> DataFrame:
    """Level by level from the root. start(root rows) and step(rows of a level, done rows of the level above) give done rows."""
    depth = tree.agg(F.max("level")).first()[0]
    if depth is None:
        return start(tree)
    done = cut(start(tree.where("level = 0")))
    parts = [done]
    for level in range(1, depth + 1):
        done = cut(step(tree.where(F.col("level") == level), done))
        parts.append(done)
    return _union(parts)


def path_sums(rows: DataFrame, x: str) -> DataFrame:
    """v, total: the sum of x over the vertices from the root down to v. rows: v, parent, x; pointer doubling."""
    s = cut(rows.select("v", F.col("parent").alias("anc"), F.col(x).cast("bigint").alias("total")))
    while not s.where("anc is not null").isEmpty():
        a = s.select(F.col("v").alias("anc"), F.col("anc").alias("next"), F.col("total").alias("more"))
        s = cut(s.join(a, "anc", "left").select("v", F.col("next").alias("anc"), (F.col("total") + F.coalesce("more", F.lit(0))).alias("total")))
    return s.drop("anc")


def upward(tree: DataFrame, values: DataFrame, sums: dict[str, Callable[[str], F.Column]]) -> DataFrame:
    """To the root: each vertex's own values (v, columns of sums) combined with those of all below it.

    sums names each column's aggregate, such as {"weight": F.sum, "height": F.max}. Level by level, work of a level is one
    partial aggregation by parent and n - 1 rows are shuffled in all. In deep trees, by doubling: what a vertex has of its
    descendants nearer than 2**k meets what its descendants at distance 2**k have of theirs.
    """
    cols = list(sums)
    depth = tree.agg(F.max("level")).first()[0] or 0
    rows = cut(tree.select("v", "parent", "level").join(values, "v"))

    def combined(every: DataFrame) -> DataFrame:
        return every.groupBy("v").agg(*[f(c).cast(values.schema[c].dataType).alias(c) for c, f in sums.items()])

    if depth > DEEP:
        s = rows.select("v", F.col("parent").alias("anc"), *cols)
        while not s.where("anc is not null").isEmpty():
            a = s.select(F.col("v").alias("anc"), F.col("anc").alias("next"))
            further = s.select("v", "anc").join(a, "anc", "left").select("v", F.col("next").alias("anc"))
            s = cut(combined(s.select("v", *cols).union(s.where("anc is not null").select("anc", *cols))).join(further, "v"))
        return s.drop("anc")
    above: DataFrame | None = None
    parts = []
    for level in range(depth, -1, -1):
        own = rows.where(F.col("level") == level)
        if above is not None:
            told = above.where(F.col("parent").isNotNull()).select(F.col("parent").alias("v"), *cols)
            own = combined(own.select("v", *cols).union(told)).join(own.select("v", "parent"), "v")
        above = cut(own.select("v", "parent", *cols))
        parts.append(above.drop("parent"))
    return _union(parts)


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return cut(out) if len(parts) > 24 else out
