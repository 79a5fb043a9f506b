"""Graphs from the given tables, small generated ones, and edge lists from files and streams."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..model import vid
from ..operators.ports import ranked


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def edges_of(*pairs: DataFrame) -> DataFrame:
    """Undirected simple edges (u < v) of pairs of two columns: loops, nulls and repeats removed."""
    every = reduce(DataFrame.union, pairs).toDF("a", "b")
    return every.where("a <> b").select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).distinct()


def geo_tree(spark: SparkSession, d: str) -> DataFrame:
    """v, parent, level: world, regions, nations, customers and suppliers, orders."""
    n = table(spark, d, "nation")
    rows = [
        spark.range(1).select(vid("world", 0).alias("v"), F.lit(None).cast("bigint").alias("parent"), F.lit(0)),
        table(spark, d, "region").select(vid("region", "r_regionkey"), vid("world", 0), F.lit(1)),
        n.select(vid("nation", "n_nationkey"), vid("region", "n_regionkey"), F.lit(2)),
        table(spark, d, "customer").select(vid("customer", "c_custkey"), vid("nation", "c_nationkey"), F.lit(3)),
        table(spark, d, "supplier").select(vid("supplier", "s_suppkey"), vid("nation", "s_nationkey"), F.lit(3)),
        table(spark, d, "orders").select(vid("order", "o_orderkey"), vid("customer", "o_custkey"), F.lit(4)),
    ]
    return reduce(DataFrame.union, rows).toDF("v", "parent", "level").withColumn("level", F.col("level").cast("bigint"))


def geo(spark: SparkSession, d: str) -> DataFrame:
    return edges_of(geo_tree(spark, d).where("parent is not null").select("v", "parent"))


def trade(spark: SparkSession, d: str) -> DataFrame:
    o, li = table(spark, d, "orders").select("o_orderkey", "o_custkey"), table(spark, d, "lineitem").select("l_orderkey", "l_suppkey")
    return edges_of(li.join(o, li.l_orderkey == o.o_orderkey).select(vid("customer", "o_custkey"), vid("supplier", "l_suppkey")))


def supply(spark: SparkSession, d: str) -> DataFrame:
    return edges_of(table(spark, d, "lineitem").select(vid("part", "l_partkey"), vid("supplier", "l_suppkey")))


def order_mesh(spark: SparkSession, d: str) -> DataFrame:
    o, li = table(spark, d, "orders"), table(spark, d, "lineitem")
    return edges_of(o.select(vid("customer", "o_custkey"), vid("order", "o_orderkey")), li.select(vid("order", "l_orderkey"), vid("part", "l_partkey")))


def event_tree(spark: SparkSession, d: str) -> DataFrame:
    """v, parent: users in a path, the events of each in a chain below."""
    e = table(spark, d, "events").select("event_id", "ts", "user_id")
    by = W.partitionBy("user_id").orderBy("ts", "event_id")
    events = e.select(vid("event", "event_id").alias("v"), F.coalesce(vid("event", F.lag("event_id").over(by)), vid("user", "user_id")).alias("parent"))
    users = _ranked(e, "user_id")
    prev = users.select((F.col("key") + 1).alias("key"), F.col("user_id").alias("prev"))
    return events.union(users.join(prev, "key", "left").select(vid("user", "user_id"), vid("user", "prev")))


def event_chain(spark: SparkSession, d: str) -> DataFrame:
    return edges_of(event_tree(spark, d).where("parent is not null"))


def conv_spider(spark: SparkSession, d: str) -> DataFrame:
    c = table(spark, d, "conversations").select("conv_id", "turn").distinct()
    turn = lambda t: vid("turn", F.col("conv_id") * 1000 + t)
    by = W.partitionBy("conv_id").orderBy("turn")
    prev = F.lag("turn").over(by)
    return edges_of(c.select(turn(F.col("turn")), F.when(prev.isNull(), vid("conversation", 0)).otherwise(turn(prev))))


def _ranked(df: DataFrame, name: str) -> DataFrame:
    """name, key: the place of each distinct value from 1 on; ranges are ranked apart and added up."""
    values = df.select(name).where(F.col(name).isNotNull()).distinct().withColumn("all", F.lit(0))
    return ranked(values, "all", [F.col(name)], "key", hubs=True).select(name, (F.col("key") + 1).alias("key"))


def doc_source(spark: SparkSession, d: str) -> DataFrame:
    docs = table(spark, d, "documents").select("doc_id", "source", "lang")
    s, g = _ranked(docs, "source").withColumnRenamed("key", "sk"), _ranked(docs, "lang").withColumnRenamed("key", "lk")
    full = docs.join(s, "source").join(g, "lang")
    return edges_of(full.select(vid("document", "doc_id"), vid("source", "sk")), full.select(vid("source", "sk"), vid("language", "lk")))


def page_links(spark: SparkSession, d: str) -> DataFrame:
    links = table(spark, d, "pages").select("page_id", F.explode(F.expr("regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)")).alias("target")).distinct()
    return edges_of(links.join(_ranked(links, "target"), "target").select(vid("page", "page_id"), vid("link", "key")))


GRAPHS = {"geo": geo, "trade": trade, "supply": supply, "order_mesh": order_mesh, "event_chain": event_chain, "conv_spider": conv_spider, "doc_source": doc_source, "page_links": page_links}


def star(spark: SparkSession, leaves: int) -> DataFrame:
    return spark.range(1, leaves + 1).select(F.lit(0).cast("bigint").alias("u"), F.col("id").alias("v"))


def path(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(max(0, n - 1)).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v"))


def random_graph(spark: SparkSession, n: int, extra: int, seed: int = 1) -> DataFrame:
    """Connected: a random recursive tree and `extra` further edges, by arithmetic hashes."""
    h = lambda a, b: F.pmod(F.xxhash64(a, F.lit(seed + b)), F.lit(2**31 - 1))
    tree = spark.range(1, n).select(F.col("id").alias("a"), F.pmod(h(F.col("id"), 0), F.col("id")).alias("b"))
    more = spark.range(extra).select(F.pmod(h(F.col("id"), 1), F.lit(n)).alias("a"), F.pmod(h(F.col("id"), 2), F.lit(n)).alias("b"))
    return edges_of(tree, more)


def edge_list(spark: SparkSession, path: str, kind: str = "csv") -> DataFrame:
    """Edges (u, v) from Parquet, CSV or JSON files with an explicit schema."""
    reader = spark.read.schema("u bigint, v bigint")
    return edges_of(getattr(reader, kind)(path))


def edge_stream(spark: SparkSession, path: str, kind: str = "parquet") -> DataFrame:
    """The same as a stream of files."""
    return spark.readStream.schema("u bigint, v bigint").format(kind).load(path)


def write_ports(ports: DataFrame, name: str, buckets: int = 8) -> None:
    """Ports as a table bucketed and sorted by src: later rounds join without moving them."""
    ports.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src", "port").saveAsTable(name)


def write_stage(df: DataFrame, path: str, *by: str) -> None:
    """A stage's frame as Parquet, partitioned by columns such as stage and round."""
    (df.write.mode("overwrite").partitionBy(*by) if by else df.write.mode("overwrite")).parquet(path)
