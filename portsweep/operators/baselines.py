"""What the bounded-memory protocols are compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import ReadOrder
from ..plans.rounds import cut
from .bfs import bfs_tree
from .ports import live, ranked


def read_all_rounds(ports: DataFrame, rounds: int) -> DataFrame:
    """v, leader_id, memory: flooding with unlimited memory, all messages of a round held in a list. For small graphs: a hub's list is its degree."""
    e = live(ports).select("src", "dst")
    state = cut(e.select(F.col("src").alias("v")).distinct().withColumns({"best": F.col("v"), "memory": F.lit(0)}))
    for _ in range(rounds):
        heard = state.join(e, F.col("v") == F.col("src")).groupBy(F.col("dst").alias("v")).agg(F.collect_list("best").alias("all"))
        state = cut(state.join(heard, "v").select("v", F.greatest("best", F.array_max("all")).alias("best"), F.greatest("memory", F.size("all")).alias("memory")))
    return state.select("v", F.col("best").alias("leader_id"), F.col("memory").cast("bigint").alias("memory"))


def exact_leader(ports: DataFrame) -> DataFrame:
    """The greatest id, by one aggregation."""
    return live(ports).agg(F.max("src").alias("leader_id"))


def gather_plan(tree: DataFrame) -> DataFrame:
    """parent, ids, words: every parent gathers all its children's ids in one round; memory grows with the hub."""
    return tree.where("parent is not null").groupBy("parent").agg(F.transform(F.array_sort(F.collect_list(F.struct("rank", "v"))), lambda x: x["v"]).alias("ids"), F.count("*").alias("words"))


def routing_table(ports: DataFrame, sources: list[int], order: ReadOrder | None = None) -> DataFrame:
    """src, dst, port: the full table of the sampled sources, n rows each (shortest paths)."""
    out = None
    for s in sources:
        t = bfs_tree(ports, s, order)
        top = t.where("level = 1").select(F.col("v").alias("first"), F.col("port_at_parent").alias("port"))
        reach = top.select(F.col("first").alias("dst"), "port")
        front = reach
        for _ in range(2, (t.agg(F.max("level")).first()[0] or 0) + 1):
            front = t.select(F.col("v").alias("next"), "parent").join(front, F.col("parent") == F.col("dst")).select(F.col("next").alias("dst"), "port")
            reach = reach.union(front)
        part = reach.select(F.lit(s).cast("bigint").alias("src"), "dst", "port")
        out = part if out is None else out.union(part)
    if out is None:
        raise ValueError("no sources")
    return out


def descendants_by_interval(numbered: DataFrame, leaves: bool = True) -> DataFrame:
    """v, weight from the numbers alone: leaves (or vertices) with a number in [lo, new_id], by prefix sums and one equi-join."""
    own = F.when(F.col("n_children") == 0, 1).otherwise(0) if leaves else F.lit(1)
    rows = numbered.select("v", "lo", "new_id", own.cast("bigint").alias("own"), F.lit(0).alias("all"))
    sums = ranked(rows, "all", [F.col("new_id")], "before", F.col("own"), hubs=True)
    start = sums.select(F.col("new_id").alias("lo"), F.col("before").alias("from"))
    return sums.join(start, "lo").select("v", (F.col("before") + F.col("own") - F.col("from")).cast("bigint").alias("weight"))
