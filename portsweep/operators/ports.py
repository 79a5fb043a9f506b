"""Ports, sends, broadcasts and receives as frame operations."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..plans.rounds import cut

#: A group beyond this many rows is ranked in two phases rather than by one task.
HUB = 1_000_000

_NONE = "cast(null as bigint)"

#: Groups are first counted together by hash, in so many sums: no group is larger than the sum it is part of.
_COARSE = 16_384


def _hubs(df: DataFrame, *groups: str) -> bool:
    """Whether any group (a value of one of these columns) has more than HUB rows: counted by hash first, then only where that leaves it open."""
    each = df.select(F.explode(F.array(*groups)).alias("g"))
    coarse = each.groupBy(F.pmod(F.xxhash64("g"), F.lit(_COARSE)).alias("h")).agg(F.count("*").alias("n")).where(F.col("n") > HUB)
    full = [r["h"] for r in coarse.select("h").collect()]  # _COARSE rows at most
    if not full:
        return False
    each = each.where(F.pmod(F.xxhash64("g"), F.lit(_COARSE)).isin(full))
    return not each.groupBy("g").agg(F.count("*").alias("n")).where(F.col("n") > HUB).isEmpty()


def ranked(df: DataFrame, group: str, order: list[Column], name: str = "rank", weight: Column | None = None, hubs: bool | None = None) -> DataFrame:
    """df with the place (from 0) of each row among its group, or with weight the sum of weight over earlier rows.

    If a group is larger than HUB (or hubs is True), rows are range-partitioned by (group, order); places inside a range
    and counts of earlier ranges add up, so no task sees a whole hub.
    """
    value = F.lit(1).cast("bigint") if weight is None else weight
    if hubs is None:
        hubs = _hubs(df, group)
    if not hubs:
        before = F.sum(value).over(W.partitionBy(group).orderBy(*order).rowsBetween(W.unboundedPreceding, -1))
        return df.withColumn(name, F.coalesce(before, F.lit(0)).cast("bigint"))
    parts = cut(df.withColumn("__value", value).repartitionByRange(group, *order).withColumn("__part", F.spark_partition_id()))
    inner = F.sum("__value").over(W.partitionBy("__part", group).orderBy(*order).rowsBetween(W.unboundedPreceding, -1))
    totals = parts.groupBy(group, "__part").agg(F.sum("__value").alias("__sum"))
    ahead = totals.select(group, "__part", F.coalesce(F.sum("__sum").over(W.partitionBy(group).orderBy("__part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("__ahead"))
    placed = parts.withColumn("__inner", F.coalesce(inner, F.lit(0))).join(ahead, [group, "__part"])
    return placed.withColumn(name, (F.col("__inner") + F.col("__ahead")).cast("bigint")).drop("__value", "__part", "__inner", "__ahead")


def assign_ports(edges: DataFrame, gap: int = 1, hubs: bool | None = None) -> DataFrame:
    """src, port, dst, rev_port, alive: two rows per edge (u, v); ports count neighbours by id, with gap - 1 dead ones before each."""
    edges = cut(edges.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")))
    if hubs is None:
        hubs = _hubs(edges, "u", "v")
    # Neighbours with smaller ids come first: a vertex counts them over the links whose greater end it is, and hands their number to its other links.
    placed = ranked(edges, "v", [F.col("u")], "rev_port", hubs=hubs)
    link = F.struct(F.col("u").alias("src"), F.col("v").alias("dst"), "rev_port", F.lit(1).cast("bigint").alias("step"))
    if hubs:
        counts = edges.groupBy("v").agg(F.count("*").alias("step"))
        rows = placed.select(link.alias("r")).select("r.*").union(counts.select("v", F.expr(_NONE), F.expr(_NONE), "step"))
    else:
        last = F.lead("u").over(W.partitionBy("v").orderBy("u")).isNull()
        count = F.struct(F.col("v").alias("src"), F.expr(_NONE).alias("dst"), F.expr(_NONE).alias("rev_port"), (F.col("rev_port") + 1).alias("step"))
        rows = placed.withColumn("last", last).select(F.explode(F.when(F.col("last"), F.array(link, count)).otherwise(F.array(link))).alias("r")).select("r.*")
    mine = ranked(rows, "src", [F.col("dst")], "port", F.col("step"), hubs=hubs).where("dst is not null")
    number = lambda c: F.col(c) * gap + (gap - 1)
    way = lambda a, x, b, y: F.struct(F.col(a).alias("src"), number(x).alias("port"), F.col(b).alias("dst"), number(y).alias("rev_port"))
    both = mine.select(F.explode(F.array(way("src", "port", "dst", "rev_port"), way("dst", "rev_port", "src", "port"))).alias("p"))
    return both.select("p.*", F.lit(True).alias("alive"))


def kill_ports(ports: DataFrame, dead: Column) -> DataFrame:
    """Ports of links for which `dead` (over src and dst, the same both ways) holds become dead; numbers stay."""
    return ports.withColumn("alive", F.col("alive") & ~dead)


def live(ports: DataFrame) -> DataFrame:
    return ports.where("alive")


def degrees(ports: DataFrame) -> DataFrame:
    return live(ports).groupBy(F.col("src").alias("v")).agg(F.count("*").alias("degree"))


def send(frontier: DataFrame, ports: DataFrame, port: str = "out_port") -> DataFrame:
    """One message on one port: frontier (v, payload, port) -> payload with src, dst, port, rev_port."""
    p = live(ports)
    return frontier.join(p, (F.col("v") == p.src) & (F.col(port) == p.port)).drop("v", port, "alive")


def broadcast_all(frontier: DataFrame, ports: DataFrame) -> DataFrame:
    """The same message on every port of each vertex of frontier (v, payload)."""
    p = live(ports)
    return frontier.join(p, F.col("v") == p.src).drop("v", "alive")


def broadcast_except(frontier: DataFrame, ports: DataFrame, skip: Column | DataFrame) -> DataFrame:
    """As broadcast_all but for ports where a predicate holds, or for those listed as (src, port)."""
    sent = broadcast_all(frontier, ports)
    return sent.join(skip, ["src", "port"], "left_anti") if isinstance(skip, DataFrame) else sent.where(~skip)


class Inbox:
    """The messages of a round as their readers see them. A buffer is read once: a second take() raises."""

    def __init__(self, messages: DataFrame):
        self._held: DataFrame | None = messages.withColumns({"reader": F.col("dst"), "in_port": F.col("rev_port")})

    def take(self) -> DataFrame:
        if self._held is None:
            raise RuntimeError("this round's messages have been read")
        held, self._held = self._held, None
        return held


def deliver(messages: DataFrame) -> Inbox:
    """The inbox of a round's messages, with columns `reader` and `in_port`."""
    return Inbox(messages)


def check_sweep(trace: DataFrame) -> DataFrame:
    """Rows of a trace (round, src, port, ...) that break the rule of one write per port and round; empty if none."""
    return trace.groupBy("round", "src", "port").agg(F.count("*").alias("writes")).where("writes > 1")
