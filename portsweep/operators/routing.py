"""Forwarding by labels on the intact tree."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import ReadOrder
from ..plans.rounds import cut, spread
from .bfs import bfs_tree
from .convergecast import heavy_lists
from .ports import live


def router_state(numbered: DataFrame, labels: DataFrame) -> DataFrame:
    """v, new_id, lo, light_lo, parent_port, light_level, heavy: what one vertex keeps."""
    return numbered.select("v", "new_id", "lo", "light_lo", "parent_port").join(labels.select("v", "light_level", "light_path"), "v").join(heavy_lists(numbered, "new_id"), "v", "left")


def next_hop(to_id: Column, to_path: Column) -> tuple[Column, Column]:
    """(action, port) at a vertex (columns of router_state) for a packet to label (to_id, to_path)."""
    here, outside = F.col("new_id") == to_id, (to_id < F.col("lo")) | (to_id > F.col("new_id"))
    light = to_id >= F.col("light_lo")
    heavy = F.get(F.filter("heavy", lambda h: h["new_id"] >= to_id), F.lit(0))
    action = F.when(here, "deliver").when(outside, "up").when(light, "light").otherwise("heavy")
    port = F.when(here, F.lit(None)).when(outside, F.col("parent_port")).when(light, F.get(to_path, F.col("light_level").cast("int"))).otherwise(heavy["port"])
    return action, port.cast("bigint")


def route(pairs: DataFrame, state: DataFrame, ports: DataFrame) -> DataFrame:
    """seq, src, dst, status, hops, path: packets (seq, src, dst) forwarded hop by hop, all in step.

    status: delivered, or lost if an end is unknown. A hop is one equi-join of the packets under way with the state.
    """
    target = state.select(F.col("v").alias("dst"), F.col("new_id").alias("to_id"), F.col("light_path").alias("to_path"))
    known = pairs.join(target, "dst").join(state.select(F.col("v").alias("src")), "src")
    under = cut(known.select("seq", "src", "dst", "to_id", "to_path", F.col("src").alias("at"), F.array("src").alias("path")))
    e = live(ports).select(F.col("src").alias("at"), F.col("port").alias("out"), F.col("dst").alias("onto"))
    e = cut(e.join(spread(cut(state.select(F.col("v").alias("at")))), "at", "left_semi"))  # hops stay in the state's component
    here = state.drop("light_path").withColumnRenamed("v", "at")
    arrived = [under.where("at = dst")]
    while True:  # a packet climbs, then goes down: it ends after twice the depth of the tree
        under = under.where("at <> dst")
        action, out = next_hop(F.col("to_id"), F.col("to_path"))
        moved = under.join(here, "at").withColumns({"action": action, "out": out}).join(e, ["at", "out"])
        under = cut(moved.select("seq", "src", "dst", "to_id", "to_path", F.col("onto").alias("at"), F.concat("path", F.array("onto")).alias("path")))
        if under.isEmpty():
            break
        arrived.append(under.where("at = dst"))
        if len(arrived) > 24:
            arrived = [cut(_joined(arrived))]
    done = _joined(arrived)
    told = done.select("seq", F.lit("delivered").alias("status"), (F.size("path") - 1).cast("bigint").alias("hops"), "path")
    return pairs.select("seq", "src", "dst").join(told, "seq", "left").withColumn("status", F.coalesce("status", F.lit("lost")))


def _joined(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def stretch(routes: DataFrame, ports: DataFrame, sources: list[int], order: ReadOrder | None = None) -> DataFrame:
    """seq, src, dst, hops, distance of the routes that begin at the sampled sources; stretch is hops / distance."""
    out = None
    for s in sources:
        far = bfs_tree(ports, s, order).select(F.col("v").alias("dst"), F.col("level").alias("distance"))
        part = routes.where(F.col("src") == s).join(far, "dst").select("seq", "src", "dst", "hops", "distance")
        out = part if out is None else out.union(part)
    if out is None:
        raise ValueError("no sources")
    return out
