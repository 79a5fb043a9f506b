"""Routing labels: the number of a vertex and the ports of the light links on its path from the root."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.rounds import DEEP, cut, downward, path_sums
from .ports import degrees

_NONE = "cast(array() as array<bigint>)"


def routing_labels(numbered: DataFrame, mode: str = "wide") -> DataFrame:
    """v, new_id, light_level, light_path. wide: whole paths are handed down (in deep trees by doubling); narrow: one port per round, nearest first."""
    if mode == "wide":
        return _doubling(numbered) if (numbered.agg(F.max("level")).first()[0] or 0) > DEEP else _wide(numbered)
    if mode == "narrow":
        return _narrow(numbered)
    if mode == "doubling":
        return _doubling(numbered)
    raise ValueError("mode is wide, narrow or doubling")


def _own(numbered: DataFrame) -> DataFrame:
    light = F.when(F.col("parent").isNull() | F.col("is_heavy"), F.expr(_NONE)).otherwise(F.array("port_at_parent"))
    return numbered.select("v", "parent", "level", "new_id", light.alias("own"))


def _done(paths: DataFrame, numbered: DataFrame) -> DataFrame:
    return cut(paths.join(numbered.select("v", "new_id"), "v").select("v", "new_id", F.size("light_path").cast("bigint").alias("light_level"), "light_path"))


def _wide(numbered: DataFrame) -> DataFrame:
    def step(level: DataFrame, above: DataFrame) -> DataFrame:
        return level.join(above.select(F.col("v").alias("parent"), F.col("light_path").alias("up")), "parent").select("v", F.concat("up", "own").alias("light_path"))

    return _done(downward(_own(numbered), lambda r: r.select("v", F.col("own").alias("light_path")), step), numbered)


def _narrow(numbered: DataFrame) -> DataFrame:
    own = _own(numbered)
    told = cut(own.select("v", F.col("parent").alias("anc"), F.col("own").alias("light_path")))
    above = own.select(F.col("v").alias("anc"), F.col("parent").alias("next"), F.col("own").alias("port"))
    while not told.where("anc is not null").isEmpty():
        told = cut(told.join(above, "anc", "left").select("v", F.col("next").alias("anc"), F.when(F.col("anc").isNull(), F.col("light_path")).otherwise(F.concat("port", "light_path")).alias("light_path")))
    return _done(told.drop("anc"), numbered)


def _doubling(numbered: DataFrame) -> DataFrame:
    """For deep trees: path pieces of twice the length each round."""
    told = cut(_own(numbered).select("v", F.col("parent").alias("anc"), F.col("own").alias("light_path")))
    while not told.where("anc is not null").isEmpty():
        a = told.select(F.col("v").alias("anc"), F.col("anc").alias("next"), F.col("light_path").alias("up"))
        told = cut(told.join(a, "anc", "left").select("v", F.col("next").alias("anc"), F.when(F.col("anc").isNull(), F.col("light_path")).otherwise(F.concat("up", "light_path")).alias("light_path")))
    return _done(told.drop("anc"), numbered)


def top_heavy(numbered: DataFrame) -> DataFrame:
    """v, top_heavy: the child of the root above v (or v itself) is heavy."""
    one = F.when((F.col("level") == 1) & F.col("is_heavy"), 1).otherwise(0)
    return path_sums(numbered.select("v", "parent", one.alias("one")), "one").select("v", (F.col("total") > 0).alias("top_heavy"))


def label_cost(numbered: DataFrame, labels: DataFrame, ports: DataFrame) -> DataFrame:
    """wide, narrow: messages of both modes; widest: words of the largest wide message."""
    deg = degrees(ports)
    top = top_heavy(numbered)
    rows = numbered.select("v", "parent", "n_children").join(labels.select("v", "light_level"), "v").join(deg, "v").join(top, "v")
    extra = F.when(F.col("parent").isNotNull() & (F.col("n_children") > 0), (F.col("degree") - 1) * (F.col("light_level") + F.col("top_heavy").cast("bigint"))).otherwise(0)
    return rows.agg(F.sum("degree").alias("wide"), (F.sum("degree") + F.sum(extra)).alias("narrow"), (F.max("light_level") + 1).alias("widest"))
