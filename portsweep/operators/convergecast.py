"""Weights from the leaves up, heavy children, and what the two ways of answering cost."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.rounds import cut, upward
from .ports import degrees


def subtree_weights(tree: DataFrame, kind: str = "leaves") -> DataFrame:
    """v, weight, size, height: leaves below (kind 'leaves') or vertices (kind 'nodes') as weight."""
    one = F.lit(1).cast("bigint")
    leaf = (F.col("n_children") == 0).cast("bigint")
    own = tree.select("v", leaf.alias("leaves"), one.alias("size"), F.col("level").alias("deepest"))
    up = upward(tree, own, {"leaves": F.sum, "size": F.sum, "deepest": F.max})
    full = up.join(tree.select("v", "level"), "v")
    return cut(full.select("v", F.col("leaves" if kind == "leaves" else "size").alias("weight"), "size", (F.col("deepest") - F.col("level")).alias("height")))


def mark_heavy(tree: DataFrame, weights: DataFrame, b: int = 2, strict: bool = False) -> DataFrame:
    """tree with weight, size, height, is_heavy (null at the root): weight * b >= (or >) the parent's weight."""
    if b < 2:
        raise ValueError("b must be 2 or more")
    t = tree.join(weights, "v")
    up = weights.select(F.col("v").alias("parent"), F.col("weight").alias("up_weight"))
    mine = F.col("weight") * b
    test = mine > F.col("up_weight") if strict else mine >= F.col("up_weight")
    return cut(t.join(up, "parent", "left").withColumn("is_heavy", test).drop("up_weight"))


def heavy_lists(marked: DataFrame, id_col: str = "v") -> DataFrame:
    """v, heavy: at most b (id, port) of heavy children, by id."""
    mine = marked.where("is_heavy").groupBy(F.col("parent").alias("v"))
    return mine.agg(F.array_sort(F.collect_list(F.struct(F.col(id_col).alias("new_id"), F.col("port_at_parent").alias("port")))).alias("heavy"))


def convergecast_cost(marked: DataFrame, ports: DataFrame) -> DataFrame:
    """asks, answers, weights, ask_total, broadcast_total: messages of both ways to answer.

    A child asks from the round after its weight until it is answered, which its parent can do once its own tallest child
    has reported; one whose port is read before that child's in the same round asks once more.
    """
    up = marked.select(F.col("v").alias("parent"), F.col("height").alias("up_height"))
    below = marked.where("parent is not null").join(up, "parent").select("parent", "v", "height", "up_height", "port_at_parent")
    tall = below.where("height = up_height - 1").groupBy("parent").agg(F.max("port_at_parent").alias("last_port"))
    late = (F.col("height") <= F.col("up_height") - 2) & (F.col("port_at_parent") < F.col("last_port"))
    asked = below.join(tall, "parent").agg(F.sum(F.greatest(F.lit(3), F.col("up_height") - F.col("height") + 1) + late.cast("bigint")).cast("bigint").alias("asks"), F.count("*").alias("weights"))
    inner = marked.where("n_children > 0").join(degrees(ports), "v").agg(F.sum("degree").alias("inner_ports"))
    both = asked.crossJoin(inner)  # one row each
    asks = F.coalesce("asks", F.lit(0)).cast("bigint")
    return both.select(asks.alias("asks"), (3 * F.col("weights")).alias("answers"), "weights", (asks + 4 * F.col("weights")).alias("ask_total"), (F.col("weights") + F.coalesce("inner_ports", F.lit(0))).cast("bigint").alias("broadcast_total"))


def choose_answer_mode(cost: DataFrame) -> DataFrame:
    """mode: the cheaper of the two ways."""
    return cost.withColumn("mode", F.when(F.col("ask_total") < F.col("broadcast_total"), "ask").otherwise("broadcast"))


def bottomup(tree: DataFrame, values: DataFrame, sums: dict[str, Callable[[str], Column]]) -> DataFrame:
    """v and an aggregate of values (v, columns of sums) over each subtree; sums such as {"revenue": F.sum}."""
    return upward(tree, values, sums)
