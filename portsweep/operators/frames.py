"""Message frames: what each protocol sends, row by row, and the costs that are read off them.

method, variant, round, src, dst, kind, words; a word holds one id, port or count. For the walk of the token the round is
its step. Frames grow with the messages, so they are for metering; the methods themselves do not need them.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import SweepLimits
from ..plans.rounds import cut
from .labels import top_heavy
from .leader import elect_leader
from .ports import live
from .recovery import adversarial_portions, recovery_portions
from .relabel import token_trace

COLUMNS = ("method", "variant", "round", "src", "dst", "kind", "words")


def _frame(rows: DataFrame, method: str, variant: str, turn: Column, src: str, dst: str, kind: str | Column, words: Column | int) -> DataFrame:
    kind, words = F.lit(kind) if isinstance(kind, str) else kind, F.lit(words) if isinstance(words, int) else words
    return rows.select(F.lit(method).alias("method"), F.lit(variant).alias("variant"), turn.cast("bigint").alias("round"), F.col(src).alias("src"), F.col(dst).alias("dst"), kind.alias("kind"), words.cast("bigint").alias("words"))


def _out(rows: DataFrame, ports: DataFrame) -> DataFrame:
    """rows (v, ...) once for each live port: columns src, dst, port."""
    return rows.join(live(ports).select("src", "dst", "port"), F.col("v") == F.col("src"))


def _times(rows: DataFrame, n: Column) -> DataFrame:
    """Each row n times, numbered by t from 0; n is bounded by the tree's height."""
    return rows.where(n > 0).withColumn("t", F.explode(F.sequence(F.lit(0).cast("bigint"), n.cast("bigint") - 1)))


def leader_frames(ports: DataFrame) -> DataFrame:
    sent: list[DataFrame] = []
    elect_leader(ports, sent=sent)
    return _frame(_out(reduce(DataFrame.unionByName, sent), ports), "leader", "fixpoint", F.col("round"), "src", "dst", "candidate", 1)


def bfs_frames(tree: DataFrame, ports: DataFrame) -> DataFrame:
    """A vertex asks on all ports but its parent's when it has joined, and accepts on that one."""
    out = _out(tree.select("v", "parent", "level"), ports)
    up = F.col("dst").eqNullSafe(F.col("parent"))
    return _frame(out, "bfs", "ascending", F.col("level"), "src", "dst", F.when(up, "accept").otherwise("join"), 1)


def weight_frames(marked: DataFrame, ports: DataFrame, variant: str) -> DataFrame:
    """ask: a child asks from the round after its weight until its parent's answer is in; broadcast: the parent tells all its ports once."""
    below = marked.where("parent is not null").select("v", "parent", "height", "port_at_parent")
    own = _frame(below, "weights", variant, F.col("height"), "v", "parent", "weight", 2)
    if variant == "broadcast":
        told = _out(marked.where("n_children > 0").select("v", "height"), ports)
        return own.union(_frame(told, "weights", variant, F.col("height"), "src", "dst", "answer", 2))
    up = marked.select(F.col("v").alias("parent"), F.col("height").alias("up_height"))
    both = below.join(up, "parent")
    tall = both.where("height = up_height - 1").groupBy("parent").agg(F.max("port_at_parent").alias("last_port"))
    late = (F.col("height") <= F.col("up_height") - 2) & (F.col("port_at_parent") < F.col("last_port"))
    # The weights are all in at up_height; an answer then takes a round, and the asks under way meanwhile are answered too.
    asks = F.greatest(F.lit(3), F.col("up_height") - F.col("height") + 1) + late.cast("bigint")
    each = _times(both.join(tall, "parent"), asks)
    answered = _times(both, F.lit(3))
    asked = _frame(each, "weights", variant, F.col("height") + 1 + F.col("t"), "v", "parent", "ask", 2)
    return own.union(asked).union(_frame(answered, "weights", variant, F.greatest(F.col("up_height"), F.col("height") + 1) + 1 + F.col("t"), "parent", "v", "answer", 1))


def walk_frames(numbered: DataFrame, ports: DataFrame) -> DataFrame:
    """The token's hops, and each child's place in its parent's list, told when the token has come back."""
    trace = token_trace(numbered, ports)
    words = F.when(F.col("kind").isin("up", "refuse"), 3).otherwise(1)
    hops = _frame(trace, "relabel", "walk", F.col("step"), "src", "dst", "hop", words)
    back = trace.where("kind = 'up'").select("step", F.col("src").alias("v"), F.col("dst").alias("parent"))
    return hops.union(_frame(back, "relabel", "walk", F.col("step") + 1, "parent", "v", "sibling", 2))


def label_frames(numbered: DataFrame, labels: DataFrame, ports: DataFrame, variant: str) -> DataFrame:
    """wide: the path goes out on all ports once; narrow: a port at first, then one relayed port a round on all ports but the parent's."""
    rows = numbered.select("v", "parent", "level", "n_children").join(labels.select("v", "light_level"), "v")
    if variant == "wide":
        return _frame(_out(rows, ports), "labels", "wide", F.col("level"), "src", "dst", "label", F.col("light_level") + 1)
    first = _frame(_out(rows, ports), "labels", "narrow", F.lit(0), "src", "dst", "port", 2)
    relays = rows.where("parent is not null and n_children > 0").join(top_heavy(numbered), "v")
    each = _times(relays, F.col("light_level") + F.col("top_heavy").cast("bigint"))
    on = _out(each, ports).where(F.col("dst") != F.col("parent"))
    return first.union(_frame(on, "labels", "narrow", F.col("t") + 1, "src", "dst", "relay", 2))


def _portion_words() -> Column:
    """Two words for each id with its port, and the successor's mark."""
    return sum((F.col(c).isNotNull().cast("bigint") for c in ("leaf_parent", "helper_parent", "left", "right")), F.lit(0)) * 2 + 1


def portion_frames(numbered: DataFrame, variant: str) -> DataFrame:
    if variant == "self_ordered":
        below = numbered.where("parent is not null").select("v", "parent")
        offers = _frame(below, "portions", variant, F.lit(0), "v", "parent", "offer", 3)
        return offers.union(_frame(recovery_portions(numbered), "portions", variant, F.lit(0), "parent", "v", "portion", _portion_words()))
    rounds = adversarial_portions(numbered)
    children = numbered.where("parent is not null").select("parent", F.col("v").alias("child"))
    offers = _frame(rounds.select("round", "parent").join(children, "parent"), "portions", variant, F.col("round"), "child", "parent", "offer", 3)
    return offers.union(_frame(rounds, "portions", variant, F.col("round"), "parent", "v", "portion", _portion_words()))


def each_frame(ports: DataFrame, numbered: DataFrame, labels: DataFrame) -> Iterator[DataFrame]:
    """The frames of all protocols on one network, one for each method and variant, made as they are asked for."""
    yield leader_frames(ports)
    yield bfs_frames(numbered, ports)
    for v in ("ask", "broadcast"):
        yield weight_frames(numbered, ports, v)
    yield walk_frames(numbered, ports)
    for v in ("wide", "narrow"):
        yield label_frames(numbered, labels, ports, v)
    for v in ("self_ordered", "adversarial"):
        yield portion_frames(numbered, v)


def all_frames(ports: DataFrame, numbered: DataFrame, labels: DataFrame) -> DataFrame:
    """The frames of all protocols on one network."""
    return reduce(DataFrame.union, each_frame(ports, numbered, labels))


def metered(frames: Iterator[DataFrame], meter: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """meter (costs or by_kind) over each frame in a job of its own: plans and statistics of all at once fill a small driver."""
    return reduce(DataFrame.union, [cut(meter(f)) for f in frames])


def by_kind(frames: DataFrame) -> DataFrame:
    """method, variant, kind, messages, max_words."""
    return frames.groupBy("method", "variant", "kind").agg(F.count("*").alias("messages"), F.max("words").alias("max_words"))


def costs(frames: DataFrame) -> DataFrame:
    """method, variant, rounds, messages, max_message_words."""
    return frames.groupBy("method", "variant").agg((F.max("round") - F.min("round") + 1).alias("rounds"), F.count("*").alias("messages"), F.max("words").alias("max_message_words"))


def enforce(cost: DataFrame, limits: SweepLimits) -> None:
    """Raise LimitError if any row of cost (max_message_words, max_memory_words) is over the limits."""
    for r in cost.select("max_memory_words", "max_message_words").distinct().collect():  # a row per protocol at most
        limits.enforce(r["max_memory_words"], r["max_message_words"])
