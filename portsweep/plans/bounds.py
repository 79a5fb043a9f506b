"""Costs measured from message frames and state, beside the proved bounds with explicit constants."""

from __future__ import annotations

from math import ceil, log2

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import SweepLimits, word_bits
from ..operators import frames
from ..operators.bfs import bfs_termination
from ..operators.recovery import adversarial_portions, sweep_memory
from ..operators.relabel import token_trace

#: Single registers of a vertex in each protocol: own id, best or parent port, counters, flags. Lists come on top, as measured.
REGISTERS = {"leader": 2, "bfs": 6, "weights": 6, "relabel": 10, "labels": 4, "portions": 2}


def cost_frames(ports: DataFrame, numbered: DataFrame, labels: DataFrame, b: int = 2) -> DataFrame:
    """method, variant, rounds, messages, max_message_words, max_memory_words; raises LimitError over the limits of the model."""
    cost = frames.metered(frames.each_frame(ports, numbered, labels), frames.costs)
    heavy = numbered.where("is_heavy").groupBy("parent").count().agg(F.max("count")).first()[0] or 0
    path = labels.agg(F.max("light_level")).first()[0] or 0
    sizes = numbered.where("n_children > 0").select(F.col("n_children").alias("size")).distinct()
    swept = sweep_memory(sizes).agg(F.max("peak_ids")).first()[0] or 0
    picked = adversarial_portions(numbered).agg(F.max("held")).first()[0] or 0
    lists = [("weights", None, 2 * heavy), ("labels", None, path), ("portions", "self_ordered", swept), ("portions", "adversarial", picked)]
    held = F.lit(0)
    for method, variant, words in lists:
        held = F.when((F.col("method") == method) & (F.lit(variant is None) | (F.col("variant") == (variant or ""))), F.lit(int(words))).otherwise(held)
    own = F.create_map(*[x for k, v in REGISTERS.items() for x in (F.lit(k), F.lit(v))])
    out = cost.withColumn("max_memory_words", (own[F.col("method")] + held).cast("bigint"))
    n = numbered.count()
    words = max(2, b) * 8 + ceil(5 * log2(max(2, n)))
    frames.enforce(out, SweepLimits(max(words * word_bits(n), word_bits(n) ** 2), max(9 * word_bits(n), word_bits(n) ** 2), n))
    return out


def bound_report(ports: DataFrame, numbered: DataFrame, labels: DataFrame, b: int = 2) -> DataFrame:
    """method, measure, measured, bound, ok."""
    s = ports.sparkSession
    n, depth, most, leaves = numbered.agg(F.count("*"), F.max("level"), F.max("n_children"), F.sum((F.col("n_children") == 0).cast("bigint"))).first()
    m = ports.where("alive").count() // 2
    degree = ports.where("alive").groupBy("src").count().agg(F.max("count")).first()[0]
    cost = {(r["method"], r["variant"]): r for r in cost_frames(ports, numbered, labels, b).collect()}  # nine rows
    term = bfs_termination(numbered, ports).agg(F.max("done_round")).first()[0]
    uses = token_trace(numbered, ports).groupBy(F.least("src", "dst"), F.greatest("src", "dst")).agg(F.count("*").alias("n")).agg(F.max("n")).first()[0]
    heavy = numbered.where("is_heavy").groupBy("parent").count().agg(F.max("count")).first()[0] or 0
    light = labels.agg(F.max("light_level")).first()[0]
    picked = adversarial_portions(numbered).agg(F.max("held")).first()[0] or 0
    diameter = 2 * depth  # the tree's is at most that of a walk over its root
    rows = [
        ("leader", "rounds", cost["leader", "fixpoint"]["rounds"], diameter + 1),
        ("bfs", "rounds", cost["bfs", "ascending"]["rounds"], depth + 1),
        ("bfs", "last stop", term, depth + 2),
        ("bfs", "messages", cost["bfs", "ascending"]["messages"], 2 * m),
        ("weights", "ask messages", cost["weights", "ask"]["messages"], n * (depth + 8)),
        ("weights", "broadcast messages", cost["weights", "broadcast"]["messages"], n * (degree + 1)),
        ("weights", "heavy children", heavy, b),
        ("relabel", "messages", cost["relabel", "walk"]["messages"], 4 * m),
        ("relabel", "uses of a link", uses, 4),
        ("labels", "wide messages", cost["labels", "wide"]["messages"], 2 * m),
        ("labels", "narrow messages", cost["labels", "narrow"]["messages"], 2 * m * (depth + 1)),
        ("labels", "light level", light, ceil(log2(max(2, leaves)))),
        ("labels", "bits of a wide message", cost["labels", "wide"]["max_message_words"] * word_bits(n), word_bits(n) ** 2 * 2),
        ("portions", "rounds", cost["portions", "self_ordered"]["rounds"], 1),
        ("portions", "adversarial rounds", cost["portions", "adversarial"]["rounds"], most),
        ("portions", "ids held", cost["portions", "self_ordered"]["max_memory_words"], ceil(5 * log2(max(2, most)))),
        ("portions", "ids held against an adversary", picked, 5),
        ("portions", "words", cost["portions", "self_ordered"]["max_message_words"], 9),
    ]
    out = s.createDataFrame([(a, x, int(y), int(z)) for a, x, y, z in rows], "method string, measure string, measured bigint, bound bigint")
    return out.withColumn("ok", F.col("measured") <= F.col("bound"))
