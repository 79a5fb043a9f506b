"""Streaming forms: a vertex as a streaming algorithm, rounds as windows, and churn as micro-batches."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..functions.halffull import portion_labels
from ..operators.healing import Healed, heal, route_healed
from ..operators.routing import router_state


def round_fold(messages: DataFrame, fold: Callable[[str], Column], width: str = "1 hour", late: str = "1 day", reader: str = "dst", value: str = "a", ts: str = "ts") -> DataFrame:
    """round (window), reader, folded: a round is a tumbling window; its answer comes when the watermark closes it, later messages are dropped."""
    w = messages.withWatermark(ts, late)
    return w.groupBy(F.window(ts, width).alias("round"), reader).agg(fold(value).alias("folded"))


def sliding_rate(messages: DataFrame, width: str = "1 day", step: str = "6 hours", late: str = "1 day", ts: str = "ts") -> DataFrame:
    """round (sliding window), messages: the moving message rate."""
    return messages.withWatermark(ts, late).groupBy(F.window(ts, width, step).alias("round")).agg(F.count("*").alias("messages"))


def activity_sessions(messages: DataFrame, gap: str = "6 hours", late: str = "1 day", reader: str = "user_id", ts: str = "ts") -> DataFrame:
    """Sessions of each reader's activity."""
    return messages.withWatermark(ts, late).groupBy(F.session_window(ts, gap).alias("session"), reader).agg(F.count("*").alias("messages"))


def one_read_per_port(messages: DataFrame, keys: tuple[str, ...] = ("event_id",), late: str = "1 day", ts: str = "ts") -> DataFrame:
    """Each message once, however often it arrives within the watermark."""
    return messages.withWatermark(ts, late).dropDuplicatesWithinWatermark(list(keys))


def matched(left: DataFrame, right: DataFrame, key: str, within: str = "1 hour", late: str = "1 day") -> DataFrame:
    """Pairs of two streams (key, ts) whose times lie within an interval; both sides keep bounded state."""
    a = left.withWatermark("ts", late).alias("l")
    b = right.withWatermark("ts", late).alias("r")
    return a.join(b, F.expr(f"l.{key} = r.{key} AND r.ts BETWEEN l.ts AND l.ts + INTERVAL {within}"))


def known_readers(messages: DataFrame, state: DataFrame, reader: str = "dst") -> DataFrame:
    """A stream's messages with what a static frame (v, ...) holds about their readers; others are dropped."""
    return messages.join(state.withColumnRenamed("v", reader), reader)


def sweep_node(messages: DataFrame, words: int = 2, reader: str = "dst", value: str = "a") -> DataFrame:
    """reader, sent: the greatest value so far, sent again only when it grows. State per vertex: `words` longs, whatever its degree."""

    def step(key: tuple, chunks: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        best, seen = state.get if state.exists else (None, 0)
        out = []
        for chunk in chunks:
            for v in chunk[value].tolist():
                seen += 1
                if best is None or v > best:
                    best = v
                    out.append((key[0], int(v)))
        state.update((int(best), int(seen)))
        yield pd.DataFrame(out, columns=[reader, "sent"])

    assert words == 2
    return messages.groupBy(reader).applyInPandasWithState(step, f"{reader} bigint, sent bigint", "best bigint, seen bigint", "append", "NoTimeout")


_PORTION = "parent bigint, rank bigint, v bigint, leaf_parent bigint, helper_parent bigint, `left` bigint, `right` bigint, left_is_leaf boolean, right_is_leaf boolean, is_successor boolean, held bigint"


def named(y: int, size: int) -> set[int]:
    """The labels that portion y names."""
    leaf, helper, left, _, right, _ = portion_labels(y, size)
    return {x for x in (leaf, helper, left, right) if x is not None}


def sweep_portions(children: DataFrame) -> DataFrame:
    """The portions of every parent from one sweep over its children, and how many ids were held when each left.

    children: a stream of parent, rank, v, size, grandparent in which a parent's children come in rank order. A portion
    leaves with the last id it names; an id is dropped when no portion that is still open names it. The state of a parent
    is the ids and portions that are open, a few times log2(size).
    """

    def step(key: tuple, chunks: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        ranks, ids, open_ = state.get if state.exists else ([], [], [])
        known, waiting, out = dict(zip(ranks, ids, strict=True)), list(open_), []
        for chunk in chunks:
            for rank, v, size, above in sorted(zip(chunk["rank"], chunk["v"], chunk["size"], chunk["grandparent"], strict=True)):
                known[int(rank)] = int(v)
                waiting.append(int(rank))
                size = int(size)
                for y in list(waiting):
                    leaf, helper, left, left_leaf, right, right_leaf = portion_labels(y, size)
                    if any(x > rank for x in named(y, size)):
                        continue
                    told = [None if x is None else known[x] for x in (leaf, helper, left, right)]
                    last = y == size - 1
                    if last:
                        told[1] = None if pd.isna(above) else int(above)
                    out.append((key[0], y, known[y], *told, left_leaf, None if last else right_leaf, last, len(known)))
                    waiting.remove(y)
                # Two children name each other or not at all, so a later portion can only name children that still wait.
                needed = set(waiting) | {x for y in waiting for x in named(y, size)}
                known = {k: x for k, x in known.items() if k in needed}
        state.update((list(known), list(known.values()), waiting))
        yield pd.DataFrame(out, columns=["parent", "rank", "v", "leaf_parent", "helper_parent", "left", "right", "left_is_leaf", "right_is_leaf", "is_successor", "held"])

    return children.groupBy("parent").applyInPandasWithState(step, _PORTION, "ranks array<bigint>, ids array<bigint>, waiting array<bigint>", "append", "NoTimeout")


def run_event_churn(events: DataFrame, ports: DataFrame, numbered: DataFrame, labels: DataFrame, out: str, users: int, vertex: Callable[[Column], Column]) -> StreamingQuery:
    """Events as churn: an `error` deletes its user's vertex, a `click` sends a packet to the vertex of user (user * 7 + 3) mod users.

    events: a stream of event_id, user_id, event_type; vertex makes the id of a user's vertex. A micro-batch heals after its
    deletions and then routes its packets with the labels from the start; seq, src, dst, status, hops stand in
    out/packets/batch=number. Repeated batches overwrite their own output, and repeated events count once.
    """
    state = router_state(numbered, labels)

    def apply(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        once = batch.dropDuplicates(["event_id"])
        once.where("event_type = 'error'").select(vertex(F.col("user_id")).alias("v")).distinct().write.mode("overwrite").parquet(f"{out}/deleted/batch={number}")
        gone = spark.read.schema("v bigint, batch int").parquet(f"{out}/deleted").where(F.col("batch") <= number)
        packets = once.where("event_type = 'click'").select(F.col("event_id").alias("seq"), vertex(F.col("user_id")).alias("src"), vertex(F.pmod(F.col("user_id") * 7 + 3, F.lit(users))).alias("dst"))
        route_healed(packets, state, ports, heal(numbered, gone)).write.mode("overwrite").parquet(f"{out}/packets/batch={number}")

    return events.writeStream.foreachBatch(apply).option("checkpointLocation", f"{out}/checkpoint").trigger(availableNow=True).start()


def run_churn(events: DataFrame, numbered: DataFrame, out: str, keep: Callable[[DataFrame], DataFrame], on_batch: Callable[[int, Healed], None] | None = None) -> StreamingQuery:
    """Heals after every micro-batch of deletions; keep(batch) gives the batch's deleted v.

    The healed tree depends on the set of deleted vertices only, so a batch writes its deletions under its number (a
    repeated batch overwrites itself) and heals from all of them.
    """

    def apply(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        keep(batch).select("v").distinct().write.mode("overwrite").parquet(f"{out}/deleted/batch={number}")
        gone = spark.read.schema("v bigint, batch int").parquet(f"{out}/deleted").where(F.col("batch") <= number)
        healed = heal(numbered, gone)
        healed.nodes.write.mode("overwrite").parquet(f"{out}/healed/batch={number}")
        if on_batch:
            on_batch(number, healed)

    return events.writeStream.foreachBatch(apply).option("checkpointLocation", f"{out}/checkpoint").trigger(availableNow=True).start()
