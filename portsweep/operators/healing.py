"""Healing of a tree after deletions, and routing over what is left.

A deleted vertex is replaced by its plan, the half-full tree over its children's slots. A slot whose subtree holds no live
vertex is empty; an inner node (helper) of a plan stays while both its sides hold live vertices, and is passed over
otherwise. So the healed tree is a function of the set of deleted vertices alone: the order of deletions does not matter,
and any batch is healed by the same few joins, with pointer doubling over chains of deleted vertices.

Between two slots that follow each other and are not empty there is exactly one helper that stays, their lowest common
ancestor in the plan, named by the top bit in which their ranks differ. It is run by the last live vertex of the slot on
its left, and no vertex runs two. A vertex keeps one link per slot and one upward, and a helper has three links: degrees
grow by three at most. Slots keep the number intervals they had at the start, so labels need no update: a helper sends a
packet left or right by comparing its target with the end of its left part.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.halffull import _above
from ..plans.rounds import cut, double, small, spread, upward
from .ports import live, ranked
from .routing import _joined, next_hop

_NULL = "cast(null as bigint)"

#: Hops of a packet in one job: where the nodes' tables are sent to every task, and where each hop moves the packets.
_HOPS, _FAR_HOPS = 4, 2


@dataclass
class Healed:
    """nodes: a, b (b = -1: the real vertex a; else helper b of the plan of a), owner, up_a, up_b (null: root), lo, hi, split.
    tops: v, a, b: the node that now fills the place of v. dead: v."""

    nodes: DataFrame
    tops: DataFrame
    dead: DataFrame


def _resolve(rows: DataFrame) -> DataFrame:
    """v, a, b for rows (v, a, b, ptr): where a is null, what ptr resolves to; doubling, null if the chain ends."""
    rows = cut(rows)
    while not rows.where("a is null and ptr is not null").isEmpty():
        t = rows.select(F.col("v").alias("ptr"), F.col("a").alias("ta"), F.col("b").alias("tb"), F.col("ptr").alias("next"))
        done = F.col("a").isNotNull()
        met = rows.join(t, "ptr", "left")
        rows = cut(met.select("v", F.when(done, F.col("a")).otherwise(F.col("ta")).alias("a"), F.when(done, F.col("b")).otherwise(F.col("tb")).alias("b"), F.when(done | F.col("ta").isNotNull(), F.expr(_NULL)).otherwise(F.col("next")).alias("ptr")))
    return rows.drop("ptr")


def heal(numbered: DataFrame, deleted: DataFrame) -> Healed:
    """The healed tree. numbered: what relabel gives; deleted: v of all vertices deleted so far (repeats and strangers are ignored)."""
    t = numbered.select("v", "parent", "rank", "n_children", "lo", "new_id", "level")
    gone = deleted.select("v").distinct().withColumn("gone", F.lit(True))
    t = t.join(gone, "v", "left").withColumn("alive", F.col("gone").isNull()).drop("gone")
    below = upward(t, t.select("v", F.col("alive").cast("bigint").alias("lives")), {"lives": F.sum})
    t = cut(t.join(below, "v"))
    full = t.where("lives > 0")
    dead = t.where("not alive")

    plans = dead.select(F.col("v").alias("x"), F.col("n_children").alias("size"))
    slots = full.select(F.col("parent").alias("x"), F.col("rank").alias("r"), F.col("v").alias("c")).join(plans, "x")
    slots = cut(ranked(slots, "x", [F.col("r")], "i"))
    after = slots.select("x", (F.col("i") - 1).alias("i"), F.col("r").alias("after"))
    held = slots.groupBy("x").agg(F.count("*").alias("held"))
    slots = cut(slots.join(after, ["x", "i"], "left").join(held, "x").withColumn("is_last", F.col("after").isNull()))
    bit = "(length(bin(r ^ after)) - 1)"
    kept = slots.where("after is not null").withColumn("p", F.expr(f"shiftleft(shiftright(after, {bit}), {bit})"))
    kept = cut(kept.select("x", "size", (F.col("p") - 1).alias("y"), F.expr("cast(bit_count((p & -p) - 1) as int)").alias("z"), F.col("c").alias("left_slot")))

    def above(items: DataFrame, base: str, first: str, *keys: str) -> DataFrame:
        """keys, py: the nearest helper over each item in the same plan."""
        each = items.select("x", "size", *keys, F.col(base).alias("base"), F.explode(F.sequence(F.expr(first), F.expr("length(bin(size))"))).alias("j"))
        named = each.withColumn("label", F.expr(_above("base", "j"))).where("label <= size - 2")
        return named.join(kept.select("x", F.col("y").alias("label")), ["x", "label"]).groupBy("x", *keys).agg(F.min_by("label", "j").alias("py"))

    slot_up = above(slots, "r", "0", "c").select(F.col("c").alias("v"), "py")
    helper_up = above(kept.where("z + 1 <= length(bin(size))"), "y", "z + 1", "y")
    state = t.select(F.col("v").alias("parent"), F.col("alive").alias("p_alive"))
    ups = full.select("v", "parent").join(state, "parent", "left").join(slot_up, "v", "left")
    null = F.expr(_NULL)
    ups = ups.select(
        "v",
        F.when(F.col("p_alive") | F.col("py").isNotNull(), F.col("parent")).otherwise(null).alias("a"),
        F.when(F.col("p_alive"), F.lit(-1)).otherwise(F.col("py")).cast("bigint").alias("b"),
        F.when(F.col("p_alive") | F.col("py").isNotNull(), null).otherwise(F.col("parent")).alias("ptr"),
    )
    ups = _resolve(ups)
    crowns = kept.join(helper_up, ["x", "y"], "left_anti").select(F.col("x").alias("v"), F.col("y").alias("crown"))
    single = slots.where("held = 1").select(F.col("x").alias("v"), F.col("c").alias("only"))
    places = full.select("v", "alive").join(crowns, "v", "left").join(single, "v", "left")
    tops = _resolve(places.select("v", F.when(F.col("alive") | F.col("crown").isNotNull(), F.col("v")).otherwise(null).alias("a"), F.when(F.col("alive"), F.lit(-1)).otherwise(F.col("crown")).cast("bigint").alias("b"), F.when(F.col("alive") | F.col("crown").isNotNull(), null).otherwise(F.col("only")).alias("ptr")))
    ends = full.select("v", "alive").join(slots.where("is_last").select(F.col("x").alias("v"), "c"), "v", "left")
    ends = _resolve(ends.select("v", F.when(F.col("alive"), F.col("v")).otherwise(null).alias("a"), F.lit(-1).cast("bigint").alias("b"), F.when(F.col("alive"), null).otherwise(F.col("c")).alias("ptr")))

    real = full.where("alive").join(ups, "v").select(F.col("v").alias("a"), F.lit(-1).cast("bigint").alias("b"), F.col("v").alias("owner"), F.col("a").alias("up_a"), F.col("b").alias("up_b"), "lo", F.col("new_id").alias("hi"), null.alias("split"))
    span = kept.withColumns({"from": F.expr("y + 1 - shiftleft(1L, z)"), "to": F.expr("least(y + shiftleft(1L, z), size - 1)")})
    kids = t.where("parent is not null").select(F.col("parent").alias("x"), "rank", "lo", F.col("new_id").alias("hi"))
    span = span.join(kids.select("x", F.col("rank").alias("from"), "lo"), ["x", "from"]).join(kids.select("x", F.col("rank").alias("to"), "hi"), ["x", "to"]).join(kids.select("x", F.col("rank").alias("y"), F.col("hi").alias("split")), ["x", "y"])
    span = span.join(helper_up, ["x", "y"], "left").join(ups.select(F.col("v").alias("x"), F.col("a").alias("ua"), F.col("b").alias("ub")), "x", "left").join(ends.select(F.col("v").alias("left_slot"), F.col("a").alias("owner")), "left_slot")
    inside = F.col("py").isNotNull()
    helpers = span.select(F.col("x").alias("a"), F.col("y").alias("b"), "owner", F.when(inside, F.col("x")).otherwise(F.col("ua")).alias("up_a"), F.when(inside, F.col("py")).otherwise(F.col("ub")).alias("up_b"), "lo", "hi", "split")
    return Healed(cut(real.unionByName(helpers)), cut(tops), cut(dead.select("v")))


def deletions_by_rule(numbered: DataFrame, rule: str, k: int, seed: int = 1) -> DataFrame:
    """seq, v: the first k deletions an adversary picks by max_degree, random, leaf_first or root_first."""
    h = F.pmod(F.col("v") % 2147483647 * 48271 + seed * 69621, F.lit(2147483647))
    order = {"max_degree": [F.desc("n_children"), "v"], "random": [h, "v"], "leaf_first": [F.desc("level"), h, "v"], "root_first": ["level", h, "v"]}[rule]
    first = numbered.select("v", "n_children", "level").orderBy(*order).limit(k)
    return first.select(F.row_number().over(W.orderBy(*order)).cast("bigint").alias("seq"), "v")  # k rows


def healed_links(h: Healed) -> DataFrame:
    """u, v: links between live vertices, helpers counted as the vertices that run them."""
    up = h.nodes.select(F.col("a").alias("up_a"), F.col("b").alias("up_b"), F.col("owner").alias("up_owner"))
    met = h.nodes.where("up_a is not null").join(up, ["up_a", "up_b"])
    return met.where("owner <> up_owner").select(F.least("owner", "up_owner").alias("u"), F.greatest("owner", "up_owner").alias("v")).distinct()


def degree_increase(numbered: DataFrame, h: Healed) -> DataFrame:
    """v, before, after, increase of the live vertices' degrees in the tree."""
    before = numbered.select("v", (F.col("n_children") + F.col("parent").isNotNull().cast("bigint")).alias("before")).join(h.dead, "v", "left_anti")
    e = healed_links(h)
    after = e.select("v").union(e.select("u")).groupBy("v").agg(F.count("*").alias("after"))
    return before.join(after, "v", "left").select("v", "before", F.coalesce("after", F.lit(0)).alias("after"), (F.coalesce("after", F.lit(0)) - F.col("before")).alias("increase"))


def _keyed(h: Healed) -> DataFrame:
    key = lambda a, b: F.struct(F.col(a).alias("a"), F.col(b).alias("b"))
    return h.nodes.select(key("a", "b").alias("v"), F.when(F.col("up_a").isNotNull(), key("up_a", "up_b")).alias("parent"))


def check_connected(h: Healed) -> bool:
    """One root, and every node leads to it."""
    return double(_keyed(h)).select("root").distinct().count() <= 1 and h.nodes.where("up_a is null").count() <= 1


def depth_growth(numbered: DataFrame, h: Healed) -> DataFrame:
    """before, after, bound: depth of the tree, of the healed tree, and before * (ceil(log2 of most children) + 1)."""
    after = double(_keyed(h)).agg(F.max("hops").alias("after"))
    b = numbered.agg(F.max("level").alias("before"), F.max("n_children").alias("most"))
    bound = F.col("before") * (F.when(F.col("most") > 1, F.length(F.bin(F.col("most") - 1))).otherwise(0) + 1)
    return b.crossJoin(after).select("before", "after", bound.cast("bigint").alias("bound"))  # one row each


def _tables(state: DataFrame, ports: DataFrame, h: Healed) -> tuple[DataFrame, DataFrame]:
    """What each node forwards by: (a, b) with its numbers, its node above, and a helper's two below; and (a, out, next_a, next_b): the node that now fills a child's place."""
    own = state.drop("light_path", "lo").withColumns({"a": F.col("v"), "b": F.lit(-1).cast("bigint")}).drop("v")
    below = h.nodes.where("up_b >= 0").select(F.col("up_a").alias("a"), F.col("up_b").alias("b"), F.struct(F.col("a").alias("a"), F.col("b").alias("b")).alias("node"), F.col("hi").alias("end"))
    below = below.join(h.nodes.where("b >= 0").select("a", "b", "split"), ["a", "b"]).groupBy("a", "b")
    below = below.agg(F.max(F.when(F.col("end") <= F.col("split"), F.col("node"))).alias("left"), F.max(F.when(F.col("end") > F.col("split"), F.col("node"))).alias("right"))
    table = h.nodes.select("a", "b", "lo", "hi", "split", "up_a", "up_b").join(own, ["a", "b"], "left").join(below, ["a", "b"], "left")
    places = cut(h.tops.select("v", F.col("a").alias("next_a"), F.col("b").alias("next_b")).join(state.select("v", F.col("parent_port").alias("rev_port")), "v"))
    e = live(ports).select(F.col("src").alias("a"), F.col("port").alias("out"), F.col("dst").alias("v"), "rev_port")
    fills = e.join(spread(places), ["v", "rev_port"])  # of the ports, packets go down by those to children only
    return cut(table), cut(fills.select("a", "out", "next_a", "next_b"))


def _hop(under: DataFrame, table: DataFrame, fills: DataFrame) -> DataFrame:
    """Packets one step on; those that have arrived stay."""
    real, there = F.col("b") == -1, (F.col("a") == F.col("dst")) & (F.col("b") == -1)
    action, out = next_hop(F.col("to_id"), F.col("to_path"))
    met = under.join(table, ["a", "b"]).withColumn("action", F.when(real, action))
    met = met.withColumn("out", F.when(F.col("action").isin("light", "heavy"), out)).join(fills, ["a", "out"], "left")
    up = F.when(real, F.col("action") == "up").otherwise(~F.col("to_id").between(F.col("lo"), F.col("hi")))
    side = F.col("to_id") <= F.col("split")
    to = lambda x: F.when(there, F.col(x)).when(up, F.col(f"up_{x}")).when(real, F.col(f"next_{x}")).when(side, F.col(f"left.{x}")).otherwise(F.col(f"right.{x}"))
    place = F.struct(to("a").alias("a"), to("b").alias("b"), (F.col("hops") + (~there).cast("bigint")).alias("hops"))
    on = met.select("seq", "dst", "to_id", "to_path", F.inline(F.array(place)))  # columns made by a generator are not unfolded hop into hop by the optimizer
    return on.where("a is not null")


def route_healed(pairs: DataFrame, state: DataFrame, ports: DataFrame, h: Healed) -> DataFrame:
    """seq, src, dst, status, hops: packets over the healed tree with the labels and tables from before the deletions.

    status is lost if an end is deleted or unknown; all others are followed until they arrive, and a packet that makes more
    than twice the healed tree's depth of steps raises an error. hops counts steps between nodes, helpers included.
    """
    alive = h.nodes.where("b = -1").select(F.col("a").alias("v"))
    table, fills = _tables(state, ports, h)
    known = pairs.join(state.select(F.col("v").alias("dst"), F.col("new_id").alias("to_id"), F.col("light_path").alias("to_path")), "dst").join(alive.select(F.col("v").alias("dst")), "dst", "left_semi").join(alive.select(F.col("v").alias("src")), "src", "left_semi")
    under = cut(known.select("seq", "dst", "to_id", "to_path", F.col("src").alias("a"), F.lit(-1).cast("bigint").alias("b"), F.lit(0).cast("bigint").alias("hops")))
    there = (F.col("a") == F.col("dst")) & (F.col("b") == -1)
    arrived = [under.where(there).select("seq", "hops")]
    deepest, steps = double(_keyed(h)).agg(F.max("hops")).first()[0] or 0, 0
    sent = spread(table), spread(fills)
    at_once = _HOPS if all(small(x) for x in (table, fills)) else _FAR_HOPS
    while not (under := under.where(~there)).isEmpty():
        more = min(at_once, 2 * deepest + 2 - steps)
        if more <= 0:
            raise RuntimeError("a packet is under way for longer than any route is")
        steps += more
        for _ in range(more):
            under = _hop(under, *sent)
        under = cut(under)
        arrived.append(under.where(there).select("seq", "hops"))
        if len(arrived) > 24:
            arrived = [cut(_joined(arrived))]
    done = _joined(arrived)
    return pairs.select("seq", "src", "dst").join(done.withColumn("status", F.lit("delivered")), "seq", "left").withColumn("status", F.coalesce("status", F.lit("lost")))
