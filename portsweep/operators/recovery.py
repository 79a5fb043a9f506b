"""Recovery portions: the share of "what to do if your parent dies" that each child keeps.

The plan of a vertex is the half-full tree over its children; child y plays leaf y and inner node y. The last child is the
successor: it has no inner node, and its helper stands between the dead vertex's parent and the plan's root.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.halffull import half_full_root, with_links
from .ports import ranked

#: Labels of a large plan are listed in pieces of this many, so that no row holds an array as long as a hub's degree.
_PIECE = 4096

_ROLES = ("leaf_parent", "helper_parent", "left", "right")


def recovery_portion(df: DataFrame) -> DataFrame:
    """Rows (y, size) with their portion in labels: leaf_parent, helper_parent, left, right, left_is_leaf, right_is_leaf, is_successor, is_top.

    helper_parent of the plan's root is the successor's label; of the successor it is null here (the dead vertex's parent).
    """
    d = with_links(df).withColumn("root", F.expr(half_full_root("size")))
    last = F.col("y") == F.col("size") - 1
    top = F.col("y") == F.col("root")
    return d.select(
        *df.columns,
        "leaf_parent",
        F.when(top, F.col("size") - 1).when(~last, F.col("node_parent")).alias("helper_parent"),
        F.when(last, F.coalesce("root", "y")).otherwise(F.col("left")).alias("left"),
        F.when(last, F.col("size") == 1).otherwise(F.col("left_is_leaf")).alias("left_is_leaf"),
        "right",
        "right_is_leaf",
        last.alias("is_successor"),
        F.coalesce(top, F.lit(False)).alias("is_top"),
    )


def recovery_portions(tree: DataFrame, parents: DataFrame | None = None) -> DataFrame:
    """parent, rank, v, leaf_parent, helper_parent, left, right (ids), left_is_leaf, right_is_leaf, is_successor for every non-root v.

    tree: v, parent, rank, n_children; parents (v, parent, n_children) where they are not rows of the tree. Each child offers its id to the portions that refer to it, four at most, found by
    arithmetic alone; grouping the offers by (parent, rank) is the protocol's one round and its only exchange, and no key of
    it is larger than four rows, however large the hub.
    """
    size = (tree if parents is None else parents).select(F.col("v").alias("parent"), F.col("n_children").alias("size"), F.col("parent").alias("grandparent")).where("size > 0")
    rows = tree.where("parent is not null").select("v", "parent", F.col("rank").alias("y")).join(size, "parent")
    own = recovery_portion(rows)

    def offer(to: F.Column, role: str, when: F.Column) -> F.Column:
        return F.when(when & to.isNotNull(), F.struct(to.alias("to"), F.lit(role).alias("role")))

    y, last, inner = F.col("y"), F.col("is_successor"), ~F.col("is_successor")
    many = F.col("size") >= 2
    under = F.col("helper_parent")
    offers = F.array(
        offer(F.col("leaf_parent"), "left", many & (F.col("leaf_parent") == y)),  # as a leaf
        offer(F.col("leaf_parent"), "right", many & (F.col("leaf_parent") < y)),
        offer(under, "left", inner & (F.col("is_top") | (under > y))),  # as an inner node, to the one above
        offer(under, "right", inner & ~F.col("is_top") & (under < y)),
        offer(F.col("left"), "leaf_parent", inner & F.col("left_is_leaf")),  # and to those below
        offer(F.col("left"), "helper_parent", inner & ~F.col("left_is_leaf")),
        offer(F.col("right"), "leaf_parent", inner & F.col("right_is_leaf")),
        offer(F.col("right"), "helper_parent", inner & ~F.col("right_is_leaf")),
        offer(F.col("left"), "helper_parent", last & many),  # the successor to the root
        offer(y, "left", last & ~many),
        F.struct(y.alias("to"), F.lit("self").alias("role")),
    )
    sent = own.select("parent", "grandparent", "v", "left_is_leaf", "right_is_leaf", "is_successor", F.explode(F.filter(offers, lambda o: o.isNotNull())).alias("o"))
    mine = F.col("o.role") == "self"
    got = sent.groupBy("parent", F.col("o.to").alias("rank")).agg(
        F.max(F.when(mine, F.col("v"))).alias("v"),
        *[F.max(F.when(F.col("o.role") == r, F.col("v"))).alias(r) for r in _ROLES],
        *[F.max(F.when(mine, F.col(c))).alias(c) for c in ("left_is_leaf", "right_is_leaf", "is_successor")],
        F.max("grandparent").alias("grandparent"),
    )
    above = F.when(F.col("is_successor"), F.col("grandparent")).otherwise(F.col("helper_parent"))
    return got.select("parent", "rank", "v", "leaf_parent", above.alias("helper_parent"), "left", "right", "left_is_leaf", "right_is_leaf", "is_successor")


def portion_cost(tree: DataFrame, mode: str = "self_ordered") -> DataFrame:
    """parents, messages, rounds, ids: what distributing all portions takes.

    self_ordered: every child sends once and gets once, in one round. adversarial: one portion a round, for which every
    child is heard again; five ids of memory do.
    """
    d = tree.where("n_children > 0").select("n_children")
    if mode == "self_ordered":
        return d.agg(F.count("*").alias("parents"), F.sum(2 * F.col("n_children")).alias("messages"), F.lit(1).cast("bigint").alias("rounds"))
    if mode == "adversarial":
        return d.agg(F.count("*").alias("parents"), F.sum(F.col("n_children") * F.col("n_children") + F.col("n_children")).alias("messages"), F.max("n_children").alias("rounds"))
    raise ValueError("mode is self_ordered or adversarial")


def labels_of(sizes: DataFrame) -> DataFrame:
    """size, y: all labels 0 .. size - 1 of each row of sizes (with its other columns)."""
    pieces = sizes.where("size > 0").withColumn("__p", F.explode(F.sequence(F.lit(0).cast("bigint"), F.floor((F.col("size") - 1) / _PIECE))))
    first = F.col("__p") * _PIECE
    return pieces.withColumn("y", F.explode(F.sequence(first, F.least(first + _PIECE - 1, F.col("size") - 1)))).drop("__p")


def adversarial_portions(tree: DataFrame) -> DataFrame:
    """round, held and the columns of recovery_portions: one portion of each parent a round, whatever order children are read in.

    In round k a parent hears all its children again and keeps only the ids that portion k names: these are asked for by
    their labels. held is how many distinct ids that is, with the receiver's own; five at most.
    """
    parents = tree.select(F.col("v").alias("parent"), F.col("n_children").alias("size"), F.col("parent").alias("grandparent")).where("size > 0")
    asked = recovery_portion(labels_of(parents)).withColumn("self", F.col("y"))
    roles = ("self", *_ROLES)
    asked = asked.withColumn("role", F.explode(F.array(*[F.struct(F.lit(r).alias("name"), F.col(r).alias("label")) for r in roles]))).where("role.label is not null")
    child = tree.where("parent is not null").select("parent", F.col("rank").alias("label"), F.col("v").alias("id"))
    kept = asked.select("parent", "grandparent", "y", "left_is_leaf", "right_is_leaf", "is_successor", "role.name", "role.label").join(child, ["parent", "label"])
    got = kept.groupBy("parent", "y").agg(
        *[F.max(F.when(F.col("name") == r, F.col("id"))).alias(r) for r in roles],
        *[F.max(c).alias(c) for c in ("left_is_leaf", "right_is_leaf", "is_successor", "grandparent")],
        F.size(F.collect_set("label")).cast("bigint").alias("held"),
    )
    above = F.when(F.col("is_successor"), F.col("grandparent")).otherwise(F.col("helper_parent"))
    return got.select(F.col("y").alias("round"), "held", "parent", F.col("y").alias("rank"), F.col("self").alias("v"), "leaf_parent", above.alias("helper_parent"), "left", "right", "left_is_leaf", "right_is_leaf", "is_successor")


def references(sizes: DataFrame) -> DataFrame:
    """size, y, ref: the siblings' labels that portion y names (sizes: column size)."""
    p = recovery_portion(labels_of(sizes.select("size")))
    return p.select("size", "y", F.explode(F.filter(F.array(*_ROLES), lambda r: r.isNotNull())).alias("ref"))


def sweep_memory(sizes: DataFrame) -> DataFrame:
    """size, peak_ids, peak_portions, uses: what one sweep in rank order holds at most.

    A portion leaves once its last id is read; an id is released once the last portion that names it, or its own, has left.
    """
    refs = references(sizes)
    every = labels_of(sizes.select("size"))
    named = refs.union(every.select("size", "y", F.col("y")))
    sent = named.groupBy("size", "y").agg(F.max("ref").alias("sent"), F.min("ref").alias("opened"))
    free = named.join(sent, ["size", "y"]).groupBy("size", F.col("ref").alias("y")).agg(F.max("sent").alias("freed"))

    def peak(spans: DataFrame, lo: str, hi: str, name: str) -> DataFrame:
        steps = spans.select("size", F.col(lo).alias("at"), F.lit(1).alias("d")).union(spans.select("size", F.col(hi) + 1, F.lit(-1)))
        held = steps.groupBy("size", "at").agg(F.sum("d").alias("d"))
        held = ranked(held, "size", [F.col("at")], "before", F.col("d")).withColumn("held", F.col("before") + F.col("d"))
        return held.groupBy("size").agg(F.max("held").cast("bigint").alias(name))

    ids = peak(free, "y", "freed", "peak_ids")
    portions = peak(sent, "opened", "sent", "peak_portions")
    uses = refs.groupBy("size", "ref").agg(F.count("*").alias("n")).groupBy("size").agg(F.max("n").alias("most_uses"))
    return ids.join(portions, "size").join(uses, "size", "left")
