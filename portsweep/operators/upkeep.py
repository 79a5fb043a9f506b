"""Plans kept up to date while vertices are deleted.

A live vertex's plan is the half-full tree over its slots that still hold live vertices, each named by the vertex that runs
the node now in its place. So after a deletion only the portions of those parents change whose slots have emptied or been
taken over, and of these only the portions whose neighbours in the plan differ: edits() finds these rows, apply_edits()
puts them in. Helpers whose owner was deleted pass to the leaf's successor, the last live vertex before it in its slot.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .healing import Healed
from .ports import ranked
from .recovery import recovery_portions

_KEY = ["parent", "rank"]


def live_plans(numbered: DataFrame, h: Healed) -> DataFrame:
    """v, parent, rank, n_children: the tree of slots of live parents, v being who fills the slot now and rank its place among those filled."""
    fill = h.tops.select(F.col("v").alias("slot"), "a", "b").join(h.nodes.select("a", "b", "owner"), ["a", "b"])
    alive = numbered.join(h.dead, "v", "left_anti")
    slots = numbered.where("parent is not null").select(F.col("v").alias("slot"), "parent", F.col("rank").alias("place")).join(alive.select(F.col("v").alias("parent")), "parent")
    filled = ranked(slots.join(fill.select("slot", "owner"), "slot"), "parent", [F.col("place")], "rank")
    sizes = filled.groupBy("parent").agg(F.count("*").alias("n_children"))
    up = h.nodes.where("b = -1").select(F.col("a").alias("v"), F.col("up_a"), F.col("up_b")).join(h.nodes.select(F.col("a").alias("up_a"), F.col("b").alias("up_b"), F.col("owner").alias("above")), ["up_a", "up_b"], "left")
    own = up.select(F.col("v").alias("parent"), F.col("above").alias("grandparent")).join(sizes, "parent")
    return filled.select(F.col("owner").alias("v"), "parent", "rank").join(own, "parent")


def live_portions(numbered: DataFrame, h: Healed, only: DataFrame | None = None) -> DataFrame:
    """The portions of all live parents, or of those in only (parent), as recovery_portions gives them."""
    plans = live_plans(numbered, h)
    if only is not None:
        plans = plans.join(only, "parent", "left_semi")
    parents = plans.select(F.col("parent").alias("v"), F.col("grandparent").alias("parent"), "n_children").distinct()
    return recovery_portions(plans.select("v", "parent", "rank"), parents)


def affected(numbered: DataFrame, before: Healed, after: Healed) -> DataFrame:
    """parent: live vertices whose plan is not what it was."""
    old, new = live_plans(numbered, before).join(after.dead.withColumnRenamed("v", "parent"), "parent", "left_anti"), live_plans(numbered, after)
    cols = ["parent", "rank", "v", "n_children", "grandparent"]
    return old.select(*cols).exceptAll(new.select(*cols)).union(new.select(*cols).exceptAll(old.select(*cols))).select("parent").distinct()


def edits(portions: DataFrame, numbered: DataFrame, before: Healed, after: Healed) -> DataFrame:
    """action ('set' or 'drop') and the columns of portions: the rows that must change, and no others."""
    gone = after.dead.select(F.col("v").alias("parent"))
    only = affected(numbered, before, after)
    new = live_portions(numbered, after, only)
    old = portions.join(only, "parent", "left_semi")
    put = new.exceptAll(old.select(*new.columns)).withColumn("action", F.lit("set"))
    lost = old.join(new.select(*_KEY), _KEY, "left_anti").unionByName(portions.join(gone, "parent", "left_semi")).withColumn("action", F.lit("drop"))
    return put.unionByName(lost.select(*put.columns)).select("action", *portions.columns)


def apply_edits(portions: DataFrame, changed: DataFrame) -> DataFrame:
    """portions with the edits in."""
    kept = portions.join(changed.select(*_KEY), _KEY, "left_anti")
    return kept.unionByName(changed.where("action = 'set'").select(*portions.columns))


def handovers(before: Healed, after: Healed) -> DataFrame:
    """a, b, owner, successor: helpers that stay while their owner was deleted, and who runs them now."""
    helper = lambda h, name: h.nodes.where("b >= 0").select("a", "b", F.col("owner").alias(name))
    both = helper(before, "owner").join(helper(after, "successor"), ["a", "b"])
    return both.where("owner <> successor").join(after.dead.withColumnRenamed("v", "owner"), "owner", "left_semi").select("a", "b", "owner", "successor")


def executed(portions: DataFrame, x: int) -> DataFrame:
    """kind ('leaf' or 'helper'), v, above: the links that the children of x make from their portions when x is deleted."""
    own = portions.where(F.col("parent") == x)
    leaf = own.where("leaf_parent is not null").select(F.lit("leaf").alias("kind"), "v", F.col("leaf_parent").alias("above"))
    return leaf.union(own.select(F.lit("helper"), "v", "helper_parent"))
