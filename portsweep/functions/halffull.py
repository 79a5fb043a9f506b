"""Full and half-full binary trees by arithmetic on labels; trees are never built.

A half-full tree over `size` leaves has the leaves 0 .. size - 1 and inner nodes 0 .. size - 2 in the same in-order
labels. Its left part is a full tree over the largest power of two below size, its right part half-full over the rest. So
an inner node's subtree is full unless it lies on the right border, and all neighbours of a label are found among the
labels that the full tree would have there, by the first one that exists.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def full_label(height: str, pos: str) -> str:
    """Label of the pos-th node at a height of a full tree (SQL; height 0: leaves)."""
    return f"(case when {height} = 0 then cast({pos} as bigint) else shiftleft(1L, cast({height} - 1 as int)) - 1 + shiftleft(cast({pos} as bigint), cast({height} as int)) end)"


def label_height(y: str) -> str:
    """Height of the inner node with label y (SQL): one more than the trailing zeros of y + 1."""
    return f"({_zeros(y)} + 1)"


def _zeros(y: str) -> str:
    return f"cast(bit_count((({y}) + 1 & -(({y}) + 1)) - 1) as int)"


def _bits(size: str) -> str:
    return f"length(bin(cast({size} as bigint)))"


def _above(y: str, j: str) -> str:
    """The inner label over y at height j + 1 in a full tree without end."""
    return f"(shiftleft(shiftright({y}, {j} + 1), {j} + 1) + shiftleft(1L, {j}) - 1)"


def half_full_root(size: str) -> str:
    """Label of the root (SQL): the largest power of two below size, less one; null below two leaves."""
    return f"(case when {size} >= 2 then shiftleft(1L, length(bin(cast({size} - 1 as bigint))) - 1) - 1 end)"


def half_full_links(y: str, size: str) -> dict[str, str]:
    """SQL for the neighbours of label y (bigint) among `size` leaves; inner ones are null where y has no inner node.

    leaf_parent: inner label over leaf y; node_parent: inner label over inner y (null: root); left, right: labels of the
    children of inner y, with left_is_leaf, right_is_leaf.
    """
    z, has = _zeros(y), f"{y} <= {size} - 2"
    first = lambda start, to: f"get(filter(transform(sequence({start}, {to}), j -> {_above(y, 'j')}), a -> a <= {size} - 2), 0)"
    inner = f"get(filter(transform(sequence({z} - 1, 0, -1), k -> {y} + shiftleft(1L, k)), a -> a <= {size} - 2), 0)"
    return {
        "leaf_parent": f"(case when {size} >= 2 then {first('0', _bits(size))} end)",
        "node_parent": f"(case when {has} then {first(f'{z} + 1', f'{z} + 1 + {_bits(size)}')} end)",
        "left": f"(case when {has} then case when {z} = 0 then {y} else {y} - shiftleft(1L, greatest({z} - 1, 0)) end end)",
        "left_is_leaf": f"(case when {has} then {z} = 0 end)",
        "right": f"(case when {has} then case when {z} = 0 then {y} + 1 else coalesce({inner}, {y} + 1) end end)",
        "right_is_leaf": f"(case when {has} then case when {z} = 0 then true else {inner} is null end end)",
    }


def with_links(df: DataFrame, y: str = "y", size: str = "size") -> DataFrame:
    return df.withColumns({k: F.expr(v) for k, v in half_full_links(y, size).items()})


def portion_labels(y: int, size: int) -> tuple[int | None, int | None, int | None, bool, int | None, bool]:
    """leaf parent, helper parent, left, left is a leaf, right, right is a leaf of child y among `size`, for one label at a time.

    The helper parent of the plan's root is the successor (size - 1); that of the successor is outside the plan (null).
    """
    root = (1 << (size - 1).bit_length() - 1) - 1 if size >= 2 else None
    over = lambda x, j: (x >> j + 1 << j + 1) + (1 << j) - 1
    above = lambda x, start: next((a for j in range(start, start + size.bit_length() + 1) if (a := over(x, j)) <= size - 2), None)
    leaf = above(y, 0) if size >= 2 else None
    if y == size - 1:
        return leaf, None, y if root is None else root, root is None, None, False
    zeros = (y + 1 & -(y + 1)).bit_length() - 1
    helper = size - 1 if y == root else above(y, zeros + 1)
    left = y - (1 << zeros - 1) if zeros else y
    inner = next((y + (1 << k) for k in range(zeros - 1, -1, -1) if y + (1 << k) <= size - 2), None)
    return leaf, helper, left, zeros == 0, y + 1 if inner is None else inner, inner is None


def register_functions(spark: SparkSession) -> None:
    """The look-ups as SQL functions of the session."""
    for name, sql in half_full_links("y", "size").items():
        kind = "BOOLEAN" if "is_leaf" in name else "BIGINT"
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION half_full_{name}(y BIGINT, size BIGINT) RETURNS {kind} RETURN {sql}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION half_full_root(size BIGINT) RETURNS BIGINT RETURN {half_full_root('size')}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION label_height(y BIGINT) RETURNS INT RETURN {label_height('y')}")
