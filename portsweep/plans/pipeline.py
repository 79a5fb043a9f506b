"""Preprocessing from a graph to routers and recovery portions."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import ReadOrder
from ..operators.bfs import bfs_tree, hang
from ..operators.convergecast import mark_heavy, subtree_weights
from ..operators.labels import routing_labels
from ..operators.leader import elect_leader
from ..operators.ports import assign_ports
from ..operators.recovery import recovery_portions
from ..operators.relabel import child_order, relabel, with_arrival
from ..operators.routing import router_state
from .rounds import cut


@dataclass
class Network:
    """What preprocessing leaves: frames keyed by vertex."""

    ports: DataFrame
    numbered: DataFrame
    labels: DataFrame
    state: DataFrame
    portions: DataFrame


def numbered_tree(tree: DataFrame, b: int = 2, kind: str = "leaves", strict: bool = False, post: bool = True, heavy_order: str = "port") -> DataFrame:
    """Weights, heavy marks and numbers; heavy_order 'arrival' puts heavy children in the order of their answered asks."""
    marked = mark_heavy(tree, subtree_weights(tree, kind), b, strict)
    if heavy_order == "arrival":
        marked = with_arrival(marked)
    return relabel(marked, child_order(marked, heavy_order), post=post)


def preprocess(edges: DataFrame, root: int | None = None, b: int = 2, order: ReadOrder | None = None, tree: DataFrame | None = None, label_mode: str = "wide") -> Network:
    """Leader (unless root or a tree is given), breadth-first tree, weights, renumbering, labels, portions."""
    ports = cut(assign_ports(edges))
    if tree is None:
        root = elect_leader(ports)[0].agg(F.max("leader_id")).first()[0] if root is None else root
        tree = bfs_tree(ports, root, order)
    elif "parent_port" not in tree.columns:
        tree = hang(tree, ports)
    numbered = numbered_tree(tree, b)
    labels = routing_labels(numbered, label_mode)
    return Network(ports, numbered, labels, cut(router_state(numbered, labels)), cut(recovery_portions(numbered)))
