"""Golden rows, invariants and variants of the protocols."""

from __future__ import annotations

import random

import pytest
from pyspark.sql import functions as F

from portsweep.functions import halffull
from portsweep.model import FOLDS, LimitError, ReadOrder, SweepLimits
from portsweep.operators import baselines, bfs, frames, healing, labels, leader, ports, recovery, relabel, routing, upkeep
from portsweep.plans import bounds, pipeline, rounds
from portsweep.plans.rounds import cut
from portsweep.sources import graphs

SF = "/root/testdata/sf0.001"
# leaf parent / inner parent / left / right of each label of the tree over 13 leaves
TREE_13 = "0/1/L0/L1 0/3/N0/N2 2/1/L2/L3 2/7/N1/N5 4/5/L4/L5 4/3/N4/N6 6/5/L6/L7 6/-/N3/N11 8/9/L8/L9 8/11/N8/N10 10/9/L10/L11 10/7/N9/L12 11/-/-/-"


def _split(lo, hi, up, out):
    if hi - lo == 1:
        out["L", lo] = up
        return "L", lo
    p = 1
    while 2 * p < hi - lo:
        p *= 2
    y = lo + p - 1
    out["N", y] = up
    out["C", y] = _split(lo, lo + p, y, out), _split(lo + p, hi, y, out)
    return "N", y


def test_half_full(spark):
    rows = halffull.with_links(spark.range(1, 130).select(F.col("id").alias("size")).select("size", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("size") - 1)).alias("y"))).collect()
    trees = {}
    for r in rows:
        if r["size"] not in trees:
            _split(0, r["size"], None, trees.setdefault(r["size"], {}))
        t = trees[r["size"]]
        assert r.leaf_parent == t["L", r.y]
        if r.y <= r["size"] - 2:
            assert r.node_parent == t["N", r.y]
            assert ((("L" if r.left_is_leaf else "N"), r.left), (("L" if r.right_is_leaf else "N"), r.right)) == t["C", r.y]
    show = lambda leaf, x: "-" if x is None else ("L" if leaf else "N") + str(x)
    own = [r for r in rows if r["size"] == 13]
    assert " ".join(f"{r.leaf_parent}/{'-' if r.node_parent is None else r.node_parent}/{show(r.left_is_leaf, r.left)}/{show(r.right_is_leaf, r.right)}" for r in own) == TREE_13


def test_labels_of_full_trees(spark):
    rows = spark.range(1, 6).selectExpr("id h").selectExpr("h", "explode(sequence(0, cast(shiftleft(1L, cast(5 - h as int)) - 1 as int))) p").selectExpr("h", "p", f"{halffull.full_label('h', 'p')} y")
    rows = rows.selectExpr("*", f"{halffull.label_height('y')} back").collect()
    assert all(r.h == r.back for r in rows) and len({r.y for r in rows}) == len(rows)


@pytest.fixture(scope="module")
def mesh(spark):
    return pipeline.preprocess(graphs.random_graph(spark, 40, 40, 3))


def test_network_invariants(mesh):
    n, m = mesh.numbered.count(), mesh.ports.count() // 2
    assert bfs.check_tree(mesh.numbered).first() == (True, True, True)
    c = bfs.bfs_cost(mesh.numbered, mesh.ports).first()
    assert c.messages == 2 * m and c.accepts == n - 1
    t = bfs.bfs_termination(mesh.numbered, mesh.ports).join(mesh.numbered.select("v", "parent"), "v")
    assert t.where("joins + yeses + if(parent is null, 0, 1) <> degree").isEmpty()
    ids = sorted(r.new_id for r in mesh.numbered.select("new_id").collect())
    assert ids == list(range(1, n + 1)) and mesh.numbered.where("parent is null").first().new_id == n
    assert mesh.numbered.where("new_id - lo + 1 <> size").isEmpty()
    trace = cut(relabel.token_trace(mesh.numbered, mesh.ports))
    assert trace.count() == trace.select("step").distinct().count() == relabel.walk_cost(n, m)["hops"]
    nxt = trace.select((F.col("step") - 1).alias("step"), F.col("src").alias("next"))
    assert trace.join(nxt, "step").where("dst <> next").isEmpty()
    for mode in ("narrow", "doubling"):
        other = labels.routing_labels(mesh.numbered, mode)
        assert other.exceptAll(mesh.labels).isEmpty() and mesh.labels.exceptAll(other).isEmpty()
    assert bounds.bound_report(mesh.ports, mesh.numbered, mesh.labels).where("not ok").isEmpty()
    assert baselines.descendants_by_interval(mesh.numbered).exceptAll(mesh.numbered.select("v", "weight")).isEmpty()


def test_read_orders_change_parents_not_levels(mesh):
    root = mesh.numbered.where("parent is null").first().v
    levels = mesh.numbered.select("v", "level")
    for order in (ReadOrder.random(5), ReadOrder.descending_port(), ReadOrder.adversarial(lambda reader, port, turn: F.pmod(port * 7 + reader, F.lit(11)))):
        other = bfs.bfs_tree(mesh.ports, root, order)
        assert other.select("v", "level").exceptAll(levels).isEmpty()
        assert bfs.bfs_cost(other, mesh.ports).first().messages == mesh.ports.count()


def test_leader_modes(spark, mesh):
    top, want = mesh.ports.agg(F.max("src")).first()[0], {r.v for r in mesh.numbered.select("v").collect()}
    for mode, more in (("known_diameter", {"diameter": 20}), ("known_size", {"n": 40}), ("known_size_wide", {"n": 40}), ("fixpoint", {})):
        got = leader.elect_leader(mesh.ports, mode, **more)[0].collect()
        assert {r.v for r in got} == want and {r.leader_id for r in got} == {top} and sum(r.is_leader for r in got) == 1
    wake = spark.createDataFrame([(3, 0), (top, 4)], "v bigint, wake_round bigint")
    assert {r.leader_id for r in leader.elect_leader(mesh.ports, wake=wake)[0].collect()} == {top}
    assert {(r.v, r.leader_id) for r in baselines.read_all_rounds(mesh.ports, 12).collect()} == {(v, top) for v in want}
    with pytest.raises(ValueError):
        leader.elect_leader(mesh.ports, "known_size")


def test_connectivity(spark):
    two = spark.createDataFrame([(1, 2), (2, 3), (10, 11)], "u bigint, v bigint")
    p = cut(ports.assign_ports(two))
    with pytest.raises(leader.Disconnected):
        leader.require_connected(p)
    assert {r.src for r in leader.giant_component(p).collect()} == {1, 2, 3}


def test_dead_ports_and_sends(spark):
    e = graphs.star(spark, 5)
    p = cut(ports.assign_ports(e, gap=2))
    assert [r.port for r in p.where("src = 0").orderBy("port").collect()] == [1, 3, 5, 7, 9]
    dead = ports.kill_ports(p, (F.col("src") == 3) | (F.col("dst") == 3))
    assert ports.degrees(dead).where("v = 0").first().degree == 4
    front = spark.createDataFrame([(0, 7)], "v bigint, a bigint")
    sent = ports.broadcast_except(front, p, F.col("port") == 3)
    assert sent.count() == 4
    trace = sent.withColumn("round", F.lit(0).cast("bigint"))
    assert ports.check_sweep(trace).isEmpty() and not ports.check_sweep(trace.union(trace)).isEmpty()
    assert ports.send(front.withColumn("out_port", F.lit(5)), p).first().dst == 3
    assert FOLDS["first"].over(ports.broadcast_all(spark.createDataFrame([(1, 5), (2, 9)], "v bigint, a bigint"), p).withColumn("round", F.lit(0))).first()["first"] == 5
    with pytest.raises(LimitError):
        SweepLimits.compact(1000, words=2).enforce(3, 1)


def test_hub_ranking(spark):
    e = graphs.star(spark, 300).union(graphs.path(spark, 40).selectExpr("u + 1000", "v + 1000"))
    a, b = ports.assign_ports(e, hubs=False), ports.assign_ports(e, hubs=True)
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


@pytest.mark.parametrize("size", [1, 2, 3, 4, 7, 8, 13, 17])
def test_portions_of_stars(spark, size):
    net = pipeline.preprocess(graphs.star(spark, size), root=0)
    got = {r["rank"]: r for r in net.portions.collect()}
    tree = {}
    _split(0, size, None, tree)
    root = next((y for (k, y), up in tree.items() if k == "N" and up is None), None)
    assert len(got) == size and [r.v for _, r in sorted(got.items())] == list(range(1, size + 1))
    for y, r in got.items():
        name = lambda x: None if x is None else x + 1
        assert r.leaf_parent == name(tree["L", y]) and r.is_successor == (y == size - 1)
        if y < size - 1:
            (lk, left), (rk, right) = tree["C", y]
            assert (r.left, r.right, r.left_is_leaf, r.right_is_leaf) == (name(left), name(right), lk == "L", rk == "L")
            assert r.helper_parent == (size if y == root else name(tree["N", y]))
        else:
            assert r.helper_parent is None and r.left == (name(root) if size > 1 else 1)


def test_sweep_memory(spark):
    got = {r["size"]: r for r in recovery.sweep_memory(spark.createDataFrame([(x,) for x in (8, 13, 32, 1024)], "size bigint")).collect()}
    assert [got[s].peak_ids for s in (8, 13, 32, 1024)] == [6, 7, 10, 20]
    assert all(r.most_uses == 4 for r in got.values())


def _healed_by_hand(rows, dead):
    """Parents of live vertices and helpers by direct recursion."""
    kids, up = {}, {}
    for r in rows:
        kids.setdefault(r.parent, []).append((r.rank, r.v))
    root = kids[None][0][1]

    def lives(v):
        return v not in dead or any(lives(c) for _, c in kids.get(v, []))

    def plan(x, lo, hi, slots):
        if hi - lo == 1:
            return top(slots[lo]) if lives(slots[lo]) else None
        p = 1
        while 2 * p < hi - lo:
            p *= 2
        a, b = plan(x, lo, lo + p, slots), plan(x, lo + p, hi, slots)
        if a is None or b is None:
            return a or b
        up[a] = up[b] = (x, lo + p - 1)
        return x, lo + p - 1

    def top(v):
        slots = [c for _, c in sorted(kids.get(v, []))]
        if v in dead:
            return plan(v, 0, len(slots), slots)
        for c in slots:
            if lives(c):
                up[top(c)] = (v, -1)
        return v, -1

    up[top(root)] = None
    return up


def test_healing(spark, mesh):
    rows = mesh.numbered.select("v", "parent", "rank").collect()
    for rule, k in (("random", 15), ("root_first", 10)):
        deleted = cut(healing.deletions_by_rule(mesh.numbered, rule, k))
        h = healing.heal(mesh.numbered, deleted)
        want = _healed_by_hand(rows, {r.v for r in deleted.collect()})
        got = {(r.a, r.b): None if r.up_a is None else (r.up_a, r.up_b) for r in h.nodes.collect()}
        assert got == want
        owners = [r.owner for r in h.nodes.where("b >= 0").collect()]
        assert len(owners) == len(set(owners)) and h.nodes.join(h.dead, F.col("owner") == F.col("v")).isEmpty()
        assert healing.degree_increase(mesh.numbered, h).agg(F.max("increase")).first()[0] <= 3
        assert healing.check_connected(h)
        d = healing.depth_growth(mesh.numbered, h).first()
        assert d.after <= d.bound


def test_routes(spark, mesh):
    random.seed(2)
    ids = [r.v for r in mesh.numbered.select("v").collect()]
    pairs = spark.createDataFrame([(i, random.choice(ids), random.choice(ids)) for i in range(150)], "seq bigint, src bigint, dst bigint")
    intact = routing.route(pairs, mesh.state, mesh.ports)
    assert intact.where("status <> 'delivered'").isEmpty()
    s = routing.stretch(intact, mesh.ports, [intact.first().src])
    assert s.where("hops < distance").isEmpty()
    h = healing.heal(mesh.numbered, healing.deletions_by_rule(mesh.numbered, "random", 20))
    after = healing.route_healed(pairs, mesh.state, mesh.ports, h)
    ends = h.dead.select("v")
    lost = after.join(ends, F.col("src") == F.col("v"), "left_anti").join(ends, F.col("dst") == F.col("v"), "left_anti").where("status = 'lost'")
    assert lost.isEmpty() and not after.where("status = 'delivered'").isEmpty()


def test_portions_stay_up_to_date(spark, mesh):
    """Edits after each batch give what a rebuild gives, and a second deletion runs from edited portions alone."""
    n = mesh.numbered
    leaf = n.where("n_children = 0 and level >= 2").orderBy("v").limit(2).select("v")
    gone, before = n.where("false").select("v"), healing.heal(n, n.where("false").select("v"))
    portions = cut(recovery.recovery_portions(n))
    assert upkeep.live_portions(n, before).exceptAll(portions).isEmpty()
    inner = n.where("n_children > 1 and parent is not null").orderBy("v").limit(1).select("v")
    for step in (leaf, inner):
        gone = cut(gone.union(step).distinct())
        after = healing.heal(n, gone)
        changed = cut(upkeep.edits(portions, n, before, after))
        assert 0 < changed.count() < portions.count()
        portions = cut(upkeep.apply_edits(portions, changed))
        rebuilt = upkeep.live_portions(n, after)
        assert portions.exceptAll(rebuilt).isEmpty() and rebuilt.exceptAll(portions).isEmpty()
        before = after
    x = portions.groupBy("parent").count().where("count > 1").orderBy("parent").first().parent
    last = healing.heal(n, gone.union(spark.createDataFrame([(x,)], "v bigint")))
    want = last.nodes.where((F.col("a") == x) & (F.col("b") >= 0)).select("b", "owner").count()
    links = upkeep.executed(portions, x)
    assert links.where("kind = 'leaf'").count() == want + 1 and links.where("kind = 'helper'").count() == want + 1


def test_helpers_pass_to_the_leafs_successor(spark, mesh):
    n = mesh.numbered
    x = n.where("n_children > 1 and parent is not null").orderBy(F.desc("n_children")).first().v
    one = spark.createDataFrame([(x,)], "v bigint")
    before = healing.heal(n, one)
    owner = before.nodes.where((F.col("a") == x) & (F.col("b") >= 0)).orderBy("b").first().owner
    after = healing.heal(n, one.union(spark.createDataFrame([(owner,)], "v bigint")))
    passed = upkeep.handovers(before, after).collect()
    alive = {r.v for r in n.select("v").collect()} - {x, owner}
    assert all(r.owner == owner and r.successor in alive for r in passed)
    assert healing.check_connected(after) and healing.degree_increase(n, after).agg(F.max("increase")).first()[0] <= 3


def test_adversarial_rounds(spark, mesh):
    got = recovery.adversarial_portions(mesh.numbered)
    assert got.select(*mesh.portions.columns).exceptAll(mesh.portions).isEmpty() and got.agg(F.max("held")).first()[0] <= 5
    assert got.where("round <> rank").isEmpty()


def test_strong_adversary_and_inbox(spark, mesh):
    root = mesh.numbered.where("parent is null").first().v
    seen = mesh.numbered.select("v", F.col("new_id").alias("state_id"))
    other = bfs.bfs_tree(mesh.ports, root, ReadOrder.strong(lambda reader, port, turn: F.pmod(F.col("state_id") * port, F.lit(7)) * 1000 + port), seen)
    assert other.select("v", "level").exceptAll(mesh.numbered.select("v", "level")).isEmpty()
    box = ports.deliver(ports.broadcast_all(spark.createDataFrame([(1, 5)], "v bigint, a bigint"), mesh.ports))
    assert box.take().where("reader = dst").count() > 0
    with pytest.raises(RuntimeError):
        box.take()


def test_heavy_children_by_arrival(mesh):
    tree = mesh.numbered.select("v", "parent", "parent_port", "port_at_parent", "level", "n_children")
    other = pipeline.numbered_tree(tree, heavy_order="arrival")
    n = tree.count()
    assert sorted(r.new_id for r in other.select("new_id").collect()) == list(range(1, n + 1)) and other.where("new_id - lo + 1 <> size").isEmpty()


def test_deep_trees_by_doubling(spark):
    """A path deeper than what is worked on level by level: weights, numbers, labels, portions and a walk of the token."""
    net = pipeline.preprocess(graphs.path(spark, 24), root=0)
    rows = net.numbered.collect()
    assert all(r.weight == 1 and r.size == 24 - r.v and r.new_id == 24 - r.v and r.height == 23 - r.v for r in rows)
    assert net.labels.where("light_level > 0").isEmpty() and net.portions.count() == 23
    assert relabel.token_trace(net.numbered, net.ports).count() == relabel.walk_cost(24, 23)["hops"]


def test_frames_agree_with_closed_forms(mesh):
    n, m = mesh.numbered.count(), mesh.ports.count() // 2
    cost = {(r.method, r.variant): r for r in frames.costs(frames.all_frames(mesh.ports, mesh.numbered, mesh.labels)).collect()}
    assert cost["bfs", "ascending"].messages == cost["labels", "wide"].messages == 2 * m
    assert cost["relabel", "walk"].messages == relabel.walk_cost(n, m)["messages"] and cost["portions", "self_ordered"].messages == 2 * (n - 1)
    assert cost["portions", "adversarial"].rounds == mesh.numbered.agg(F.max("n_children")).first()[0]
    assert cost["labels", "narrow"].max_message_words == 2 and cost["portions", "self_ordered"].max_message_words <= 9
    assert cost["leader", "fixpoint"].messages == sum(x for _, x in leader.elect_leader(mesh.ports)[1])
    with pytest.raises(LimitError):
        frames.enforce(bounds.cost_frames(mesh.ports, mesh.numbered, mesh.labels), SweepLimits.compact(40, words=1))


def test_costs_frame_by_frame(mesh):
    whole = frames.costs(frames.all_frames(mesh.ports, mesh.numbered, mesh.labels)).collect()
    apart = frames.metered(frames.each_frame(mesh.ports, mesh.numbered, mesh.labels), frames.costs)
    assert sorted(whole) == sorted(apart.collect()) and len(whole) == 9
    plan = apart._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "Aggregate" not in plan  # nothing but the counted rows is left to one job


def test_small_frontiers_are_sent_to_every_task(spark, mesh, monkeypatch):
    plan = lambda df: df._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan(ports.assign_ports(graphs.random_graph(spark, 40, 40, 3)))  # both numbers come from one pass over the links each
    few = cut(spark.range(10))
    sent = rounds.spread(few)
    assert "broadcast" in sent._jdf.queryExecution().analyzed().toString()
    root = mesh.numbered.where("parent is null").first().v
    want = mesh.numbered.select("v", "parent", "level")
    monkeypatch.setattr(rounds, "SMALL", 0)
    assert "broadcast" not in rounds.spread(few)._jdf.queryExecution().analyzed().toString()
    got = bfs.bfs_tree(mesh.ports, root).select("v", "parent", "level")
    assert got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()


def test_healed_routes_take_several_hops_a_job(mesh, monkeypatch):
    dead = healing.deletions_by_rule(mesh.numbered, "max_degree", 6)
    h = healing.heal(mesh.numbered, dead)
    ends = mesh.numbered.select("new_id", "v")
    pairs = ends.select(F.col("new_id").alias("seq"), F.col("v").alias("src"), (F.col("new_id") * 7 % 40 + 1).alias("to")).join(ends.toDF("to", "dst"), "to").select("seq", "src", "dst")
    up = {(r.a, r.b): None if r.up_a is None else (r.up_a, r.up_b) for r in h.nodes.collect()}

    def over(x):
        return [x, *over(up[x])] if up.get(x) else [x]

    def far(src, dst):
        a, b = over((src, -1)), over((dst, -1))
        return len({*a} ^ {*b})

    written = []
    monkeypatch.setattr(healing, "cut", lambda df: written.append(1) or cut(df))
    gone = {r.v for r in dead.collect()}
    got = [r for r in healing.route_healed(pairs, mesh.state, mesh.ports, h).collect() if r.status == "delivered"]
    assert len(got) == sum(not {r.src, r.dst} & gone for r in pairs.collect())
    assert all(r.hops == far(r.src, r.dst) for r in got)
    assert len(written) <= 5 + max(r.hops for r in got) // 2


def test_hubs_are_found_by_coarse_counts(spark, monkeypatch):
    monkeypatch.setattr(ports, "HUB", 3)
    for groups in (16_384, 2):
        monkeypatch.setattr(ports, "_COARSE", groups)
        assert ports._hubs(graphs.star(spark, 9), "u", "v") and not ports._hubs(graphs.path(spark, 9), "u", "v")
