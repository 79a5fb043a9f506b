"""The driver's contract, SQL oracles on the smallest tables, and streams."""

from __future__ import annotations

from collections import Counter
from pathlib import Path

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from portsweep.operators import healing
from portsweep.plans import pipeline, registry
from portsweep.sources import graphs
from portsweep.streaming import sweep

SF = "/root/testdata/sf0.001"
SOME = ("ports_trade", "leader_messages_trade", "bfs_parents_mesh", "heavy_marks_b2", "ask_vs_broadcast_cost", "postorder_geo", "child_list_geo", "light_paths_mesh", "narrow_label_cost", "recovery_portions_geo", "sweep_memory_profile", "bottomup_revenue_geo", "event_chain_levels", "revenue_rollup", "last_event_before_error", "heal_live_owners", "heal_degree_geo", "heal_routes_mesh", "adversarial_portions_geo", "postorder_chain", "routes_mesh", "message_counts_mesh", "grouped_sales", "price_percentiles", "supplier_volume", "approximate_users", "events_per_day")


def test_entry(spark):
    df = entry.entry(spark)
    assert df.count() > 1000 and set(registry.queries()) <= set(entry.queries()) and set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", SOME)
def test_oracle(spark, name):
    con = duckdb.connect()
    for p in Path(SF).glob("*.parquet"):
        con.execute(f"CREATE VIEW {p.stem} AS SELECT * FROM '{p}'")
    got = registry.queries()[name](spark, SF)
    want = con.execute(registry.oracle_sql()[name])
    names = [c[0] for c in want.description]
    assert sorted(names) == sorted(got.columns)
    assert Counter(tuple(r) for r in got.select(*names).collect()) == Counter(want.fetchall())


def test_bounds_hold(spark):
    assert registry.queries()["bound_report"](spark, SF).first()[0] == 0
    assert registry.queries()["heal_degree_geo"](spark, SF).agg(F.max("increase")).first()[0] <= 3


def test_streams(spark, tmp_path):
    e = spark.read.parquet(f"{SF}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", F.col("event_id").alias("a"), F.col("user_id").alias("dst"))
    src = tmp_path / "in"
    e.repartition(3).write.parquet(str(src))
    stream = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(str(src))

    def run(df, name, mode="append"):
        q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.table(name)

    total = run(sweep.round_fold(stream, F.max, "1 day", "40 days"), "folds", "complete")
    assert total.groupBy("dst").agg(F.max("folded")).exceptAll(e.groupBy("dst").agg(F.max("a"))).isEmpty()
    sent = run(sweep.sweep_node(stream), "sent")
    assert sent.groupBy("dst").agg(F.max("sent")).exceptAll(e.groupBy("dst").agg(F.max("a"))).isEmpty()
    assert run(sweep.one_read_per_port(stream, late="40 days"), "once").count() == e.count()
    few = spark.createDataFrame([(1, "a"), (2, "b")], "v bigint, note string")
    assert run(sweep.known_readers(stream, few), "known").count() == e.where("dst in (1, 2)").count()
    assert run(sweep.sliding_rate(stream, late="40 days"), "rate", "complete").agg(F.sum("messages")).first()[0] == 4 * e.count()
    assert run(sweep.activity_sessions(stream, late="40 days"), "sessions", "complete").agg(F.sum("messages")).first()[0] == e.count()
    both = run(sweep.matched(stream.select("event_id", "ts"), stream.select("event_id", "ts"), "event_id", late="40 days"), "matched")
    assert both.count() == e.count()


@pytest.mark.parametrize("size", [1, 2, 13, 40])
def test_portions_of_a_child_stream(spark, tmp_path, size):
    """One sweep over children in rank order gives the portions, and holds few ids."""
    net = pipeline.preprocess(graphs.star(spark, size), root=0)
    kids = net.numbered.where("parent is not null").select("parent", "rank", "v", F.lit(size).cast("bigint").alias("size"), F.lit(None).cast("bigint").alias("grandparent"))
    schema = kids.schema
    for k, part in enumerate(range(0, size, 7)):
        kids.where((F.col("rank") >= part) & (F.col("rank") < part + 7)).coalesce(1).write.parquet(f"{tmp_path}/in/part={k}")
    files = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"{tmp_path}/in")
    q = sweep.sweep_portions(files).writeStream.format("memory").queryName(f"portions{size}").outputMode("append").option("checkpointLocation", f"{tmp_path}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    got = spark.table(f"portions{size}")
    want = net.portions
    assert sorted(map(tuple, got.select(*want.columns).collect()), key=str) == sorted(map(tuple, want.collect()), key=str)
    assert got.agg(F.max("held")).first()[0] <= max(4, 5 * (size - 1).bit_length())


def test_event_churn(spark, tmp_path):
    """Errors delete, clicks send: packets between live vertices arrive, others are lost."""
    e = spark.read.parquet(f"{SF}/events.parquet").select("event_id", "user_id", "event_type", "ts").where("event_id < 60 or event_type <> 'error'").orderBy("ts").limit(200)
    users = spark.read.parquet(f"{SF}/events.parquet").agg(F.max("user_id")).first()[0] + 1
    net = pipeline.preprocess(graphs.random_graph(spark, users, 5, 3))
    half = e.count() // 2
    rows = e.collect()
    for k, part in enumerate((rows[:half], rows[half:])):
        spark.createDataFrame(part, e.schema).coalesce(1).write.parquet(f"{tmp_path}/in/{k}")
    stream = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"{tmp_path}/in")
    q = sweep.run_event_churn(stream, net.ports, net.numbered, net.labels, str(tmp_path / "out"), users, lambda u: u)
    q.awaitTermination()
    assert q.exception() is None
    dead = {r.v: r.batch for r in spark.read.parquet(f"{tmp_path}/out/deleted").groupBy("v").agg(F.min("batch").alias("batch")).collect()}
    packets = spark.read.parquet(f"{tmp_path}/out/packets").collect()
    assert packets and all((r.status == "lost") == any(dead.get(x, 99) <= r.batch for x in (r.src, r.dst)) for r in packets)


def test_churn(spark, tmp_path):
    net = pipeline.preprocess(graphs.random_graph(spark, 40, 10, 7))
    src = tmp_path / "gone"
    for k in range(2):
        spark.createDataFrame([(v,) for v in range(3 + 5 * k, 8 + 5 * k)], "v bigint").coalesce(1).write.mode("append").parquet(str(src))
    seen = []
    q = sweep.run_churn(spark.readStream.schema("v bigint").option("maxFilesPerTrigger", 1).parquet(str(src)), net.numbered, str(tmp_path / "out"), lambda b: b, lambda n, h: seen.append(h))
    q.awaitTermination()
    assert q.exception() is None and len(seen) >= 2
    last = healing.heal(net.numbered, spark.range(3, 13).withColumnRenamed("id", "v"))
    assert seen[-1].nodes.exceptAll(last.nodes).isEmpty() and last.nodes.exceptAll(seen[-1].nodes).isEmpty()


@pytest.fixture(scope="module")
def apart(tmp_path_factory):
    """The smallest tables twice, keys of the copy shifted: the mesh and the trade graph have two components."""
    d, con = tmp_path_factory.mktemp("apart"), duckdb.connect()
    for p in Path(SF).glob("*.parquet"):
        names = [c[0] for c in con.execute(f"SELECT * FROM '{p}' LIMIT 0").description]
        keys = [c for c in names if c.endswith("key") and c[2:] not in ("nationkey", "regionkey")]
        more = f"UNION ALL SELECT * REPLACE ({', '.join(f'{c} + 1000000 AS {c}' for c in keys)}) FROM '{p}'" if keys else ""
        con.execute(f"COPY (SELECT * FROM '{p}' {more}) TO '{d / p.name}' (FORMAT parquet)")
    return str(d)


@pytest.mark.parametrize("name", ("bfs_message_count", "dfs_walk_cost", "dfs_link_uses", "leader_mesh", "leader_trade"))
def test_several_components(spark, apart, name):
    con = duckdb.connect()
    for p in Path(apart).glob("*.parquet"):
        con.execute(f"CREATE VIEW {p.stem} AS SELECT * FROM '{p}'")
    got = registry.queries()[name](spark, apart)
    want = con.execute(registry.oracle_sql()[name])
    names = [c[0] for c in want.description]
    assert sorted(names) == sorted(got.columns)
    assert Counter(tuple(r) for r in got.select(*names).collect()) == Counter(want.fetchall())


def test_plans_of_thirteen_orders(spark):
    got, orders = registry.queries()["half_full_links_13"](spark, SF), graphs.table(spark, SF, "orders")
    assert got.count() == orders.count() and any(p.endswith("orders.parquet") for p in got.inputFiles())
    test_oracle(spark, "half_full_links_13")
