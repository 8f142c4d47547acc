"""Shapes of plans, sources, and grouped graphs."""

import re

from pyspark.sql import functions as F

from walkrank.functions.grouped import rank_grouped, register_table_function
from walkrank.functions.ids import key_of, kind_of, pack
from walkrank.operators import levels as L
from walkrank.operators.criteria import FixedLevels
from walkrank.operators.engine import rank_nodes, top_k
from walkrank.operators.graph import Graph
from walkrank.plans import layout
from walkrank.sources import store, tables
from walkrank.workloads.graphs import build, part_supplier_heavy


def operators(df):
    """Names of the physical plan's nodes, without what stands behind caches."""

    def walk(node):
        kids = node.children()
        return [node.nodeName(), *(x for i in range(kids.size()) for x in walk(kids.apply(i)))]

    root = df._jdf.queryExecution().executedPlan()
    return walk(root.initialPlan() if root.nodeName() == "AdaptiveSparkPlan" else root)


def test_a_level_shuffles_only_sums(spark, sf):
    old = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        g = part_supplier_heavy(spark, sf)
        g.parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
        state = rank_nodes(g, FixedLevels(2)).state
        with layout.fixed(spark, g.parts):
            names = operators(L.advance_level(g.placed, state, "scaled", 0.01, 3))
        assert names.count("Exchange") == 1 and names.count("HashAggregate") == 2
        assert not re.search("Python|Pandas|Arrow", " ".join(names))
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", old)


def test_partitions_change_nothing(spark, sf):
    one = top_k(part_supplier_heavy(spark, sf), 10, 1e-4)
    g = part_supplier_heavy(spark, sf)
    g.parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    many = top_k(g, 10, 1e-4)
    assert one.report.live == many.report.live
    assert [x.id for x in one.ranking(10).collect()] == [x.id for x in many.ranking(10).collect()]


def test_hubs_are_split(spark):
    from walkrank.operators.baselines import dense_exact

    pairs = [(0, x) for x in range(1, 90)] + [(x, x + 1) for x in range(1, 60)]
    g = Graph.from_edges(spark.createDataFrame(pairs, "src long, dst long"), undirected=True)
    exact = dense_exact(g)
    g.parts = 4
    assert [r.id for r in g.placed.hubs.collect()] == [0] and g.placed.hub_edges.count() == 89
    assert g.placed.edges.where("dst = 0").isEmpty() and g.placed.edges.count() + 89 == g.stats.m
    frame = rank_nodes(g, FixedLevels(60)).frame
    assert all(abs(r.floor - exact[r.id]) < 1e-6 for r in frame.collect())


def test_scans_are_pruned(spark, sf):
    plan = build("part_supplier_heavy", spark, sf).edges._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<l_partkey:bigint,l_suppkey:bigint,l_quantity:double>" in plan
    assert "GreaterThanOrEqual(l_quantity,45.0)" in plan


def test_ids(spark):
    row = spark.range(7, 8).select(pack("supplier", "id").alias("x")).select(kind_of(F.col("x")).alias("k"), key_of(F.col("x")).alias("v")).first()
    assert tuple(row) == ("supplier", 7)


def test_sources(spark, tmp_path):
    e = spark.createDataFrame([(1, 2), (2, 3)], "src long, dst long")
    e.write.parquet(f"{tmp_path}/p")
    e.write.orc(f"{tmp_path}/o")
    e.write.csv(f"{tmp_path}/c", sep="\t")
    (tmp_path / "t.txt").write_text("# comment\n1 2\n\n2\t3 7\nbad line\n")
    (tmp_path / "j.json").write_text('{"src":1,"dst":2,"op":"insert","seq":1}\n')
    want = sorted(map(tuple, e.collect()))
    for got in (tables.edges_parquet(spark, f"{tmp_path}/p"), tables.edges_orc(spark, f"{tmp_path}/o"), tables.edges_csv(spark, f"{tmp_path}/c"), tables.edges_text(spark, f"{tmp_path}/t.txt")):
        assert sorted(map(tuple, got.collect())) == want
    assert tables.mutations_json(spark, f"{tmp_path}/j.json").first().op == "insert"
    store.save_bucketed(e, "edges_by_dst", "dst", 2)
    assert sorted(map(tuple, tables.edges_bucketed(spark, "edges_by_dst").collect())) == want
    spark.sql("drop table edges_by_dst")


def test_grouped_graphs(spark, sf):
    edges = part_supplier_heavy(spark, sf).edges.where("src < dst").withColumn("grp", F.col("src") % 2)
    got = {(r.grp, r.rank): r.id for r in rank_grouped(edges, "grp", 2, 1e-6).collect()}
    for grp in (0, 1):
        alone = top_k(Graph.from_edges(edges.where(F.col("grp") == grp), undirected=True), 2, 1e-6).ranking(2)
        assert {(grp, r["rank"]): r.id for r in alone.collect()} == {k: v for k, v in got.items() if k[0] == grp}
    register_table_function(spark)
    edges.createOrReplaceTempView("grouped_edges")
    found = spark.sql("select * from katz_rank(table(grouped_edges) partition by (grp), 2, 1e-6D)").collect()
    assert sorted(r.id for r in found) == sorted(got.values())


def test_edges_lie_in_packs(spark, sf, monkeypatch):
    """A level reads a row for each few edges of a target, made once for all numbers of partitions."""
    monkeypatch.setattr(layout, "PACK_BITS", 3)
    whole = part_supplier_heavy(spark, sf)
    arcs = sorted(map(tuple, whole.edges.select("src", "dst").collect()))
    made = []
    written = layout.written
    monkeypatch.setattr(layout, "written", lambda df, name: made.append(name) or written(df, name))
    for n in (1, 3):
        g = whole.dealt(n).placed
        rows = g.packs.collect()
        assert max(len(r.srcs) for r in rows) <= 8 and len(rows) < len(arcs)
        assert g.packs.rdd.getNumPartitions() == n
        assert sorted(map(tuple, g.laid_out().select("src", "dst").collect())) == arcs
    assert made.count("packs") == 1


def test_sums_find_room(spark):
    """The map of a task's sums grows with the nodes, and the session is as it was afterwards."""
    key = "spark.sql.codegen.aggregate.fastHashMap.capacityBit"
    before = spark.conf.get(key, None)
    with layout.fixed(spark, 2, 300_000):
        assert spark.conf.get(key) == "19"
    with layout.fixed(spark, 2, 10**9):
        assert spark.conf.get(key) == "21"
    assert spark.conf.get(key, None) == before
