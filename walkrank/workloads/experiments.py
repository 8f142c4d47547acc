"""The experiments as functions that return tables of figures. Seconds are wall clock of whole runs."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines, dynamic, measures
from ..operators.criteria import RankingCriterion, TopKCriterion
from ..operators.engine import LastTerm, Report, ladder, rank_nodes
from ..operators.graph import Graph
from ..plans import layout
from .graphs import build

EPS = tuple(10.0**-i for i in range(1, 13))
TPS_TOL, CG_TIGHT, CG_LOOSE = 1e-9, 1e-15, 1e-4


#: Ten graphs of the tables, made undirected for the linear solve.
TEN = ("part_supplier", "part_supplier_heavy", "customer_supplier", "part_copurchase", "order_tree", "user_hour_event", "document_line", "user_follow", "conversation_token", "page_link")


def undirected(spark: SparkSession, sf_dir: str, graph: str) -> Graph:
    g = build(graph, spark, sf_dir)
    g = g if g.undirected else g.as_undirected()
    g.stats  # noqa: B018  the graph is laid out before any clock starts
    return g


def epsilon_sweep(spark: SparkSession, sf_dir: str, graph: str = "part_supplier_heavy", grid: tuple[float, ...] = EPS, max_levels: int = 200) -> DataFrame:
    """The ranking criterion for each eps against a partial sum to a tolerance and a tight solve: levels, seconds, share of
    strictly separated pairs, seconds relative to the loosest eps. One run goes from eps to eps; the seconds of one are
    those up to where it held. The partial sum looks at the levels of the same run; its seconds are those of the levels
    and of its own looks."""
    g, out, spent, term = undirected(spark, sf_dir, graph), [], 0.0, LastTerm(TPS_TOL)
    for eps, r in zip(grid, ladder(g, [RankingCriterion(eps) for eps in grid], max_levels=max_levels, term=term), strict=True):
        spent += r.report.seconds
        out.append((graph, f"eps {eps:g}", r.report.levels, r.report.converged, spent, measures.separated_fraction(r.frame, g.stats.n)[2]))
    for name, r in ((f"partial sum {TPS_TOL:g}", term), (f"linear solve {CG_TIGHT:g}", baselines.solve_cg(g, CG_TIGHT))):
        out.append((graph, name, r.levels, r.converged, r.seconds, None))
    g.placed.release()
    table = spark.createDataFrame(out, "graph string, method string, levels int, converged boolean, seconds double, separated double")
    return measures.relative_to(table, ["graph"], "seconds", F.col("method") == f"eps {grid[0]:g}")


def topk_sweep(spark: SparkSession, sf_dir: str, graphs: tuple[str, ...] = ("part_supplier", "customer_supplier", "part_copurchase", "order_tree"), ks: tuple[int, ...] = (1, 10, 100, 1000, 10000), eps: float = 1e-6) -> DataFrame:
    """Top-k for each k against the full ranking, and a loose solve for the best hundred; the geometric mean of the
    speed-ups over the graphs is beside each. One run goes from k to k and on to the full ranking, which can't hold before
    them; the seconds of one are those up to where it held."""
    out = []
    for graph in graphs:
        g, spent, found = undirected(spark, sf_dir, graph), 0.0, []
        rising = sorted(ks)
        for name, r in zip([*(f"top {k}" for k in rising), "full"], ladder(g, [*(TopKCriterion(k, eps) for k in rising), RankingCriterion(eps)]), strict=True):
            spent += r.report.seconds
            found.append((name, r.report.levels, spent))
        full = found[-1][2]
        out += [(graph, name, levels, seconds, full / max(seconds, 1e-9)) for name, levels, seconds in found]
        loose = baselines.solve_cg(g, CG_LOOSE)
        out.append((graph, f"linear solve {CG_LOOSE:g}", loose.levels, loose.seconds, full / max(loose.seconds, 1e-9)))
        g.placed.release()
    table = spark.createDataFrame(out, "graph string, method string, levels int, seconds double, speedup double")
    return table.join(table.groupBy("method").agg(measures.geo_mean("speedup").alias("mean_speedup")), "method")


def measured_anew(g: Graph, criterion) -> tuple[float, Report]:
    """Seconds of a new state, and the report of the static algorithm."""
    begun = time.monotonic()
    dynamic.start(g, criterion)
    spent = time.monotonic() - begun
    report = rank_nodes(g, criterion).report
    g.placed.release()
    return spent, report


def batch_sweep(spark: SparkSession, sf_dir: str, graphs: tuple[str, ...] = ("part_supplier_heavy",), sizes: tuple[int, ...] = (1, 10, 100, 1000, 10000), k: int = 1000, eps: float = 1e-4, inserts: bool = False, seed: int | None = 1) -> DataFrame:
    """Batches of random deletions (or of insertions of edges held out before) against the static algorithm on the changed
    graph, whose layout isn't counted (relative), and against a new state, with layout and exact counts (to_new_state). A
    batch of more than half of the edges is left out. restored: whether the levels
    of inserted edges are those of the graph that had them. That graph is the one each batch of insertions leads to, so its
    static run and new state are measured once for all sizes. mean_relative: the geometric mean over graphs."""
    criterion, out = TopKCriterion(k, eps), []
    for graph in graphs:
        g, whole = build(graph, spark, sf_dir).as_undirected(), None
        g.tables  # noqa: B018  the graph is built before any clock starts
        begun = time.monotonic()
        base = dynamic.start(g, criterion)
        if inserts:
            whole = time.monotonic() - begun, rank_nodes(g, criterion).report
        for size in sizes:
            if 4 * size > g.stats.m:
                continue
            some = layout.commit(dynamic.chosen_edges(g.placed.arcs, size, True, seed))
            state, batch = base, dynamic.EdgeBatch.of(deletes=some)
            if inserts:
                state, batch = dynamic.apply_batch(base, batch), dynamic.EdgeBatch.of(inserts=some)
            begun = time.monotonic()
            after = dynamic.apply_batch(state, batch)
            spent = time.monotonic() - begun
            state_anew, anew = whole or measured_anew(Graph(after.graph.edges, after.graph.nodes, True), criterion)
            restored = None
            if inserts:
                both = after.levels[base.depth].join(base.levels[base.depth].withColumnRenamed("w", "_w"), "id")
                restored = both.where("w <> _w").isEmpty()
            out.append((graph, size, after.depth, sum(after.frontier), anew.levels, spent, anew.seconds, spent / anew.seconds, spent / state_anew, restored))
        g.placed.release()
    table = spark.createDataFrame(out, "graph string, batch int, levels int, touched long, static_levels int, seconds double, static_seconds double, relative double, to_new_state double, restored boolean")
    return table.join(table.groupBy("batch").agg(measures.geo_mean("relative").alias("mean_relative")), "batch")


def instances(spark: SparkSession, sf_dir: str, graphs: tuple[str, ...] = TEN, grid: tuple[float, ...] = (1e-1, 1e-3, 1e-5)) -> DataFrame:
    """The epsilon sweep on several graphs: levels and seconds relative to the loosest eps of each."""
    out = None
    for graph in graphs:
        part = epsilon_sweep(spark, sf_dir, graph, grid)
        out = part if out is None else out.unionByName(part)
    return out


def summary(table: DataFrame) -> DataFrame:
    """Over graphs: mean levels and seconds, geometric means of the separated share and of the relative time."""
    return table.groupBy("method").agg(F.avg("levels").alias("levels"), F.avg("seconds").alias("seconds"), measures.geo_mean(F.nullif("separated", F.lit(0.0))).alias("separated"), measures.geo_mean("relative").alias("relative"))


def scaling(spark: SparkSession, sf_dir: str, graphs: tuple[str, ...] = ("part_supplier", "part_copurchase"), parts: tuple[int, ...] = (1, 2, 4, 8), k: int = 10000, eps: float = 1e-6) -> DataFrame:
    """One top-k run for each number of partitions, which is the number of tasks that a level runs at once: levels, seconds,
    seconds relative to one partition, and the geometric mean of these over graphs. The graphs are laid out as large ones
    are, each time from the same tables. `bench.py --cores` does the same for sessions of so many cores."""
    out = []
    for graph in graphs:
        g = build(graph, spark, sf_dir).as_undirected()
        for n in parts:
            one = g.dealt(n)
            one.stats  # noqa: B018
            report = rank_nodes(one, TopKCriterion(k, eps)).report
            out.append((graph, n, report.levels, report.seconds))
            one.placed.release()
    table = spark.createDataFrame(out, "graph string, partitions int, levels int, seconds double")
    table = measures.relative_to(table, ["graph"], "seconds", F.col("partitions") == parts[0])
    return table.join(table.groupBy("partitions").agg(measures.geo_mean("relative").alias("mean_relative")), "partitions")


def webs(spark: SparkSession, sf_dir: str, k: int = 20, eps: float = 1e-6) -> DataFrame:
    """Pages by the walks that arrive at them."""
    return rank_nodes(build("page_link", spark, sf_dir).reverse(), TopKCriterion(k, eps)).ranking(k)
