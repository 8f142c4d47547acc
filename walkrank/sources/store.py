"""Results kept as tables, by version: counts of all levels, edges and nodes as they were laid out, what batches have
changed since, and one row of figures.

A version that only adds changes writes these alone and names the version whose tables they are added to on reading; once
the changes have become many, the state has a new base and the version is whole again. A version is complete once its
figures are written, so a reader never sees half of one, and a batch that is written twice counts once."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import criteria
from ..operators.dynamic import DELTA, KatzState
from ..operators.engine import Report
from ..operators.graph import Graph
from ..operators.levels import EXACT
from ..plans import layout

META = "version long, base long, batch long, undirected boolean, depth int, alpha double, gamma double, n long, m long, d_max long, cap double, criterion string, k long, first long, second long, levels int, eps double, bar_floor double, bar_id long"
WHOLE, CHANGES = ("base", "edges", "nodes"), ("delta", "arcs", "meta")


def _path(root: str, name: str, version: int) -> str:
    return f"{root}/{name}/version={version}"


def save(state: KatzState, root: str, batch: int = -1) -> KatzState:
    """Writes the state as its version; batch: what it comes from (for streams). Returns the state as it is stored."""
    spark, c, placed = state.base.sparkSession, state.criterion, state.graph.placed
    to = lambda name: _path(root, name, state.version)
    if not state.stored or state.stored[0] != root:
        state.base.select("id", "ws").write.mode("overwrite").parquet(to("base"))
        placed.laid_out().select("src", "dst").sortWithinPartitions("dst").write.mode("overwrite").parquet(to("edges"))
        placed.nodes.select("id").write.mode("overwrite").parquet(to("nodes"))
        state = replace(state, stored=(root, state.version))
    delta = state.delta if state.delta is not None else DELTA.empty_table()
    spark.createDataFrame(delta).write.mode("overwrite").parquet(to("delta"))
    arcs = placed.table_of(placed.fresh).withColumn("op", F.lit("insert")).unionByName(placed.table_of(placed.gone).withColumn("op", F.lit("delete")))
    arcs.write.mode("overwrite").parquet(to("arcs"))
    bar, stats = state.bar or (None, None), placed.stats
    row = (state.version, state.stored[1], batch, state.graph.undirected, state.depth, state.alpha, state.report.gamma, stats.n, stats.m, stats.d_max, state.cap, c.name, getattr(c, "k", None), getattr(c, "first", None), getattr(c, "second", None), getattr(c, "levels", None), float(c.eps), *bar)
    spark.createDataFrame([row], META).write.mode("overwrite").parquet(to("meta"))
    return state


def _exists(spark: SparkSession, path: str) -> bool:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(where)


def versions(spark: SparkSession, root: str) -> DataFrame | None:
    """The figures of all complete versions."""
    if not _exists(spark, f"{root}/meta"):
        return None
    return spark.read.schema(META).option("basePath", f"{root}/meta").parquet(f"{root}/meta/version=*")


def load(spark: SparkSession, root: str, version: int | None = None) -> tuple[KatzState, int] | None:
    """A state (the latest without a version) and the batch it comes from."""
    known = versions(spark, root)
    if known is None:
        return None
    row = known.where(F.col("version") == version).first() if version is not None else known.orderBy(F.desc("version")).first()
    if row is None:
        return None
    kinds = {"ranking": lambda: criteria.RankingCriterion(row.eps), "top-k": lambda: criteria.TopKCriterion(row.k, row.eps), "score": lambda: criteria.ScoreCriterion(row.eps), "pair": lambda: criteria.PairCriterion(row.first, row.second, row.eps), "levels": lambda: criteria.FixedLevels(row.levels)}
    whole = lambda name: spark.read.parquet(_path(root, name, row.base))
    edges, nodes = whole("edges").select("src", "dst"), whole("nodes").select("id")
    delta = spark.read.schema(f"id long, level int, d {EXACT}").parquet(_path(root, "delta", row.version)).toArrow().cast(DELTA)
    arcs = spark.read.schema("src long, dst long, op string").parquet(_path(root, "arcs", row.version)).collect()
    fresh, gone = (tuple((r.src, r.dst) for r in arcs if r.op == op) for op in ("insert", "delete"))

    def lay_out() -> layout.Placed:
        return replace(layout.placed(edges, nodes, row.undirected), fresh=fresh, gone=gone, stats=layout.Stats(row.n, row.m, row.d_max))

    now = edges
    if gone:
        now = now.join(F.broadcast(spark.createDataFrame(list(gone), "src long, dst long")), ["src", "dst"], "left_anti")
    if fresh:
        now = now.unionByName(spark.createDataFrame(list(fresh), "src long, dst long"))
    report = Report(row.criterion, row.eps, row.alpha, row.gamma, row.d_max, row.depth, True)
    bar = None if row.bar_id is None else (row.bar_floor, row.bar_id)
    graph = Graph(now, nodes, row.undirected, None, lay_out)
    state = KatzState(graph, whole("base").select("id", "ws"), row.depth, kinds[row.criterion](), row.alpha, report, bar, row.cap, row.version, [], delta if delta.num_rows else None, (root, row.base))
    return state, row.batch


def compact(spark: SparkSession, root: str, keep: int = 2) -> list[int]:
    """Drops all but the last versions, and whole tables that none of those needs; returns the versions dropped."""
    known = versions(spark, root)
    rows = sorted((r.version, r.base) for r in known.select("version", "base").collect()) if known is not None else []
    old, needed = rows[:-keep], {b for _, b in rows[-keep:]}
    jvm = spark.sparkContext._jvm

    def drop(name: str, version: int) -> None:
        where = jvm.org.apache.hadoop.fs.Path(_path(root, name, version))
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)

    for version, _ in old:
        for name in reversed(CHANGES):
            drop(name, version)
    for version in {v for pair in old for v in pair} - needed:
        for name in WHOLE:
            drop(name, version)
    return [v for v, _ in old]


def save_bucketed(df: DataFrame, name: str, key: str, buckets: int) -> None:
    """A table bucketed and sorted by a key, for joins without an exchange."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def renumbered(state: KatzState, version: int) -> KatzState:
    return replace(state, version=version)
