"""Where rows lie: edges by target, states by node, both in the same number of partitions.

Edges are kept as packs: a target with an array of up to 2 ^ PACK_BITS sources. So a level joins a row for each pack rather than for
each edge. Packs are made in all of the session's shuffle partitions, however few the graph is laid out in. The join of a level then needs no exchange, and the only rows shuffled are partial sums by source. Each state goes to
the shared folder, which ends its lineage, so a lost executor costs one level at most. Levels are planned without adaptive
changes: their partitions are fixed, and a checkpoint keeps the partitioning of such a plan. The states of large graphs are
persisted as well, as a level reads them twice and the second reading of a bare checkpoint loses its partitioning; those of
small graphs are sent to the edges. (States that are persisted alone between checkpoints were tried: plans double with
each level, and levels took two to three times as long.)"""

from __future__ import annotations

import uuid
from collections.abc import Callable
from contextlib import contextmanager
from dataclasses import dataclass, field, replace

import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import BROADCAST_ROWS, PACK_BITS, PARTITION_ROWS, SMALL_ROWS, SUM_BITS, shared_folder


@contextmanager
def fixed(spark: SparkSession, parts: int, nodes: int = 0):
    """Plans made meanwhile have so many shuffle partitions and keep them. nodes: those of a graph, which a task's sums by
    source should find room for in their fast map (2 ^ 16 of them else), up to 2 ^ SUM_BITS."""
    bits = min(SUM_BITS, max(16, nodes.bit_length()))
    want = {"spark.sql.adaptive.enabled": "false", "spark.sql.shuffle.partitions": str(parts), "spark.sql.codegen.aggregate.fastHashMap.capacityBit": str(bits)}
    before = {k: spark.conf.get(k, None) for k in want}
    try:
        for k, v in want.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def kept(df: DataFrame, placed: Placed, level: int, hold: bool = False) -> DataFrame:
    """A state as its level leaves it, in the shared folder. Those of large graphs are persisted too; the ones of two levels
    before are let go, unless they are to be held (in placed.held)."""
    with fixed(df.sparkSession, placed.parts, placed.stats.n):
        df = commit(df)
    if placed.large:
        df = settled(df, placed.parts)
        placed.held.append(df)
        while not hold and len(placed.held) > 2:
            placed.held.pop(0).unpersist()
    return df


def settled(df: DataFrame, parts: int) -> DataFrame:
    """df persisted and computed, with its partitions as planned."""
    with fixed(df.sparkSession, parts):
        df = df.persist(StorageLevel.MEMORY_AND_DISK)
        df.count()
    return df


def commit(df: DataFrame) -> DataFrame:
    """df computed once and kept in the shared folder."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def written(df: DataFrame, name: str) -> DataFrame:
    """df as a Parquet table in the shared folder."""
    path = f"{shared_folder(df.sparkSession)}/walkrank-graphs/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


@dataclass
class Stats:
    n: int
    m: int
    d_max: int


@dataclass
class Placed:
    """A graph ready for levels."""

    #: src, dst of all edges but those to hubs, unpacked
    edges: DataFrame
    nodes: DataFrame
    stats: Stats
    parts: int
    undirected: bool
    large: bool
    #: all edges, as the table they were written to
    arcs: DataFrame
    #: edges as they lie: dst, srcs
    packs: DataFrame
    #: edges to hubs, dealt by source, and the hubs' ids; edges has the others
    hub_edges: DataFrame | None = None
    hubs: DataFrame | None = None
    #: arcs that came, and laid-out ones that went, since: few enough for the driver
    fresh: tuple[tuple[int, int], ...] = ()
    gone: tuple[tuple[int, int], ...] = ()
    #: states that are persisted
    held: list[DataFrame] = field(default_factory=list, repr=False)

    def table_of(self, arcs) -> DataFrame:
        columns = list(zip(*arcs, strict=True)) or [(), ()]
        return self.nodes.sparkSession.createDataFrame(pa.table({name: pa.array(x, pa.int64()) for name, x in zip(("src", "dst"), columns, strict=True)}))

    def laid_out(self) -> DataFrame:
        """All arcs as they were laid out, by target."""
        return self.edges if self.hub_edges is None else self.edges.unionByName(self.hub_edges)

    def brought(self, values: DataFrame) -> DataFrame:
        """src of the laid-out edges and what values (dst, and others; few enough to be sent) say of their targets."""
        few = F.broadcast(values)
        found = unpacked(self.packs.join(few, "dst"))
        return found if self.hub_edges is None else found.unionByName(self.hub_edges.join(few, "dst").select(found.columns))

    def current(self) -> DataFrame:
        """All arcs, src and dst."""
        arcs = self.arcs
        if self.gone:
            arcs = arcs.join(F.broadcast(self.table_of(self.gone)), ["src", "dst"], "left_anti")
        return arcs.unionByName(self.table_of(self.fresh)) if self.fresh else arcs

    def release(self) -> None:
        for kept_ in (self.packs, self.nodes, self.hub_edges, self.hubs, *self.held):
            if kept_ is not None:
                kept_.unpersist()
        self.held.clear()


def changed(before: Placed, comes: list[tuple[int, int]], goes: list[tuple[int, int]]) -> Placed:
    """With arcs added that aren't there and others taken away that are. Once these are many all is laid out anew; the
    figures but d_max are those of the changed graph."""
    fresh, gone = dict.fromkeys(before.fresh), dict.fromkeys(before.gone)
    for arc in goes:
        if arc in fresh:
            del fresh[arc]
        else:
            gone[arc] = None
    for arc in comes:
        if arc in gone:
            del gone[arc]
        else:
            fresh[arc] = None
    after = replace(before, fresh=tuple(fresh), gone=tuple(gone), stats=replace(before.stats, m=before.stats.m + len(comes) - len(goes)))
    if len(fresh) + len(gone) > min(BROADCAST_ROWS, max(1000, after.stats.m // 10)):
        return placed(after.current(), after.nodes, after.undirected, after.parts if after.large else None)
    return after


def placed(edges: DataFrame, nodes: DataFrame | Callable[[DataFrame], DataFrame], undirected: bool, parts: int | None = None) -> Placed:
    """edges and nodes as tables, laid out for levels."""
    return laid_out(*tables(edges, nodes), undirected, parts)


def tables(edges: DataFrame, nodes: DataFrame | Callable[[DataFrame], DataFrame]) -> tuple[DataFrame, DataFrame, Stats]:
    """edges (src, dst, distinct) and nodes (id, with all ends, or what makes them from the edges) as written tables, with
    their figures."""
    arcs = written(edges.select("src", "dst"), "edges")
    ids = written((nodes(arcs) if callable(nodes) else nodes).select("id"), "nodes")
    by_source = arcs.groupBy("src").count()
    m, d_max = by_source.agg(F.coalesce(F.sum("count"), F.lit(0)), F.coalesce(F.max("count"), F.lit(0))).first()
    return arcs, ids, Stats(ids.count(), m, d_max)


def packed(arcs: DataFrame, parts: int = 0) -> DataFrame:
    """dst, srcs: arcs by target, at most 2 ^ PACK_BITS in a row, in all of the session's shuffle partitions or more."""
    wide = max(parts, int(arcs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    # in this order a task that is run again makes the same packs
    each = arcs.repartition(wide, "dst").sortWithinPartitions("dst", "src").withColumn("_pack", F.shiftright(F.monotonically_increasing_id(), PACK_BITS))
    return each.groupBy("dst", "_pack").agg(F.collect_list("src").alias("srcs")).select("dst", "srcs")


def unpacked(packs: DataFrame) -> DataFrame:
    """src and the columns of packs."""
    return packs.select(F.explode("srcs").alias("src"), *[c for c in packs.columns if c != "srcs"])


def laid_out(arcs: DataFrame, ids: DataFrame, stats: Stats, undirected: bool, parts: int | None = None, packs: DataFrame | None = None) -> Placed:
    """Tables that were written, laid out for levels. packs: of all arcs, where they are at hand."""
    m, rows = stats.m, max(stats.m, stats.n)
    large = parts is not None or rows > SMALL_ROWS
    parts = parts or (int(arcs.sparkSession.conf.get("spark.sql.shuffle.partitions")) if large else -(-rows // PARTITION_ROWS) or 1)
    others, hub_edges, hubs = arcs if packs is None else packs, None, None
    if large:
        # nodes with half a partition of edges that arrive at them: at most two for each partition, so they can be sent
        hubs = settled(arcs.groupBy(F.col("dst").alias("id")).count().where(F.col("count") > max(1, m // (2 * parts))).select("id"), parts)
        if hubs.isEmpty():
            hubs.unpersist()
            hubs = None
        else:
            known = F.broadcast(hubs.select(F.col("id").alias("dst")))
            hub_edges, others = settled(arcs.join(known, "dst", "left_semi").select("src", "dst").repartition(parts, "src"), parts), others.join(known, "dst", "left_anti").select(others.columns)
    packs = packed(others, parts) if packs is None else others
    packs = settled(packs.repartition(parts, "dst").sortWithinPartitions("dst"), parts)
    return Placed(
        unpacked(packs).select("src", "dst"),
        settled(ids.repartition(parts, "id").sortWithinPartitions("id"), parts),
        stats, parts, undirected, large, arcs, packs, hub_edges, hubs,
    )
