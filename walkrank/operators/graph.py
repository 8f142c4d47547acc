"""Graphs as edge and node tables."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import layout


def symmetrize(edges: DataFrame) -> DataFrame:
    """Both arcs of each edge. Edges are told apart by their lesser and greater end, so half of the arcs are dealt out."""
    once = edges.select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct()
    arc = lambda src, dst: F.struct(F.col(src).alias("src"), F.col(dst).alias("dst"))
    both = F.when(F.col("a") == F.col("b"), F.array(arc("a", "b"))).otherwise(F.array(arc("a", "b"), arc("b", "a")))
    return once.select(F.inline(both))


def ends(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()


@dataclass
class Graph:
    """edges: src, dst (distinct; both arcs of each edge if undirected). nodes: id, with all ends and isolated ones."""

    edges: DataFrame
    nodes: DataFrame
    undirected: bool = False
    parts: int | None = field(default=None, compare=False)
    #: lays the graph out, where that is other than from its edges
    layout: Callable[[], layout.Placed] | None = field(default=None, compare=False)
    #: the nodes from arcs that are at hand, so that these aren't made twice
    nodes_of: Callable[[DataFrame], DataFrame] | None = field(default=None, compare=False)

    @staticmethod
    def from_edges(edges: DataFrame, nodes: DataFrame | None = None, undirected: bool = False, drop_loops: bool = False) -> Graph:
        """Repeated edges count once; edges without an end are left out; nodes beyond the ends are isolated."""
        clean = edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")).dropna()
        if drop_loops:
            clean = clean.where("src <> dst")
        clean = symmetrize(clean) if undirected else clean.distinct()

        def nodes_of(arcs: DataFrame) -> DataFrame:
            ids = arcs.select(F.col("src").alias("id")).distinct() if undirected else ends(arcs)
            return ids if nodes is None else ids.unionByName(nodes.select(F.col("id").cast("long").alias("id")).dropna()).distinct()

        return Graph(clean, nodes_of(clean), undirected, nodes_of=nodes_of)

    @staticmethod
    def of_placed(placed: layout.Placed) -> Graph:
        """A graph that is laid out, with edges that came and went since."""
        return Graph(placed.current(), placed.nodes.select("id"), placed.undirected, placed.parts if placed.large else None, lambda: placed)

    @cached_property
    def placed(self) -> layout.Placed:
        return self.layout() if self.layout else layout.laid_out(*self.tables, self.undirected, self.parts)

    @cached_property
    def tables(self) -> tuple[DataFrame, DataFrame, layout.Stats]:
        """Edges and nodes as written tables, and their figures."""
        return layout.tables(self.edges, self.nodes_of or self.nodes)

    @property
    def stats(self) -> layout.Stats:
        return self.placed.stats

    def reverse(self) -> Graph:
        """All arcs turned round: its scores are those of walks that arrive."""
        return Graph(self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")), self.nodes, self.undirected, self.parts, nodes_of=self.nodes_of)

    def as_undirected(self) -> Graph:
        return self if self.undirected else Graph(symmetrize(self.edges), self.nodes, True, self.parts, nodes_of=self.nodes_of)

    def dealt(self, parts: int) -> Graph:
        """The same graph laid out as a large one in so many partitions, from tables that are written once. It isn't laid out
        itself for that."""
        arcs, ids, stats = self.tables
        return Graph(arcs, ids, self.undirected, parts, lambda: layout.laid_out(arcs, ids, stats, self.undirected, parts, self.packs))

    @cached_property
    def packs(self) -> DataFrame:
        """All edges as packs, as a written table."""
        return layout.written(layout.packed(self.tables[0]), "packs")


def out_degrees(graph: Graph) -> DataFrame:
    """id, deg; zero for nodes without arcs."""
    counts = graph.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("deg"))
    return graph.nodes.join(counts, "id", "left").select("id", F.coalesce("deg", F.lit(0)).alias("deg"))


def max_out_degree(graph: Graph) -> int:
    return graph.stats.d_max


def is_complete(graph: Graph) -> bool:
    """Whether all pairs of different nodes are linked."""
    n = graph.nodes.count()
    return graph.edges.where("src <> dst").count() == n * (n - 1)


def is_symmetric(edges: DataFrame) -> bool:
    turned = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    return edges.join(turned, ["src", "dst"], "left_anti").isEmpty()
