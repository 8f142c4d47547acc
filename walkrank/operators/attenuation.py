"""The attenuation factor: default, given, and the limits it must keep."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import functions as F

from ..plans import layout
from .graph import Graph
from .levels import spread


@dataclass(frozen=True)
class Attenuation:
    """value: fixed, or None for 1 / (1 + headroom * d_max)."""

    value: float | None = None
    headroom: float = 1.0

    @staticmethod
    def default(headroom: float = 1.0) -> Attenuation:
        return Attenuation(None, headroom)

    @staticmethod
    def fixed(alpha: float) -> Attenuation:
        if not alpha > 0:
            raise ValueError("alpha must be positive")
        return Attenuation(float(alpha))

    def of(self, d_max: int, ceiling: bool = True) -> float:
        """The factor for a graph; with a ceiling it must be below 1 / d_max."""
        alpha = self.value if self.value is not None else 1.0 / (1.0 + self.headroom * d_max)
        if ceiling and alpha * d_max >= 1:
            raise ValueError(f"alpha {alpha} must be below 1 / d_max = 1 / {d_max} for a ceiling")
        return alpha


def sigma_max(graph: Graph, tol: float = 1e-6, max_iter: int = 200) -> float:
    """The largest singular value of the adjacency matrix, by power iteration on the matrix times its transpose.

    Two steps at a time converge also where the largest eigenvalues come as a pair of opposite signs."""
    placed = graph.placed
    turned = placed if graph.undirected else placed.arcs.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    vector, before = placed.nodes.select("id", F.lit(1.0).alias("w")), 0.0
    for step in range(max_iter):
        away = layout.kept(spread(turned, spread(placed, vector)), placed, step)
        norm, old = away.agg(F.sqrt(F.sum(F.col("w") * F.col("w")))).first()[0], vector.agg(F.sqrt(F.sum(F.col("w") * F.col("w")))).first()[0]
        if not norm:
            return 0.0
        now = (norm / old) ** 0.5
        if abs(now - before) <= tol * now:
            return now
        before, vector = now, away.withColumn("w", F.col("w") / norm)
    return before


def attenuation_limits(graph: Graph) -> tuple[float, float]:
    """Below the first there is a ceiling; below the second the scores are finite."""
    d, s = graph.stats.d_max, sigma_max(graph)
    return (1 / d if d else float("inf")), (1 / s if s else float("inf"))
