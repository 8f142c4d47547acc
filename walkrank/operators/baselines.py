"""What certified ranking is compared with: partial sums to a tolerance, linear solves, degrees, exact solutions."""

from __future__ import annotations

import time
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import layout
from . import levels as L
from .attenuation import Attenuation
from .engine import ranked
from .graph import Graph, is_symmetric, out_degrees


@dataclass
class Solved:
    """scores: id, score."""

    scores: DataFrame
    levels: int
    converged: bool
    alpha: float
    seconds: float

    def ranking(self) -> DataFrame:
        return ranked(self.scores, "score").select("rank", "id", "score")

    def top(self, k: int) -> DataFrame:
        return self.scores.orderBy(F.desc("score"), "id").limit(k)


def factor(graph: Graph, alpha: Attenuation | float | None) -> float:
    kind = alpha if isinstance(alpha, Attenuation) else Attenuation.fixed(alpha) if alpha is not None else Attenuation.default()
    return kind.of(graph.stats.d_max, ceiling=False)


def tolerance_partial_sum(graph: Graph, tol: float = 1e-9, alpha: Attenuation | float | None = None, norm: str = "max", max_levels: int = 500) -> Solved:
    """Partial sums until the largest (norm max) or the summed (norm sum) last term is below tol. No certificate."""
    begun, placed, a = time.monotonic(), graph.placed, factor(graph, alpha)
    state, size = L.init_state(placed), {"max": F.max, "sum": F.sum}[norm]
    level, done = 0, False
    while level < max_levels and not done:
        level += 1
        state = layout.kept(L.advance_level(placed, state, "scaled", a, level), placed, level)
        done = (state.agg(size("w")).first()[0] or 0.0) < tol
    return Solved(state.select("id", F.col("k").alias("score")), level, done, a, time.monotonic() - begun)


def solve_cg(graph: Graph, tol: float = 1e-15, alpha: Attenuation | float | None = None, max_iter: int = 500, patience: int = 12) -> Solved:
    """Conjugate gradients for (1 - alpha A) z = 1 without preconditioner; the scores are z - 1 = alpha A z.

    The residual is relative to the right side. It gives up if the residual hasn't shrunk for `patience` steps. A must be
    symmetric."""
    begun, placed, a = time.monotonic(), graph.placed, factor(graph, alpha)
    if not graph.undirected and not is_symmetric(graph.edges):
        raise ValueError("conjugate gradients need a symmetric graph")
    one = F.lit(1.0)
    state = placed.nodes.select("id", F.lit(0.0).alias("x"), one.alias("res"), one.alias("dir"))
    rhs = rs = float(placed.stats.n)
    best, since, steps = rs, 0, 0
    while rhs and (rs / rhs) ** 0.5 >= tol and steps < max_iter and since < patience:
        steps += 1
        moved = L.spread(placed, state, "dir")
        q = state.alias("s").join(moved.alias("m"), F.col("s.id") == F.col("m.id"), "left").select("s.*", (F.col("dir") - a * F.coalesce("m.w", F.lit(0.0))).alias("q"))
        q = layout.kept(q, placed, steps)
        step = rs / q.agg(F.sum(F.col("dir") * F.col("q"))).first()[0]
        res = F.col("res") - step * F.col("q")
        now = q.agg(F.sum(res * res)).first()[0]
        state = q.select("id", (F.col("x") + step * F.col("dir")).alias("x"), res.alias("res"), (res + (now / rs) * F.col("dir")).alias("dir"))
        rs = now
        best, since = (rs, 0) if rs < best else (best, since + 1)
        if not rs:
            break
    scores = L.spread(placed, state, "x")
    scores = placed.nodes.join(scores, "id", "left").select("id", (a * F.coalesce("w", F.lit(0.0))).alias("score"))
    return Solved(layout.kept(scores, placed, steps + 1), steps, not rhs or (rs / rhs) ** 0.5 < tol, a, time.monotonic() - begun)


def solve_fixed_point(graph: Graph, tol: float = 1e-12, alpha: Attenuation | float | None = None, max_iter: int = 2000) -> Solved:
    """z <- 1 + alpha A z from z = 1 until no entry moves by tol; also for directed graphs."""
    begun, placed, a = time.monotonic(), graph.placed, factor(graph, alpha)
    state, steps, moved = placed.nodes.select("id", F.lit(1.0).alias("w")), 0, float("inf")
    while moved >= tol and steps < max_iter:
        steps += 1
        sums = L.spread(placed, state)
        both = state.alias("s").join(sums.alias("n"), F.col("s.id") == F.col("n.id"), "left").select("s.id", (1.0 + a * F.coalesce("n.w", F.lit(0.0))).alias("w"), F.col("s.w").alias("old"))
        state = layout.kept(both, placed, steps)
        moved = state.agg(F.max(F.abs(F.col("w") - F.col("old")))).first()[0] or 0.0
        state = state.select("id", "w")
    return Solved(state.select("id", (F.col("w") - 1.0).alias("score")), steps, moved < tol, a, time.monotonic() - begun)


def degree_rank(graph: Graph) -> DataFrame:
    """rank, id, deg: the ranking after one level."""
    return ranked(out_degrees(graph), "deg").select("rank", "id", "deg")


DENSE_NODES = 2000


def dense_exact(graph: Graph, alpha: float | None = None) -> dict[int, float]:
    """Exact scores of a small graph by a dense solve on the driver."""
    ids = sorted(r.id for r in graph.nodes.limit(DENSE_NODES + 1).collect())
    if len(ids) > DENSE_NODES:
        raise ValueError(f"more than {DENSE_NODES} nodes")
    at, a = {k: i for i, k in enumerate(ids)}, np.zeros((len(ids), len(ids)))
    for r in graph.edges.toLocalIterator():
        a[at[r.src], at[r.dst]] = 1
    d_max = int(a.sum(1).max(initial=0))
    f = alpha if alpha is not None else 1.0 / (1 + d_max)
    z = np.linalg.solve(np.eye(len(ids)) - f * a, np.ones(len(ids)))
    return {k: float(f * (a @ z)[i]) for k, i in at.items()}
