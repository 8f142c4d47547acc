"""Certified ranking: bounds refined level by level until a criterion holds."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import DRIVER_ROWS, MAX_LEVELS
from ..functions import bounds as B
from ..plans import layout, ordered
from . import levels as L
from .attenuation import Attenuation
from .criteria import FixedLevels, PairCriterion, RankingCriterion, ScoreCriterion, TopKCriterion, Verdict, stays, top_verdicts
from .graph import Graph

BOUNDS = ("standard", "tight", "ratio")


@dataclass
class Report:
    criterion: str
    eps: float
    alpha: float
    gamma: float
    d_max: int
    levels: int = 0
    converged: bool = False
    live: list[int] = field(default_factory=list)
    frontier: list[int] = field(default_factory=list)
    seconds: float = 0.0
    winner: tuple[int, int] | None = None
    #: floor and id of the k-th node at the end, where the criterion has a live set
    bar: tuple[float, int] | None = None


def report_metrics(spark: SparkSession, report: Report) -> DataFrame:
    """The figures of a run as a map of those that are not zero, and as JSON."""
    named = {"eps": report.eps, "alpha": report.alpha, "gamma": report.gamma, "d_max": report.d_max, "levels": report.levels, "live": report.live[-1] if report.live else 0, "touched": sum(report.frontier)}
    entries = F.array(*[F.struct(F.lit(k).alias("key"), F.lit(float(v)).alias("value")) for k, v in named.items()])
    found = spark.range(1).select(F.lit(report.criterion).alias("criterion"), F.map_filter(F.map_from_entries(entries), lambda _, v: v != 0).alias("metrics"))
    return found.withColumn("json", F.to_json(F.struct("criterion", "metrics")))


@dataclass
class RankResult:
    """state: id, w, k, live. frame: id, floor, ceiling, live."""

    state: DataFrame
    frame: DataFrame
    report: Report
    history: list[DataFrame] = field(default_factory=list)

    def ranking(self, k: int | None = None) -> DataFrame:
        """rank, id, floor, ceiling in order of floor, then id. Ranks of all nodes, or of more than the driver takes, come by
        ranges of the floor."""
        if k is not None and k > DRIVER_ROWS:
            return ranked(self.frame.where("live")).where(F.col("rank") <= k).select("rank", "id", "floor", "ceiling")
        if k is not None:
            top = self.frame.where("live").orderBy(F.desc("floor"), "id").limit(k)
            from pyspark.sql import Window

            return top.select(F.row_number().over(Window.orderBy(F.desc("floor"), "id")).cast("long").alias("rank"), "id", "floor", "ceiling")
        return ranked(self.frame)

    def scores(self) -> DataFrame:
        """id and the middle of its bounds."""
        return self.frame.select("id", ((F.col("floor") + F.col("ceiling")) / 2).alias("score"))


def ranked(frame: DataFrame, value: str = "floor", per_range: int | None = None) -> DataFrame:
    """rank by value descending, then id."""
    return ordered.numbered(frame, value, per_range or ordered.ROWS_PER_RANGE)


def with_bounds(state: DataFrame, level: int, undirected: bool, alpha: float, gamma: float, numeric: str, kind: str = "standard", ratio: tuple[float, float] | None = None) -> DataFrame:
    """A state with floor and ceiling."""
    part, term = F.col("k"), L.term_of(numeric, alpha, level)
    floor = B.floor_undirected(part, term, alpha) if undirected else B.floor_directed(part, term)
    ceiling = B.ceiling(part, term, alpha, gamma)
    if kind == "tight" and undirected:
        floor = B.floor_geometric(part, term, alpha)
    if kind == "ratio" and ratio and alpha * ratio[1] < 1:
        low, high = B.ratio_bounds(part, term, alpha, *ratio)
        floor, ceiling = F.greatest(floor, low), F.least(ceiling, high)
    return state.withColumns({"floor": floor if level else part, "ceiling": ceiling})


def bounded(state: DataFrame, *args, **kw) -> DataFrame:
    """id, floor, ceiling and live of a state."""
    return with_bounds(state, *args, **kw).select("id", "floor", "ceiling", "live")


def growth(before: DataFrame, now: DataFrame, numeric: str, alpha: float) -> tuple[float, float]:
    """Least and largest growth of walk counts between two levels."""
    factor = 1 / alpha if numeric == "scaled" else 1.0
    ratio = now.alias("n").join(before.alias("b"), "id").where("b.w > 0").select((F.col("n.w").cast("double") / F.col("b.w").cast("double") * factor).alias("r"))
    low, high = ratio.agg(F.min("r"), F.max("r")).first()
    return (low or 0.0) * (1 - 1e-12), (high or 0.0) * (1 + 1e-12)


@dataclass
class LastTerm:
    """When a partial sum would stop, seen on the levels of a run: on the first whose largest term is below tol. seconds:
    those of the levels up to there and of these looks at them, without the run's own checks."""

    tol: float
    levels: int = 0
    converged: bool = False
    seconds: float = 0.0
    #: seconds of the looks
    own: float = 0.0

    def see(self, state: DataFrame, level: int, numeric: str, alpha: float, seconds: float) -> None:
        if self.converged:
            return
        begun = time.monotonic()
        self.converged = (state.agg(F.max(L.term_of(numeric, alpha, level))).first()[0] or 0.0) < self.tol
        spent = time.monotonic() - begun
        self.levels, self.seconds, self.own = level, self.seconds + seconds + spent, self.own + spent


def run(placed: layout.Placed, state: DataFrame, level: int, criterion, alpha: float, gamma: float, numeric: str, kind: str, max_levels: int, history: list[DataFrame] | None, report: Report, term: LastTerm | None = None) -> tuple[DataFrame, DataFrame]:
    """Goes on from a state until the criterion holds or max_levels are done. term: looks at each level, too."""
    last = criterion.levels if isinstance(criterion, FixedLevels) else max_levels
    known, ratio = (placed.undirected, alpha, gamma, numeric, kind), None
    with layout.fixed(placed.edges.sparkSession, placed.parts, placed.stats.n):
        frame = bounded(state, level, *known)
        verdict = criterion.check(frame, placed.stats.n) if level else Verdict(False, placed.stats.n)
        while level < last and not verdict.done:
            if not L.surely_fits(numeric, placed.stats.d_max, level + 1):
                L.check_room(numeric, state.agg(F.max("w")).first()[0], placed.stats.d_max)
            before = state
            if verdict.bar is not None:
                state = with_bounds(state, level, *known, ratio).withColumn("live", F.col("live") & stays(verdict.bar, criterion.eps)).select("id", "w", "k", "live")
            level, begun = level + 1, time.monotonic()
            state = layout.kept(L.advance_level(placed, state, numeric, alpha, level), placed, level, history is not None)
            if term:
                term.see(state, level, numeric, alpha, time.monotonic() - begun)
            if history is not None:
                history.append(state.select("id", "w"))
            ratio = growth(before, state, numeric, alpha) if kind == "ratio" else None
            frame = bounded(state, level, *known, ratio)
            verdict = criterion.check(frame, placed.stats.n)
            report.live.append(verdict.live)
    report.levels, report.winner, report.bar = level, verdict.winner, verdict.bar
    report.converged = verdict.done or isinstance(criterion, FixedLevels)
    if verdict.bar is not None:
        frame = frame.withColumn("live", F.col("live") & stays(verdict.bar, criterion.eps))
    return state, frame


def rank_nodes(graph: Graph, criterion, alpha: Attenuation | float | None = None, numeric: str = "scaled", bounds: str = "standard", max_levels: int = MAX_LEVELS, keep_levels: bool = False) -> RankResult:
    """Ranks the nodes of a graph by the walks that leave them, each step times alpha (of the reversed graph: by those
    that arrive). The report says whether the criterion held within max_levels."""
    begun = time.monotonic()
    placed = graph.placed
    factor = (alpha if isinstance(alpha, Attenuation) else Attenuation.fixed(alpha) if alpha is not None else Attenuation.default()).of(placed.stats.d_max)
    gamma = B.tail_factor(factor, placed.stats.d_max)
    report = Report(criterion.name, criterion.eps, factor, gamma, placed.stats.d_max)
    history: list[DataFrame] | None = [] if keep_levels else None
    state, frame = run(placed, L.init_state(placed, numeric), 0, criterion, factor, gamma, numeric, bounds, max_levels, history, report)
    report.seconds = time.monotonic() - begun
    return RankResult(state, frame, report, history or [])


def ladder(graph: Graph, criteria: list, alpha: Attenuation | float | None = None, numeric: str = "scaled", bounds: str = "standard", max_levels: int = MAX_LEVELS, term: LastTerm | None = None):
    """Results for criteria of growing strictness, each going on from the one before: a looser one that doesn't hold spares
    the look at the next. For one eps, top-k is stricter for larger k and a ranking stricter still. term: is seen on the
    same levels, and on more of them where it needs these; its looks don't count in a report's seconds."""
    placed = graph.placed
    factor = (alpha if isinstance(alpha, Attenuation) else Attenuation.fixed(alpha) if alpha is not None else Attenuation.default()).of(placed.stats.d_max)
    gamma, state, level = B.tail_factor(factor, placed.stats.d_max), L.init_state(placed, numeric), 0
    for criterion in criteria:
        begun, looks, report = time.monotonic(), term.own if term else 0.0, Report(criterion.name, criterion.eps, factor, gamma, placed.stats.d_max)
        # those that another criterion has ruled out may be among the first of this one
        state, frame = run(placed, state.withColumn("live", F.lit(True)), level, criterion, factor, gamma, numeric, bounds, max_levels, None, report, term)
        level, report.seconds = report.levels, time.monotonic() - begun - (term.own - looks if term else 0.0)
        yield RankResult(state, frame, report)
    while term and not term.converged and level < max_levels:
        level += 1
        state, _ = run(placed, state, level - 1, FixedLevels(level), factor, gamma, numeric, bounds, max_levels, None, Report("levels", 0.0, factor, gamma, placed.stats.d_max), term)


def top_k_sweep(graph: Graph, ks: list[int], eps: float, alpha: Attenuation | float | None = None, numeric: str = "scaled", bounds: str = "standard", max_levels: int = MAX_LEVELS) -> dict[int, Report]:
    """The reports of top-k for several k, from one run of levels: on each level all k are looked at together."""
    placed = graph.placed
    factor = (alpha if isinstance(alpha, Attenuation) else Attenuation.fixed(alpha) if alpha is not None else Attenuation.default()).of(placed.stats.d_max)
    gamma, state, level, begun = B.tail_factor(factor, placed.stats.d_max), L.init_state(placed, numeric), 0, time.monotonic()
    found = {k: Report("top-k", eps, factor, gamma, placed.stats.d_max) for k in ks}
    left = set(ks)
    while left and level < max_levels:
        level += 1
        with layout.fixed(placed.edges.sparkSession, placed.parts, placed.stats.n):
            state = layout.kept(L.advance_level(placed, state, numeric, factor, level), placed, level)
            frame = bounded(state, level, placed.undirected, factor, gamma, numeric, bounds)
            for k, verdict in top_verdicts(frame, sorted(left), eps, placed.stats.n).items():
                found[k].live.append(verdict.live)
                found[k].levels, found[k].bar, found[k].seconds = level, verdict.bar, time.monotonic() - begun
                if verdict.done:
                    found[k].converged = True
                    left.remove(k)
    return found


def top_k(graph: Graph, k: int, eps: float, **kw) -> RankResult:
    return rank_nodes(graph, TopKCriterion(k, eps), **kw)


def full_ranking(graph: Graph, eps: float, **kw) -> RankResult:
    return rank_nodes(graph, RankingCriterion(eps), **kw)


def scores(graph: Graph, eps: float, **kw) -> RankResult:
    return rank_nodes(graph, ScoreCriterion(eps), **kw)


def compare(graph: Graph, first: int, second: int, eps: float, **kw) -> RankResult:
    return rank_nodes(graph, PairCriterion(first, second, eps), **kw)


def level_bounds(graph: Graph, levels: int, **kw) -> RankResult:
    return rank_nodes(graph, FixedLevels(levels), **kw)
