"""When a run may stop: the frames they look at have id, floor, ceiling and live."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import DRIVER_ROWS
from ..plans import ordered


@dataclass
class Verdict:
    done: bool
    live: int
    #: floor and id of the k-th node: those behind it whose ceiling less eps is below this floor leave the live set
    bar: tuple[float, int] | None = None
    winner: tuple[int, int] | None = None


def positive(eps: float) -> float:
    if not eps > 0:
        raise ValueError("eps must be positive: equal scores are never strictly apart")
    return eps


@dataclass(frozen=True)
class RankingCriterion:
    """All pairs apart by floor and ceiling, up to eps. In descending order of floors neighbours suffice."""

    eps: float
    name = "ranking"

    def check(self, frame: DataFrame, n: int) -> Verdict:
        return Verdict(ordered.adjacent_failures(frame, positive(self.eps), n) == 0, n)


@dataclass(frozen=True)
class TopKCriterion:
    """Only k nodes live, and these apart up to eps. k at least n is a ranking."""

    k: int
    eps: float
    name = "top-k"

    def check(self, frame: DataFrame, n: int) -> Verdict:
        eps, k = positive(self.eps), min(self.k, n)
        if k >= n:
            return RankingCriterion(eps).check(frame, n)
        if not k:
            return Verdict(True, 0)
        live = frame.where("live")
        if k > DRIVER_ROWS:
            return self.check_large(live, n, k)
        top = live.orderBy(F.desc("floor"), "id").limit(k).select("id", "floor", "ceiling").collect()
        bar = top[-1].floor, top[-1].id
        count = live.where(stays(bar, eps)).count()
        apart = all(a.floor > b.ceiling - eps for a, b in zip(top[:-1], top[1:], strict=True))
        return Verdict(count <= k and apart, count, bar)

    def check_large(self, live: DataFrame, n: int, k: int) -> Verdict:
        """The same for a k beyond what the driver takes: the k-th floor by ranges, neighbours by ranges."""
        floor, ahead = kth_largest(live, "floor", k, n)
        ties = live.where(F.col("floor") == floor).orderBy("id").limit(k - ahead)
        bar = floor, ties.agg(F.max("id")).first()[0]
        kept = live.where(stays(bar, self.eps))
        count = kept.count()
        return Verdict(count <= k and ordered.adjacent_failures(kept, self.eps, count) == 0, count, bar)


def top_verdicts(frame: DataFrame, ks: list[int], eps: float, n: int) -> dict[int, Verdict]:
    """Top-k for several k on one frame: the rows of the largest k and one count of those that may still be among them."""
    out = {k: TopKCriterion(k, eps).check(frame, n) for k in ks if not 0 < k < n or k > DRIVER_ROWS}
    few = [k for k in ks if k not in out]
    if few:
        top = frame.orderBy(F.desc("floor"), "id").limit(max(few)).select("id", "floor", "ceiling").collect()
        bars = {k: (top[k - 1].floor, top[k - 1].id) for k in few}
        counts = frame.agg(*[F.count_if(stays(bars[k], positive(eps))) for k in few]).first()
        # how many of the first rows are apart, one after another
        apart = next((i for i in range(1, len(top)) if not top[i - 1].floor > top[i].ceiling - eps), len(top))
        out |= {k: Verdict(count <= k and apart >= k, count, bars[k]) for k, count in zip(few, counts, strict=True)}
    return out


def kth_largest(frame: DataFrame, value: str, k: int, n: int) -> tuple[float, int]:
    """The k-th largest value and how many are larger."""
    part = ordered.range_of(value, ordered.boundaries(frame, value, n))
    left = k
    for r in frame.groupBy(part.alias("part")).count().orderBy("part").collect():
        if r["count"] >= left:
            inside = frame.where(part == r.part)
            bar = inside.orderBy(F.desc(value)).select(value).limit(left).agg(F.min(value)).first()[0]
            return bar, k - left + inside.where(F.col(value) > bar).count()
        left -= r["count"]
    raise ValueError("fewer than k rows")


def stays(bar: tuple[float, int], eps: float) -> Column:
    """A node is of the k first, or not behind the k-th by more than eps."""
    floor, last = bar
    first = (F.col("floor") > floor) | ((F.col("floor") == floor) & (F.col("id") <= last))
    return first | (F.col("ceiling") - eps >= floor)


@dataclass(frozen=True)
class ScoreCriterion:
    """All scores known to less than eps."""

    eps: float
    name = "score"

    def check(self, frame: DataFrame, n: int) -> Verdict:
        width = frame.agg(F.max(F.col("ceiling") - F.col("floor"))).first()[0]
        return Verdict(width is None or width < positive(self.eps), n)


@dataclass(frozen=True)
class PairCriterion:
    """Two nodes apart, either way round."""

    first: int
    second: int
    eps: float
    name = "pair"

    def check(self, frame: DataFrame, n: int) -> Verdict:
        rows = {r.id: r for r in frame.where(F.col("id").isin(self.first, self.second)).select("id", "floor", "ceiling").collect()}
        if len(rows) < 2:
            raise ValueError("the graph lacks one of the two nodes")
        a, b = rows[self.first], rows[self.second]
        for x, y in sorted(((a, b), (b, a)), key=lambda p: (-p[0].floor, p[0].id)):
            if x.floor > y.ceiling - positive(self.eps):
                return Verdict(True, 2, winner=(x.id, y.id))
        return Verdict(False, 2)


@dataclass(frozen=True)
class FixedLevels:
    """A number of levels, whatever the bounds."""

    levels: int
    eps: float = 0.0
    name = "levels"

    def check(self, frame: DataFrame, n: int) -> Verdict:
        return Verdict(False, n)
