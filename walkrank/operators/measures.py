"""Costs and accuracy of rankings."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans import layout, ordered


def pairs_of(n: int) -> int:
    return n * (n - 1) // 2


def separated_fraction(frame: DataFrame, n: int | None = None) -> tuple[int, int, float]:
    """Strictly separated pairs, all pairs, and their share."""
    n = frame.count() if n is None else n
    found = ordered.separated_pairs(frame, n)
    return found, pairs_of(n), found / pairs_of(n) if n > 1 else 1.0


def tied_pairs(scores: DataFrame, decimals: int = 12, value: str = "score") -> int:
    """Pairs of equal scores, to so many decimals; no bounds ever part them."""
    counts = scores.groupBy(F.round(value, decimals).alias("at")).count()
    return int(counts.agg(F.coalesce(F.sum(F.col("count").cast("decimal(19,0)") * (F.col("count") - 1).cast("decimal(19,0)") / 2), F.lit(0))).first()[0])


def near_ties(scores: DataFrame, eps: float) -> DataFrame:
    """Classes of equal scores that differ by less than eps: low, high (their least ids), low_nodes, high_nodes (how many
    they have); a class of several nodes is a pair with itself. Buckets of width eps make this an equi-join."""
    classes = scores.groupBy("score").agg(F.min("id").alias("id"), F.count("*").alias("nodes")).withColumn("bucket", F.floor(F.col("score") / eps))
    other = classes.select(F.col("id").alias("id2"), F.col("score").alias("score2"), F.col("nodes").alias("nodes2"), F.explode(F.array(F.col("bucket") - 1, F.col("bucket"), F.col("bucket") + 1)).alias("bucket"))
    near = classes.join(other, "bucket").where((F.col("id") <= F.col("id2")) & (F.abs(F.col("score") - F.col("score2")) < eps) & ((F.col("id") != F.col("id2")) | (F.col("nodes") > 1)))
    return near.select(F.col("id").alias("low"), F.col("id2").alias("high"), F.col("nodes").alias("low_nodes"), F.col("nodes2").alias("high_nodes"))


def topk_overlap(a: DataFrame, b: DataFrame) -> int:
    """How many ids two top lists share."""
    return a.select("id").intersect(b.select("id")).count()


def max_abs_error(scores: DataFrame, exact: DataFrame) -> float:
    both = scores.select("id", F.col("score").alias("a")).join(exact.select("id", F.col("score").alias("b")), "id")
    return both.agg(F.max(F.abs(F.col("a") - F.col("b")))).first()[0] or 0.0


def bound_violations(frame: DataFrame, exact: DataFrame, slack: float = 1e-12) -> int:
    """Exact scores outside their floor and ceiling."""
    both = frame.join(exact.select("id", "score"), "id")
    return both.where((F.col("score") < F.col("floor") - slack) | (F.col("score") > F.col("ceiling") + slack)).count()


def monotone_violations(before: DataFrame, now: DataFrame, slack: float = 1e-12) -> int:
    """Nodes whose floor fell or whose ceiling rose."""
    both = before.alias("b").join(now.alias("n"), "id")
    return both.where((F.col("n.floor") < F.col("b.floor") - slack) | (F.col("n.ceiling") > F.col("b.ceiling") + slack)).count()


def growth_violations(before: DataFrame, now: DataFrame, d_max: int) -> int:
    """Nodes whose walk count grew by more than the largest degree."""
    both = before.alias("b").join(now.alias("n"), "id")
    return both.where(F.col("n.w") > F.col("b.w") * d_max).count()


def misranked_pairs(scores: DataFrame, exact: DataFrame, eps: float = 0.0, per_range: int = ordered.ROWS_PER_RANGE) -> int:
    """Pairs in the wrong order: x is ahead of y by eps or more (strictly if eps is 0) in exact, but behind in scores.

    Both orders become whole numbers. Of two different numbers there is one bit, the highest in which they differ, that
    tells which is larger: so for each bit of the one and each bit of the other the pairs that are told by these two are
    counted in cells of the bits above, by sums alone. Equal rows are summed up before, and no cell is gathered."""
    both = scores.select("id", F.col("score").alias("b")).join(exact.select("id", F.col("score").alias("a")), "id")
    lead = both.select("a", "b", F.lit(1).alias("lead"))
    lag = both.select((F.col("a") + eps).alias("a"), "b", F.lit(0).alias("lead"))
    events = layout.commit(lead.unionByName(lag).groupBy("a", "b", "lead").agg(F.count("*").alias("n")))
    for v in ("a", "b"):
        places = ordered.numbered(events.select(v).distinct(), v, per_range, None, f"_{v}")
        events = events.join(places, v)
    # numbers rise as values fall, from 1; a lead of an equal value is ahead if eps is not 0
    a = 2 * F.col("_a") - (F.col("lead") if eps else F.lit(0))
    events = layout.commit(events.select(a.cast("long").alias("a"), F.col("_b").alias("b"), "lead", "n"))
    most = events.agg(F.max("a"), F.max("b")).first()
    if most[0] is None:
        return 0
    bits = [F.sequence(F.lit(0), F.lit(int(m).bit_length() - 1)) for m in most]
    each = events.select("a", "b", "lead", "n", F.explode(bits[0]).alias("i")).select("*", F.explode(bits[1]).alias("j"))
    bit = lambda v, k: F.expr(f"shiftright({v}, {k}) & 1")
    above = lambda v, k: F.expr(f"shiftright({v}, {k} + 1)")
    ahead = (F.col("lead") == 1) & (bit("a", "i") == 0) & (bit("b", "j") == 1)
    behind = (F.col("lead") == 0) & (bit("a", "i") == 1) & (bit("b", "j") == 0)
    whole = lambda x: F.sum(F.when(x, F.col("n")).otherwise(0)).cast("decimal(19,0)")
    cells = each.where(ahead | behind).groupBy("i", "j", above("a", "i").alias("p"), above("b", "j").alias("q")).agg(whole(ahead).alias("x"), whole(behind).alias("y"))
    return int(cells.agg(F.coalesce(F.sum(F.col("x") * F.col("y")), F.lit(0))).first()[0])


def geo_mean(value: str | Column) -> Column:
    """Geometric mean of positive values."""
    value = F.col(value) if isinstance(value, str) else value
    return F.exp(F.avg(F.log(value)))


def relative_to(table: DataFrame, keys: list[str], value: str, base: Column) -> DataFrame:
    """Adds `relative`: value over the value of the base row of the same keys."""
    bases = table.where(base).select(*keys, F.col(value).alias("_base"))
    return table.join(bases, keys).withColumn("relative", F.col(value) / F.nullif(F.col("_base"), F.lit(0.0))).drop("_base")
