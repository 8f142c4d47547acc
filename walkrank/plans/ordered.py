"""Neighbours and running counts in a global order, without a window over one partition.

Rows are dealt to ranges of the ordering value by boundaries from a quantile sketch; windows run inside a range, and
ranges are stitched by one summary row each."""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import layout

#: Rows of a range, and most ranges: beyond these the ranges grow, and are sorted with spilling.
ROWS_PER_RANGE, RANGES = 500_000, 10_000


def boundaries(df: DataFrame, value: str, n: int, per_range: int = ROWS_PER_RANGE) -> list[float]:
    """Ascending values that cut df into ranges of about per_range rows."""
    ranges = min(RANGES, max(1, -(-n // per_range)))
    if ranges == 1:
        return []
    cuts = df.agg(F.percentile_approx(value, [k / ranges for k in range(1, ranges)], 10 * ranges)).first()[0]
    return sorted(set(cuts or []))


def constants(values: list) -> Column:
    """An array as one literal, however long."""
    return F.from_json(F.lit(json.dumps(values)), f"array<{'double' if values and isinstance(values[0], float) else 'bigint'}>")


def range_of(value: str | Column, cuts: list[float]) -> Column:
    """0 for values above the last boundary, then 1 and so on: ranges in descending order. Found by halving."""
    value = F.col(value) if isinstance(value, str) else value
    if not cuts:
        return F.lit(0)
    falling = constants([float(c) for c in reversed(cuts)])
    steps = F.array(*[F.lit(1 << k) for k in range(len(cuts).bit_length() - 1, -1, -1)])
    return F.aggregate(steps, F.lit(0), lambda at, step: at + F.when(F.try_element_at(falling, at + step) >= value, step).otherwise(0))


def numbered(df: DataFrame, value: str, per_range: int = ROWS_PER_RANGE, tie: str | None = "id", name: str = "rank") -> DataFrame:
    """df with a number from 1 in descending order of value, then of tie: row numbers inside ranges of the value, behind
    the counts of those before."""
    df = layout.commit(df)
    cuts = boundaries(df, value, df.count(), per_range)
    dealt, ahead, before = df.withColumn("_part", range_of(value, cuts)), 0, [0] * (len(cuts) + 1)
    sizes = {r._part: r["count"] for r in dealt.groupBy("_part").count().collect()} if cuts else {}
    for part in range(len(cuts) + 1):
        before[part], ahead = ahead, ahead + sizes.get(part, 0)
    order = [F.desc(value), *([tie] if tie else [])]
    own = F.row_number().over(Window.partitionBy("_part").orderBy(*order))
    return dealt.select((own + F.element_at(constants(before), F.col("_part") + 1)).cast("long").alias(name), *df.columns)


def followed(df: DataFrame, by: list[str], value: str, name: str, per_range: int = ROWS_PER_RANGE) -> DataFrame:
    """df with the value of the next row in the order of some columns (null for the last one). Ranges of that order, of
    about per_range rows whatever the columns hold, are looked at each on its own and stitched by one row each."""
    n = df.count()
    parts = min(RANGES, max(1, -(-n // per_range)))
    dealt = layout.commit(df.repartitionByRange(parts, *by)).withColumn("_part", F.spark_partition_id())
    place = F.struct(*by)
    heads = dealt.groupBy("_part").agg(F.min_by(value, place).alias("_head"), F.max(place).alias("_last"))
    heads = heads.withColumn("_next", F.lead("_head").over(Window.orderBy("_part"))).select("_part", "_last", "_next")
    inside = F.lead(value).over(Window.partitionBy("_part").orderBy(*by))
    joined = dealt.withColumn(name, inside).join(F.broadcast(heads), "_part")
    return joined.withColumn(name, F.when(place == F.col("_last"), F.col("_next")).otherwise(F.col(name))).select(*df.columns, name)


def adjacent_failures(frame: DataFrame, eps: float, n: int, per_range: int = ROWS_PER_RANGE) -> int:
    """How many neighbours in descending order of floor are not apart: floor of the one > ceiling of the next - eps.

    Nodes of one floor are summed up first (any order of those is a ranking, so all but one of them must be apart from
    their own ceiling); what is left has distinct floors."""
    groups = frame.groupBy("floor").agg(F.max("ceiling").alias("ceiling"), F.count_if(F.col("ceiling") - eps >= F.col("floor")).alias("bad"))
    cuts = boundaries(groups, "floor", n, per_range)
    dealt = groups.withColumn("part", range_of("floor", cuts))
    before = F.lag("floor").over(Window.partitionBy("part").orderBy(F.desc("floor")))
    marked = dealt.withColumn("before", before)
    rows = marked.groupBy("part").agg(
        F.sum(F.greatest(F.col("bad") - 1, F.lit(0))).alias("ties"),
        F.count_if(F.col("before") <= F.col("ceiling") - eps).alias("inside"),
        F.min("floor").alias("last"), F.max_by("ceiling", "floor").alias("first"),
    ).orderBy("part").collect()
    failures = sum(r.ties + r.inside for r in rows)
    return failures + sum(a.last <= b.first - eps for a, b in zip(rows[:-1], rows[1:], strict=True))


def separated_pairs(frame: DataFrame, n: int, per_range: int = ROWS_PER_RANGE) -> int:
    """How many unordered pairs have the floor of one above the ceiling of the other.

    Floors and ceilings are events on a line: going down, each ceiling counts the floors strictly above it."""
    floors = frame.groupBy(F.col("floor").alias("at")).agg(F.count("*").alias("floors"), F.lit(0).cast("long").alias("ceilings"))
    ceilings = frame.groupBy(F.col("ceiling").alias("at")).agg(F.lit(0).cast("long").alias("floors"), F.count("*").alias("ceilings"))
    events = floors.unionByName(ceilings).groupBy("at").agg(F.sum("floors").alias("floors"), F.sum("ceilings").alias("ceilings"))
    dealt = events.withColumn("part", range_of("at", boundaries(events, "at", 2 * n, per_range)))
    above = F.sum("floors").over(Window.partitionBy("part").orderBy(F.desc("at")).rowsBetween(Window.unboundedPreceding, -1))
    counted = dealt.withColumn("above", F.coalesce(above, F.lit(0)))
    product = F.col("ceilings").cast("decimal(19,0)") * F.col("above").cast("decimal(19,0)")
    rows = counted.groupBy("part").agg(F.sum(product).alias("pairs"), F.sum("floors").alias("floors"), F.sum("ceilings").alias("ceilings")).orderBy("part").collect()
    total = seen = 0
    for r in rows:
        total += int(r.pairs) + seen * r.ceilings
        seen += r.floors
    return total
