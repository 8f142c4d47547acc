"""Walk counts level by level: one join of edges and counts, one grouped sum."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.layout import Placed

#: How counts are kept: scaled doubles, exact decimals, or longs.
NUMERIC = ("scaled", "exact", "bigint")
EXACT = "decimal(38,0)"
EXACT_LIMIT = 10**38
LONG_LIMIT = 2**63


def one(numeric: str) -> Column:
    return F.lit(1).cast({"scaled": "double", "exact": EXACT, "bigint": "long"}[numeric])


def init_state(placed: Placed, numeric: str = "scaled") -> DataFrame:
    """Level 0: one walk of no edges from each node, nothing summed up, all live."""
    return placed.nodes.select("id", one(numeric).alias("w"), F.lit(0.0).alias("k"), F.lit(True).alias("live"))


def spread(edges: Placed | DataFrame, values: DataFrame, value: str = "w") -> DataFrame:
    """For each source the sum over its targets: id, w. Only sources with a target in values have a row.

    The values of a placed graph's hubs are sent to their edges, which lie by source, so no partition holds all of them."""
    side = values.select(F.col("id").alias("dst"), F.col(value).alias("_w"))
    if not isinstance(edges, Placed):
        return edges.join(side, "dst").groupBy(F.col("src").alias("id")).agg(F.sum("_w").alias("w"))
    brought = edges.packs.join(side, "dst").select(F.explode("srcs").alias("src"), "_w")
    if edges.hubs is not None:
        known = side.join(F.broadcast(edges.hubs.select(F.col("id").alias("dst"))), "dst", "left_semi")
        brought = brought.unionByName(edges.hub_edges.join(F.broadcast(known), "dst").select("src", "_w"))
    for arcs, sign in ((edges.fresh, 1), (edges.gone, -1)):  # what edges that came bring, and those that went don't
        if arcs:
            few = F.broadcast(edges.table_of(arcs))
            kind = values.schema[value].dataType
            brought = brought.unionByName(side.join(few, "dst").select("src", (F.col("_w") * sign).cast(kind).alias("_w")))
    return brought.groupBy(F.col("src").alias("id")).agg(F.sum("_w").alias("w"))


def advance_level(placed: Placed, state: DataFrame, numeric: str, alpha: float, level: int) -> DataFrame:
    """The state of the next level, all nodes; ruled-out ones go on feeding others."""
    sums = spread(placed, state)
    if numeric == "scaled":
        count, term = F.coalesce("n.w", F.lit(0.0)) * alpha, F.coalesce("n.w", F.lit(0.0)) * alpha
    else:
        count = F.coalesce(F.col("n.w").cast(EXACT if numeric == "exact" else "long"), F.lit(0).cast(EXACT if numeric == "exact" else "long"))
        term = count.cast("double") * (alpha**level)
    return state.alias("s").join(sums.alias("n"), F.col("s.id") == F.col("n.id"), "left").select("s.id", count.alias("w"), (F.col("s.k") + term).alias("k"), "s.live")


def term_of(numeric: str, alpha: float, level: int) -> Column:
    """The last term of the partial score."""
    return F.col("w") if numeric == "scaled" else F.col("w").cast("double") * (alpha**level)


def surely_fits(numeric: str, d_max: int, level: int) -> bool:
    """Whether no count of a level can pass the range, as none grows by more than the largest degree."""
    limit = {"exact": EXACT_LIMIT, "bigint": LONG_LIMIT}.get(numeric)
    return limit is None or max(d_max, 1) ** level < limit


def check_room(numeric: str, largest: int | None, d_max: int) -> None:
    """Raises if the next level's counts may not fit."""
    limit = {"exact": EXACT_LIMIT, "bigint": LONG_LIMIT}.get(numeric)
    if limit and largest is not None and int(largest) * max(d_max, 1) >= limit:
        raise OverflowError(f"walk counts of the next level may pass the range of {numeric}; use scaled counts")
