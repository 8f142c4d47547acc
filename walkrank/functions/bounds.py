"""Bounds of a node's score after r levels, from its partial score and its last term.

partial is the sum of alpha^i times the walks of length i, for i up to r; term is the last of these."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def tail_factor(alpha: float, d_max: float) -> float:
    """What all later levels can add, as a multiple of alpha times the last term. Needs alpha * d_max < 1."""
    if alpha * d_max >= 1:
        raise ValueError(f"alpha {alpha} is not below 1 / {d_max}: there is no ceiling")
    return d_max / (1 - alpha * d_max)


def floor_directed(partial: Column, term: Column) -> Column:
    return partial


def floor_undirected(partial: Column, term: Column, alpha: float) -> Column:
    """A walk may go back along its last edge, so the next level has no fewer walks than this one."""
    return partial + alpha * term


def floor_geometric(partial: Column, term: Column, alpha: float) -> Column:
    """The same step back repeated for ever."""
    return partial + term * (alpha / (1 - alpha)) if alpha < 1 else partial


def ceiling(partial: Column, term: Column, alpha: float, gamma: float) -> Column:
    return partial + alpha * gamma * term


def ratio_bounds(partial: Column, term: Column, alpha: float, low: float, high: float) -> tuple[Column, Column]:
    """Floor and ceiling from the least and largest growth of walk counts between the last two levels: levels are linear,
    so later growth stays between them. Needs alpha * high < 1."""
    if alpha * high >= 1:
        raise ValueError("walks grow too fast for this alpha")
    return partial + term * (alpha * low / (1 - alpha * low)), partial + term * (alpha * high / (1 - alpha * high))


def separated(floor: Column, other_ceiling: Column) -> Column:
    """The node of this floor is ahead for sure."""
    return floor > other_ceiling


def eps_separated(floor: Column, other_ceiling: Column, eps: float) -> Column:
    """Ahead, or behind by less than eps."""
    return floor > other_ceiling - F.lit(eps)
