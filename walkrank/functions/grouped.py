"""Many small graphs at once: each group of edges ranked in one task; and the same as a table function in SQL."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

RESULT = "rank long, id long, floor double, ceiling double"


def rank_arrays(src: np.ndarray, dst: np.ndarray, k: int, eps: float, undirected: bool = True, max_levels: int = 200) -> list[tuple[int, int, float, float]]:
    """The certified top k of one graph in memory."""
    pairs = {(int(a), int(b)) for a, b in zip(src, dst, strict=True)}
    if undirected:
        pairs |= {(b, a) for a, b in pairs}
    ids = sorted({x for p in pairs for x in p})
    if not ids:
        return []
    at = {x: i for i, x in enumerate(ids)}
    a, b = (np.array([at[p[i]] for p in pairs]) for i in (0, 1))
    n, d_max = len(ids), int(np.bincount(a).max())
    alpha = 1 / (1 + d_max)
    gamma, s, total, k = d_max / (1 - alpha * d_max), np.ones(n), np.zeros(n), min(k, n)
    for _ in range(max_levels):
        s = alpha * np.bincount(a, s[b], n)
        total += s
        floor, ceiling = total + (alpha * s if undirected else 0), total + alpha * gamma * s
        order = np.lexsort([ids, -floor])
        bar = floor[order[k - 1]]
        top = order[:k]
        if (ceiling - eps >= bar).sum() <= k and (floor[top[:-1]] > ceiling[top[1:]] - eps).all():
            break
    return [(r + 1, ids[i], float(floor[i]), float(ceiling[i])) for r, i in enumerate(order[:k])]


def rank_grouped(edges: DataFrame, key: str, k: int, eps: float, undirected: bool = True) -> DataFrame:
    """edges: key, src, dst. The top k of each key's graph; a group must fit a task."""

    def one(group: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        found = rank_arrays(rows.src.to_numpy(), rows.dst.to_numpy(), k, eps, undirected)
        out = pd.DataFrame(found, columns=["rank", "id", "floor", "ceiling"])
        out.insert(0, key, group[0])
        return out

    kind = edges.schema[key].dataType.simpleString()
    return edges.select(key, "src", "dst").groupBy(key).applyInPandas(one, f"{key} {kind}, {RESULT}")


def register_table_function(spark: SparkSession, name: str = "katz_rank") -> None:
    """select * from katz_rank(table(edges) partition by (grp), k, eps): edges has src and dst."""

    @F.udtf(returnType=RESULT)
    class KatzRank:
        def __init__(self):
            self.rows, self.k, self.eps = [], 10, 1e-6

        def eval(self, row, k: int, eps: float):
            self.rows.append((row["src"], row["dst"]))
            self.k, self.eps = k, eps

        def terminate(self):
            if self.rows:
                a, b = (np.array(x) for x in zip(*self.rows, strict=True))
                yield from rank_arrays(a, b, self.k, self.eps)

    spark.udtf.register(name, KatzRank)
