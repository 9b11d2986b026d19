"""Connected components of a table of links, by minimum labels and pointer jumping."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gpart.session import cut


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, component) of every node that has a link; component is its smallest reachable node. links: (a, b), in either order.

    Each round, a node takes the smallest label among its neighbours' and then the label of that label's node, so labels
    travel twice as far each time; each round's labels are written before the next, and links are never gathered anywhere.
    """
    both = links.select("a", "b").unionAll(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct()
    both = cut(both)
    labels = cut(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("least")).select("node", F.least("node", "least").alias("component")))
    for _ in range(most_rounds):
        beside = both.join(labels.withColumnRenamed("node", "b"), "b").groupBy(F.col("a").alias("node")).agg(F.min("component").alias("beside"))
        nearer = labels.join(beside, "node").select("node", F.col("component").alias("before"), F.least("component", "beside").alias("component"))
        of_label = labels.select(F.col("node").alias("component"), F.col("component").alias("next"))
        moved = cut(nearer.join(of_label, "component").select("node", "before", F.least("component", "next").alias("component")))
        labels = moved.select("node", "component")
        if moved.where("before <> component").isEmpty():
            return labels
    raise RuntimeError(f"labels still move after {most_rounds} rounds")


def forest(links: np.ndarray, rows: np.ndarray, columns: np.ndarray) -> list[tuple[int, int]]:
    """A spanning forest of the links between the nodes `rows` and `columns` (which may be the same)."""
    root: dict[int, int] = {}

    def find(x: int) -> int:
        root.setdefault(x, x)
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    out = []
    for r, c in zip(*np.nonzero(links), strict=True):
        a, b = find(int(rows[r])), find(int(columns[c]))
        if a != b:
            root[max(a, b)] = min(a, b)
            out.append((int(rows[r]), int(columns[c])))
    return out
