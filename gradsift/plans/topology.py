"""Merging sketches over other graphs than a star: along a spanning tree, level by level."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def ring(workers: int) -> list[tuple[int, int]]:
    return [(i, (i + 1) % workers) for i in range(workers)]


def complete(workers: int) -> list[tuple[int, int]]:
    return [(i, j) for i in range(workers) for j in range(i + 1, workers)]


def spanning_tree(edges, workers: int, root: int = 0) -> list[tuple[int, int, int]]:
    """(child, parent, level) of a minimum spanning tree; edges (a, b) or (a, b, weight)."""
    lead = list(range(workers))

    def find(x):
        while lead[x] != x:
            lead[x] = lead[lead[x]]
            x = lead[x]
        return x

    near = [[] for _ in range(workers)]
    for a, b, *_ in sorted(edges, key=lambda e: (e[2] if len(e) > 2 else 1, e[0], e[1])):
        if find(a) != find(b):
            lead[find(a)] = find(b)
            near[a].append(b)
            near[b].append(a)
    out, seen, layer = [], {root}, [root]
    level = 0
    while layer:
        level, following = level + 1, []
        for p in layer:
            for c in near[p]:
                if c not in seen:
                    seen.add(c)
                    out.append((c, p, level))
                    following.append(c)
        layer = following
    if len(seen) != workers:
        raise ValueError("the graph is not connected")
    return out


def merge_over(cells: DataFrame, tree: list[tuple[int, int, int]]) -> DataFrame:
    """Cells per worker summed towards the root; each edge carries one sketch."""
    for level in range(max((t[2] for t in tree), default=0), 0, -1):
        up = {c: p for c, p, lv in tree if lv == level}
        to = F.create_map(*(F.lit(x) for pair in up.items() for x in pair))
        cells = cells.withColumn("worker", F.coalesce(F.try_element_at(to, F.col("worker")), F.col("worker"))).groupBy("worker", "row", "bucket").agg(F.sum("cell").alias("cell"))
    return cells.groupBy("row", "bucket").agg(F.sum("cell").alias("cell"))
