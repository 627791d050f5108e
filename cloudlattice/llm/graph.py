"""Connected components of a link table, without gathering any component in one place."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cloudlattice.llm.work import written


def smallest(edges: DataFrame) -> DataFrame:
    """u, m: the smallest id among u and its neighbours."""
    return edges.groupBy("u").agg(F.min("v").alias("v")).select("u", F.least("u", "v").alias("m"))


def components(edges: DataFrame) -> DataFrame:
    """(id, component_id) for every id in ``edges`` (columns u, v), component_id the smallest reachable id.

    Alternates two contractions until nothing moves: every larger neighbour of an id
    is linked to the smallest id around it, then every id and its smaller neighbours
    are linked to the smallest of them. The number of links never grows, minima are
    aggregated before the shuffle, and the joins leave skewed ids to the engine.
    """
    links = written(edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u > v").distinct(), "links")
    nodes = links
    while True:
        both = links.unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = both.join(smallest(both), "u").where("v > u and v > m").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v"))).distinct()
        small = written(small, "links")
        moved = small.join(links, ["u", "v"], "left_anti").limit(1).count() + links.join(small, ["u", "v"], "left_anti").limit(1).count()
        links = small
        if not moved:
            break
    leaves = links.select(F.col("u").alias("id"), F.col("v").alias("component_id"))
    roots = nodes.select(F.explode(F.array("u", "v")).alias("id")).distinct().join(leaves, "id", "left_anti").select("id", F.col("id").alias("component_id"))
    return leaves.unionByName(roots)


class Forest:
    """Union-find over 0..n-1 with smallest roots."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def find(self, x: int) -> int:
        up = self.up
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    def join(self, a: int, b: int) -> bool:
        a, b = self.find(a), self.find(b)
        if a == b:
            return False
        self.up[max(a, b)] = min(a, b)
        return True
