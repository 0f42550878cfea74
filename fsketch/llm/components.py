"""Connected components of a table of links, by rounds of star contraction.

Every round hangs all larger neighbours of a node on the least of its neighbours (large star), then all smaller ones
(small star); the number of rounds grows with the logarithm of the longest path. A node's least neighbour is an
aggregate with partial sums; it meets the links again in a join, which Spark splits where one node has very many.
Nothing is collected: links and components stay in tables, written each round to the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .store import materialise


def _least(links: DataFrame) -> DataFrame:
    """(u, least): the least of a node and its neighbours, over links given in both directions."""
    return links.groupBy("u").agg(F.min("v").alias("_m")).select("u", F.least("u", "_m").alias("least"))


def connected_components(links: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, component): the least node that can be reached, for every node with a link; links to itself and repeated
    links are ignored."""
    edges = materialise(
        links.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct(), "links"
    )
    state = None
    for _ in range(max_rounds):
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = materialise(_least(both), "least")
        large = both.where(F.col("v") > F.col("u")).join(least, "u").select(F.col("v").alias("u"), F.col("least").alias("v"))
        down = materialise(large.where(F.col("u") > F.col("v")).distinct(), "large-star")
        least = materialise(_least(down), "least")
        hung = down.join(least, "u").select(F.col("v").alias("u"), F.col("least").alias("v"))
        small = hung.unionByName(least.select("u", F.col("least").alias("v"))).where(F.col("u") > F.col("v")).distinct()
        edges = materialise(small, "small-star")
        now = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if tuple(now) == state:
            roots = edges.select(F.col("v").alias("node")).distinct()
            return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(
                roots.select("node", F.col("node").alias("component"))
            )
        state = tuple(now)
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")


#: A key that at least one in so many rows bears is hot; there are at most so many of these.
HOT_SHARE = 1000


def join_labels(rows: DataFrame, labels: DataFrame, key: str, count: str = "n") -> DataFrame:
    """``rows`` with the columns of ``labels``, which has one row per key and in ``count`` the number of rows that bear it. No task
    gets all rows of a hot key: the labels of these, ``HOT_SHARE`` at most, are broadcast, and only the other rows are shuffled."""
    hot = F.col(count) * HOT_SHARE >= F.lit(rows.count())
    heavy, light = F.broadcast(labels.where(hot).drop(count)), labels.where(~hot).drop(count)
    rest = rows.join(F.broadcast(labels.where(hot).select(key)), key, "left_anti")
    return rows.join(heavy, key).unionByName(rest.join(light, key))
