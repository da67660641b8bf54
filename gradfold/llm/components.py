"""Connected components of a graph given as a table of links (distributed union-find).

Rounds of two star contractions: first every node hands its larger neighbours to
its smallest one, then every node hands its smaller neighbours to the smallest of
those.  Both keep connectivity, and the number of rounds grows with the logarithm
of the longest chain.  A node with very many links is met by partial aggregation
(its smallest neighbour) and by a join that adaptive execution can split.
Each round is written to shared storage, so lineage stays short.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import apart, discard, stored


def _settled(edges: DataFrame) -> bool:
    """Has every node but the roots exactly one link, to a root?  Links go from a larger to a smaller node, so a root is the least of its component then."""
    ends = edges.select(F.col("u").alias("n"), F.lit(1).alias("out"), F.lit(0).alias("into")).union(edges.select("v", F.lit(0), F.lit(1)))
    return ends.groupBy("n").agg(F.sum("out").alias("out"), F.max("into").alias("into")).where("out > 1 or (out = 1 and into = 1)").isEmpty()


def components(links: DataFrame, a: str = "a", b: str = "b", most_rounds: int = 60) -> DataFrame:
    """(node, component) for every node that has a link; component is the smallest node reachable.

    `links` holds two columns of one orderable type, in any direction, with or
    without repeats.  Links from a node to itself and nulls are ignored.
    """
    x, y = F.col(a), F.col(b)
    edges = links.where(x.isNotNull() & y.isNotNull() & (x != y))
    edges = stored(edges.select(F.greatest(x, y).alias("u"), F.least(x, y).alias("v")).distinct(), "links")
    for _ in range(most_rounds):
        if _settled(edges):
            break
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("k"), F.least("u", "m").alias("m"))
        large = both.where("v > u").join(apart(least), F.col("u") == F.col("k")).select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        large = stored(large, "large-star")
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(apart(least.withColumnRenamed("u", "k")), F.col("u") == F.col("k")).where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        old, edges = edges, stored(small.union(least.select("u", F.col("m").alias("v"))).where("u != v").distinct(), "small-star")
        discard(old, large)
    else:
        raise RuntimeError(f"components did not settle in {most_rounds} rounds")
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).union(edges.select("v", F.col("v").alias("component")).distinct())
