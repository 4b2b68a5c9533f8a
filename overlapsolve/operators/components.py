"""Connected components by alternating star contraction, all on executors.

Every round points edges at smaller ids: first each larger neighbour of a node is tied to the smallest id around that
node, then each node ties its smaller neighbours to the smallest of them. The number of rounds grows with the logarithm
of the longest path. Minima are found by partial aggregation, so a hub doesn't gather its edges in one task; what is
joined with them is read back from a checkpoint, so both sides are shuffled and Spark may split a skewed one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from overlapsolve.session import checkpoint, discard


def _large_star(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    both = edges.select(F.col("parent").alias("hub"), F.col("child").alias("other")).union(edges.select(F.col("child").alias("hub"), F.col("parent").alias("other")))
    minima = checkpoint(both.groupBy("hub").agg(F.min("other").alias("least")).select(F.col("hub").alias("parent"), F.least("hub", "least").alias("least")))
    return edges.join(minima, "parent").select("child", F.col("least").alias("parent")).distinct(), minima


def _small_star(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    minima = checkpoint(edges.groupBy("child").agg(F.min("parent").alias("least")))
    up = F.struct(F.col("parent").alias("child"), F.col("least").alias("parent"))
    own = F.struct("child", F.col("least").alias("parent"))
    # An edge to the smallest parent needs no second one; arrays keep the join from being run once a side of a union.
    tied = edges.join(minima, "child").select(F.explode(F.when(F.col("parent") > F.col("least"), F.array(up, own)).otherwise(F.array(own))).alias("e"))
    return tied.select("e.child", "e.parent").distinct(), minima


def _settled(edges: DataFrame) -> bool:
    """True if each child has one parent that is no child."""
    inner = edges.select(F.col("parent").alias("child"), F.lit(1).alias("n")).distinct()
    seen = edges.groupBy("child").agg(F.count("*").alias("n")).unionByName(inner)
    return seen.groupBy("child").agg(F.sum("n").alias("n")).where("n > 1").isEmpty()


def connected_components(edges: DataFrame, left: str = "u", right: str = "v") -> DataFrame:
    """(node, component) for every node with an edge to another one; component is the smallest node id it can reach.

    Edges are undirected; repeated edges and loops do no harm; an edge with a null end is left out.
    """
    e = edges.select(F.greatest(left, right).alias("child"), F.least(left, right).alias("parent")).where(F.col(left).isNotNull() & F.col(right).isNotNull() & (F.col(left) != F.col(right))).distinct()
    e = checkpoint(e)
    while not _settled(e):
        large, least = _large_star(e)
        half = checkpoint(large)
        discard(e, least)
        small, least = _small_star(half)
        e = checkpoint(small)
        discard(half, least)
    return e.select(F.col("child").alias("node"), F.col("parent").alias("component")).union(e.select("parent", "parent").distinct())
