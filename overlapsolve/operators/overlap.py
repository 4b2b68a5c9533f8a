"""Overlapping sets: growth along the graph, surfaces, ownership, and the identities they must satisfy."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def grow_overlap(owner: DataFrame, entries: DataFrame, delta: int = 1) -> DataFrame:
    """(p, i, layer): each part and what `delta` steps along the matrix reach; layer 0 is the part itself."""
    edges = entries.where("i <> j").select(F.col("i").alias("here"), F.col("j").alias("i"))
    member = owner.select("p", "i", F.lit(0).alias("layer"))
    front = member
    for layer in range(1, delta + 1):
        reached = front.select("p", F.col("i").alias("here")).join(edges, "here").select("p", "i").distinct()
        front = reached.join(member, ["p", "i"], "left_anti").withColumn("layer", F.lit(layer))
        member = member.union(front)
    return member


def mark_surface(member: DataFrame, entries: DataFrame) -> DataFrame:
    """member with `surface`: the node couples to a node outside the set."""
    touching = member.select("p", "i").join(entries.where("i <> j"), "i").select("p", "i", "j")
    inside = member.select("p", F.col("i").alias("j"))
    outside = touching.join(inside, ["p", "j"], "left_anti").select("p", "i").distinct().withColumn("surface", F.lit(True))
    return member.join(outside, ["p", "i"], "left").withColumn("surface", F.coalesce("surface", F.lit(False)))


def mark_owned(member: DataFrame, owner: DataFrame) -> DataFrame:
    """member with `owned`: the Boolean weights; layer 0 is what the base partition gave the part."""
    return member.join(owner.withColumnRenamed("p", "own"), "i").withColumn("owned", F.col("p") == F.col("own")).drop("own")


def number_slots(member: DataFrame) -> DataFrame:
    """member with `slot`: local indices from 0 in order of node id."""
    return member.withColumn("slot", (F.row_number().over(Window.partitionBy("p").orderBy("i")) - 1).cast("int"))


def decompose(owner: DataFrame, entries: DataFrame, delta: int = 1) -> DataFrame:
    """(p, i, slot, layer, owned, surface)."""
    m = number_slots(mark_owned(mark_surface(grow_overlap(owner, entries, delta), entries), owner))
    return m.select("p", "i", "slot", "layer", "owned", "surface")


def check_decomposition(member: DataFrame, entries: DataFrame) -> DataFrame:
    """(rule, p, i) of violations; none for a valid decomposition with at least one layer.

    once: a node is owned exactly once. hidden: an owned node isn't on the surface. closed: what couples to an owned node
    of a set lies in the set, so the set's own matrix does for vectors that live on owned nodes.
    """
    none = F.lit(None).cast("int")
    once = member.groupBy("i").agg(F.sum(F.col("owned").cast("int")).alias("n")).where("n <> 1").select(F.lit("once").alias("rule"), none.alias("p"), "i")
    hidden = member.where("owned and surface").select(F.lit("hidden"), "p", "i")
    needed = member.where("owned").select("p", F.col("i").alias("j")).join(entries, "j").select("p", "i").distinct()
    closed = needed.join(member, ["p", "i"], "left_anti").select(F.lit("closed"), "p", "i")
    return once.union(hidden).union(closed)


def routes(member: DataFrame) -> DataFrame:
    """(src, dst, i, src_slot, dst_slot) of shared nodes of two different sets."""
    a = member.select(F.col("p").alias("src"), "i", F.col("slot").alias("src_slot"))
    b = member.select(F.col("p").alias("dst"), "i", F.col("slot").alias("dst_slot"))
    return a.join(b, "i").where("src <> dst").select("src", "dst", "i", "src_slot", "dst_slot")


def partition_stats(member: DataFrame) -> DataFrame:
    """(p, nodes, owned, surface, neighbours, sent): sizes and message volumes; sent counts shared nodes over all neighbours."""
    sizes = member.groupBy("p").agg(F.count("*").alias("nodes"), F.sum(F.col("owned").cast("long")).alias("owned"), F.sum(F.col("surface").cast("long")).alias("surface"))
    sent = routes(member).groupBy("src").agg(F.count_distinct("dst").alias("neighbours"), F.count("*").alias("sent"))
    zero = F.lit(0).cast("long")
    return sizes.join(sent, sizes.p == sent.src, "left").select("p", "nodes", "owned", "surface", F.coalesce("neighbours", zero).alias("neighbours"), F.coalesce("sent", zero).alias("sent"))
