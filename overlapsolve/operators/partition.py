"""Base partitions: each node is owned by one part."""

from __future__ import annotations

from math import prod

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from overlapsolve.session import checkpoint
from overlapsolve.sources.mesh import axis


def _box(position: Column, length: int, boxes: int) -> Column:
    return F.floor(position * F.lit(boxes) / F.lit(length)).cast("int")


def partition_box(nodes: DataFrame, shape: tuple[int, ...], boxes: tuple[int, ...]) -> DataFrame:
    """(i, p) of row-major lattice nodes: equal boxes along each axis. No shuffle."""
    p = F.lit(0)
    for k, b in enumerate(boxes):
        p = p * b + _box(axis(F.col("i"), shape, k), shape[k], b)
    return nodes.select("i", p.cast("int").alias("p"))


def partition_imbalanced(nodes: DataFrame, shape: tuple[int, ...], parts: int, factor: float = 1.5, which: int = 0) -> DataFrame:
    """Slices along the first axis, one of them `factor` times as thick as the rest."""
    unit = shape[0] / (parts - 1 + factor)
    cuts = [round(unit * (k + (factor - 1 if k > which else 0))) for k in range(1, parts)]
    x = axis(F.col("i"), shape, 0)
    return nodes.select("i", sum((F.when(x >= c, 1).otherwise(0) for c in cuts), F.lit(0)).cast("int").alias("p"))


def partition_box_imbalanced(nodes: DataFrame, shape: tuple[int, ...], boxes: tuple[int, ...], factor: float = 1.5) -> DataFrame:
    """Boxes whose first one is about `factor` times as large as the others: its axes' first cuts are moved by the same share."""
    p, share = F.lit(0), factor ** (1 / len(shape))
    for k, b in enumerate(boxes):
        unit = shape[k] / (b - 1 + share)
        cuts = [round(unit * (m - 1 + share)) for m in range(1, b)]
        x = axis(F.col("i"), shape, k)
        p = p * b + sum((F.when(x >= c, 1).otherwise(0) for c in cuts), F.lit(0))
    return nodes.select("i", p.cast("int").alias("p"))


def partition_key(nodes: DataFrame, key: str) -> DataFrame:
    """(i, p): parts numbered by the sorted distinct keys, which are few enough to broadcast only if Spark finds so."""
    keys = nodes.select(key).distinct().orderBy(key)
    # Positions within range partitions, shifted by the sizes of those before: no window over all keys.
    placed = checkpoint(keys.select(key, F.spark_partition_id().alias("part"), F.monotonically_increasing_id().alias("at")))
    sizes = placed.groupBy("part").agg(F.count("*").alias("n"), F.min("at").alias("first")).orderBy("part").collect()  # one row a partition
    before, shifts = 0, []
    for r in sizes:
        shifts.append((r["part"], r["first"] - before))
        before += r["n"]
    shift = nodes.sparkSession.createDataFrame(shifts, "part int, shift long")
    ids = placed.join(F.broadcast(shift), "part").select(key, (F.col("at") - F.col("shift")).cast("int").alias("p"))
    return nodes.join(ids, key).select("i", "p")


def partition_graph(edges: DataFrame, parts: int, rounds: int = 12, seed: int = 42) -> DataFrame:
    """(i, p) of the nodes of weighted edges (u, v, w): regions grown from seeds, then refined along their borders.

    Seeds are the nodes with the smallest hashes. In a round each free node joins the part it is tied to most; ties go to
    the smaller part number. Nodes that no region reaches go to parts by their hash. In the refining rounds a node moves
    to the part with the greater total weight around it; every other round by hash parity, so neighbours don't swap.
    """
    both = checkpoint(edges.select(F.col("u").alias("i"), F.col("v").alias("j"), "w").union(edges.select("v", "u", "w")))
    nodes = both.select("i").distinct().withColumn("h", F.xxhash64("i", F.lit(seed)))
    first = nodes.orderBy("h", "i").limit(parts).withColumn("p", (F.row_number().over(Window.orderBy("h", "i")) - 1).cast("int"))
    owner = checkpoint(nodes.join(first.select("i", "p"), "i", "left").select("i", "h", "p"))

    def pulls(o: DataFrame) -> DataFrame:
        held = o.where("p is not null").select(F.col("i").alias("j"), "p")
        by = both.join(held, "j").groupBy("i", "p").agg(F.sum("w").alias("w"))
        return by.groupBy("i").agg(F.max_by(F.struct("p", "w"), F.struct("w", -F.col("p"))).alias("best"))

    for _ in range(rounds):
        grown = owner.join(pulls(owner), "i", "left").select("i", "h", F.coalesce("p", "best.p").alias("p"))
        before, owner = owner, checkpoint(grown)
        if owner.where("p is null").count() == before.where("p is null").count():
            break
    owner = owner.select("i", "h", F.coalesce("p", F.pmod("h", F.lit(parts)).cast("int")).alias("p"))
    for turn in range(2):
        move = F.pmod("h", F.lit(2)) == turn
        owner = checkpoint(owner.join(pulls(owner), "i", "left").select("i", "h", F.when(move & F.col("best").isNotNull(), F.col("best.p")).otherwise(F.col("p")).alias("p")))
    return owner.select("i", "p")


def geometric_members(nodes: DataFrame, shape: tuple[int, ...], boxes: tuple[int, ...], delta: int) -> DataFrame:
    """(p, i) of lattice nodes within `delta` steps of a box along each axis: interval joins done by exploding bins."""
    spans = []
    for k, b in enumerate(boxes):
        x = axis(F.col("i"), shape, k)
        low = _box(F.greatest(x - delta, F.lit(0)), shape[k], b)
        high = _box(F.least(x + delta, F.lit(shape[k] - 1)), shape[k], b)
        spans.append(F.sequence(low, high))
    out = nodes
    for k, s in enumerate(spans):
        out = out.withColumn(f"b{k}", F.explode(s))
    p = F.lit(0)
    for k, b in enumerate(boxes):
        p = p * b + F.col(f"b{k}")
    return out.select(p.cast("int").alias("p"), "i")


def number_of(boxes: tuple[int, ...]) -> int:
    return prod(boxes)
