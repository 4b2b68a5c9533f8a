"""Matrices on lattices and simplicial meshes, generated on executors."""

from __future__ import annotations

from itertools import permutations, product
from math import pi, prod

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def strides(shape: tuple[int, ...]) -> list[int]:
    return [prod(shape[k + 1 :]) for k in range(len(shape))]


def axis(i: Column, shape: tuple[int, ...], k: int) -> Column:
    """The k-th lattice index of a row-major node id."""
    return F.pmod(F.floor(i / F.lit(strides(shape)[k])), F.lit(shape[k])).cast("long")


def lattice(spark: SparkSession, shape: tuple[int, ...]) -> DataFrame:
    """(i, x0, x1, ...) of every node."""
    i = F.col("i")
    return spark.range(prod(shape)).select(F.col("id").alias("i")).select("i", *[axis(i, shape, k).alias(f"x{k}") for k in range(len(shape))])


def stencil_entries(spark: SparkSession, shape: tuple[int, ...], diagonal: float, off: float = -1.0) -> DataFrame:
    """(i, j, a): the diagonal everywhere, `off` to each axis neighbour, zero outside the lattice."""
    steps = [(k, s) for k in range(len(shape)) for s in (-1, 1)]
    offsets = F.array(*[F.struct(F.lit(k).alias("k"), F.lit(s).alias("s"), F.lit(s * strides(shape)[k]).cast("long").alias("o")) for k, s in steps])
    x = F.array(*[F.col(f"x{k}") for k in range(len(shape))])
    ends = F.array(*[F.lit(n) for n in shape])
    nodes = lattice(spark, shape)
    moved = nodes.select("i", x.alias("x"), F.explode(offsets).alias("m")).withColumn("to", F.get("x", F.col("m.k")) + F.col("m.s"))
    inside = moved.where((F.col("to") >= 0) & (F.col("to") < F.get(ends, F.col("m.k"))))
    return inside.select("i", (F.col("i") + F.col("m.o")).alias("j"), F.lit(float(off)).alias("a")).union(nodes.select("i", F.col("i").alias("j"), F.lit(float(diagonal)).alias("a")))


def sine_load(spark: SparkSession, d: int, n: int) -> DataFrame:
    """(i, x): the lumped load of the problem whose solution is the product of sin(pi x_k), for the plain stencil (2d on the diagonal)."""
    h = 1.0 / (n + 1)
    wave = lambda k: F.sin(F.lit(pi) * (F.col(f"x{k}") + 1) * F.lit(h))
    value = F.lit(d * pi * pi * h * h)
    for k in range(d):
        value = value * wave(k)
    return lattice(spark, (n,) * d).select("i", value.alias("x"))


def assemble_p1(spark: SparkSession, d: int, n: int, drop_zeros: bool = False) -> DataFrame:
    """Stiffness matrix of piecewise linear elements on the cube of (n+1)^d cells, each cut into d! simplices; interior nodes only.

    A simplex of a permutation climbs from the cell's lowest to its highest corner one axis after another. Its gradients
    are unit differences along these axes, so the element matrix couples consecutive corners only, in units of h^(d-2) / d!;
    couplings that cancel stay as structural zeros unless dropped. The sum is scaled to 2D: 4 on the diagonal; 3D: 6h.
    """
    h = 1.0 / (n + 1)
    factorial = prod(range(1, d + 1))
    scale = h ** (d - 2) / factorial
    local = []
    for order in permutations(range(d)):
        corners, at = [(0,) * d], [0] * d
        for axis_k in order:
            at[axis_k] = 1
            corners.append(tuple(at))
        for a, b in product(range(d + 1), repeat=2):
            # Basis a falls along the step into it and rises along the step out of it.
            steps_a, steps_b = {a - 1: 1, a: -1}, {b - 1: 1, b: -1}
            value = sum(steps_a[s] * steps_b[s] for s in steps_a if s in steps_b and 0 <= s < d)
            local.append((corners[a], corners[b], value * scale))
    side = n + 1
    cells = spark.range(side**d).select(*[axis(F.col("id"), (side,) * d, k).alias(f"c{k}") for k in range(d)])
    items = F.array(*[F.struct(*[F.lit(a[k]).alias(f"a{k}") for k in range(d)], *[F.lit(b[k]).alias(f"b{k}") for k in range(d)], F.lit(float(v)).alias("v")) for a, b, v in local])
    each = cells.select("*", F.explode(items).alias("e"))
    corner = lambda k, s: F.col(f"c{k}") + F.col(f"e.{s}{k}") - 1  # noqa: E731  interior index, -1 or n on the boundary
    inside = F.lit(True)
    for k in range(d):
        for s in "ab":
            inside = inside & corner(k, s).between(0, n - 1)
    node = lambda s: sum((corner(k, s) * strides((n,) * d)[k] for k in range(1, d)), corner(0, s) * strides((n,) * d)[0]).cast("long")
    total = each.where(inside).select(node("a").alias("i"), node("b").alias("j"), F.col("e.v").alias("v")).groupBy("i", "j").agg(F.sum("v").alias("a"))
    return total.where(F.abs("a") > 1e-14 * h) if drop_zeros else total


def convection_diffusion(spark: SparkSession, d: int, n: int, wind: tuple[float, ...], kappa: float = 1.0, upwind: bool = True) -> DataFrame:
    """(i, j, a) of -kappa(x) Laplace u + wind . grad u, scaled by h^2, on the lattice of n^d interior nodes.

    The coefficient kappa varies by a checkerboard of factor `kappa`. Upwind differences keep an M-matrix, central ones may not.
    """
    h = 1.0 / (n + 1)
    shape = (n,) * d
    coefficient = F.when(F.pmod(sum((F.col(f"x{k}") for k in range(1, d)), F.col("x0")), F.lit(2)) == 0, F.lit(1.0)).otherwise(F.lit(float(kappa)))
    nodes = lattice(spark, shape).withColumn("kap", coefficient)
    steps = []
    for k, s in product(range(d), (-1, 1)):
        w = wind[k] * h
        drift = -max(s * -w, 0.0) if upwind else s * w / 2
        steps.append((k, s, drift))
    items = F.array(*[F.struct(F.lit(k).alias("k"), F.lit(s).alias("s"), F.lit(s * strides(shape)[k]).cast("long").alias("o"), F.lit(float(w)).alias("w")) for k, s, w in steps])
    x = F.array(*[F.col(f"x{k}") for k in range(d)])
    each = nodes.select("i", x.alias("x"), "kap", F.explode(items).alias("m")).withColumn("to", F.get("x", F.col("m.k")) + F.col("m.s"))
    inside = each.where((F.col("to") >= 0) & (F.col("to") < n)).select("i", (F.col("i") + F.col("m.o")).alias("j"), (F.col("m.w") - F.col("kap")).alias("a"))
    spread = sum(abs(w) * h for w in wind) if upwind else 0.0
    return inside.union(nodes.select("i", F.col("i").alias("j"), (F.lit(2.0 * d) * F.col("kap") + F.lit(spread)).alias("a")))
