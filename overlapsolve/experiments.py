"""The experiment workloads: each returns (trace, summary). Sizes are parameters; the defaults fit one machine.

Simulated runs do the real iterations under a made-up clock (plans/simulate.py); `bsp` rows are timed supersteps. A run is
repeated `Sizes.repeats` times; `mean_of_runs` has the means, and the summary the single runs.
"""

from __future__ import annotations

import math
import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from overlapsolve.functions import metrics
from overlapsolve.operators import coarse, partition
from overlapsolve.plans import bsp
from overlapsolve.plans.simulate import Case, Costs, mean_of_runs, simulate, summary
from overlapsolve.session import checkpoint
from overlapsolve.sources import mesh, problems
from overlapsolve.system import Config, Sys

BSP = "workload string, mode string, P int, n int, n0 int, repeat int, iterations int, seconds double, r0 double, r_final double, per_iteration double, provenance string"
#: Declared costs of the two-level runs: parts so large that a local solve takes longer than a message by far.
LARGE_PARTS = Costs(unknown=2e-5, noise="network")


@dataclass(frozen=True)
class Sizes:
    side: int = 31
    parts: tuple[int, ...] = (4, 16, 64)
    weak: tuple[tuple[int, int, int], ...] = ((15, 4, 3), (31, 16, 7), (63, 64, 15))  # side, parts, coarse side
    cube: tuple[tuple[int, int, int], ...] = ((7, 8, 3), (11, 27, 3))
    repeats: int = 5
    tol: float = 1e-8
    max_iter: int = 2000

    @property
    def seeds(self) -> tuple[int, ...]:
        return tuple(range(1, self.repeats + 1))


def poisson(spark: SparkSession, d: int, side: int, parts: int, imbalance: float = 1.0, coarse_side: int | None = None) -> Sys:
    """The sine problem on side^d nodes in equal boxes; with imbalance the first slab of boxes is so much thicker than the others."""
    shape, nodes = (side,) * d, spark.range(side**d).select(F.col("id").alias("i"))
    k = round(parts ** (1 / d))
    if k**d != parts:
        raise ValueError(f"{parts} is no power of {d}")
    if imbalance == 1:
        owner = partition.partition_box(nodes, shape, (k,) * d)
    else:
        owner = partition.partition_box_imbalanced(nodes, shape, (k,) * d, imbalance)
    interp = coarse.coarse_geometric(nodes, shape, (coarse_side,) * d) if coarse_side else None
    return Sys(mesh.stencil_entries(spark, shape, 2.0 * d), mesh.sine_load(spark, d, side), owner, parts, interp=interp, extra={"coarse_shape": (coarse_side,) * d} if coarse_side else {})


def both(spark: SparkSession, cases: list[Case], sizes: Sizes) -> tuple[DataFrame, DataFrame]:
    trace = checkpoint(simulate(spark, cases, sizes.seeds))
    return trace, summary(trace)


def one_level_strong(spark: SparkSession, sizes: Sizes = Sizes(), imbalance: float = 1.0) -> tuple[DataFrame, DataFrame]:
    """W4, and with imbalance W6: a fixed system in more and more parts."""
    cfg = Config(tol=sizes.tol, max_iter=sizes.max_iter)
    name = "one-level strong" if imbalance == 1 else "one-level strong, imbalanced"
    return both(spark, [Case(name, poisson(spark, 2, sizes.side, p, imbalance), imbalance, Costs(), cfg) for p in sizes.parts], sizes)


def two_level_weak(spark: SparkSession, sizes: Sizes = Sizes(), imbalance: float = 1.0) -> tuple[DataFrame, DataFrame]:
    """W7, and with imbalance W9: system and coarse space grow with the parts."""
    cfg = Config(tol=sizes.tol, max_iter=sizes.max_iter)
    name = "two-level weak" if imbalance == 1 else "two-level weak, imbalanced"
    return both(spark, [Case(name, poisson(spark, 2, n, p, imbalance, c), imbalance, LARGE_PARTS, cfg) for n, p, c in sizes.weak], sizes)


def two_level_strong(spark: SparkSession, sizes: Sizes = Sizes(), imbalance: float = 1.0, coarse_side: int = 7) -> tuple[DataFrame, DataFrame]:
    """W10: a fixed system and coarse space in more and more parts."""
    cfg = Config(tol=sizes.tol, max_iter=sizes.max_iter)
    name = "two-level strong" if imbalance == 1 else "two-level strong, imbalanced"
    return both(spark, [Case(name, poisson(spark, 2, sizes.side, p, imbalance, coarse_side), imbalance, LARGE_PARTS, cfg) for p in sizes.parts], sizes)


def two_level_cube(spark: SparkSession, sizes: Sizes = Sizes()) -> tuple[DataFrame, DataFrame]:
    """W11: three dimensions, local solves by incomplete-factorisation conjugate gradients, the coarse one by a geometric V-cycle."""
    cfg = Config(tol=sizes.tol, max_iter=sizes.max_iter, solver="cg_ic", coarse="multigrid")
    return both(spark, [Case("two-level cube", poisson(spark, 3, n, p, 1.0, c), 1.0, LARGE_PARTS, cfg) for n, p, c in sizes.cube], sizes)


def convection(spark: SparkSession, sizes: Sizes = Sizes(), wind: tuple[float, float] = (8.0, -4.0), kappa: float = 10.0) -> tuple[DataFrame, DataFrame]:
    """W12: convection and a coefficient that varies, by upwind differences; the load is one."""
    cfg, out = Config(tol=sizes.tol, max_iter=sizes.max_iter), []
    for p in sizes.parts[:2]:
        base = poisson(spark, 2, sizes.side, p)
        load = base.rhs.select("i", F.lit(1.0).alias("x"))
        out.append(Case("convection-diffusion", Sys(mesh.convection_diffusion(spark, 2, sizes.side, wind, kappa), load, base.owner, p), 1.0, Costs(), cfg))
    return both(spark, out, sizes)


def histogram(trace: DataFrame, width: int, mode: str = "async") -> DataFrame:
    """W5 and W8: (workload, P, low, parts), parts by their local iterations, summed over repeats."""
    low = (F.floor(F.col("iterations") / width) * width).cast("long").alias("low")
    return trace.where(F.col("mode") == mode).groupBy("workload", "P", low).agg(F.count("*").alias("parts"))


def krylov(spark: SparkSession, d: int = 2, sizes: Sizes = Sizes(repeats=1), cases: tuple[tuple[int, int, int], ...] | None = None) -> tuple[DataFrame, DataFrame]:
    """W2 and W3: GMRES with the two-level additive method as right preconditioner, on the geometric coarse space and on the
    spectral one, which stands in for an external library's. Timed supersteps."""
    rows = []
    for n, p, c in cases or (sizes.weak[:2] if d == 2 else sizes.cube[:1]):
        for name in ("geometric", "spectral"):
            for k in range(sizes.repeats):
                sys = poisson(spark, d, n, p, 1.0, c)
                if name == "spectral":
                    sys = spectral(sys, max(1, round(c**d / p)))
                begun = time.time()
                found = bsp.gmres(sys, Config(tol=sizes.tol, max_iter=100), "ras2")
                took = time.time() - begun
                rows.append((f"krylov {d}D", name, p, n**d, None, k, found.iterations, took, found.history[0][1], found.history[-1][1], took / max(1, found.iterations), "bsp"))
    trace = spark.createDataFrame(rows, BSP)
    return trace, trace.groupBy("workload", "mode", "P", "n").agg(F.count("*").alias("runs"), F.avg("seconds").alias("seconds"), F.avg("per_iteration").alias("per_iteration"), F.max("iterations").alias("iterations"), F.max("r_final").alias("r_final"))


def spectral(sys: Sys, nu: int) -> Sys:
    """The system with the coarse space of each part's `nu` lowest modes."""
    blocks = bsp.pack_blocks(Sys(sys.entries, sys.rhs, sys.owner, sys.parts, member=checkpoint(bsp.decompose(sys.owner, sys.entries, 1))))
    return Sys(sys.entries, sys.rhs, sys.owner, sys.parts, interp=checkpoint(coarse.coarse_spectral(blocks, nu)))


def table_systems(spark: SparkSession, sf_dir: str) -> dict[str, Callable[[], Sys]]:
    """W13: what makes each of the systems that the tables carry ready to be solved; only what is called reads its tables."""
    ids = lambda n: spark.range(n).select(F.col("id").alias("i"))
    hashed = lambda f, n: f.select("i", F.pmod(F.xxhash64("i"), F.lit(n)).cast("int").alias("p"))

    def chain() -> Sys:
        e, f = problems.eventchain(spark, sf_dir)
        return Sys(e, f, partition.partition_box(ids(problems.HOURS), (problems.HOURS,), (4,)), 4)

    def chats() -> Sys:
        return Sys(*problems.chatchain(spark, sf_dir), 4)

    def graph(source: Callable) -> Callable[[], Sys]:
        def made() -> Sys:
            e, f = (checkpoint(x) for x in source(spark, sf_dir)[:2])
            return Sys(e, f, hashed(f, 4), 4)

        return made

    def cube() -> Sys:
        shape = (problems.MONTHS, problems.QUANTITIES, problems.DISCOUNTS)
        e, f = problems.shipgrid3d(spark, sf_dir)
        return Sys(e, f, partition.partition_box(ids(math.prod(shape)), shape, (8, 4, 1)), 32)

    return {"chain": chain, "chats": chats, "pages": graph(problems.pagegraph), "documents": graph(problems.docgraph), "neighbours": graph(problems.knn), "cube": cube}


def winners(runs: DataFrame) -> DataFrame:
    """(workload, P, async_wins) by mean seconds."""
    return metrics.speedup(runs).select("workload", "P", (F.col("speedup") > 1).alias("async_wins"))


__all__ = ["Sizes", "convection", "histogram", "krylov", "mean_of_runs", "one_level_strong", "table_systems", "two_level_cube", "two_level_strong", "two_level_weak", "winners"]
