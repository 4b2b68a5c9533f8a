"""Coarse spaces, the Galerkin product, and coarse solves."""

from __future__ import annotations

from dataclasses import replace
from itertools import product
from math import prod

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from overlapsolve.functions.solvers import LatticeMultigrid, VCycle, factor, to_csr
from overlapsolve.operators.local import Block
from overlapsolve.session import checkpoint
from overlapsolve.sources.mesh import axis
from overlapsolve.system import Sys


def coarse_aggregate(owner: DataFrame) -> DataFrame:
    """(i, c, weight): one indicator a part."""
    return owner.select("i", F.col("p").cast("long").alias("c"), F.lit(1.0).alias("weight"))


def coarse_geometric(nodes: DataFrame, shape: tuple[int, ...], coarse: tuple[int, ...]) -> DataFrame:
    """(i, c, weight): multilinear interpolation from interior nodes of a coarser lattice that vanishes outside; weights over 0 only."""
    corners = F.array(*[F.struct(*[F.lit(s).alias(f"s{k}") for k, s in enumerate(ss)]) for ss in product((0, 1), repeat=len(shape))])
    d = nodes.select("i", F.explode(corners).alias("e"))
    c, weight, inside = F.lit(0).cast("long"), F.lit(1.0), F.lit(True)
    for k, (n, m) in enumerate(zip(shape, coarse, strict=True)):
        x = (axis(F.col("i"), shape, k) + 1) * F.lit((m + 1) / (n + 1))  # in coarse steps; the boundary is at 0 and m + 1
        low = F.floor(x + 1e-12)
        at = low + F.col(f"e.s{k}")
        part = F.when(F.col(f"e.s{k}") == 1, x - low).otherwise(F.lit(1.0) - (x - low))
        inside = inside & at.between(1, m) & (part > 1e-12)
        c, weight = c * m + (at - 1), weight * part
    return d.where(inside).select("i", c.cast("long").alias("c"), weight.alias("weight"))


def coarse_spectral(blocks: DataFrame, nu: int = 2) -> DataFrame:
    """(i, c, weight): the nu lowest modes of each local matrix, on owned nodes. Dense: for parts of up to a few thousand nodes."""

    def modes(batches):
        for b in batches:
            rows = []
            for row in b.to_pylist():
                block = Block.of(row)
                a = np.zeros((block.n, block.n))
                np.add.at(a, (np.repeat(np.arange(block.n), np.diff(block.indptr)), block.indices), block.data)
                values, vectors = np.linalg.eigh((a + a.T) / 2)
                for k in range(min(nu, block.n)):
                    v = vectors[:, np.argsort(values)[k]]
                    v = v * np.sign(v[np.abs(v).argmax()])
                    rows += [(int(i), block.p * nu + k, float(x)) for i, x, own in zip(block.ids, v, block.owned, strict=True) if own and x]
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate((pa.int64(), pa.int64(), pa.float64()))], names=["i", "c", "weight"])

    return blocks.mapInArrow(modes, "i long, c long, weight double")


def galerkin(entries: DataFrame, interp: DataFrame) -> DataFrame:
    """(c, d, a): the coarse matrix; sums are made before the second shuffle as far as keys allow."""
    left = interp.select("i", "c", F.col("weight").alias("wi"))
    right = interp.select(F.col("i").alias("j"), F.col("c").alias("d"), F.col("weight").alias("wj"))
    half = entries.join(left, "i").groupBy("c", "j").agg(F.sum(F.col("a") * F.col("wi")).alias("a"))
    return half.join(right, "j").groupBy("c", "d").agg(F.sum(F.col("a") * F.col("wj")).alias("a"))


def coarse_rhs(slabs: DataFrame, interp: DataFrame) -> DataFrame:
    """(c, x): all shares (p, i, s) projected, whole sets and not only owned rows."""
    return slabs.join(interp, "i").groupBy("c").agg(F.sum(F.col("s") * F.col("weight")).alias("x"))


def coarse_correction(v0: DataFrame, interp: DataFrame, member: DataFrame) -> DataFrame:
    """(p, i, x): the coarse solution (c, x) on each set."""
    values = interp.join(v0, "c").groupBy("i").agg(F.sum(F.col("weight") * F.col("x")).alias("x"))
    return member.select("p", "i").join(values, "i", "left").select("p", "i", F.coalesce("x", F.lit(0.0)).alias("x"))


COARSE_SOLVERS = ("direct", "vcycle", "multigrid", "decomposed")


def coarse_problem(sys, cfg):
    """What solves the coarse system: on the driver up to cfg.coarse_limit unknowns, or as a decomposed system of its own."""
    if cfg.coarse not in COARSE_SOLVERS:
        raise ValueError(f"coarse is one of {COARSE_SOLVERS}")
    if cfg.coarse == "decomposed":
        return DecomposedCoarse(sys.entries, sys.interp, cfg)
    return CoarseProblem(sys.entries, sys.interp, cfg.coarse_limit, cfg.coarse, sys.extra.get("coarse_shape"))


class DecomposedCoarse:
    """The coarse system split over several owners and solved by the one-level method, synchronously with the level above.

    Owners hold ranges of coarse numbers. The matrix stays on executors; vectors of the coarse size pass through the driver.
    """

    def __init__(self, entries: DataFrame, interp: DataFrame, cfg):
        self.a0 = checkpoint(galerkin(entries, interp).select(F.col("c").alias("i"), F.col("d").alias("j"), "a"))
        self.n = int(self.a0.agg(F.max("i")).first()[0]) + 1
        self.parts = min(cfg.coarse_parts, self.n)
        self.owner = self.a0.select("i").distinct().withColumn("p", F.floor(F.col("i") * self.parts / self.n).cast("int"))
        self.cfg = replace(cfg, tol=max(1e-13, 1e-3 * cfg.tol), coarse="direct", solver="direct")
        self.member = None

    def solve(self, r0: np.ndarray) -> np.ndarray:
        from overlapsolve.plans.bsp import ras_sync

        spark = self.a0.sparkSession
        rhs = spark.createDataFrame(list(enumerate(r0.tolist())), "i long, x double").join(self.owner.select("i"), "i", "left_semi")
        sys = Sys(self.a0, rhs, self.owner, self.parts, member=self.member)
        found = ras_sync(sys, self.cfg).u.toPandas()  # the coarse size
        self.member = sys.member
        out = np.zeros(self.n)
        out[found.i.to_numpy()] = found.x.to_numpy()
        return out


class CoarseProblem:
    """The coarse matrix on the driver; refused beyond `limit` unknowns, where a coarse system is to be decomposed itself."""

    def __init__(self, entries: DataFrame, interp: DataFrame, limit: int = 200_000, kind: str = "direct", shape: tuple[int, ...] | None = None):
        a0 = galerkin(entries, interp)
        n, most = a0.agg(F.count("*"), F.max("c")).first()
        self.n = 0 if most is None else int(most) + 1
        if self.n > limit or n > 64 * limit:
            raise ValueError(f"{self.n} coarse unknowns: over {limit}, set Config.coarse to decomposed")
        table = a0.toArrow()
        c, d, a = (table.column(k).to_numpy() for k in ("c", "d", "a"))
        used = np.unique(np.concatenate([c, np.zeros(0, c.dtype)]))
        rest = np.setdiff1d(np.arange(self.n), used)
        csr = to_csr(self.n, np.concatenate([c, rest]), np.concatenate([d, rest]), np.concatenate([a, np.ones(len(rest))]))
        if kind == "multigrid":
            if shape is None or prod(shape) != self.n:
                raise ValueError("multigrid needs the coarse lattice's shape")
            self.solver = LatticeMultigrid(*csr, shape)
        else:
            self.solver = VCycle(*csr) if kind == "vcycle" else factor(*csr)

    def solve(self, r0: np.ndarray) -> np.ndarray:
        return self.solver.solve(r0)
