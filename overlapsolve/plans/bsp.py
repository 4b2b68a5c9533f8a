"""Synchronous methods as supersteps: one row a part, one shuffle of slabs an iteration.

A superstep groups what was sent to each part with the part's packed block, which stays where it is (same partitioning,
cached), and sends on. Several supersteps form one plan; every `checkpoint_every` of them the state is written to the shared
folder and the driver reads one number, the residual norm.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from overlapsolve.functions.solvers import factor, kept
from overlapsolve.operators.coarse import coarse_problem
from overlapsolve.operators.local import Block, pack_blocks, residual_global
from overlapsolve.operators.overlap import decompose
from overlapsolve.session import checkpoint, discard
from overlapsolve.system import Config, Sys

#: kind: 0 own iterate, 1 slab (at: its tick, where slabs of several ticks meet), 2 own correction, 3 a peer's correction, 4 share of the coarse right-hand side, 5 a kept vector, 6 a basis
#: vector that is passed on, 7 a new one, 8 shares of inner products.
MESSAGE = "dst int, src int, kind int, vals array<double>, at array<int>, resid double"
COARSE = -1
#: A residual below this share of the sizes of its terms: the iterate is known well enough to tell what rounding leaves of the residual.
SETTLED = 1e-3


@dataclass
class Result:
    """u (i, x), the residual norms seen (iteration, norm), iterations done, the last state, and whether a norm was below the tolerance."""

    u: DataFrame
    history: list[tuple[int, float]]
    iterations: int
    state: DataFrame
    converged: bool = False


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    dst, src, kind, vals, at, resid = zip(*rows, strict=True) if rows else ((),) * 6
    return pa.RecordBatch.from_arrays(
        [pa.array(dst, pa.int32()), pa.array(src, pa.int32()), pa.array(kind, pa.int32()), pa.array([None if v is None else np.asarray(v, float) for v in vals], pa.list_(pa.float64())), pa.array([None if a is None else np.asarray(a, np.int32) for a in at], pa.list_(pa.int32())), pa.array(resid, pa.float64())],
        names=["dst", "src", "kind", "vals", "at", "resid"],
    )


def arrays(column: pa.ChunkedArray) -> list[np.ndarray | None]:
    """The lists of a column as arrays of their own, without a Python object for each value."""
    return [None if v.values is None else v.values.to_numpy(zero_copy_only=False).copy() for v in column]


def own(p: int, w: np.ndarray, resid: float = 0.0, kind: int = 0) -> tuple:
    return (p, p, kind, w, None, resid)


def slabs(b: Block, s: np.ndarray, coarse: bool = False) -> list[tuple]:
    out = [(q, b.p, 1, v, None, 0.0) for q, v in b.outgoing(s)]
    if coarse:
        used = np.unique(b.coarse_id)
        out.append((COARSE, b.p, 4, b.to_coarse(s, int(used[-1]) + 1 if len(used) else 0)[used], used, 0.0))
    return out


Step = Callable[[Block, dict], list[tuple]]


class Supersteps:
    """Blocks in place, and what moves messages between them."""

    def __init__(self, sys: Sys, cfg: Config):
        if sys.member is None:
            sys.member = checkpoint(decompose(sys.owner, sys.entries, cfg.delta))
        self.sys, self.cfg, self.name = sys, cfg, sys.name or uuid.uuid4().hex
        self.blocks = pack_blocks(sys).repartition("p").persist()
        self.coarse = coarse_problem(sys, cfg) if sys.interp is not None else None

    def solver(self) -> Callable[[Block], object]:
        name, kind, rtol = self.name, self.cfg.solver, self.cfg.rtol
        return lambda b: kept((name, b.p, kind), lambda: factor(b.indptr, b.indices, b.data, kind, rtol))

    def begin(self, start: DataFrame | None = None, coarse: bool = False) -> DataFrame:
        """Iterates of zero, or given (i, x), and their slabs."""
        if start is None:
            def first(batches):
                for batch in batches:
                    for row in batch.to_pylist():
                        b = Block.of(row)
                        w = np.zeros(b.n)
                        yield _batch([own(b.p, w), *slabs(b, b.slab(w), coarse)])

            return checkpoint(self.blocks.mapInArrow(first, MESSAGE))
        given = self.sys.member.join(start, "i").groupBy("p").agg(F.transform(F.array_sort(F.collect_list(F.struct("slot", "x"))), lambda t: t["x"]).alias("vals"))
        rows = given.select(F.col("p").alias("dst"), F.col("p").alias("src"), F.lit(0).alias("kind"), "vals", F.lit(None).cast("array<int>").alias("at"), F.lit(0.0).alias("resid"))
        return checkpoint(self.step(rows, lambda b, m: [own(b.p, m["w"]), *slabs(b, b.slab(m["w"]), coarse)]))

    def step(self, messages: DataFrame, f: Step, only: list[int] | None = None) -> DataFrame:
        """What f makes of each part's block and messages; of the parts in `only`, if given, without moving another one's block."""

        def of(key: tuple, mine: pa.Table, block: pa.Table) -> pa.Table:
            if not block.num_rows:
                return pa.Table.from_batches([_batch([])])
            b = Block.of({k: block.column(k)[0].as_py() if k == "p" else arrays(block.column(k))[0] for k in block.column_names})
            m: dict = {"slabs": {}, "dated": {}, "peers": {}, "kept": {}, "basis": {}}
            vals, plain = arrays(mine.column("vals")), mine.select(["src", "kind", "at"]).to_pylist()
            for r, v in zip(plain, vals, strict=True):
                if r["kind"] == 0:
                    m["w"] = v
                elif r["kind"] == 1 and r["at"]:
                    m["dated"][r["src"], r["at"][0]] = v
                elif r["kind"] == 1:
                    m["slabs"][r["src"]] = v
                elif r["kind"] == 2:
                    m["v"] = v
                elif r["kind"] == 3:
                    m["peers"][r["src"]] = v
                elif r["kind"] in (5, 6):
                    m["kept" if r["kind"] == 5 else "basis"][r["at"][0]] = v
            return pa.Table.from_batches([_batch(f(b, m))])

        inbox = messages.where(F.col("dst") >= 0)
        blocks = self.blocks if only is None else self.blocks.where(F.col("p").isin(only))
        return inbox.groupBy("dst").cogroup(blocks.groupBy("p")).applyInArrow(of, MESSAGE)

    def coarse_values(self, messages: DataFrame) -> np.ndarray:
        """Shares of the coarse right-hand side, added in order of the parts; bounded by the coarse size times the parts that touch an unknown."""
        r0 = np.zeros(self.coarse.n)
        shares = messages.where((F.col("dst") == COARSE) & (F.col("kind") == 4)).select("src", "at", "vals")
        if self.cfg.transfer == "tree":
            z = F.explode(F.arrays_zip("at", "vals")).alias("z")
            total = shares.select(z).groupBy(F.col("z.at").alias("c")).agg(F.sum("z.vals").alias("x")).toArrow()
            r0[total.column("c").to_numpy()] = total.column("x").to_numpy()
            return r0
        if self.cfg.transfer != "p2p":
            raise ValueError("transfer is p2p or tree")
        for r in sorted(shares.collect(), key=lambda r: r["src"]):
            np.add.at(r0, np.array(r["at"], np.int64), np.array(r["vals"], float))
        return r0

    def norm(self, messages: DataFrame) -> float:
        return float(np.sqrt(sum(r[0] for r in sorted(messages.where("kind = 0").select("resid").collect()))))

    def rounding(self, messages: DataFrame) -> float:
        """What rounding leaves of the residual norm at this iterate: no method gets below it, whatever tolerance is asked for.

        A row's residual is a sum of k terms, which rounds by about sqrt(k) units in the last place of the sum of their sizes.
        """

        def noise(b: Block, m: dict) -> list[tuple]:
            size = np.abs(b.rhs) + np.bincount(np.repeat(np.arange(b.n), np.diff(b.indptr)), weights=np.abs(b.data * m["w"][b.indices]), minlength=b.n)
            return [own(b.p, np.zeros(0), _masked_square(b, np.finfo(float).eps * np.sqrt(np.diff(b.indptr) + 1.0) * size))]

        return self.norm(self.step(messages.where("kind = 0"), noise))

    def solution(self, messages: DataFrame, every: bool = False) -> DataFrame:
        """(i, x): owned values, or those of every node. Masked iterates are the restrictions of the solution, so nothing is added up."""
        w = messages.where("kind = 0").select(F.col("dst").alias("p"), "vals")
        both = w.join(self.blocks.select("p", "ids", "owned"), "p")
        each = both.select(F.explode(F.arrays_zip("ids", "owned", "vals")).alias("z"))
        return each.where(F.lit(every) | F.col("z.owned")).select(F.col("z.ids").alias("i"), F.col("z.vals").alias("x"))

    def close(self) -> None:
        self.blocks.unpersist()


def _masked_square(b: Block, r: np.ndarray) -> float:
    return float(r[b.owned] @ r[b.owned])


def one_level_step(solve, sweeps: int = 1) -> Step:
    """Accumulate, solve, update without communication, and send the next slabs. More sweeps reuse the peers' slabs."""

    def f(b: Block, m: dict) -> list[tuple]:
        w, s = m["w"], b.slab(m["w"])
        r = b.accumulated(s, m["slabs"])
        resid = _masked_square(b, r)
        for k in range(sweeps):
            w = w + solve(b).solve(r)
            s = b.slab(w)
            if k + 1 < sweeps:
                r = b.accumulated(s, m["slabs"])
        return [own(b.p, w, resid), *slabs(b, s)]

    return f


def overlapped_step(solve) -> Step:
    """The same iterates with the solve of a part's own share done while slabs travel: solves are linear, so after the exchange
    only what came in is solved for and added. Exact for direct solvers."""

    def f(b: Block, m: dict) -> list[tuple]:
        came = b.accumulated(np.zeros(b.n), m["slabs"])
        s = b.slab(m["w"])
        w = m["w"] + m["v"] + solve(b).solve(came)
        new = b.slab(w)
        return [own(b.p, w, _masked_square(b, s + came)), *slabs(b, new), own(b.p, solve(b).solve(new), 0.0, 2)]

    return f


def _loop(run: Supersteps, messages: DataFrame, advance: Callable[[DataFrame], DataFrame], cfg: Config, exact: int | None) -> Result:
    """Iterate to the tolerance or to what rounding allows, or `exact` times. A norm belongs to the iterate before the superstep that reports it."""
    history, done, latest, target, settled = [], 0, messages, cfg.tol, False
    most = cfg.max_iter if exact is None else exact
    while done < most:
        for _ in range(min(cfg.checkpoint_every, most - done)):
            messages, done = advance(messages), done + 1
        before, messages = latest, checkpoint(messages)
        latest = messages
        discard(before)
        norm = run.norm(messages)
        history.append((done - 1, norm))
        if exact is None and norm >= cfg.tol and not settled:
            left = run.rounding(messages)
            target, settled = max(cfg.tol, left), norm < SETTLED * left / np.finfo(float).eps
        if exact is None and norm < target:
            break
    result = Result(run.solution(messages), history, done, messages, bool(history) and history[-1][1] < target)
    run.close()
    return result


def true_norm(sys: Sys, u: DataFrame) -> float:
    """The residual norm of (i, x), from the whole matrix."""
    return float(residual_global(sys.entries, u, sys.rhs).agg(F.sqrt(F.sum(F.col("x") * F.col("x")))).first()[0] or 0.0)


def ras_sync(sys: Sys, cfg: Config = Config(), exact: int | None = None, communicate_update: bool = False, overlap_exchange: bool = False, start: DataFrame | None = None) -> Result:
    """One-level restricted additive method; with communicate_update the unreduced form, which also exchanges corrections."""
    run = Supersteps(sys, cfg)
    if overlap_exchange:
        solve = run.solver()
        begun = run.step(run.begin(start).where("kind = 0"), lambda b, m: [own(b.p, m["w"]), *slabs(b, s := b.slab(m["w"])), own(b.p, solve(b).solve(s), 0.0, 2)])
        return _loop(run, checkpoint(begun), lambda m: run.step(m, overlapped_step(solve)), cfg, exact)
    if communicate_update:
        return _two_exchanges(run, cfg, exact, masked=True, theta=1.0, start=start)
    f = one_level_step(run.solver(), cfg.sweeps)
    return _loop(run, run.begin(start), lambda m: run.step(m, f), cfg, exact)


def as_sync(sys: Sys, cfg: Config = Config(), exact: int | None = None, theta: float = 1.0) -> Result:
    """The additive method: corrections add up in overlaps, damped by theta."""
    return _two_exchanges(Supersteps(sys, cfg), cfg, exact, masked=False, theta=theta, start=None)


def _two_exchanges(run: Supersteps, cfg: Config, exact: int | None, masked: bool, theta: float, start: DataFrame | None) -> Result:
    solve = run.solver()

    def correct(b: Block, m: dict) -> list[tuple]:
        r = b.accumulated(b.slab(m["w"]), m["slabs"])
        v = solve(b).solve(r)
        if masked:
            v = np.where(b.owned, v, 0.0)
        return [own(b.p, m["w"], _masked_square(b, r)), own(b.p, v, 0.0, 2), *[(q, b.p, 3, x, None, 0.0) for q, x in b.outgoing(v)], own(b.p, np.array([_masked_square(b, r)]), 0.0, 5)[:4] + ([0], 0.0)]

    def update(b: Block, m: dict) -> list[tuple]:
        w = m["w"] + theta * b.accumulated(m["v"], m["peers"])
        return [own(b.p, w, float(m["kept"][0][0])), *slabs(b, b.slab(w))]

    return _loop(run, run.begin(start), lambda m: run.step(run.step(m, correct), update), cfg, exact)


def ras2_sync(sys: Sys, cfg: Config = Config(), exact: int | None = None) -> Result:
    """Two-level additive method: weighted local and coarse corrections of the same residual."""
    run, (wl, wc) = Supersteps(sys, cfg), cfg.weights
    solve = run.solver()

    def advance(messages: DataFrame) -> DataFrame:
        v0 = run.coarse.solve(run.coarse_values(messages))

        def f(b: Block, m: dict) -> list[tuple]:
            r = b.accumulated(b.slab(m["w"]), m["slabs"])
            w = m["w"] + wl * solve(b).solve(r) + wc * b.from_coarse(v0)
            return [own(b.p, w, _masked_square(b, r)), *slabs(b, b.slab(w), True)]

        new = checkpoint(run.step(messages, f))
        discard(messages)
        return new

    return _loop(run, run.begin(coarse=True), advance, cfg, exact)


def ras2_mult_sync(sys: Sys, cfg: Config = Config(), exact: int | None = None) -> Result:
    """Two-level multiplicative method: the coarse correction first, then the one-level step on the new residual."""
    run = Supersteps(sys, cfg)
    solve = run.solver()

    def advance(messages: DataFrame) -> DataFrame:
        v0 = run.coarse.solve(run.coarse_values(messages))

        def lift(b: Block, m: dict) -> list[tuple]:
            w = m["w"] + b.from_coarse(v0)
            return [own(b.p, w), *slabs(b, b.slab(w))]

        def local(b: Block, m: dict) -> list[tuple]:
            r = b.accumulated(b.slab(m["w"]), m["slabs"])
            w = m["w"] + solve(b).solve(r)
            return [own(b.p, w, _masked_square(b, r)), *slabs(b, b.slab(w), True)]

        new = checkpoint(run.step(run.step(messages, lift), local))
        discard(messages)
        return new

    return _loop(run, run.begin(coarse=True), advance, cfg, exact)


PRECONDITIONERS = ("none", "ras", "as", "ras2")


def gmres(sys: Sys, cfg: Config = Config(), precond: str = "ras", restart: int = 60) -> Result:
    """GMRES with right preconditioner `ras`, `as`, `ras2` (two-level additive, on the system's coarse space) or none.

    A basis vector is written once, consistent over overlaps, and read where it lies; what a step moves between parts is
    slabs. Step k makes the k-th vector from the last product, multiplies it, and returns each part's share of all inner
    products in one small collect. The coarse share of a vector follows from those of the products by the same combination.
    """
    if precond not in PRECONDITIONERS:
        raise ValueError(f"precond is one of {PRECONDITIONERS}")
    two = precond == "ras2"
    run = Supersteps(sys, cfg)
    if two and run.coarse is None:
        raise ValueError("ras2 needs a coarse space")
    solve = run.solver()

    def masked(b: Block, q: np.ndarray, v0: np.ndarray | None) -> np.ndarray:
        z = q if precond == "none" else solve(b).solve(q)
        return np.where(b.owned, z if v0 is None else 0.5 * z + 0.5 * b.from_coarse(v0), 0.0)

    def product(b: Block, z: np.ndarray) -> list[tuple]:
        s = b.times(np.where(b.owned, z, 0.0))
        return [own(b.p, s, 0.0, 2), *[(q, b.p, 1, x, None, 0.0) for q, x in b.outgoing(s)]]

    def share(b: Block, y: np.ndarray) -> list[tuple]:
        if not two:
            return []
        used = np.unique(b.coarse_id)
        r0 = b.to_coarse(np.where(b.owned, y, 0.0), int(used[-1]) + 1 if len(used) else 0)
        return [(COARSE, b.p, 4, r0[used], used, 0.0)]

    def first(b: Block, m: dict) -> list[tuple]:
        r = b.accumulated(b.slab(m["w"]), m["slabs"])
        return [own(b.p, m["w"], _masked_square(b, r)), (b.p, b.p, 5, r, [0], 0.0), *share(b, r)]

    def combined(frame: DataFrame, basis: list[DataFrame]) -> DataFrame:
        out = frame
        for j, q in enumerate(basis):
            out = out.union(q.select("dst", "src", F.lit(6).alias("kind"), "vals", F.array(F.lit(j)).alias("at"), "resid"))
        return out

    history: list[tuple[int, float]] = []
    messages, done = run.begin(), 0
    while True:
        state = checkpoint(run.step(messages, first))
        beta = run.norm(state)
        history.append((done, beta))
        target = cfg.tol if beta < cfg.tol else max(cfg.tol, run.rounding(state))
        if beta < target or done >= cfg.max_iter:
            result = Result(run.solution(state), history, done, state, beta < target)
            run.close()
            return result
        iterate = state.where("kind = 0")
        coarse_y, coarse_q = run.coarse_values(state) if two else None, []
        latest, basis, sizes, h = state.where("kind = 5"), [], [], np.zeros((restart + 1, restart))
        coeffs, factor_y, steps, y = np.zeros(0), 1.0, 0, np.zeros(0)
        for k in range(min(restart, cfg.max_iter - done)):
            v0 = None
            if two:
                coarse_q.append(factor_y * coarse_y - sum((c * q for c, q in zip(coeffs, coarse_q, strict=False)), np.zeros(run.coarse.n)))
                v0 = run.coarse.solve(coarse_q[-1])

            def multiply(b: Block, m: dict, v0=v0, coeffs: np.ndarray = coeffs, factor_y: float = factor_y) -> list[tuple]:
                q = factor_y * m["kept"][0] - sum(c * m["basis"][j] for j, c in enumerate(coeffs))
                keep = [(b.p, b.p, 6, q, [len(coeffs)], 0.0), *[(b.p, b.p, 6, m["basis"][j], [j], 0.0) for j in range(len(coeffs))]]
                if precond == "as":  # corrections add up in overlaps before they are multiplied
                    v = solve(b).solve(q)
                    return [*keep, own(b.p, v, 0.0, 2), *[(p, b.p, 3, x, None, 0.0) for p, x in b.outgoing(v)]]
                return [*keep, *product(b, masked(b, q, v0))]

            def add(b: Block, m: dict) -> list[tuple]:
                return [*[(b.p, b.p, 6, q, [j], 0.0) for j, q in m["basis"].items()], *product(b, b.accumulated(m["v"], m["peers"]))]

            def project(b: Block, m: dict, k: int = k) -> list[tuple]:
                y = b.accumulated(m["v"], m["slabs"])
                q = m["basis"][k]
                dots = [float(y[b.owned] @ m["basis"][j][b.owned]) for j in range(k + 1)] + [_masked_square(b, y), _masked_square(b, q)]
                return [(b.p, b.p, 5, y, [0], 0.0), (b.p, b.p, 7, q, [k], 0.0), (COARSE, b.p, 8, dots, [0], 0.0), *share(b, y)]

            moved = run.step(combined(latest, basis), multiply)
            if precond == "as":
                moved = run.step(moved, add)
            new = checkpoint(run.step(moved, project))
            rows = sorted(new.where("kind = 8").select("src", "vals").collect())
            dots = np.sum([r[1] for r in rows], axis=0)
            size = float(np.sqrt(dots[-1]))
            if k:
                h[k, k - 1] = size
            sizes.append(size)
            h[: k + 1, k] = dots[: k + 1] / size / np.array(sizes)
            # What the next vector's size will be; the exact one is found when it is made.
            h[k + 1, k] = np.sqrt(max(dots[-2] / size**2 - (h[: k + 1, k] ** 2).sum(), 0.0))
            coeffs, factor_y = h[: k + 1, k] / np.array(sizes), 1.0 / size
            latest, coarse_y, steps = new.where("kind = 5"), run.coarse_values(new) if two else None, k + 1
            basis.append(new.where("kind = 7"))
            g = np.zeros(steps + 1)
            g[0] = beta
            y, *_ = np.linalg.lstsq(h[: steps + 1, :steps], g, rcond=None)
            rest = float(np.linalg.norm(g - h[: steps + 1, :steps] @ y))
            history.append((done + steps, rest))
            if rest < 0.5 * target or h[k + 1, k] < 1e-14 * beta:
                break
        weights = y / np.array(sizes)
        v0 = run.coarse.solve(sum(c * q for c, q in zip(weights, coarse_q, strict=True))) if two else None

        def finish(b: Block, m: dict, weights: np.ndarray = weights, v0=v0) -> list[tuple]:
            q = sum(c * m["basis"][j] for j, c in enumerate(weights))
            if precond == "as":
                v = solve(b).solve(q)
                return [own(b.p, m["w"]), own(b.p, v, 0.0, 2), *[(p, b.p, 3, x, None, 0.0) for p, x in b.outgoing(v)]]
            w = m["w"] + masked(b, q, v0)
            return [own(b.p, w), *slabs(b, b.slab(w))]

        def settle(b: Block, m: dict) -> list[tuple]:
            w = m["w"] + b.accumulated(m["v"], m["peers"])
            return [own(b.p, w), *slabs(b, b.slab(w))]

        messages = run.step(combined(iterate, basis), finish)
        messages, done = checkpoint(run.step(messages, settle) if precond == "as" else messages), done + steps


def stationary(sys: Sys, k: int, cfg: Config = Config(), precond: str = "ras", theta: float = 1.0) -> DataFrame:
    """(i, x) after k steps u + theta M (f - A u) in the global form: the residual is taken from the whole matrix.

    M is `ras` (owned values of local solves), `as` (their sum), `ras2` (half of `ras` and half of the coarse correction) or
    `jacobi` (local solves on the parts themselves, without overlap).
    """
    if precond not in ("ras", "as", "ras2", "jacobi"):
        raise ValueError("precond is one of ras, as, ras2, jacobi")
    if precond == "jacobi":
        sys.member = checkpoint(decompose(sys.owner, sys.entries, 0))
    run = Supersteps(sys, cfg)
    solve = run.solver()
    u = checkpoint(sys.rhs.select("i", F.lit(0.0).alias("x")))
    entries = checkpoint(sys.entries)
    for _ in range(k):
        r = checkpoint(residual_global(entries, u, sys.rhs))
        rows = sys.member.join(r, "i").groupBy("p").agg(F.transform(F.array_sort(F.collect_list(F.struct("slot", "x"))), lambda t: t["x"]).alias("vals"))
        sent = rows.select(F.col("p").alias("dst"), F.col("p").alias("src"), F.lit(0).alias("kind"), "vals", F.lit(None).cast("array<int>").alias("at"), F.lit(0.0).alias("resid"))
        v = run.solution(run.step(sent, lambda b, m: [own(b.p, solve(b).solve(m["w"]))]), every=precond == "as")
        v = v.groupBy("i").agg(F.sum("x").alias("v"))
        if precond == "ras2":
            shares = sys.interp.join(r, "i").groupBy("c").agg(F.sum(F.col("weight") * F.col("x")).alias("x")).toPandas()  # the coarse size
            r0 = np.zeros(run.coarse.n)
            r0[shares.c.to_numpy()] = shares.x.to_numpy()
            v0 = u.sparkSession.createDataFrame(list(enumerate(run.coarse.solve(r0).tolist())), "c long, y double")
            lifted = sys.interp.join(v0, "c").groupBy("i").agg(F.sum(F.col("weight") * F.col("y")).alias("y"))
            v = v.join(lifted, "i", "left").select("i", (cfg.weights[0] * F.col("v") + cfg.weights[1] * F.coalesce("y", F.lit(0.0))).alias("v"))
        new = checkpoint(u.join(v, "i", "left").select("i", (F.col("x") + theta * F.coalesce("v", F.lit(0.0))).alias("x")))
        discard(u, r)
        u = new
    run.close()
    return u


def ras_global(sys: Sys, k: int, cfg: Config = Config()) -> np.ndarray:
    """Iterates of the global form by dense algebra on the driver: an oracle for small systems; columns are nodes in order of id."""
    e = sys.entries.toPandas()
    ids = np.unique(e.i)
    at = {int(i): n for n, i in enumerate(ids)}
    a = np.zeros((len(ids), len(ids)))
    for i, j, v in e.itertuples(index=False):
        a[at[i], at[j]] += v
    f = np.zeros(len(ids))
    for i, x in sys.rhs.toPandas().itertuples(index=False):
        f[at[i]] = x
    m = (sys.member if sys.member is not None else decompose(sys.owner, sys.entries, cfg.delta)).toPandas()
    u, out = np.zeros(len(ids)), []
    sets = [(np.array([at[i] for i in g.i]), g.owned.to_numpy()) for _, g in m.groupby("p")]
    for _ in range(k):
        r, new = f - a @ u, u.copy()
        for s, own_ in sets:
            v = np.linalg.solve(a[np.ix_(s, s)], r[s])
            new[s[own_]] += v[own_]
        u = new
        out.append(u)
    return np.array(out)


def chaotic_relaxation(entries: DataFrame, f: DataFrame, sweeps: int, updated: Callable[[int], object] | None = None, checkpoint_every: int = 8) -> DataFrame:
    """(i, x) after `sweeps` point relaxations; updated(n) is a condition on i that names who takes part in sweep n (all without it)."""
    diagonal = entries.where("i = j").select("i", F.col("a").alias("d"))
    off = checkpoint(entries.where("i <> j"))
    base = checkpoint(f.join(diagonal, "i").select("i", F.col("x").alias("f"), "d"))
    u = base.select("i", F.lit(0.0).alias("x"))
    for n in range(1, sweeps + 1):
        pull = off.join(u.withColumnRenamed("i", "j"), "j").groupBy("i").agg(F.sum(F.col("a") * F.col("x")).alias("y"))
        new = base.join(pull, "i", "left").select("i", ((F.col("f") - F.coalesce("y", F.lit(0.0))) / F.col("d")).alias("x"))
        if updated is not None:
            new = new.join(u.withColumnRenamed("x", "old"), "i").select("i", F.when(updated(n), F.col("x")).otherwise(F.col("old")).alias("x"))
        # With a condition, a sweep reads the one before it twice, so plans may not be chained.
        u = checkpoint(new) if updated is not None or n % checkpoint_every == 0 else new
    return u


def cg_global(entries: DataFrame, f: DataFrame, tol: float = 1e-10, most: int = 500) -> DataFrame:
    """(i, x) by conjugate gradients on triples: an exact-solve oracle for symmetric positive definite systems."""
    entries = checkpoint(entries)
    x = checkpoint(f.select("i", F.lit(0.0).alias("u"), F.col("x").alias("r"), F.col("x").alias("p")))
    rr = x.agg(F.sum(F.col("r") * F.col("r"))).first()[0]
    for _ in range(most):
        if rr is None or rr < tol * tol:
            break
        q = entries.join(x.select(F.col("i").alias("j"), "p"), "j").groupBy("i").agg(F.sum(F.col("a") * F.col("p")).alias("q"))
        both = checkpoint(x.join(q, "i"))
        alpha = rr / both.agg(F.sum(F.col("p") * F.col("q"))).first()[0]
        new = checkpoint(both.select("i", (F.col("u") + alpha * F.col("p")).alias("u"), (F.col("r") - alpha * F.col("q")).alias("r"), "p"))
        nn = new.agg(F.sum(F.col("r") * F.col("r"))).first()[0]
        x, rr = new.select("i", "u", "r", (F.col("r") + nn / rr * F.col("p")).alias("p")), nn
    return x.select("i", F.col("u").alias("x"))


def block_jacobi(sys: Sys, k: int, cfg: Config = Config()) -> DataFrame:
    """(i, x) after k steps without overlap: owned nodes lie on surfaces, so there is no local form."""
    return stationary(sys, k, cfg, "jacobi")
