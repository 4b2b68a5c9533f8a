"""The live engine: barrier tasks start together and then run freely, several parts in each, with no shuffle and no driver.

Slabs go through mailbox windows; a part uses what it finds there. The last task plays the coarse solver and the master of the
convergence test; if it is `dedicated`, it has no parts. All task slots are needed at once, so speculation must be off.

`progress` says who moves a slab from its writer to its reader: nobody (passive: the writer puts it where the reader looks), the
reader within its own loop (inline), a thread of the reader's task (thread), or the last task (dedicated).
"""

from __future__ import annotations

import json
import threading
import time
import uuid
from collections.abc import Callable
from dataclasses import replace
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark import BarrierTaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from overlapsolve.functions.handshake import AdaptiveSleep, CoarseHandshake, FileCounters
from overlapsolve.functions.solvers import factor
from overlapsolve.live.mailbox import Option, Window, all_options, exchange, torus_neighbors
from overlapsolve.operators.local import Block
from overlapsolve.plans.bsp import Supersteps, true_norm
from overlapsolve.session import checkpoint, shared_dir
from overlapsolve.system import Config, Sys

TRACE = "p int, iterations int, seconds double, resid_sq double, coarse_used int, coarse_solves int, poll_ratio double, converged boolean, ids array<bigint>, vals array<double>"


def local_path(spark) -> Path:
    """The shared folder as a path that every task can open; live runs need one."""
    path = shared_dir(spark).removeprefix("file://")
    if "://" in path:
        raise ValueError("live runs need a shared folder that can be opened as files")
    return Path(path.removeprefix("file:"))


PROGRESS = ("passive", "inline", "thread", "dedicated")


def run_live(sys: Sys, cfg: Config = Config(), tasks: int = 3, delay: dict[int, float] | None = None, sync: bool = False, option: Option = Option(kind="atomic"), dedicated: bool = False, progress: str = "passive", start: DataFrame | None = None) -> DataFrame:
    """One row a part, as in TRACE. `delay` adds seconds to each iteration of a part; with sync, parts wait for each other's
    slabs and, with a coarse space, for its correction. `start` (i, x) is the first iterate, else zero. A dedicated last task needs a slot more.

    Stops when the master's sum of the parts' latest squared norms falls below tol^2, which may be early; see run_confirmed.
    """
    if progress not in PROGRESS:
        raise ValueError(f"progress is one of {PROGRESS}")
    run = Supersteps(sys, cfg)
    folder, n0 = str(local_path(sys.entries.sparkSession) / f"live-{uuid.uuid4().hex}"), run.coarse.n if run.coarse else 0
    solver0 = run.coarse.solver if run.coarse else None
    parts = sorted(r[0] for r in run.blocks.select("p").collect())
    total = tasks + dedicated
    given = run.blocks
    if start is not None:
        first = sys.member.join(start, "i").groupBy("p").agg(F.transform(F.array_sort(F.collect_list(F.struct("slot", "x"))), lambda t: t["x"]).alias("first"))
        given = given.join(first, "p", "left")
    dealt = given.withColumn("task", F.pmod("p", F.lit(tasks)).cast("int"))
    placed = dealt.repartitionById(total, F.col("task")) if hasattr(dealt, "repartitionById") else dealt.repartition(total, "task")

    def play(batches):
        rows = [row for batch in batches for row in batch.to_pylist()]
        blocks = [Block.of({k: v for k, v in row.items() if k not in ("task", "first")}) for row in rows]
        iterates = [np.array(row["first"], float) if row.get("first") is not None else np.zeros(b.n) for row, b in zip(rows, blocks, strict=True)]
        context = BarrierTaskContext.get()
        context.barrier()
        yield from _play(Path(folder), blocks, iterates, parts, context.partitionId() == total - 1, n0, solver0, cfg, delay or {}, sync, option, progress)

    return placed.mapInArrow(play, TRACE, barrier=True)


def run_confirmed(sys: Sys, cfg: Config = Config(), rounds: int = 4, **options) -> tuple[DataFrame, DataFrame, float]:
    """(trace, (i, x), residual norm): after each stop the norm is computed from the whole matrix, and while it isn't below the
    tolerance the run goes on from where it was, held to a quarter of the sum before."""
    u, tol = None, cfg.tol
    for _ in range(rounds):
        trace = checkpoint(run_live(sys, replace(cfg, tol=tol), start=u, **options))
        u = checkpoint(solution_of(trace))
        norm = true_norm(sys, u)
        if norm < cfg.tol:
            break
        tol /= 4
    return trace, u, norm


def _raise_flag(path: Path, text: str = "1") -> None:
    path.parent.mkdir(parents=True, exist_ok=True)
    temp = path.with_suffix(f".{uuid.uuid4().hex}")
    temp.write_text(text)
    temp.replace(path)


class _Part:
    def __init__(self, root: Path, b: Block, w: np.ndarray, n0: int, cfg: Config, option: Option, progress: str, hand: CoarseHandshake, number: int):
        self.b, self.root, self.n0, self.cfg, self.hand, self.number = b, root, n0, cfg, hand, number
        self.w, self.solver = w, factor(b.indptr, b.indices, b.data, cfg.solver, cfg.rtol)
        box = lambda at, src, dst, k: Window(root / at / str(dst) / f"{src}.bin", len(b.shared(k)) + 1, option)
        put_at = "box" if progress == "passive" else "out"
        self.out = [box(put_at, b.p, q, k) for k, q in enumerate(b.peers)]
        self.inn = [box("box", q, b.p, k) for k, q in enumerate(b.peers)]
        self.move = [(box("out", q, b.p, k), w) for k, (q, w) in enumerate(zip(b.peers, self.inn, strict=True))] if progress != "passive" else []
        self.count = self.used = 0
        self.resid = np.inf
        self.post = Window(root / "coarse" / f"rhs{b.p}.bin", max(n0, 1), Option(kind="atomic"))
        self.corr = Window(root / "coarse" / f"corr{b.p}.bin", max(n0, 1), Option(kind="atomic"))

    def stamp(self) -> int:
        return int(min((w.get()[0] for w in self.inn), default=self.count))

    def bring(self) -> None:
        """Move what peers have put out for this part to where it looks."""
        for source, target in self.move:
            target.put(source.get())

    def publish(self) -> np.ndarray:
        s = self.b.slab(self.w)
        for w, (_, v) in zip(self.out, self.b.outgoing(s), strict=True):
            w.put(np.concatenate([[self.count], v]))
            w.complete_one()
        for w in self.out:
            w.complete()
        return s

    def offer(self, s: np.ndarray) -> None:
        if self.n0 and self.hand.may_post(self.number):
            self.post.put(self.b.to_coarse(s, self.n0))
            self.hand.posted(self.number)

    def turn(self, s: np.ndarray) -> None:
        b, cfg = self.b, self.cfg
        self.offer(s)
        letters = {int(q): w.get() for q, w in zip(b.peers, self.inn, strict=True)}
        r = b.accumulated(s, {q: x[1:] for q, x in letters.items() if x[0] >= 0})
        self.resid = float(r[b.owned] @ r[b.owned])
        v = self.solver.solve(r)
        if self.n0 and self.hand.has_correction(self.number):
            self.w = self.w + cfg.weights[0] * v + cfg.weights[1] * b.from_coarse(self.corr.get())
            self.hand.consumed(self.number)
            self.used += 1
        else:
            self.w = self.w + v
        self.count += 1


def _play(root: Path, blocks: list[Block], iterates: list[np.ndarray], parts: list[int], master: bool, n0: int, solver0, cfg: Config, delay: dict[int, float], sync: bool, option: Option, progress: str):
    hand = CoarseHandshake(len(parts), False, FileCounters(root / "counts"))
    number = {p: k for k, p in enumerate(parts)}
    mine = [_Part(root, b, w, n0, cfg, option, progress, hand, number[b.p]) for b, w in zip(blocks, iterates, strict=True)]
    begun, stop = time.time(), root / "flags" / "stop"
    late = lambda: stop.exists() or time.time() - begun > cfg.timeout_s
    pause, wake = AdaptiveSleep(), 0.0
    bringing = threading.Thread(target=_bring_all, args=([p.bring for p in mine], late), daemon=True) if progress == "thread" else None
    if bringing:
        bringing.start()
    movers = _movers(root, option) if progress == "dedicated" and master else None

    def serve() -> None:
        """What the master does between its parts' turns: the coarse solve, moving slabs, and the convergence test."""
        nonlocal wake
        if movers:
            movers()
        if n0 and time.time() >= wake:
            ready = hand.can_solve()
            if ready:
                r0 = sum(np.frombuffer((root / "coarse" / f"rhs{p}.bin").read_bytes(), "<f8") for p in parts)
                v0 = solver0.solve(np.array(r0))
                for p in parts:
                    Window(root / "coarse" / f"corr{p}.bin", n0, Option(kind="atomic")).put(v0)
                hand.solved()
            wake = time.time() + pause.poll(ready)
        seen = [json.loads(x.read_text()) for p in parts if (x := root / "norms" / str(p)).exists()]
        if len(seen) == len(parts) and min(n for n, _ in seen) > 1 and sum(r for _, r in seen) < cfg.tol**2:
            _raise_flag(stop)

    while not late():
        sent = []
        for part in mine:
            if delay.get(part.b.p):
                time.sleep(delay[part.b.p])
            sent.append(part.publish())
            if sync:
                part.offer(sent[-1])
        for part, s in zip(mine, sent, strict=True):
            if progress == "inline":
                part.bring()
            if sync:  # all slabs of this round, and the correction that belongs to it
                while part.stamp() < part.count or (n0 and not hand.has_correction(part.number)):
                    if late():
                        break
                    if progress == "inline":
                        part.bring()
                    if master:
                        serve()
                    time.sleep(1e-4)
            part.turn(s)
            _raise_flag(root / "norms" / str(part.b.p), json.dumps([part.count, part.resid]))
        if master:
            serve()
        if not mine:
            time.sleep(1e-4)
        if mine and min(p.count for p in mine) >= cfg.max_iter:
            _raise_flag(stop)
    seconds = time.time() - begun
    for part in mine:
        b = part.b
        keep = b.owned
        columns = [[b.p], [part.count], [seconds], [part.resid], [part.used], [hand.solves], [pause.ratio], [stop.exists() and part.count < cfg.max_iter], [b.ids[keep].tolist()], [part.w[keep].tolist()]]
        types = [pa.int32(), pa.int32(), pa.float64(), pa.float64(), pa.int32(), pa.int32(), pa.float64(), pa.bool_(), pa.list_(pa.int64()), pa.list_(pa.float64())]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names=[x.split()[0] for x in TRACE.split(", ")])


def _bring_all(bring: list[Callable], late: Callable) -> None:
    while not late():
        for f in bring:
            f()
        time.sleep(1e-4)


def _movers(root: Path, option: Option) -> Callable:
    """Moves every slab that has been put out, for all parts."""
    known: dict[Path, tuple[Window, Window]] = {}

    def move() -> None:
        for path in (root / "out").glob("*/*.bin"):
            if path not in known:
                width = path.stat().st_size // 8
                if not width:
                    continue
                known[path] = (Window(path, width, option), Window(root / "box" / path.parent.name / path.name, width, option))
            source, target = known[path]
            target.put(source.get())

    return move


def solution_of(trace: DataFrame) -> DataFrame:
    """(i, x) from a live trace."""
    return trace.select(F.explode(F.arrays_zip("ids", "vals")).alias("z")).select(F.col("z.ids").alias("i"), F.col("z.vals").alias("x"))


def comm_bench(spark, options: list[Option] | None = None, tasks: int = 3, reps: int = 20, width: int = 500, shape: tuple[int, int, int] = (4, 4, 4), loads: DataFrame | None = None) -> DataFrame:
    """(option, seconds, inconsistent, reads): the neighbour exchange on a periodic grid, each option in turn, tasks in step at each start.

    loads (rank, at, n) has what each rank sends at each of the `width` places, 0 where it has no row; ranks times width numbers at most.
    """
    sent = None
    if loads is not None:
        table, sent = loads.toArrow(), {u: np.ones(width) for u in range(shape[0] * shape[1] * shape[2])}
        for u, at, n in zip(*(table.column(c).to_pylist() for c in ("rank", "at", "n")), strict=True):
            sent[u][at] += n
    pairs, folder = torus_neighbors(*shape), str(local_path(spark) / f"comm-{uuid.uuid4().hex}")
    chosen = options or all_options()

    def play(batches: Callable):
        for _ in batches:
            pass
        context = BarrierTaskContext.get()
        rows = []
        for k, option in enumerate(chosen):
            context.barrier()
            rows.append((option.name, *exchange(Path(folder) / str(k), context.partitionId(), tasks, pairs, option, reps, width, loads=sent)))
        names = ["option", "seconds", "torn", "reads"]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.string(), pa.float64(), pa.int64(), pa.int64()), strict=True)], names=names)

    each = spark.range(0, tasks, 1, tasks).mapInArrow(play, "option string, seconds double, torn long, reads long", barrier=True)
    return each.groupBy("option").agg(F.max("seconds").alias("seconds"), (F.sum("torn") / F.sum("reads")).alias("inconsistent"), F.sum("reads").alias("reads"))
