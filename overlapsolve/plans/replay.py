"""Asynchronous iterations replayed from explicit schedules: which parts update at a tick, and how old the data are that they see.

A schedule is a table `ticks` (n, p) and a table `stamps` (n, p, q, tau): at tick n part p uses what q had published after
tick tau; with a column `component`, single values of a slab may have different ages (torn reads). Slabs are kept in a
history (src, stamp, dst, vals), and a tick reads the latest slab that isn't newer than its stamp: an as-of join. The same
schedule gives the same iterates on any cluster.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Iterable
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from overlapsolve.functions.handshake import CoarseHandshake
from overlapsolve.operators.coarse import CoarseProblem
from overlapsolve.operators.local import Block
from overlapsolve.plans.bsp import Supersteps
from overlapsolve.session import checkpoint, discard, together
from overlapsolve.system import Config, Sys

KINDS = ("sync", "cyclic", "random", "slow_one", "adversarial", "starved")


def make_schedule(spark: SparkSession, parts: int, ticks: int, kind: str, seed: int = 42, delay: int = 3, outages: dict[int, tuple[int, int]] | None = None) -> tuple[DataFrame, DataFrame]:
    """(ticks, stamps) of a kind; `outages` maps a part to the ticks [from, to) it misses, after which it goes on from its last state.

    sync: all, with data of the tick before. cyclic: one part a tick, fresh data. random: each part by a fair keyed coin, data
    up to `delay` ticks old. slow_one: part 0 every third tick. adversarial: all, always `delay` ticks old. starved: part 1 never.
    """
    if kind not in KINDS:
        raise ValueError(f"kind is one of {KINDS}")
    grid = spark.range(1, ticks + 1).select(F.col("id").alias("n")).crossJoin(spark.range(parts).select(F.col("id").cast("int").alias("p")))  # ticks x parts, both given
    coin = F.pmod(F.xxhash64("n", "p", F.lit(seed)), F.lit(2)) == 0
    on = {"cyclic": F.pmod(F.col("n") - 1, F.lit(parts)) == F.col("p"), "random": coin | (F.pmod("n", F.lit(8)) == F.pmod("p", F.lit(8))), "slow_one": (F.col("p") > 0) | (F.pmod("n", F.lit(3)) == 0), "starved": F.col("p") != 1}.get(kind, F.lit(True))
    chosen = grid.where(on)
    for p, (a, b) in (outages or {}).items():
        chosen = chosen.where(~((F.col("p") == p) & F.col("n").between(a, b - 1)))
    age = {"random": 1 + F.pmod(F.xxhash64("n", "p", "q", F.lit(seed + 1)), F.lit(delay)), "adversarial": F.lit(delay)}.get(kind, F.lit(1))
    pairs = chosen.withColumn("q", F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))).where("p <> q")
    return chosen.select("n", "p"), pairs.select("n", "p", "q", F.greatest(F.col("n") - age, F.lit(0)).cast("long").alias("tau"))


def audit_schedule(ticks: DataFrame, stamps: DataFrame, parts: int, max_gap: int = 16, max_delay: int = 16, monotone: bool = False) -> DataFrame:
    """(rule, n, p, q) of violations; none for an admissible schedule.

    future: data from the tick itself or later. starved: a part that doesn't update for more than `max_gap` ticks. stale: data
    older than `max_delay`. backwards, only if `monotone`: a part sees older data than before, which slabs that overtake each other
    may cause and convergence allows. A finite schedule can only be held to such bounds.
    """
    none = F.lit(None).cast("int")
    future = stamps.where("tau >= n").select(F.lit("future").alias("rule"), "n", "p", "q")
    stale = stamps.where(F.col("n") - F.col("tau") > max_delay).select(F.lit("stale"), "n", "p", "q")
    before = F.lag("tau").over(Window.partitionBy("p", "q").orderBy("n"))
    backwards = stamps.withColumn("before", before).where("tau < before").select(F.lit("backwards"), "n", "p", "q")
    last = ticks.agg(F.max("n").alias("n"))
    all_parts = ticks.sparkSession.range(parts).select(F.col("id").cast("int").alias("p"))
    bounds = all_parts.select(F.lit(0).cast("long").alias("n"), "p").union(ticks.select("n", "p")).union(all_parts.join(F.broadcast(last)).select("n", "p"))
    gap = F.col("n") - F.lag("n").over(Window.partitionBy("p").orderBy("n"))
    starved = bounds.withColumn("gap", gap).where(F.col("gap") > max_gap).select(F.lit("starved"), "n", "p", none)
    found = future.union(starved).union(stale)
    return found.union(backwards) if monotone else found


class Replay:
    """Iterates and slabs are DataFrames, one a tick; the handshake's flags and vectors of the coarse size are on the driver."""

    def __init__(self, sys: Sys, cfg: Config = Config()):
        self.run, self.cfg = Supersteps(sys, cfg), cfg
        self.coarse: CoarseProblem | None = self.run.coarse
        self.hand = CoarseHandshake(0)
        self.correction: np.ndarray | None = None  # the last coarse solution; a vector of the coarse size
        self.posted: dict[int, tuple] = {}

    @property
    def lost_corrections(self) -> int:
        return self.hand.lost

    @property
    def coarse_solves(self) -> int:
        return self.hand.solves

    def solve(self, ticks: DataFrame, stamps: DataFrame, strict_handshake: bool = False, max_delay: int = 16) -> DataFrame:
        """(i, x) after the last tick. Ticks are replayed in order; schedules are small, their rows come to the driver."""
        plan: dict[int, list[int]] = {}
        for n, p in ticks.collect():
            plan.setdefault(n, []).append(p)
        ages = stamps.toPandas()
        if len(ages) and int((ages.n - ages.tau).max()) > max_delay:
            raise ValueError(f"stamps reach back further than max_delay={max_delay}")
        run, two = self.run, self.coarse is not None
        begun = run.begin(coarse=two)
        frames = {0: checkpoint(begun.withColumn("at", F.when(F.col("kind") <= 1, F.array(F.lit(0))).otherwise(F.col("at"))))}
        discard(begun)
        shares = {r["src"]: (r["at"], r["vals"]) for r in frames[0].where("kind = 4").collect()} if two else {}
        solver = run.solver()
        wl, wc = self.cfg.weights
        parts = sorted(r[0] for r in frames[0].where("kind = 0").select("dst").collect())
        wanted = _slabs_of(plan, ages, parts)
        last_use = {stamp: n for n in sorted(wanted) for sources in wanted[n].values() for _, _, stamp in sources}
        latest = dict.fromkeys(parts, 0)
        self.hand, number = CoarseHandshake(len(parts), strict_handshake), {p: k for k, p in enumerate(parts)}
        for n in sorted(plan):
            active = sorted(set(plan[n]) & set(parts))
            ready = {}
            if two:
                for p in active:
                    # Hazards: the right-hand side comes from the state before a pending correction is applied.
                    if self.hand.try_post(number[p]):
                        self.posted[p] = shares[p]
                ready = {p: self.correction for p in active if self.hand.try_consume(number[p])}
            sees = wanted.get(n, {})

            def f(b: Block, m: dict, n=n, sees=sees, ready=ready) -> list[tuple]:
                w = m["w"]
                r = b.accumulated(b.slab(w), _seen(sees.get(b.p, ()), m["dated"]))
                v = solver(b).solve(r)
                w = w + (wl * v + wc * b.from_coarse(ready[b.p]) if b.p in ready else v)
                s = b.slab(w)
                out = [(b.p, b.p, 0, w, [n], float(r[b.owned] @ r[b.owned]))] + [(q, b.p, 1, x, [n], 0.0) for q, x in b.outgoing(s)]
                if two:
                    used = np.unique(b.coarse_id)
                    out.append((-1, b.p, 4, b.to_coarse(s, int(used[-1]) + 1 if len(used) else 0)[used], used, 0.0))
                return out

            slabs = {stamp for sources in sees.values() for _, _, stamp in sources}
            read = together([frames[s] for s in sorted(slabs | {latest[p] for p in active})])
            slab = (F.col("kind") == 1) & F.col("dst").isin(active) & F.get("at", F.lit(0)).isin(sorted(slabs))
            new = checkpoint(run.step(read.where(slab | _iterates({p: latest[p] for p in active})), f, active))
            frames[n] = new
            latest |= dict.fromkeys(active, n)
            for s in [s for s in frames if last_use.get(s, 0) <= n and s not in latest.values()]:
                discard(frames.pop(s))
            if two:
                shares |= {r["src"]: (r["at"], r["vals"]) for r in new.where("kind = 4").collect()}
                if self.hand.try_solve():
                    r0 = np.zeros(self.coarse.n)
                    for p in parts:
                        at, vals = self.posted[p]
                        np.add.at(r0, np.array(at, np.int64), np.array(vals, float))
                    self.correction, self.posted = self.coarse.solve(r0), {}  # old right-hand sides don't add up
        return run.solution(together([frames[s] for s in sorted(set(latest.values()))]).where(_iterates(latest)))


def _iterates(latest: dict[int, int]) -> Column:
    """Whether a message is the iterate of a part from the tick named for it."""
    of: dict[int, list[int]] = {}
    for p, n in latest.items():
        of.setdefault(n, []).append(p)
    named = [(F.get("at", F.lit(0)) == n) & F.col("dst").isin(ps) for n, ps in of.items()]
    return (F.col("kind") == 0) & reduce(lambda x, y: x | y, named, F.lit(False))


def _slabs_of(plan: dict[int, list[int]], ages: pd.DataFrame, parts: list[int]) -> dict[int, dict[int, list[tuple[int, int, int]]]]:
    """By tick and part: (source, component, stamp) of what it sees; a stamp is the source's last tick up to the given one, a component -1 the whole slab."""
    updates: dict[int, list[int]] = {p: [0] for p in parts}
    for n in sorted(plan):
        for p in set(plan[n]) & set(parts):
            updates[p].append(n)
    active = {n: set(ps) for n, ps in plan.items()}
    components = ages.component if "component" in ages.columns else np.full(len(ages), -1)
    out: dict[int, dict[int, list[tuple[int, int, int]]]] = {}
    for n, p, q, tau, c in zip(ages.n.tolist(), ages.p.tolist(), ages.q.tolist(), ages.tau.tolist(), components.tolist() if len(ages) else [], strict=True):
        if p in active.get(n, ()) and q in updates and tau >= 0:
            out.setdefault(n, {}).setdefault(p, []).append((q, int(c), updates[q][bisect_right(updates[q], tau) - 1]))
    return out


def _seen(sources: Iterable[tuple[int, int, int]], dated: dict[tuple[int, int], np.ndarray]) -> dict[int, np.ndarray]:
    """By source the slab that is seen, of values from different stamps where single components are named."""
    found: dict[int, np.ndarray] = {}
    for q, c, stamp in sorted(sources, key=lambda x: (x[0], x[1])):  # whole slabs first
        x = dated.get((q, stamp))
        if x is None:
            continue
        if q not in found:
            found[q] = x.copy()
        elif 0 <= c < len(x):
            found[q][c] = x[c]
    return found


def replay(sys: Sys, ticks: DataFrame, stamps: DataFrame, cfg: Config = Config(), **options) -> DataFrame:
    """One-level, or two-level if the system has a coarse space. History must reach back as far as stamps do."""
    return Replay(sys, cfg).solve(ticks, stamps, **options)


def torn_stamps(stamps: DataFrame, width: int, seed: int = 1) -> DataFrame:
    """stamps with a component column: about half the values of each slab are one tick older."""
    each = stamps.withColumn("component", F.explode(F.sequence(F.lit(0), F.lit(width - 1))))
    older = F.pmod(F.xxhash64("n", "p", "q", "component", F.lit(seed)), F.lit(2))
    return each.withColumn("tau", F.greatest(F.col("tau") - older, F.lit(0)))
