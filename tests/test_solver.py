"""The solver: hand-derived fixtures, equivalences of forms, premises of the theory, and pieces against dense algebra."""

import math
from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from overlapsolve import experiments
from overlapsolve import queries as q
from overlapsolve.functions import metrics, solvers
from overlapsolve.functions.handshake import AdaptiveSleep, CoarseHandshake
from overlapsolve.live import engine
from overlapsolve.live.mailbox import Option, Window, all_options, torn, torus_neighbors
from overlapsolve.operators import coarse, overlap, partition
from overlapsolve.operators.components import connected_components
from overlapsolve.plans import bsp, replay, simulate
from overlapsolve.sources import mesh
from overlapsolve.system import Config, Sys


def xs(u):
    return [r[1] for r in sorted(u.collect())]


@pytest.mark.parametrize("k,want,square", [(1, [2, 3, 3, 3, 3, 2], 6), (2, [2.6, 4.2, 4.8, 4.8, 4.2, 2.6], 2)])
def test_one_level_fixture(spark, k, want, square):
    r = bsp.ras_sync(q.micro(spark), exact=k)
    assert xs(r.u) == pytest.approx(want) and r.history[-1][1] ** 2 == pytest.approx(square)


def test_two_level_fixture(spark):
    assert xs(bsp.ras2_sync(q.micro(spark, True), exact=1).u) == pytest.approx([2.5, 3, 3, 3, 3, 2.5])


def test_forms_agree(spark):
    """The reduced form, the one that exchanges updates, and the global one give the same iterates."""
    want = bsp.ras_global(q.micro(spark), 3)[-1]
    assert xs(bsp.ras_sync(q.micro(spark), exact=3).u) == pytest.approx(want, abs=1e-12)
    assert xs(bsp.ras_sync(q.micro(spark), exact=3, communicate_update=True).u) == pytest.approx(want, abs=1e-12)
    assert xs(replay.replay(q.micro(spark), *replay.make_schedule(spark, 2, 3, "sync"))) == pytest.approx(want, abs=1e-12)


@pytest.mark.parametrize("tau,want", [(1, [2, 3, 3, 4.8, 4.2, 2.6]), (0, [2, 3, 3, 3, 3, 2])])
def test_replay_fixture(spark, tau, want):
    ticks = spark.createDataFrame([(1, 0), (2, 1)], "n long, p int")
    stamps = spark.createDataFrame([(1, 0, 1, 0), (2, 1, 0, tau)], "n long, p int, q int, tau long")
    assert xs(replay.replay(q.micro(spark), ticks, stamps)) == pytest.approx(want)


def test_krylov(spark):
    exact = [3, 5, 6, 6, 5, 3]
    assert xs(bsp.gmres(q.micro(spark), Config(tol=1e-10)).u) == pytest.approx(exact)
    assert xs(bsp.gmres(q.micro(spark, True), Config(tol=1e-10), "ras2").u) == pytest.approx(exact)
    assert xs(bsp.cg_global(q.micro(spark).entries, q.micro(spark).rhs)) == pytest.approx(exact)


def test_schedules(spark):
    for kind in replay.KINDS:
        found = {r.rule for r in replay.audit_schedule(*replay.make_schedule(spark, 4, 40, kind), 4).collect()}
        assert found == ({"starved"} if kind == "starved" else set())
    ticks, stamps = replay.make_schedule(spark, 2, 10, "sync")
    assert {r.rule for r in replay.audit_schedule(ticks, stamps.withColumn("tau", F.col("n")), 2).collect()} == {"future"}


def lattice_system(spark, n=8, boxes=(2, 2)):
    nodes = q.ids(spark, n * n)
    return mesh.stencil_entries(spark, (n, n), 4.0), partition.partition_box(nodes, (n, n), boxes)


def test_decomposition_rules(spark):
    entries, owner = lattice_system(spark)
    m = overlap.decompose(owner, entries, 1)
    assert overlap.check_decomposition(m, entries).isEmpty()
    without = overlap.decompose(owner, entries, 0)
    assert {r.rule for r in overlap.check_decomposition(without, entries).collect()} == {"hidden", "closed"}
    geometric = {tuple(r) for r in partition.geometric_members(q.ids(spark, 64), (8, 8), (2, 2), 1).collect()}
    assert {(r.p, r.i) for r in m.collect()} <= geometric


def test_contraction_premise(spark):
    entries, owner = lattice_system(spark)
    a = np.zeros((64, 64))
    for i, j, v in entries.collect():
        a[i, j] += v
    sets = [(g.i.to_numpy(), g.owned.to_numpy()) for _, g in overlap.decompose(owner, entries, 1).toPandas().groupby("p")]
    weights = np.linalg.solve(a, np.ones(64))
    assert metrics.contraction_constant(a, sets, weights) < 1
    assert metrics.is_m_matrix(entries)
    assert not metrics.is_m_matrix(mesh.convection_diffusion(spark, 2, 8, (300.0, 0.0), upwind=False))


def csr(a):
    rows, cols = np.nonzero(a)
    return solvers.to_csr(len(a), rows, cols, a[rows, cols])


def test_local_solvers():
    rng = np.random.default_rng(1)
    n = 7
    a = 4.5 * np.eye(n * n) - sum(np.kron(*p) for p in ((np.eye(n), np.eye(n, k=1) + np.eye(n, k=-1)), (np.eye(n, k=1) + np.eye(n, k=-1), np.eye(n))))
    r = rng.normal(size=n * n)
    want = np.linalg.solve(a, r)
    assert solvers.Banded(*csr(a)).solve(r) == pytest.approx(want)
    assert solvers.Dense(a).solve(r) == pytest.approx(want)
    rough = solvers.IncompleteCG(*csr(a), rtol=0.1).solve(r)
    assert np.linalg.norm(r - a @ rough) <= 0.1 * np.linalg.norm(r)
    cycle, x = solvers.VCycle(*csr(a), coarsest=8), np.zeros(n * n)
    for _ in range(30):
        x += cycle.solve(r - a @ x)
    assert x == pytest.approx(want, abs=1e-6)
    chain = 2 * np.eye(9) - np.eye(9, k=1) - np.eye(9, k=-1)
    assert solvers.green_1d(9) @ chain == pytest.approx(np.eye(9))


def test_coarse_spaces(spark):
    entries, owner = lattice_system(spark, 7, (1, 1))
    interp = coarse.coarse_geometric(q.ids(spark, 49), (7, 7), (3, 3))
    total = {r.i: r.w for r in interp.groupBy("i").agg(F.sum("weight").alias("w")).collect()}
    assert total[3 * 7 + 3] == pytest.approx(1.0)
    a0 = coarse.galerkin(entries, coarse.coarse_aggregate(owner)).collect()
    assert [(r.c, r.d, r.a) for r in a0] == [(0, 0, pytest.approx(49 * 4 - 2 * 84))]


def test_handshake():
    h = CoarseHandshake(2)
    assert h.try_post(0) and not h.try_post(0) and not h.try_solve()
    assert h.try_post(1) and h.try_solve() and h.try_consume(0) and not h.try_consume(0)
    assert h.try_post(0) and h.try_post(1) and h.try_solve() and h.lost == 1
    strict = CoarseHandshake(1, strict=True)
    assert strict.try_post(0) and strict.try_solve() and not strict.try_post(0)
    s = AdaptiveSleep(pause=0.01)
    for _ in range(40):
        s.poll(True)
    assert s.pause < 0.01
    for _ in range(2000):
        s.poll(False)
    assert s.pause > 0.01


def test_mailbox(tmp_path):
    assert len(all_options()) == 16 and len({o.name for o in all_options()}) == 16
    for o in all_options():
        w = Window(tmp_path / o.name / "x.bin", 5, o)
        w.put(np.arange(5.0))
        w.complete_one()
        w.complete()
        assert w.get().tolist() == [0, 1, 2, 3, 4]
    assert torn(np.array([1.0, 2.0])) and not torn(np.ones(4))
    assert len(torus_neighbors(4, 4, 4)) == 1664


def test_live_run_solves(spark):
    n = 7
    entries, owner = lattice_system(spark, n, (2, 2))
    trace = engine.run_live(Sys(entries, mesh.sine_load(spark, 2, n), owner, 4), Config(tol=1e-9, timeout_s=60, max_iter=20_000), tasks=2, delay={0: 0.002}, option=Option(kind="atomic")).cache()
    h = math.pi / (n + 1)
    scale = h * h / (4 * math.sin(h / 2) ** 2)
    for i, x in engine.solution_of(trace).collect():
        assert x == pytest.approx(scale * math.sin(h * (i // n + 1)) * math.sin(h * (i % n + 1)), abs=1e-6)


def test_components(spark):
    edges = [(k, k + 1) for k in range(40)] + [(100, 101), (101, 100), (200, 200)] + [(500, k) for k in range(501, 560)]
    found = {r.node: r.component for r in connected_components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert {found[k] for k in range(41)} == {0} and found[101] == 100 and 200 not in found and {found[k] for k in range(500, 560)} == {500}


def test_experiments_reproduce_who_wins(spark):
    """Synchronous runs win with 4 parts, asynchronous ones from 16 on, and under imbalance by more; histograms are of real counts."""
    few = experiments.Sizes(repeats=2, parts=(4, 16), side=23)
    trace, runs = experiments.one_level_strong(spark, few)
    wins = {r.P: r.async_wins for r in experiments.winners(runs).collect()}
    assert wins == {4: False, 16: True}
    rows = {(r.P, r["mode"], r.seed): r for r in runs.collect()}
    assert len(rows) == 8
    assert all(r.rho == pytest.approx((r.r_final / r.r0) ** (1 / r.iters_max), rel=0.2) for k, r in rows.items() if k[1] == "sync")
    assert all(r.r_seen < 1e-8 for r in rows.values())
    assert experiments.histogram(trace, 10).agg(F.sum("parts")).first()[0] == 2 * (4 + 16)
    assert {r.runs for r in experiments.mean_of_runs(runs).collect()} == {2}


def test_sync_simulation_equals_supersteps(spark):
    sys = experiments.poisson(spark, 2, 11, 4, 1.0, 3)
    from overlapsolve.operators.local import Block

    run = bsp.Supersteps(sys, Config(tol=1e-6))
    blocks = [Block.of(r.asDict()) for r in run.blocks.orderBy("p").collect()]
    solve = [solvers.factor(b.indptr, b.indices, b.data) for b in blocks]
    found = simulate.run_sync(blocks, solve, simulate.Costs(), Config(tol=1e-6), run.coarse, run.coarse.n)
    want = bsp.ras2_sync(experiments.poisson(spark, 2, 11, 4, 1.0, 3), exact=found.iterations[0])
    assert found.r_final == pytest.approx(bsp.true_norm(sys, want.u), rel=1e-6)


def test_lattice_multigrid_converges():
    for shape in ((15, 15), (9, 7, 5)):
        n = int(np.prod(shape))
        a = np.zeros((n, n))
        for i in np.ndindex(*shape):
            at = np.ravel_multi_index(i, shape)
            a[at, at] = 2.0 * len(shape)
            for k in range(len(shape)):
                j = list(i)
                j[k] += 1
                if j[k] < shape[k]:
                    to = np.ravel_multi_index(j, shape)
                    a[at, to] = a[to, at] = -1.0
        rows, cols = np.nonzero(a)
        csr = solvers.to_csr(n, rows, cols, a[rows, cols])
        r = np.random.default_rng(0).normal(size=n)
        exact = np.linalg.solve(a, r)
        one = solvers.LatticeMultigrid(*csr, shape).solve(r)
        many = solvers.LatticeMultigrid(*csr, shape, cycles=12).solve(r)
        assert np.linalg.norm(one - exact) < 0.35 * np.linalg.norm(exact) and np.linalg.norm(many - exact) < 1e-5 * np.linalg.norm(exact)


def test_far_rows_of_an_m_matrix_are_reached(spark):
    assert metrics.is_m_matrix(mesh.stencil_entries(spark, (40,), 2.0))


@pytest.mark.parametrize("wrong", [lambda s: bsp.gmres(q.micro(s), precond="nothing"), lambda s: bsp.ras2_sync(q.micro(s, True), Config(coarse="odd"))])
def test_unknown_names_are_refused(spark, wrong):
    with pytest.raises(ValueError):
        wrong(spark)


def test_components_of_a_long_shuffled_path(spark):
    from overlapsolve.operators.components import connected_components

    place = lambda c: F.pmod(c * F.lit(7919), F.lit(20011))
    edges = spark.range(19_999).select(place(F.col("id")).alias("u"), place(F.col("id") + 1).alias("v"))
    found = connected_components(edges)
    assert found.count() == 20_000
    assert [r[0] for r in found.select("component").distinct().collect()] == [0]


@pytest.mark.parametrize("options", [{"dedicated": True, "tasks": 2}, {"sync": True, "tasks": 2}, {"progress": "inline", "tasks": 2}, {"progress": "thread", "tasks": 2}, {"progress": "dedicated", "dedicated": True, "tasks": 2}])
def test_two_level_live_runs_are_confirmed(spark, options):
    sys = experiments.poisson(spark, 2, 9, 4, 1.0, 3)
    trace, u, norm = engine.run_confirmed(sys, Config(tol=1e-8, timeout_s=30, max_iter=5000), **options)
    assert norm < 1e-8 and u.count() == 81
    rows = trace.collect()
    assert len(rows) == 4 and all(r.coarse_solves > 0 for r in rows)


def test_exchange_on_a_torus(spark):
    """64 ranks, all options: what is locked exclusively, published atomically or received is never inconsistent."""
    found = {r.option: r for r in engine.comm_bench(spark, tasks=3, reps=5, width=64).collect()}
    assert len(found) == 16 and all(r.reads == 1664 * 5 for r in found.values())
    assert all(found[o].inconsistent == 0 for o in found if o.startswith("exclusive") or o in ("atomic", "two_sided"))


def test_streams_equal_tables(spark, tmp_path):
    from overlapsolve.streaming import engine as stream

    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet")
    events.write.parquet(str(tmp_path / "events"))
    live = spark.readStream.schema(events.schema).parquet(str(tmp_path / "events"))
    query = stream.hourly(live, "60 days").writeStream.format("memory").queryName("hourly").outputMode("complete").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "c")).start()
    query.awaitTermination(60)
    got = {r.hour: round(r.x, 6) for r in spark.table("hourly").collect()}
    assert got == {r.hour: round(r.x, 6) for r in stream.hourly(events).collect()}


def test_streaming_solver(spark):
    from overlapsolve.streaming import engine as stream

    u, history = stream.run_streaming(q.micro(spark), Config(tol=1e-4, timeout_s=90))
    assert xs(u) == pytest.approx([3, 5, 6, 6, 5, 3], abs=1e-3) and history.count() > 4


def test_replay_refuses_what_it_no_longer_keeps(spark):
    ticks = spark.createDataFrame([(40, 0)], "n long, p int")
    stamps = spark.createDataFrame([(40, 0, 1, 0)], "n long, p int, q int, tau long")
    with pytest.raises(ValueError):
        replay.replay(q.micro(spark), ticks, stamps)


def test_replay_keeps_only_the_frames_that_later_ticks_name(spark):
    from overlapsolve.session import scratch

    ticks, stamps = replay.make_schedule(spark, 2, 24, "random")
    folders = lambda: len(list(Path(scratch(spark).removeprefix("file:")).iterdir()))
    run = replay.Replay(q.micro(spark))
    before = folders()
    assert xs(run.solve(ticks, stamps)) == pytest.approx([3, 5, 6, 6, 5, 3], abs=0.1)
    assert folders() - before <= 2


def test_torn_replay_takes_each_value_from_its_own_tick():
    dated = {(1, 3): np.array([1.0, 2.0]), (1, 4): np.array([5.0, 6.0]), (2, 4): np.array([7.0])}
    seen = replay._seen([(1, 0, 4), (1, 1, 3), (1, 9, 3), (2, -1, 4), (3, -1, 4)], dated)
    assert seen[1].tolist() == [5.0, 2.0] and seen[2].tolist() == [7.0] and sorted(seen) == [1, 2]
