"""The engine's queries over the given tables: setup, single steps, whole solves, schedules and reports."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from overlapsolve import experiments
from overlapsolve.functions import metrics
from overlapsolve.live import engine
from overlapsolve.live.mailbox import Option
from overlapsolve.operators import coarse as coarse_ops
from overlapsolve.operators import local, overlap, partition
from overlapsolve.plans import bsp, convergence, replay
from overlapsolve.session import checkpoint
from overlapsolve.sources import mesh, problems
from overlapsolve.streaming import engine as stream
from overlapsolve.system import Config, Sys

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
GRID = (problems.WEEKS, problems.QUANTITIES)
TIGHT = Config(tol=1e-11, max_iter=400, checkpoint_every=6)


def query(f: Query) -> Query:
    QUERIES[f.__name__] = f
    return f


def rounded(x: Column | str, digits: int = 4) -> Column:
    return F.round(x, digits) + F.lit(0.0)


def ids(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n).select(F.col("id").alias("i"))


# Setup.

query(problems.grid2d_rhs)
query(problems.grid3d_rhs)


@query
def chain_rhs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return problems.chain_rhs(spark, sf_dir).select("i", rounded("x").alias("x"))


@query
def tree_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return problems.tree_nodes(spark, sf_dir).select("i", "parent", "nation", rounded("f", 6).alias("f"))


query(problems.page_links)
query(problems.chat_edges)


@query
def grid2d_entries(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cell_entries(spark, sf_dir)


@query
def p1_assembly_2d(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mesh.assemble_p1(spark, 2, 15).select("i", "j", rounded("a", 9).alias("a"))


@query
def p1_assembly_3d(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mesh.assemble_p1(spark, 3, 7).select("i", "j", rounded(F.col("a") * 8, 9).alias("a"))


@query
def tree_entries(spark: SparkSession, sf_dir: str) -> DataFrame:
    return problems.startree(spark, sf_dir)[0]


@query
def galerkin_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    entries, _, owner = problems.startree(spark, sf_dir)
    return coarse_ops.galerkin(entries, coarse_ops.coarse_aggregate(owner))


@query
def upwind_entries(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mesh.convection_diffusion(spark, 2, 15, (8.0, -4.0)).select("i", "j", rounded("a", 9).alias("a"))


@query
def m_matrix_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The premise holds for the lattice and for upwind differences; with a strong wind central differences lose it."""
    cases = {"lattice": mesh.stencil_entries(spark, (15, 15), 4.0), "upwind": mesh.convection_diffusion(spark, 2, 15, (200.0, 0.0)), "central": mesh.convection_diffusion(spark, 2, 15, (200.0, 0.0), upwind=False)}
    return spark.createDataFrame([(k, metrics.is_m_matrix(v)) for k, v in cases.items()], "problem string, m_matrix boolean")


# Decomposition of the week and quantity grid into four slices.


def grid_parts(spark: SparkSession, parts: int = 4) -> DataFrame:
    return partition.partition_box(ids(spark, math.prod(GRID)), GRID, (parts, 1))


def cell_entries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The grid's matrix on the cells that lineitem has rows in; the others are boundary."""
    cells = problems.grid2d_cells(spark, sf_dir)
    inner = mesh.stencil_entries(spark, GRID, 5.0).join(cells, "i", "left_semi")
    return inner.join(cells.select(F.col("i").alias("j")), "j", "left_semi").select("i", "j", "a")


def cell_member(spark: SparkSession, sf_dir: str, delta: int = 1) -> tuple[DataFrame, DataFrame]:
    entries = checkpoint(cell_entries(spark, sf_dir))
    return overlap.decompose(partition.partition_box(entries.where("i = j").select("i"), GRID, (4, 1)), entries, delta), entries


def grid_member(spark: SparkSession, delta: int = 1) -> tuple[DataFrame, DataFrame]:
    entries = mesh.stencil_entries(spark, GRID, 5.0)
    return overlap.decompose(grid_parts(spark), entries, delta), entries


@query
def box_owner(spark: SparkSession, sf_dir: str) -> DataFrame:
    return partition.partition_box(problems.grid2d_cells(spark, sf_dir), GRID, (4, 2))


@query
def key_owner(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = problems.load_table(spark, sf_dir, "customer")
    return partition.partition_key(c.select(F.col("c_custkey").alias("i"), "c_mktsegment"), "c_mktsegment")


@query
def imbalanced_owner(spark: SparkSession, sf_dir: str) -> DataFrame:
    owner = partition.partition_imbalanced(problems.grid2d_cells(spark, sf_dir), GRID, 4)
    return owner.groupBy("p").agg(F.count("*").alias("nodes"))


@query
def overlap_member(spark: SparkSession, sf_dir: str) -> DataFrame:
    m, _ = cell_member(spark, sf_dir)
    return m.select("p", "i", "slot", "layer")


@query
def surface_set(spark: SparkSession, sf_dir: str) -> DataFrame:
    m, _ = grid_member(spark)
    return m.where("surface").select("p", "i")


@query
def owned_mask(spark: SparkSession, sf_dir: str) -> DataFrame:
    m, _ = cell_member(spark, sf_dir)
    return m.select("p", "i", "owned")


@query
def partition_of_unity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """No violations: the result is empty."""
    m, entries = cell_member(spark, sf_dir)
    return overlap.check_decomposition(m, entries)


@query
def routes_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    m, _ = grid_member(spark)
    return overlap.routes(m).groupBy("src", "dst").agg(F.count("*").alias("shared"))


@query
def partition_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    m, _ = cell_member(spark, sf_dir, 2)
    return overlap.partition_stats(m)


@query
def graph_partition_cover(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Grown regions own each node once, whatever their shape."""
    edges = mesh.stencil_entries(spark, (24, 24), 4.0).where("i < j").select(F.col("i").alias("u"), F.col("j").alias("v"), F.lit(1.0).alias("w"))
    owner = partition.partition_graph(edges, 4)
    return owner.agg(F.count("*").alias("nodes"), F.count_distinct("i").alias("distinct_nodes"), F.count_distinct("p").alias("parts"))


@query
def geometric_members(spark: SparkSession, sf_dir: str) -> DataFrame:
    return partition.geometric_members(problems.grid2d_cells(spark, sf_dir), GRID, (4, 2), 2).groupBy("p").agg(F.count("*").alias("nodes"))


@query
def overlap_growth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nodes in all sets over nodes, for a local grid and for the hub graph that isn't local."""
    m, _ = grid_member(spark)
    hub, _ = problems.cosupply(spark, sf_dir)
    owner = hub.select("i").distinct().select("i", F.pmod(F.floor(F.col("i") / 2), F.lit(8)).cast("int").alias("p"))
    grown = overlap.grow_overlap(owner, hub)
    ratio = lambda df, name: df.agg(F.lit(name).alias("problem"), F.count("*").alias("members"), F.count_distinct("i").alias("nodes"))
    return ratio(m, "grid").union(ratio(grown, "hubs"))


# Single steps from a fixed iterate.


def step_inputs(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    m, entries = grid_member(spark)
    w = m.select("p", "i", ((F.pmod("i", F.lit(7)) + F.col("p") + 1) / F.lit(8.0)).alias("x"))
    return m, entries, w, problems.grid2d_rhs(spark, sf_dir)


@query
def local_residual_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    m, entries, w, f = step_inputs(spark, sf_dir)
    return local.local_residual(entries, m, w, f)


@query
def accumulated_residual_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    m, entries, w, f = step_inputs(spark, sf_dir)
    return local.accumulate(local.local_residual(entries, m, w, f), m)


@query
def residual_norm_local(spark: SparkSession, sf_dir: str) -> DataFrame:
    m, entries, w, f = step_inputs(spark, sf_dir)
    r = local.accumulate(local.local_residual(entries, m, w, f), m)
    return local.residual_norm(r, m).select(rounded("norm").alias("norm"))


@query
def coarse_rhs_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    m, entries, w, f = step_inputs(spark, sf_dir)
    interp = coarse_ops.coarse_aggregate(grid_parts(spark))
    return coarse_ops.coarse_rhs(local.local_residual(entries, m, w, f), interp)


@query
def coarse_geometric_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    interp = coarse_ops.coarse_geometric(problems.grid2d_cells(spark, sf_dir), GRID, (178, 16))
    return interp.select("i", "c", rounded("weight", 9).alias("weight"))


# The micro-fixture: six nodes in a line.


def micro(spark: SparkSession, coarse: bool = False) -> Sys:
    owner = ids(spark, 6).select("i", F.floor(F.col("i") / 3).cast("int").alias("p"))
    load = ids(spark, 6).select("i", F.lit(1.0).alias("x"))
    return Sys(mesh.stencil_entries(spark, (6,), 2.0), load, owner, 2, interp=coarse_ops.coarse_aggregate(owner) if coarse else None)


def shown(u: DataFrame, digits: int = 4) -> DataFrame:
    return u.select("i", rounded("x", digits).alias("x"))


@query
def ras_micro_k3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(bsp.ras_sync(micro(spark), exact=3).u, 9)


@query
def ras_micro_communicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(bsp.ras_sync(micro(spark), exact=3, communicate_update=True).u, 9)


@query
def ras2_micro_k3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(bsp.ras2_sync(micro(spark, True), exact=3).u, 9)


@query
def ras2_mult_micro_k2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(bsp.ras2_mult_sync(micro(spark, True), exact=2).u, 9)


@query
def as_micro_k2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(bsp.as_sync(micro(spark), exact=2).u, 9)


@query
def async_replay_micro(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Part 0, then part 1 with the fresh slab, and the same with the stale one."""
    ticks = spark.createDataFrame([(1, 0), (2, 1)], "n long, p int")
    out = []
    for name, tau in (("fresh", 1), ("stale", 0)):
        stamps = spark.createDataFrame([(1, 0, 1, 0), (2, 1, 0, tau)], "n long, p int, q int, tau long")
        out.append(replay.replay(micro(spark), ticks, stamps).select(F.lit(name).alias("run"), "i", rounded("x", 9).alias("x")))
    return out[0].union(out[1])


# Converged solves.


def chain(spark: SparkSession, sf_dir: str, parts: int = 4, coarse: bool = False) -> Sys:
    entries, f = problems.eventchain(spark, sf_dir)
    owner = partition.partition_box(ids(spark, problems.HOURS), (problems.HOURS,), (parts,))
    return Sys(entries, f, owner, parts, interp=coarse_ops.coarse_aggregate(owner) if coarse else None)


@query
def ras_chain_solution(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(bsp.ras_sync(chain(spark, sf_dir), TIGHT).u)


@query
def ras2_chain_solution(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(bsp.ras2_sync(chain(spark, sf_dir, coarse=True), TIGHT).u)


@query
def ras2_mult_chain_solution(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(bsp.ras2_mult_sync(chain(spark, sf_dir, coarse=True), TIGHT).u)


@query
def async_chain_solution(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(replay.replay(chain(spark, sf_dir), *replay.make_schedule(spark, 4, 48, "random")))


@query
def point_relaxation_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The earliest scheme: all single nodes relaxed at once, 16 times."""
    entries, f = problems.eventchain(spark, sf_dir)
    return shown(bsp.chaotic_relaxation(entries, f, 16))


@query
def chaotic_relaxation_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Odd and even nodes take turns, 24 times."""
    entries, f = problems.eventchain(spark, sf_dir)
    return shown(bsp.chaotic_relaxation(entries, f, 24, lambda n: F.pmod(F.col("i"), F.lit(2)) == n % 2))


@query
def block_jacobi_chain_solution(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(bsp.block_jacobi(chain(spark, sf_dir), 16))


def tree(spark: SparkSession, sf_dir: str, coarse: bool = False) -> Sys:
    entries, f, owner = problems.startree(spark, sf_dir)
    return Sys(entries, f, owner, 25, interp=coarse_ops.coarse_aggregate(owner) if coarse else None)


@query
def ras_tree_solution(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(bsp.ras_sync(tree(spark, sf_dir), TIGHT).u)


@query
def ras2_tree_solution(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(bsp.ras2_sync(tree(spark, sf_dir, True), TIGHT).u)


@query
def async2_tree_solution(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(replay.replay(tree(spark, sf_dir, True), *replay.make_schedule(spark, 25, 80, "random"), cfg=TIGHT))


def grid(spark: SparkSession, sf_dir: str, parts: int = 16, coarse: bool = False) -> Sys:
    entries, f = problems.shipgrid2d(spark, sf_dir)
    owner = grid_parts(spark, parts)
    return Sys(entries, f, owner, parts, interp=coarse_ops.coarse_aggregate(owner) if coarse else None)


@query
def ras_grid2d_solution(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(bsp.ras_sync(grid(spark, sf_dir), TIGHT).u)


@query
def ras2_grid2d_solution(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(bsp.ras2_sync(grid(spark, sf_dir, coarse=True), TIGHT).u)


@query
def gmres_grid2d_solution(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(bsp.gmres(grid(spark, sf_dir, 8), TIGHT).u)


def sines(spark: SparkSession, d: int, n: int, boxes: tuple[int, ...], coarse: tuple[int, ...] | None = None) -> Sys:
    shape, nodes = (n,) * d, ids(spark, n**d)
    owner = partition.partition_box(nodes, shape, boxes)
    interp = coarse_ops.coarse_geometric(nodes, shape, coarse) if coarse else None
    return Sys(mesh.stencil_entries(spark, shape, 2.0 * d), mesh.sine_load(spark, d, n), owner, math.prod(boxes), interp=interp)


@query
def poisson2d_solution(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(bsp.gmres(sines(spark, 2, 31, (2, 2), (7, 7)), TIGHT, "ras2").u, 6)


@query
def poisson3d_solution(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Local solves by incomplete-factorisation conjugate gradients, to a tenth of the residual."""
    cfg = Config(tol=1e-10, max_iter=300, solver="cg_ic", checkpoint_every=6)
    return shown(bsp.ras2_sync(sines(spark, 3, 9, (2, 2, 2), (2, 2, 2)), cfg).u, 6)


@query
def poisson_error_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The discretisation error falls by four for each halving of the spacing."""
    out = None
    for n in (7, 15):
        u = bsp.gmres(sines(spark, 2, n, (2, 1)), TIGHT).u
        row = metrics.error_norms(u, 2, n).select(F.lit(n).alias("n"), rounded("max_error", 6).alias("max_error"))
        out = row if out is None else out.union(row)
    return out


# Schedules, measures and reports.


@query
def schedule_audit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Only the schedule that starves a part is found out."""
    out = None
    for kind in replay.KINDS:
        found = replay.audit_schedule(*replay.make_schedule(spark, 4, 40, kind), 4).groupBy("rule").agg(F.count("*").alias("violations"))
        found = found.select(F.lit(kind).alias("kind"), "rule", "violations")
        out = found if out is None else out.union(found)
    return out


@query
def torus_neighbors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(rank, neighbour) on the periodic 4 x 4 x 4 grid, in DataFrame form."""
    r = ids(spark, 64)
    steps = F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.lit(c).alias("c")) for a in (-1, 0, 1) for b in (-1, 0, 1) for c in (-1, 0, 1) if (a, b, c) != (0, 0, 0)])
    e = r.select("i", F.explode(steps).alias("s"))
    turn = lambda k, s: F.pmod(mesh.axis(F.col("i"), (4, 4, 4), k) + F.col(f"s.{s}"), F.lit(4))
    return e.select(F.col("i").alias("rank"), (turn(0, "a") * 16 + turn(1, "b") * 4 + turn(2, "c")).cast("long").alias("neighbour"))


@query
def contraction_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both contraction factors agree for a synchronous run; doubling the synchronous step time squares the second. A user's events stand in for a run: norms fall from the largest to the smallest value."""
    e = problems.load_table(spark, sf_dir, "events").where("value > 0").groupBy("user_id")
    runs = e.agg(F.max("value").alias("r0"), F.min("value").alias("rf"), F.count("*").alias("k")).withColumn("seconds", F.col("k") / F.lit(10.0))
    cases = F.explode(F.array(*[F.struct(F.lit(run).alias("run"), F.lit(tau).alias("tau")) for run, tau in (("sync", 0.1), ("doubled", 0.2))])).alias("case")
    return runs.select("*", cases).select("*", "case.*").select("user_id", "run", rounded(metrics.contraction(F.col("r0"), F.col("rf"), F.col("k")), 9).alias("per_iteration"), rounded(metrics.contraction_time(F.col("r0"), F.col("rf"), F.col("seconds"), F.col("tau")), 9).alias("per_time"))


@query
def iteration_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Local iterations by user stand in for those by part: a trace of the events table, in bins of 10."""
    e = problems.load_table(spark, sf_dir, "events").select(F.lit("events").alias("run_id"), F.col("user_id").alias("p"))
    return metrics.iteration_histogram(e, 10)


def few(**more) -> experiments.Sizes:
    return experiments.Sizes(**{"repeats": 2, **more})


@query
def one_level_strong_winners(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Balanced one-level runs on a simulated clock: synchronous ones win with few parts, asynchronous ones with many."""
    return experiments.winners(experiments.one_level_strong(spark, few())[1])


@query
def one_level_imbalanced_winners(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One part half as large again: the asynchronous runs win from fewer parts on or by more."""
    return experiments.winners(experiments.one_level_strong(spark, few(), 1.5)[1])


@query
def crossover_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """From how many parts on the asynchronous runs win, balanced and not, over the runs just made."""
    runs = experiments.one_level_strong(spark, few())[1].unionByName(experiments.one_level_strong(spark, few(), 1.5)[1])
    return metrics.crossover(runs.select("workload", "mode", "P", "seconds"))


@query
def two_level_weak_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both modes reach the tolerance; the synchronous one needs about as many iterations at each size."""
    runs = experiments.two_level_weak(spark, few(weak=((15, 4, 3), (31, 16, 7))))[1]
    return runs.groupBy("workload", "P", "mode").agg((F.max("r_final") < 2e-8).alias("reached"), (F.max("iters_max") <= 150).alias("few_iterations"))


@query
def two_level_imbalanced_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    runs = experiments.two_level_weak(spark, few(weak=((15, 4, 3), (31, 16, 7))), 1.5)[1]
    return runs.groupBy("workload", "P", "mode").agg((F.max("r_final") < 2e-8).alias("reached"))


@query
def two_level_strong_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    runs = experiments.two_level_strong(spark, few(parts=(4, 16)))[1]
    return runs.groupBy("workload", "P", "mode").agg((F.max("r_final") < 2e-8).alias("reached"))


@query
def two_level_cube_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Iterative local solves and a multigrid coarse solve reach the tolerance too."""
    runs = experiments.two_level_cube(spark, few(cube=((7, 8, 3),)))[1]
    return runs.groupBy("workload", "P", "mode").agg((F.max("r_final") < 2e-8).alias("reached"))


@query
def convection_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The master sums what parts last sent, so an asynchronous run may end a little above its tolerance of 1e-8."""
    runs = experiments.convection(spark, few(side=15))[1]
    return runs.groupBy("workload", "P", "mode").agg((F.max("r_final") < 1e-7).alias("reached"))


@query
def local_iterations_vary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Asynchronous parts make different numbers of local iterations, synchronous ones the same."""
    trace = experiments.one_level_strong(spark, few(parts=(4, 16)))[0]
    return trace.groupBy("P", "mode").agg((F.count_distinct("iterations") > 1).alias("differ"))


@query
def krylov_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """GMRES on the geometric and on the spectral coarse space: both converge, in few iterations."""
    runs = experiments.krylov(spark, 2, cases=((15, 4, 3),))[1]
    return runs.select("mode", "P", (F.col("r_final") < 1e-8).alias("converged"), (F.col("iterations") <= 30).alias("few_iterations"))


def table_solution(name: str, digits: int = 4) -> Query:
    return lambda spark, sf_dir: shown(bsp.ras_sync(experiments.table_systems(spark, sf_dir)[name](), TIGHT).u, digits)


QUERIES |= {f"{name}_solution": table_solution(name) for name in ("chats", "documents", "neighbours", "cube")}


@query
def pages_solution(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The values of the pages; those of the addresses they link to are left out, as their numbers are hashes."""
    u = bsp.ras_sync(experiments.table_systems(spark, sf_dir)["pages"](), TIGHT).u
    return u.where(F.pmod("i", F.lit(2)) == 0).select(F.floor(F.col("i") / 2).alias("page_id"), rounded("x").alias("x"))


@query
def stationary_micro(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two steps of the stationary form with each preconditioner."""
    out = None
    for name in ("ras", "as", "ras2", "jacobi"):
        rows = bsp.stationary(micro(spark, True), 2, precond=name).select(F.lit(name).alias("precond"), "i", rounded("x", 9).alias("x"))
        out = rows if out is None else out.union(rows)
    return out


@query
def overlapped_exchange_micro(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(bsp.ras_sync(micro(spark), exact=3, overlap_exchange=True).u, 9)


@query
def gmres_additive_micro(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shown(bsp.gmres(micro(spark), Config(tol=1e-11), "as").u, 6)


@query
def coarse_decomposed_micro(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two steps with the coarse system solved as a decomposed one, shares added on the executors."""
    return shown(bsp.ras2_sync(micro(spark, True), Config(coarse="decomposed", coarse_parts=2, transfer="tree"), exact=2).u, 6)


@query
def detection_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A master that sums the parts' latest norms stops too early here; a confirming residual puts it right. An hour's events are what four groups of users send, its and the next hour's the true norm."""
    tol = 14.0
    e = problems.load_table(spark, sf_dir, "events").select(problems.hour_index(F.col("ts")).cast("int").alias("t"), F.pmod("user_id", F.lit(4)).cast("int").alias("p"), "value")
    sent = checkpoint(e.groupBy("p", "t").agg(F.avg("value").alias("resid_sq")))
    polls = sent.select("t").distinct()
    later = e.select(F.explode(F.array(F.col("t"), F.col("t") - 1)).alias("t"), "p", "value").groupBy("t", "p").agg(F.avg("value").alias("r"))
    true = later.groupBy("t").agg(F.sqrt(F.sum("r")).alias("norm"))
    first = convergence.stop_master(sent, polls, 4, tol).select(F.lit("master").alias("rule"), "t")
    sure = convergence.stop_confirmed(polls, true, tol).select(F.lit("confirmed").alias("rule"), "t")
    return first.union(sure)


@query
def comm_bench_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each exchange option among 64 ranks with 26 neighbours: reads made, and whether the options that guarantee it never showed half a slab.

    A slab holds a rank's events by hour; ranks are groups of users."""
    e = problems.load_table(spark, sf_dir, "events").select(F.pmod("user_id", F.lit(64)).cast("int").alias("rank"), problems.inside(problems.hour_index(F.col("ts")), 0, problems.HOURS, "hour").alias("at"))
    loads = checkpoint(e.where("rank is not null and at is not null").groupBy("rank", "at").agg(F.count("*").alias("n")))
    found = engine.comm_bench(spark, tasks=2, reps=10, width=problems.HOURS, loads=loads).crossJoin(loads.agg(F.sum("n").alias("events")))
    sure = F.col("option").isin("atomic", "two_sided") | F.col("option").startswith("exclusive")
    return found.select("option", "reads", "events", F.when(sure, F.col("inconsistent") == 0).alias("whole"))


@query
def live_two_level_solution(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Free-running tasks with a coarse solver in a task of its own, confirmed by the norm from the whole matrix."""
    return shown(engine.run_confirmed(experiments.poisson(spark, 2, 15, 4, 1.0, 3), Config(tol=1e-10, timeout_s=60, max_iter=20_000), tasks=2, dedicated=True)[1])


@query
def live_async_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The chain solved by free-running tasks; every part stops below the tolerance."""
    trace = engine.run_live(chain(spark, sf_dir), Config(tol=1e-8, timeout_s=60, max_iter=20_000), tasks=2, option=Option(kind="atomic"))
    return trace.select("p", "converged", (F.col("iterations") > 1).alias("iterated"))


@query
def streaming_micro(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The six nodes solved by a stateful stream."""
    return shown(stream.run_streaming(micro(spark), Config(tol=1e-6))[0])


@query
def hourly_load(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = stream.hourly(problems.load_table(spark, sf_dir, "events"))
    return e.select(problems.hour_index(F.col("hour")).alias("i"), rounded("x").alias("x"))


@query
def sliding_load(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = stream.sliding(problems.load_table(spark, sf_dir, "events"))
    return e.select(problems.hour_index(F.col("start")).alias("i"), rounded("x", 9).alias("x"))


@query
def user_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = stream.sessions(problems.load_table(spark, sf_dir, "events"))
    return e.select("user_id", F.unix_timestamp("start").alias("start"), "events")


def queries() -> dict[str, Query]:
    return dict(QUERIES)
