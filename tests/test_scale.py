"""Solves at the sizes of larger tables: leaves first, stops at what rounding leaves, and only the tables that a system needs."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from overlapsolve import experiments
from overlapsolve import queries as q
from overlapsolve.functions import solvers
from overlapsolve.plans import bsp
from overlapsolve.sources import problems
from overlapsolve.system import Config, Sys


def laplacian(n, i, j, v=None):
    a = np.zeros((n, n))
    np.add.at(a, (i, j), -1.0)
    np.add.at(a, (j, i), -1.0 if v is None else -v)
    a += np.diag(1.0 - a.sum(axis=1))
    rows, cols = np.nonzero(a)
    return a, solvers.to_csr(n, rows, cols, a[rows, cols])


@pytest.mark.parametrize("kind", ["hub", "chain", "random", "uneven", "rings"])
def test_leaves_are_eliminated_exactly(kind):
    rng, n = np.random.default_rng(3), 1600
    i = np.arange(1, n)
    j = {"hub": np.zeros(n - 1, int), "chain": i - 1}.get(kind, rng.integers(0, i))
    if kind == "rings":
        i, j = np.append(i, rng.integers(0, n, 20)), np.append(j, rng.integers(0, n, 20))
    a, csr = laplacian(n, i, j, rng.random(len(i)) if kind == "uneven" else None)
    r = rng.normal(size=n)
    solver = solvers.factor(*csr)
    assert solver.solve(r) == pytest.approx(np.linalg.solve(a, r), abs=1e-11)
    assert solver.size < 1 << 20  # the band of the hub took 20 MB


def test_wide_symmetric_blocks_are_solved_to_rounding(monkeypatch):
    monkeypatch.setattr(solvers, "BAND_BYTES", 1 << 20)
    rng, n = np.random.default_rng(4), 1700
    a, csr = laplacian(n, rng.integers(0, n, 4 * n), rng.integers(0, n, 4 * n))
    r = rng.normal(size=n)
    solver = solvers.factor(*csr)
    assert isinstance(solver.rest, solvers.ExactCG) and solver.solve(r) == pytest.approx(np.linalg.solve(a, r), abs=1e-11)


def test_large_loads_stop_where_rounding_does(spark):
    """A tolerance below what rounding leaves was iterated for until max_iter."""
    small = q.micro(spark)
    sys = Sys(small.entries, small.rhs.select("i", (F.col("x") * 1e9).alias("x")), small.owner, 2)
    cfg = Config(tol=1e-11, max_iter=200, checkpoint_every=20)
    for found in (bsp.ras_sync(sys, cfg), bsp.gmres(sys, cfg)):
        assert found.converged and found.iterations < 200
        assert [r[1] for r in sorted(found.u.collect())] == pytest.approx([3e9, 5e9, 6e9, 6e9, 5e9, 3e9], rel=1e-13)


def test_a_system_reads_its_own_tables_only(spark, tmp_path):
    (tmp_path / "conversations.parquet").symlink_to("/root/testdata/sf0.001/conversations.parquet")
    assert experiments.table_systems(spark, str(tmp_path))["chats"]().parts == 4


def test_nearest_vectors_equal_brute_force(spark, tmp_path):
    """Ties, null components and unequal lengths included; pairs are no rows any more."""
    rng = np.random.default_rng(5)
    rows = [(k, v.tolist(), 0) for k, v in enumerate(rng.integers(-2, 3, (200, 6)).astype(float))] + [(200, [1.0, None, 0.0, 0.0, 0.0, 0.0], 0), (201, [1.0, 1.0], 0), (202, None, 0)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(str(tmp_path / "embeddings.parquet"))
    entries = problems.knn(spark, str(tmp_path))[0]
    vectors = {k: v for k, v, _ in rows if v is not None}
    cell = {k: sum(1 << b for b in range(3) if b < len(v) and (v[b] or 0) > 0) for k, v in vectors.items()}
    want = set()
    for a, v in vectors.items():
        near = []
        for b, w in vectors.items():
            if a != b and (cell[a] ^ cell[b]).bit_count() < 2:
                none = len(v) != len(w) or None in v or None in w
                near.append((none, 0.0 if none else -sum(x * y for x, y in zip(v, w, strict=True)), b))
        want |= {(min(a, b), max(a, b)) for _, _, b in sorted(near)[:8]}
    assert {(r.i, r.j) for r in entries.collect() if r.i < r.j} == want
    assert "zip_with" not in entries._jdf.queryExecution().toString()


def test_nodes_with_few_neighbours_are_eliminated_exactly():
    """Nodes between hubs, each tied to two or three of them, some unevenly: the band of what was left held most of the matrix."""
    rng, hubs, n = np.random.default_rng(6), 40, 1900
    i = np.concatenate([np.arange(hubs, n), np.arange(hubs, n), np.arange(hubs, n, 3), np.arange(hubs + 1, n, 50)])
    j = np.concatenate([rng.integers(0, 20, n - hubs), rng.integers(20, 39, n - hubs), np.full(len(range(hubs, n, 3)), 39), np.arange(hubs, n - 1, 50)])
    for v in (None, rng.random(len(i))):
        a, csr = laplacian(n, i, j, v)
        r = rng.normal(size=n)
        solver = solvers.factor(*csr)
        assert solver.solve(r) == pytest.approx(np.linalg.solve(a, r), abs=1e-11)
        assert solver.size < 1 << 20
        assert len(solver.core) > solvers.DENSE and len(solver.left) < 100  # the hubs and nodes with four neighbours


def test_nodes_without_a_core_are_eliminated_exactly():
    """Rings: nothing is left over. Some couplings go one way only."""
    n = 1800
    i = np.arange(n)
    j = i // 6 * 6 + (i + 1) % 6
    a, csr = laplacian(n, i, j, np.where(i % 7 == 0, 0.0, 1.0))
    r = np.random.default_rng(7).normal(size=n)
    solver = solvers.factor(*csr)
    assert not len(solver.left) and solver.rest is None
    assert solver.solve(r) == pytest.approx(np.linalg.solve(a, r), abs=1e-11)


def test_windows_of_documents_are_hashed_once(spark, tmp_path):
    """The ties are those of the hashes of lists of words; nothing that reads them hashes a text again."""
    rng = np.random.default_rng(8)
    texts = [" ".join(rng.choice(["a", "B", "c\n", "é"], rng.integers(0, 12))) for _ in range(150)] + [None, "", "one two three", "one two three", "one two three four five", "five " * 40, "five " * 50]
    rows = [(k, t) for k, t in enumerate(texts)]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(0, 1), (3, 0)], "doc_id long, quality int").write.parquet(str(tmp_path / "labels.parquet"))
    entries, f = problems.docgraph(spark, str(tmp_path))
    assert "xxhash64" not in entries._jdf.queryExecution().toString() + f._jdf.queryExecution().toString()

    words = spark.createDataFrame(rows, "i long, t string").select("i", F.split(F.lower(F.coalesce("t", F.lit(""))), r"\s+").alias("w"))
    hashes = words.selectExpr("i", "transform(sequence(0, greatest(size(w) - 5, 0)), k -> xxhash64(slice(w, k + 1, 5))) h")
    held = {}
    for r in hashes.collect():
        for h in sorted(set(r.h))[:4]:
            held.setdefault(h, []).append(r.i)
    want = {}
    for k in held.values():
        for v in set(k) - {min(k)}:
            want[min(k), v] = want.get((min(k), v), 0.0) + 1.0
    got = {(r.i, r.j): -r.a for r in entries.collect() if r.i < r.j}
    assert len(want) > 20 and got == {k: v for k, v in want.items() if not {0, 3} & {*k}}
