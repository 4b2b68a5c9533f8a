"""DuckDB SQL for the engine's queries."""

from __future__ import annotations

CALENDAR2 = "CAST(floor(date_diff('day', DATE '1995-01-02', CAST(l_shipdate AS DATE)) / 7.0) AS BIGINT)"

GRID_F = f"""gf AS (
  SELECT n.i, coalesce(c.x, 0.0) AS x FROM (SELECT range AS i FROM range(17850)) n
  LEFT JOIN (SELECT {CALENDAR2} * 50 + CAST(l_quantity AS BIGINT) - 1 AS i, CAST(count(*) AS DOUBLE) AS x FROM lineitem GROUP BY 1) c ON n.i = c.i)"""

GRID_E = """gn AS (SELECT range AS i, range // 50 AS wk, range % 50 AS qt FROM range(17850)),
ge AS (
  SELECT i, i - 50 AS j FROM gn WHERE wk > 0 UNION ALL SELECT i, i + 50 FROM gn WHERE wk < 356
  UNION ALL SELECT i, i - 1 FROM gn WHERE qt > 0 UNION ALL SELECT i, i + 1 FROM gn WHERE qt < 49)"""


#: The same of the cells that lineitem has rows in.
CELLS_E = f"""gn AS (SELECT i, i // 50 AS wk, i % 50 AS qt FROM (SELECT DISTINCT {CALENDAR2} * 50 + CAST(l_quantity AS BIGINT) - 1 AS i FROM lineitem) WHERE i IS NOT NULL),
ge AS (
  SELECT a.i, b.i AS j FROM gn a JOIN gn b ON b.i = a.i - 50 UNION ALL SELECT a.i, b.i FROM gn a JOIN gn b ON b.i = a.i + 50
  UNION ALL SELECT a.i, b.i FROM gn a JOIN gn b ON b.i = a.i - 1 WHERE a.qt > 0 UNION ALL SELECT a.i, b.i FROM gn a JOIN gn b ON b.i = a.i + 1 WHERE a.qt < 49)"""


def members(delta: int, grid: str = GRID_E) -> str:
    layers = ["m0 AS (SELECT CAST(floor(wk * 4 / 357.0) AS INTEGER) AS p, i, 0 AS layer FROM gn)"]
    for k in range(1, delta + 1):
        layers.append(f"m{k} AS (SELECT p, i, min(layer) AS layer FROM (SELECT * FROM m{k - 1} UNION ALL SELECT m.p, e.j, {k} FROM m{k - 1} m JOIN ge e ON e.i = m.i) GROUP BY p, i)")
    return f"""{grid}, {", ".join(layers)},
m AS (SELECT k.p, k.i, k.layer, CAST(row_number() OVER (PARTITION BY k.p ORDER BY k.i) - 1 AS INTEGER) AS slot, (o.p = k.p) AS owned FROM m{delta} k JOIN m0 o ON o.i = k.i),
s AS (SELECT DISTINCT m.p, m.i FROM m JOIN ge e ON e.i = m.i LEFT JOIN m x ON x.p = m.p AND x.i = e.j WHERE x.i IS NULL)"""


STEP = f"""WITH {members(1)}, {GRID_F},
w AS (SELECT p, i, (i % 7 + p + 1) / 8.0 AS x FROM m WHERE owned),
shares AS (
  SELECT p, i, sum(s) AS s FROM (
    SELECT m.p, m.i, gf.x AS s FROM m JOIN gf ON gf.i = m.i WHERE m.owned
    UNION ALL SELECT p, i, -5.0 * x FROM w
    UNION ALL SELECT w.p, e.j, w.x FROM w JOIN ge e ON e.i = w.i)
  GROUP BY p, i)"""

CHAIN_F = """f AS (
  SELECT n.i, coalesce(c.x, 0.0) AS x FROM (SELECT range AS i FROM range(720)) n
  LEFT JOIN (SELECT CAST(floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 3600) AS BIGINT) AS i, sum(value) / 100.0 AS x FROM events GROUP BY 1) c ON n.i = c.i)"""


def chain_jacobi(sweeps: int) -> str:
    return f"""WITH RECURSIVE {CHAIN_F},
it AS (
  SELECT 0 AS k, i, CAST(0 AS DOUBLE) AS x FROM f
  UNION ALL
  SELECT t.k + 1, t.i, (max(f.x) + sum(t.x)) / 3.0
  FROM (SELECT it.k, it.i + d.d AS i, it.x FROM it CROSS JOIN (VALUES (-1), (1)) d(d) WHERE it.k < {sweeps}) t JOIN f ON f.i = t.i
  GROUP BY t.k, t.i)
SELECT i, round(x, 4) + 0.0 AS x FROM it WHERE k = {sweeps}"""


GRID_JACOBI = f"""WITH RECURSIVE {GRID_E}, {GRID_F},
it AS (
  SELECT 0 AS k, i, CAST(0 AS DOUBLE) AS x FROM gf
  UNION ALL
  SELECT it.k + 1, e.i, (max(gf.x) + sum(it.x)) / 5.0
  FROM it JOIN ge e ON e.j = it.i JOIN gf ON gf.i = e.i WHERE it.k < 150 GROUP BY it.k, e.i)
SELECT i, round(x, 4) + 0.0 AS x FROM it WHERE k = 150"""

TREE_NODES = """tn AS (
  SELECT CAST(r_regionkey AS BIGINT) AS i, CAST(NULL AS BIGINT) AS parent, CAST(coalesce(min(n_nationkey), 0) AS INTEGER) AS nation, CAST(0 AS DOUBLE) AS f
  FROM region LEFT JOIN nation ON n_regionkey = r_regionkey GROUP BY r_regionkey
  UNION ALL SELECT 1000 + n_nationkey, n_regionkey, n_nationkey, 0.0 FROM nation
  UNION ALL SELECT 1000000 + c_custkey, 1000 + c_nationkey, c_nationkey, c_acctbal / 1000 FROM customer
  UNION ALL SELECT 1000000000 + o_orderkey, 1000000 + o_custkey, c_nationkey, o_totalprice / 1000 FROM orders JOIN customer ON c_custkey = o_custkey)"""

TREE_E = f"""{TREE_NODES},
ed AS (SELECT i, parent AS j FROM tn WHERE parent IS NOT NULL UNION ALL SELECT parent, i FROM tn WHERE parent IS NOT NULL),
te AS (SELECT i, j, CAST(-1 AS DOUBLE) AS a FROM ed UNION ALL SELECT i, i, CAST(count(*) + 1 AS DOUBLE) FROM ed GROUP BY i)"""

#: Leaves are eliminated into their parents, level by level, and then put back. A node's pivot is its degree + 1 less what its children take.
TREE_SOLUTION = f"""WITH {TREE_NODES},
l3 AS (SELECT i, parent, CAST(2 AS DOUBLE) AS d, f AS b FROM tn WHERE i >= 1000000000),
l2 AS (SELECT t.i, t.parent, 2 + coalesce(c.n, 0) - coalesce(c.p, 0) AS d, t.f + coalesce(c.b, 0) AS b
  FROM tn t LEFT JOIN (SELECT parent, count(*) AS n, sum(1 / d) AS p, sum(b / d) AS b FROM l3 GROUP BY parent) c ON c.parent = t.i WHERE t.i >= 1000000 AND t.i < 1000000000),
l1 AS (SELECT t.i, t.parent, 2 + coalesce(c.n, 0) - coalesce(c.p, 0) AS d, t.f + coalesce(c.b, 0) AS b
  FROM tn t LEFT JOIN (SELECT parent, count(*) AS n, sum(1 / d) AS p, sum(b / d) AS b FROM l2 GROUP BY parent) c ON c.parent = t.i WHERE t.i >= 1000 AND t.i < 1000000),
l0 AS (SELECT t.i, 1 + coalesce(c.n, 0) - coalesce(c.p, 0) AS d, t.f + coalesce(c.b, 0) AS b
  FROM tn t LEFT JOIN (SELECT parent, count(*) AS n, sum(1 / d) AS p, sum(b / d) AS b FROM l1 GROUP BY parent) c ON c.parent = t.i WHERE t.i < 1000),
x0 AS (SELECT i, b / d AS x FROM l0),
x1 AS (SELECT l1.i, (l1.b + x0.x) / l1.d AS x FROM l1 JOIN x0 ON x0.i = l1.parent),
x2 AS (SELECT l2.i, (l2.b + x1.x) / l2.d AS x FROM l2 JOIN x1 ON x1.i = l2.parent),
x3 AS (SELECT l3.i, (l3.b + x2.x) / l3.d AS x FROM l3 JOIN x2 ON x2.i = l3.parent)
SELECT i, round(x, 4) + 0.0 AS x FROM (SELECT * FROM x0 UNION ALL SELECT * FROM x1 UNION ALL SELECT * FROM x2 UNION ALL SELECT * FROM x3)"""


def sine_solution(d: int, n: int) -> str:
    """The lumped sine load is an eigenvector of the stencil, so the discrete solution is a known multiple of the continuous one."""
    waves = " * ".join(f"sin(pi() * (i // {n ** (d - 1 - k)} % {n} + 1) / {n + 1}.0)" for k in range(d))
    factor = f"pi() * pi() / {(n + 1) ** 2}.0 / (4 * pow(sin(pi() / {2 * (n + 1)}.0), 2))"
    return f"SELECT i, round({factor} * {waves}, 6) + 0.0 AS x FROM (SELECT range AS i FROM range({n**d}))"


def sine_error(n: int) -> str:
    return f"SELECT {n} AS n, round((pi() * pi() / {(n + 1) ** 2}.0 / (4 * pow(sin(pi() / {2 * (n + 1)}.0), 2)) - 1) * max(sin(pi() * k / {n + 1}.0)) * max(sin(pi() * k / {n + 1}.0)), 6) + 0.0 AS max_error FROM range(1, {n + 1}) t(k)"


def values(rows: list[tuple], columns: str) -> str:
    text = lambda v: f"'{v}'" if isinstance(v, str) else "NULL" if v is None else str(v)
    return f"SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(text, r)) + ')' for r in rows)}) t({columns})"


def line(xs: list[float]) -> str:
    rows = ", ".join(f"({i}, {x})" for i, x in enumerate(xs))
    return f"SELECT CAST(i AS BIGINT) AS i, round(CAST(x AS DOUBLE), 9) + 0.0 AS x FROM (VALUES {rows}) t(i, x)"


P1_2D = """WITH n AS (SELECT range AS i, range // 15 AS a, range % 15 AS b FROM range(225))
SELECT n.i, m.i AS j, CAST(CASE WHEN n.i = m.i THEN 4 WHEN n.a = m.a OR n.b = m.b THEN -1 ELSE 0 END AS DOUBLE) AS a
FROM n JOIN n m ON (m.a - n.a, m.b - n.b) IN ((0, 0), (0, 1), (0, -1), (1, 0), (-1, 0), (1, 1), (-1, -1))"""

P1_3D = """WITH n AS (SELECT range AS i, range // 49 AS a, range // 7 % 7 AS b, range % 7 AS c FROM range(343)),
p AS (SELECT n.i, m.i AS j, m.a - n.a AS x, m.b - n.b AS y, m.c - n.c AS z FROM n JOIN n m ON abs(m.a - n.a) <= 1 AND abs(m.b - n.b) <= 1 AND abs(m.c - n.c) <= 1)
SELECT i, j, CAST(CASE abs(x) + abs(y) + abs(z) WHEN 0 THEN 6 WHEN 1 THEN -1 ELSE 0 END AS DOUBLE) AS a
FROM p WHERE least(x, y, z) >= 0 OR greatest(x, y, z) <= 0"""



def jacobi(setup: str, sweeps: int, shown: str) -> str:
    """Sweeps on tables e (i, j, w) of couplings, d (i, d) of diagonals and f (i, x)."""
    return f"""WITH RECURSIVE {setup},
it AS (
  SELECT 0 AS k, i, CAST(0 AS DOUBLE) AS x FROM f
  UNION ALL
  SELECT s.k + 1, s.i, (max(f.x) + sum(s.y)) / max(d.d)
  FROM (SELECT it.k, e.i, e.w * it.x AS y FROM it JOIN e ON e.j = it.i WHERE it.k < {sweeps} UNION ALL SELECT k, i, 0 FROM it WHERE k < {sweeps}) s JOIN f ON f.i = s.i JOIN d ON d.i = s.i
  GROUP BY s.k, s.i)
SELECT {shown} FROM it WHERE k = {sweeps}"""


CHATS = """c AS (SELECT conv_id * 1000 + turn AS i, lag(conv_id * 1000 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS u, CAST(length(text) AS DOUBLE) AS x FROM conversations),
f AS (SELECT i, x FROM c),
e AS (SELECT i, u AS j, 1.0 AS w FROM c WHERE u IS NOT NULL UNION ALL SELECT u, i, 1.0 FROM c WHERE u IS NOT NULL),
d AS (SELECT f.i, 1.0 + count(e.j) AS d FROM f LEFT JOIN e ON e.i = f.i GROUP BY f.i)"""

PAGES = """l AS (SELECT page_id, anchor, count(*) AS w FROM (SELECT page_id, unnest(regexp_extract_all(html, '<a href="([^"]*)"', 1)) AS anchor FROM pages) GROUP BY 1, 2),
n AS (SELECT page_id, -dense_rank() OVER (ORDER BY anchor) AS a, CAST(w AS DOUBLE) AS w FROM l),
e AS (SELECT page_id AS i, a AS j, w FROM n UNION ALL SELECT a, page_id, w FROM n),
d AS (SELECT i, 2 * sum(w) AS d FROM e GROUP BY i),
f AS (SELECT d.i, coalesce(length(p.html) / 1000.0, 0) AS x FROM d LEFT JOIN pages p ON p.page_id = d.i)"""

CUBE = """r AS (SELECT (CAST((year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 AS BIGINT) * 50 + CAST(l_quantity AS BIGINT) - 1) * 11 + CAST(round(100 * l_discount) AS BIGINT) AS i, CAST(count(*) AS DOUBLE) AS x FROM lineitem GROUP BY 1),
n AS (SELECT range AS i, range // 550 AS a, range // 11 % 50 AS b, range % 11 AS c FROM range(45650)),
f AS (SELECT n.i, coalesce(r.x, 0.0) AS x FROM n LEFT JOIN r ON r.i = n.i),
d AS (SELECT i, 7.0 AS d FROM n),
e AS (SELECT i, i - 550 AS j, 1.0 AS w FROM n WHERE a > 0 UNION ALL SELECT i, i + 550, 1.0 FROM n WHERE a < 82 UNION ALL SELECT i, i - 11, 1.0 FROM n WHERE b > 0
  UNION ALL SELECT i, i + 11, 1.0 FROM n WHERE b < 49 UNION ALL SELECT i, i - 1, 1.0 FROM n WHERE c > 0 UNION ALL SELECT i, i + 1, 1.0 FROM n WHERE c < 10)"""

MICRO = {"ras": [2.6, 4.2, 4.8, 4.8, 4.2, 2.6], "as": [2.6, 4.2, 4.2, 4.2, 4.2, 2.6], "ras2": [2.8, 3.85, 4.15, 4.15, 3.85, 2.8], "jacobi": [1.875, 2.75, 2.625, 2.625, 2.75, 1.875]}


def two_level_micro(additive: bool, steps: int) -> str:
    """Six nodes in a line by joins with closed forms: the inverse of a line of n is min(i, j) (n + 1 - max(i, j)) / (n + 1).

    In each step the residual is taken, solved for on nodes 0 to 3 and 2 to 5 with owned results kept, and on the two halves'
    indicators, whose matrix is a line of two. Additively both corrections count half; else the coarse one comes first.
    """
    residual = lambda u: f"SELECT n.i, 1 - 2 * n.x + coalesce(a.x, 0) + coalesce(b.x, 0) AS r FROM {u} n LEFT JOIN {u} a ON a.i = n.i - 1 LEFT JOIN {u} b ON b.i = n.i + 1"
    local = lambda r: f"SELECT p.i, sum(least(p.s, q.s) * (5 - greatest(p.s, q.s)) / 5.0 * r.r) AS v FROM g p JOIN g q ON q.p = p.p JOIN {r} r ON r.i = q.i WHERE p.p = p.i // 3 GROUP BY p.i"
    half = lambda r: f"SELECT n.i, (2 * sum(CASE WHEN r.i // 3 = n.i // 3 THEN r.r ELSE 0 END) + sum(CASE WHEN r.i // 3 <> n.i // 3 THEN r.r ELSE 0 END)) / 3.0 AS v FROM u0 n, {r} r GROUP BY n.i"
    parts = ["u0 AS (SELECT range AS i, CAST(0 AS DOUBLE) AS x FROM range(6))", "g AS (SELECT p.p, s.s + 2 * p.p - 1 AS i, s.s FROM (VALUES (0), (1)) p(p), (VALUES (1), (2), (3), (4)) s(s))"]
    for k in range(1, steps + 1):
        parts += [f"r{k} AS ({residual(f'u{k - 1}')})", f"c{k} AS ({half(f'r{k}')})"]
        if additive:
            parts += [f"l{k} AS ({local(f'r{k}')})", f"u{k} AS (SELECT u.i, u.x + l.v / 2 + c.v / 2 AS x FROM u{k - 1} u JOIN l{k} l ON l.i = u.i JOIN c{k} c ON c.i = u.i)"]
        else:
            parts += [f"m{k} AS (SELECT u.i, u.x + c.v AS x FROM u{k - 1} u JOIN c{k} c ON c.i = u.i)", f"q{k} AS ({residual(f'm{k}')})", f"l{k} AS ({local(f'q{k}')})", f"u{k} AS (SELECT m.i, m.x + l.v AS x FROM m{k} m JOIN l{k} l ON l.i = m.i)"]
    return f"WITH {', '.join(parts)} SELECT i, round(x, 9) + 0.0 AS x FROM u{steps}"


def per_mode(name: str, sizes: tuple[int, ...], *flags: bool, columns: str) -> str:
    return values([(name, p, m, *flags) for p in sizes for m in ("sync", "async")], f"workload, P, mode, {columns}")


ORACLES: dict[str, str] = {
    "chats_solution": jacobi(CHATS, 90, "i, round(x, 4) + 0.0 AS x"),
    "pages_solution": jacobi(PAGES, 60, "i AS page_id, round(x, 4) + 0.0 AS x").replace("WHERE k = 60", "WHERE k = 60 AND i >= 0"),
    "cube_solution": jacobi(CUBE, 180, "i, round(x, 4) + 0.0 AS x"),
    "ras2_micro_k3": two_level_micro(True, 3),
    "ras2_mult_micro_k2": two_level_micro(False, 2),
    "as_micro_k2": line(MICRO["as"]),
    "stationary_micro": " UNION ALL ".join(f"SELECT '{k}' AS precond, i, x FROM ({line(v)})" for k, v in MICRO.items()),
    "overlapped_exchange_micro": line([2.84, 4.68, 5.52, 5.52, 4.68, 2.84]),
    "gmres_additive_micro": line([3, 5, 6, 6, 5, 3]),
    "coarse_decomposed_micro": two_level_micro(True, 2).replace("round(x, 9)", "round(x, 6)"),
    "one_level_strong_winners": values([("one-level strong", p, p > 4) for p in (4, 16, 64)], "workload, P, async_wins"),
    "one_level_imbalanced_winners": values([("one-level strong, imbalanced", p, p > 4) for p in (4, 16, 64)], "workload, P, async_wins"),
    "two_level_weak_report": per_mode("two-level weak", (4, 16), True, True, columns="reached, few_iterations"),
    "two_level_imbalanced_report": per_mode("two-level weak, imbalanced", (4, 16), True, columns="reached"),
    "two_level_strong_report": per_mode("two-level strong", (4, 16), True, columns="reached"),
    "two_level_cube_report": per_mode("two-level cube", (8,), True, columns="reached"),
    "convection_report": per_mode("convection-diffusion", (4, 16), True, columns="reached"),
    "local_iterations_vary": values([(p, m, m == "async") for p in (4, 16) for m in ("sync", "async")], "P, mode, differ"),
    "live_two_level_solution": sine_solution(2, 15).replace(", 6)", ", 4)"),
    "live_async_report": "SELECT CAST(range AS INTEGER) AS p, true AS converged, true AS iterated FROM range(4)",
    "comm_bench_report": " UNION ALL ".join(
        f"SELECT '{o}' AS option, CAST(16640 AS BIGINT) AS reads, (SELECT count(*) FROM events WHERE user_id IS NOT NULL AND ts IS NOT NULL) AS events, CAST({'true' if o.startswith('exclusive') or o in ('atomic', 'two_sided') else 'NULL'} AS BOOLEAN) AS whole"
        for o in [*[f"{s}-unlock-{p}" for s in ("exclusive", "shared") for p in ("writer", "reader")], *[f"global-{f}-{p}" for f in ("none", "all", "local_all", "local_each", "each") for p in ("writer", "reader")], "two_sided", "atomic"]
    ),
    "streaming_micro": line([3, 5, 6, 6, 5, 3]),
    "hourly_load": "SELECT CAST(floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 3600) AS BIGINT) AS i, round(sum(value), 4) + 0.0 AS x FROM events GROUP BY 1",
    "sliding_load": "SELECT i, round(avg(value), 9) + 0.0 AS x FROM (SELECT CAST(floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 3600) AS BIGINT) - d.d AS i, value FROM events, range(6) d(d)) GROUP BY 1",
    "user_sessions": """WITH e AS (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS before FROM events),
      s AS (SELECT user_id, ts, sum(CASE WHEN before IS NULL OR ts >= before + INTERVAL 30 MINUTE THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS n FROM e)
      SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS events FROM s GROUP BY user_id, n""",
    "krylov_report": values([(m, 4, True, True) for m in ("geometric", "spectral")], "mode, P, converged, few_iterations"),
    "grid2d_rhs": f"WITH {GRID_F} SELECT i, x FROM gf",
    "grid3d_rhs": """SELECT n.i, coalesce(c.x, 0.0) AS x FROM (SELECT range AS i FROM range(45650)) n LEFT JOIN (
      SELECT (CAST((year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 AS BIGINT) * 50 + CAST(l_quantity AS BIGINT) - 1) * 11 + CAST(round(100 * l_discount) AS BIGINT) AS i, CAST(count(*) AS DOUBLE) AS x
      FROM lineitem GROUP BY 1) c ON n.i = c.i""",
    "chain_rhs": f"WITH {CHAIN_F} SELECT i, round(x, 4) + 0.0 AS x FROM f",
    "tree_nodes": f"WITH {TREE_NODES} SELECT i, parent, nation, round(f, 6) + 0.0 AS f FROM tn",
    "page_links": """SELECT page_id, anchor, CAST(count(*) AS DOUBLE) AS w FROM (SELECT page_id, unnest(regexp_extract_all(html, '<a href="([^"]*)"', 1)) AS anchor FROM pages) GROUP BY 1, 2""",
    "chat_edges": """SELECT u, v, CAST(1 AS DOUBLE) AS w FROM (SELECT conv_id * 1000 + turn AS v, lag(conv_id * 1000 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS u FROM conversations) WHERE u IS NOT NULL""",
    "grid2d_entries": f"WITH {CELLS_E} SELECT i, j, CAST(-1 AS DOUBLE) AS a FROM ge UNION ALL SELECT i, i, 5.0 FROM gn",
    "p1_assembly_2d": P1_2D,
    "p1_assembly_3d": P1_3D,
    "tree_entries": f"WITH {TREE_E} SELECT i, j, a FROM te",
    "galerkin_tree": f"WITH {TREE_E} SELECT CAST(x.nation AS BIGINT) AS c, CAST(y.nation AS BIGINT) AS d, sum(te.a) AS a FROM te JOIN tn x ON x.i = te.i JOIN tn y ON y.i = te.j GROUP BY 1, 2",
    "upwind_entries": """WITH n AS (SELECT range AS i, range // 15 AS a, range % 15 AS b FROM range(225))
      SELECT n.i, m.i AS j, round(CASE WHEN n.i = m.i THEN 4 + 12 / 16.0 WHEN m.a = n.a - 1 THEN -1 - 8 / 16.0 WHEN m.b = n.b + 1 THEN -1 - 4 / 16.0 ELSE -1.0 END, 9) + 0.0 AS a
      FROM n JOIN n m ON abs(m.a - n.a) + abs(m.b - n.b) <= 1""",
    "m_matrix_report": values([("lattice", True), ("upwind", True), ("central", False)], "problem, m_matrix"),
    "box_owner": f"WITH {CELLS_E} SELECT i, CAST(floor(wk * 4 / 357.0) * 2 + floor(qt * 2 / 50.0) AS INTEGER) AS p FROM gn",
    "key_owner": "SELECT c_custkey AS i, CAST(dense_rank() OVER (ORDER BY c_mktsegment) - 1 AS INTEGER) AS p FROM customer",
    "imbalanced_owner": f"""WITH {CELLS_E}, u AS (SELECT 357 / 4.5 AS u)
      SELECT CAST((wk >= round(1.5 * u))::INT + (wk >= round(2.5 * u))::INT + (wk >= round(3.5 * u))::INT AS INTEGER) AS p, count(*) AS nodes FROM gn, u GROUP BY 1""",
    "overlap_member": f"WITH {members(1, CELLS_E)} SELECT p, i, slot, layer FROM m",
    "surface_set": f"WITH {members(1)} SELECT p, i FROM s",
    "owned_mask": f"WITH {members(1, CELLS_E)} SELECT p, i, owned FROM m",
    "partition_of_unity": "SELECT 'none' AS rule, 0 AS p, CAST(0 AS BIGINT) AS i WHERE false",
    "routes_count": f"WITH {members(1)} SELECT a.p AS src, b.p AS dst, count(*) AS shared FROM m a JOIN m b ON a.i = b.i AND a.p <> b.p GROUP BY 1, 2",
    "partition_stats": f"""WITH {members(2, CELLS_E)}, r AS (SELECT a.p, count(DISTINCT b.p) AS neighbours, count(*) AS sent FROM m a JOIN m b ON a.i = b.i AND a.p <> b.p GROUP BY a.p)
      SELECT m.p, count(*) AS nodes, CAST(sum(m.owned::INT) AS BIGINT) AS owned, CAST(count(s.i) AS BIGINT) AS surface, max(r.neighbours) AS neighbours, max(r.sent) AS sent
      FROM m LEFT JOIN s ON s.p = m.p AND s.i = m.i JOIN r ON r.p = m.p GROUP BY m.p""",
    "graph_partition_cover": "SELECT CAST(576 AS BIGINT) AS nodes, CAST(576 AS BIGINT) AS distinct_nodes, CAST(4 AS BIGINT) AS parts",
    "geometric_members": f"""WITH {CELLS_E}, fn AS (SELECT range // 50 AS wk, range % 50 AS qt FROM range(17850)),
      box AS (SELECT CAST(floor(wk * 4 / 357.0) AS BIGINT) AS a, CAST(floor(qt * 2 / 50.0) AS BIGINT) AS c, min(wk) AS w0, max(wk) AS w1, min(qt) AS q0, max(qt) AS q1 FROM fn GROUP BY 1, 2)
      SELECT CAST(box.a * 2 + box.c AS INTEGER) AS p, count(*) AS nodes FROM box JOIN gn ON wk BETWEEN w0 - 2 AND w1 + 2 AND qt BETWEEN q0 - 2 AND q1 + 2 GROUP BY 1""",
    "overlap_growth": f"""WITH {members(1)},
      h AS (SELECT DISTINCT 2 * o_custkey AS u, 2 * l_suppkey + 1 AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey),
      he AS (SELECT u AS i, v AS j FROM h UNION ALL SELECT v, u FROM h), ho AS (SELECT DISTINCT i, (i // 2) % 8 AS p FROM he),
      hm AS (SELECT p, i FROM ho UNION SELECT ho.p, he.j FROM ho JOIN he ON he.i = ho.i)
      SELECT 'grid' AS problem, count(*) AS members, count(DISTINCT i) AS nodes FROM m UNION ALL SELECT 'hubs', count(*), count(DISTINCT i) FROM hm""",
    "local_residual_step": f"{STEP} SELECT p, i, s FROM shares",
    "accumulated_residual_step": f"{STEP} SELECT m.p, m.i, coalesce(t.r, 0.0) AS r FROM m LEFT JOIN (SELECT i, sum(s) AS r FROM shares GROUP BY i) t ON t.i = m.i",
    "residual_norm_local": f"{STEP} SELECT round(sqrt(sum(t.r * t.r)), 4) + 0.0 AS norm FROM m JOIN (SELECT i, sum(s) AS r FROM shares GROUP BY i) t ON t.i = m.i WHERE m.owned",
    "coarse_rhs_step": f"{STEP} SELECT CAST(o.p AS BIGINT) AS c, sum(shares.s) AS x FROM shares JOIN m0 o ON o.i = shares.i GROUP BY 1",
    "coarse_geometric_weights": f"""WITH {CELLS_E}, n AS (SELECT i, wk + 1 AS x, qt + 1 AS y FROM gn),
      e AS (SELECT i, x, y, x // 2 + a.a AS cx, y // 3 + b.b AS cy FROM n, range(2) a(a), range(2) b(b))
      SELECT i, (cx - 1) * 16 + cy - 1 AS c, round((1 - abs(x / 2.0 - cx)) * (1 - abs(y / 3.0 - cy)), 9) + 0.0 AS weight
      FROM e WHERE cx BETWEEN 1 AND 178 AND cy BETWEEN 1 AND 16 AND abs(x - 2 * cx) < 2 AND abs(y - 3 * cy) < 3""",
    "ras_micro_k3": line([2.84, 4.68, 5.52, 5.52, 4.68, 2.84]),
    "ras_micro_communicated": line([2.84, 4.68, 5.52, 5.52, 4.68, 2.84]),
    "async_replay_micro": " UNION ALL ".join(f"SELECT '{r}' AS run, i, x FROM ({line(xs)})" for r, xs in (("fresh", [2, 3, 3, 4.8, 4.2, 2.6]), ("stale", [2, 3, 3, 3, 3, 2]))),
    "ras_chain_solution": chain_jacobi(80),
    "ras2_chain_solution": chain_jacobi(80),
    "ras2_mult_chain_solution": chain_jacobi(80),
    "async_chain_solution": chain_jacobi(80),
    "block_jacobi_chain_solution": chain_jacobi(80),
    "chaotic_relaxation_chain": f"""WITH RECURSIVE {CHAIN_F},
      it AS (SELECT 0 AS k, i, CAST(0 AS DOUBLE) AS x FROM f UNION ALL
        SELECT t.k + 1, t.i, CASE WHEN t.i % 2 = (t.k + 1) % 2 THEN (max(f.x) + sum(CASE WHEN t.d <> 0 THEN t.x END)) / 3.0 ELSE max(CASE WHEN t.d = 0 THEN t.x END) END
        FROM (SELECT it.k, it.i + d.d AS i, it.x, d.d FROM it CROSS JOIN (VALUES (-1), (0), (1)) d(d) WHERE it.k < 24) t JOIN f ON f.i = t.i GROUP BY t.k, t.i)
      SELECT i, round(x, 4) + 0.0 AS x FROM it WHERE k = 24""",
    "point_relaxation_chain": chain_jacobi(16),
    "ras_tree_solution": TREE_SOLUTION,
    "ras2_tree_solution": TREE_SOLUTION,
    "async2_tree_solution": TREE_SOLUTION,
    "ras_grid2d_solution": GRID_JACOBI,
    "ras2_grid2d_solution": GRID_JACOBI,
    "gmres_grid2d_solution": GRID_JACOBI,
    "poisson2d_solution": sine_solution(2, 31),
    "poisson3d_solution": sine_solution(3, 9),
    "poisson_error_table": f"{sine_error(7)} UNION ALL {sine_error(15)}",
    "schedule_audit": "SELECT 'starved' AS kind, 'starved' AS rule, CAST(1 AS BIGINT) AS violations",
    "torus_neighbors": """WITH r AS (SELECT range AS i, range // 16 AS a, range // 4 % 4 AS b, range % 4 AS c FROM range(64))
      SELECT x.i AS rank, y.i AS neighbour FROM r x JOIN r y ON x.i <> y.i AND (x.a - y.a + 5) % 4 <= 2 AND (x.b - y.b + 5) % 4 <= 2 AND (x.c - y.c + 5) % 4 <= 2""",
    "contraction_report": """WITH r AS (SELECT user_id, min(value) / max(value) AS drop, CAST(count(*) AS DOUBLE) AS k FROM events WHERE value > 0 GROUP BY user_id)
      SELECT user_id, 'sync' AS run, round(pow(drop, 1 / k), 9) + 0.0 AS per_iteration, round(pow(drop, 1 / k), 9) + 0.0 AS per_time FROM r
      UNION ALL SELECT user_id, 'doubled', round(pow(drop, 1 / k), 9) + 0.0, round(pow(drop, 2 / k), 9) + 0.0 FROM r""",
    "iteration_histogram": "SELECT 'events' AS run_id, CAST(n // 10 * 10 AS BIGINT) AS low, count(*) AS parts FROM (SELECT user_id, count(*) AS n FROM events GROUP BY user_id) GROUP BY 2",
    "crossover_report": values([("one-level strong", 16), ("one-level strong, imbalanced", 16)], "workload, P"),
    "detection_report": """WITH e AS (SELECT CAST(floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 3600) AS INTEGER) AS t, user_id % 4 AS p, value FROM events),
      s AS (SELECT p, t, avg(value) AS r FROM e GROUP BY p, t), polls AS (SELECT DISTINCT t FROM s),
      l AS (SELECT polls.t, s.p, arg_max(s.r, s.t) AS r FROM polls JOIN s ON s.t <= polls.t GROUP BY 1, 2),
      m AS (SELECT t FROM l GROUP BY t HAVING count(*) = 4 AND sum(r) < 196.0),
      b AS (SELECT t, p, avg(value) AS r FROM (SELECT t, p, value FROM e UNION ALL SELECT t - 1, p, value FROM e) GROUP BY t, p),
      c AS (SELECT t FROM b GROUP BY t HAVING sqrt(sum(r)) < 14.0 AND t IN (SELECT t FROM polls))
      SELECT 'master' AS rule, min(t) AS t FROM m HAVING min(t) IS NOT NULL UNION ALL SELECT 'confirmed', min(t) FROM c HAVING min(t) IS NOT NULL""",
}


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
