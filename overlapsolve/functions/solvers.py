"""Local and coarse solvers in numpy; what is factored stays in the worker process that did it."""

from __future__ import annotations

import ctypes
import re
from collections import OrderedDict
from pathlib import Path

import numpy as np



def one_thread() -> None:
    """Keep the linear algebra library of this process to one thread: Spark's tasks are the parallelism, and its threads may
    wait for ever in a process that has forked. Nothing happens where no such library is found."""
    maps = Path("/proc/self/maps")
    for path in set(re.findall(r"/\S*openblas\S*\.so\S*", maps.read_text())) if maps.exists() else ():
        library = ctypes.CDLL(path)
        for name in ("scipy_openblas_set_num_threads64_", "openblas_set_num_threads64_", "scipy_openblas_set_num_threads", "openblas_set_num_threads"):
            if hasattr(library, name):
                getattr(library, name)(1)
                break


one_thread()
DENSE = 1500
BAND_BYTES = 256 << 20
_KEPT: OrderedDict[tuple, object] = OrderedDict()
KEPT_BYTES = 512 << 20


def bandwidth_order(indptr: np.ndarray, indices: np.ndarray) -> np.ndarray:
    """Nodes by breadth-first level sets from a far node, which keeps couplings near the diagonal."""
    n = len(indptr) - 1
    degree = np.diff(indptr)

    def levels(root: int, seen: np.ndarray) -> list[int]:
        order, at = [root], 0
        seen[root] = True
        while at < len(order):
            i = order[at]
            at += 1
            new = [j for j in indices[indptr[i] : indptr[i + 1]] if not seen[j]]
            new = sorted(set(new), key=lambda j: (degree[j], j))
            for j in new:
                seen[j] = True
            order += new
        return order

    done, out = np.zeros(n, bool), []
    for root in range(n):
        if not done[root]:
            first = levels(root, done)
            done[first] = False  # all of this component, which the second walk marks again
            out += levels(int(first[-1]), done)
    return np.array(out[::-1], np.int64)


class Dense:
    def __init__(self, a: np.ndarray):
        self.inverse = np.linalg.inv(a)
        self.size = a.nbytes

    def solve(self, r: np.ndarray) -> np.ndarray:
        return self.inverse @ r


class Banded:
    """LU without pivoting in band storage, after reordering; sound for M-matrices and symmetric positive definite ones."""

    def __init__(self, indptr: np.ndarray, indices: np.ndarray, data: np.ndarray, order: np.ndarray | None = None):
        n = len(indptr) - 1
        self.order = bandwidth_order(indptr, indices) if order is None else order
        place = np.empty(n, np.int64)
        place[self.order] = np.arange(n)
        rows = place[np.repeat(np.arange(n), np.diff(indptr))]
        cols = place[indices]
        self.band = b = int(np.abs(rows - cols).max()) if len(rows) else 0
        a = np.zeros((n + b, 2 * b + 1))
        np.add.at(a, (rows, cols - rows + b), data)
        # Entry (i, j) is a[i, j - i + b], so the block below and right of a pivot is a strided view of the rows.
        step = a.strides
        for k in range(n - 1):
            m = min(b, n - 1 - k)
            if not m:
                break
            below = np.lib.stride_tricks.as_strided(a[k + 1 :, b - 1 :], (m,), (step[0] - step[1],))
            below /= a[k, b]
            block = np.lib.stride_tricks.as_strided(a[k + 1 :, b:], (m, m), (step[0] - step[1], step[1]))
            block -= below[:, None] * a[k, b + 1 : b + 1 + m][None, :]
        self.a, self.n, self.size = a, n, a.nbytes

    def solve(self, r: np.ndarray) -> np.ndarray:
        a, b, n = self.a, self.band, self.n
        y = np.concatenate([np.zeros(b), r[self.order], np.zeros(b)])
        for i in range(1, n):
            y[b + i] -= a[i, :b] @ y[i : i + b]
        for i in range(n - 1, -1, -1):
            y[b + i] = (y[b + i] - a[i, b + 1 :] @ y[b + i + 1 : b + i + 1 + b]) / a[i, b]
        out = np.empty(n)
        out[self.order] = y[b : b + n]
        return out


class IncompleteCG:
    """Conjugate gradients with a zero-fill incomplete factorisation, to a relative tolerance."""

    def __init__(self, indptr: np.ndarray, indices: np.ndarray, data: np.ndarray, rtol: float = 0.1, most: int = 200):
        self.n, self.rtol, self.most = len(indptr) - 1, rtol, most
        self.rows = np.repeat(np.arange(self.n), np.diff(indptr))
        self.cols, self.data, self.size = indices, data, 3 * data.nbytes
        lower: list[dict[int, float]] = []
        for i in range(self.n):
            row = {int(j): float(v) for j, v in zip(indices[indptr[i] : indptr[i + 1]], data[indptr[i] : indptr[i + 1]], strict=True) if j <= i}
            new: dict[int, float] = {}
            for j in sorted(row):
                s = row[j] - sum(v * lower[j].get(k, 0.0) for k, v in new.items() if k < j) if j < i else row[j] - sum(v * v for v in new.values())
                new[j] = s / lower[j][j] if j < i else np.sqrt(max(s, 1e-12))
            lower.append(new)
        self.lower = [(np.array([j for j in r if j < i], np.int64), np.array([v for j, v in r.items() if j < i]), r[i]) for i, r in enumerate(lower)]

    def times(self, x: np.ndarray) -> np.ndarray:
        return np.bincount(self.rows, weights=self.data * x[self.cols], minlength=self.n)

    def precondition(self, r: np.ndarray) -> np.ndarray:
        y = r.copy()
        for i, (at, v, d) in enumerate(self.lower):
            y[i] = (y[i] - v @ y[at]) / d
        for i in range(self.n - 1, -1, -1):
            at, v, d = self.lower[i]
            y[i] /= d
            y[at] -= v * y[i]
        return y

    def solve(self, r: np.ndarray) -> np.ndarray:
        x, rest, stop = np.zeros_like(r), r.copy(), self.rtol * np.linalg.norm(r)
        if not stop:
            return x
        z = self.precondition(rest)
        p, rz = z.copy(), rest @ z
        for _ in range(self.most):
            q = self.times(p)
            alpha = rz / (p @ q)
            x += alpha * p
            rest -= alpha * q
            if np.linalg.norm(rest) <= stop:
                break
            z = self.precondition(rest)
            rz, old = rest @ z, rz
            p = z + rz / old * p
        return x


class ExactCG:
    """Conjugate gradients with diagonal scaling, run until rounding stops them: for symmetric positive definite matrices whose
    factors wouldn't fit. Raises ArithmeticError where it doesn't converge."""

    def __init__(self, rows: np.ndarray, cols: np.ndarray, data: np.ndarray, n: int, rtol: float = 1e-15):
        self.rows, self.cols, self.data, self.n, self.rtol, self.size = rows, cols, data, n, rtol, 3 * data.nbytes
        self.diagonal = np.bincount(rows[rows == cols], weights=data[rows == cols], minlength=n)

    def times(self, x: np.ndarray) -> np.ndarray:
        return np.bincount(self.rows, weights=self.data * x[self.cols], minlength=self.n)

    def solve(self, r: np.ndarray) -> np.ndarray:
        x, rest, first = np.zeros_like(r), r.copy(), float(np.linalg.norm(r))
        if not first:
            return x
        z = rest / self.diagonal
        p, rz, norm = z, float(rest @ z), first
        for _ in range(20 * self.n + 100):
            q = self.times(p)
            alpha = rz / float(p @ q)
            x = x + alpha * p
            rest = rest - alpha * q
            norm = float(np.linalg.norm(rest))
            if norm <= self.rtol * first:
                return x
            z = rest / self.diagonal
            rz, old = float(rest @ z), rz
            p = z + rz / old * p
        raise ArithmeticError(f"no convergence: residual {norm / first:.1e}")


def thinned(indptr: np.ndarray, indices: np.ndarray, data: np.ndarray, most: int = 3) -> tuple[list[tuple[np.ndarray, ...]], np.ndarray, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(rounds, left, matrix): nodes with up to `most` neighbours taken out, and the matrix of those that are left.

    With three the couplings that fill in are no more than those that go. A round takes out nodes that aren't neighbours, of
    two low ones that with fewer neighbours; rounds end when less than a twentieth of the nodes would go, as on lattices.
    A round is (nodes, pivots, and the couplings to them and from them as ends and factors).
    """
    n = len(indptr) - 1
    rows, k = np.repeat(np.arange(n), np.diff(indptr)), np.arange(n)
    none = np.zeros(len(rows) + n)  # a coupling has both its directions, a node its diagonal
    matrix = to_csr(n, np.concatenate([rows, indices, k]), np.concatenate([indices, rows, k]), np.concatenate([data, none]))
    left, lot, rounds = k, np.random.default_rng(0).permutation(n), []
    while len(left):
        m, (ptr, cols, vals) = len(left), matrix
        rows = np.repeat(np.arange(m), np.diff(ptr))
        off = rows != cols
        degree = np.diff(ptr) - 1
        low, rank = degree <= most, degree * n + lot[left]
        rival = off & low[rows] & low[cols] & (rank[cols] < rank[rows])
        goes = low.copy()
        goes[rows[rival]] = False
        if 20 * goes.sum() < m:
            break
        pivot = vals[~off]
        up = np.flatnonzero(off & goes[rows])
        down = np.flatnonzero(off & goes[cols])
        down = down[np.lexsort((rows[down], cols[down]))]  # by the node that goes, as `up` is
        share = vals[down] / pivot[cols[down]]
        rounds.append((left[goes], pivot[goes], left[rows[down]], left[cols[down]], share, left[rows[up]], left[cols[up]], vals[up]))
        # Each coupling to a node that goes meets each one from it.
        size = degree[cols[down]]
        first = np.searchsorted(rows[up], cols[down])
        each = np.repeat(np.arange(len(down)), size)
        with_ = up[first[each] + np.arange(len(each)) - np.repeat(np.cumsum(size) - size, size)]
        stays = ~goes
        place = np.cumsum(stays) - 1
        inside = stays[rows] & stays[cols]
        i, j = np.concatenate([rows[inside], rows[down[each]]]), np.concatenate([cols[inside], cols[with_]])
        matrix = to_csr(int(stays.sum()), place[i], place[j], np.concatenate([vals[inside], -share[each] * vals[with_]]))
        left = left[stays]
    return rounds, left, matrix


class Eliminated:
    """LU that takes out nodes with one neighbour left, round by round, which fills nothing in, and factors what is left over,
    if that is much without the nodes that `thinned` takes out.

    A forest is taken out whole, in memory and time in proportion to its nodes. A round is done at once by numpy. Sound
    without pivoting for M-matrices and symmetric positive definite ones.
    """

    def __init__(self, indptr: np.ndarray, indices: np.ndarray, data: np.ndarray):
        n = self.n = len(indptr) - 1
        indptr, indices, data = to_csr(n, np.repeat(np.arange(n), np.diff(indptr)), indices, data)
        rows = np.repeat(np.arange(n), np.diff(indptr))
        key = rows * n + indices

        def entry(i: np.ndarray, j: np.ndarray) -> np.ndarray:
            at = np.minimum(np.searchsorted(key, i * n + j), max(0, len(key) - 1))
            return np.where(key[at] == i * n + j, data[at], 0.0)

        off = rows != indices
        pairs = np.unique(np.concatenate([key[off], indices[off] * n + rows[off]]))  # couplings in either direction
        a, b = pairs // n, pairs % n
        degree = np.bincount(a, minlength=n)
        others = np.bincount(a, weights=b, minlength=n).astype(np.int64)  # sum of the neighbours: of one neighbour, which one
        pivot = entry(np.arange(n), np.arange(n)) if n else np.zeros(0)
        free = np.ones(n, bool)
        self.rounds: list[tuple[np.ndarray, ...]] = []
        front = np.flatnonzero(degree <= 1)
        while len(front):
            tied = degree[front] == 1
            mate = np.where(tied, others[front], -1)
            last = ~tied | ~((degree[mate] == 1) & (mate < front))  # of two that are left with each other, the smaller goes first
            out, to = front[last & tied], mate[last & tied]
            alone = front[~tied]
            down = entry(to, out) / pivot[out]
            up = entry(out, to)
            np.subtract.at(pivot, to, down * up)
            np.subtract.at(degree, to, 1)
            np.subtract.at(others, to, out)
            free[out] = free[alone] = False
            self.rounds.append((out, to, down, up, alone))
            front = np.unique(to)
            front = front[free[front] & (degree[front] <= 1)]
        self.pivot = pivot
        self.core = np.flatnonzero(free)
        self.rest, self.wider, self.left = None, [], np.zeros(0, np.int64)
        if len(self.core):
            place = np.full(n, -1)
            place[self.core] = np.arange(len(self.core))
            inside = free[rows] & free[indices] & off
            k = np.arange(len(self.core))
            r, c, v = np.concatenate([place[rows[inside]], k]), np.concatenate([place[indices[inside]], k]), np.concatenate([data[inside], pivot[self.core]])
            matrix, self.left = to_csr(len(self.core), r, c, v), k
            if len(k) > DENSE:
                self.wider, self.left, matrix = thinned(*matrix)
            if len(self.left):
                self.rest = whole(*matrix)
        self.size = pivot.nbytes + sum(sum(x.nbytes for x in t) for t in self.rounds + self.wider) + (self.rest.size if self.rest else 0)

    def solve(self, r: np.ndarray) -> np.ndarray:
        y = r.astype(float)
        for out, to, down, _, _ in self.rounds:
            np.subtract.at(y, to, down * y[out])
        z = y[self.core]
        for _, _, to, out, share, _, _, _ in self.wider:
            np.subtract.at(z, to, share * z[out])
        if self.rest is not None:
            z[self.left] = self.rest.solve(z[self.left])
        for out, pivot, _, _, _, of, to, up in reversed(self.wider):
            np.subtract.at(z, of, up * z[to])
            z[out] /= pivot
        y[self.core] = z
        for out, to, _, up, alone in reversed(self.rounds):
            y[alone] /= self.pivot[alone]
            y[out] = (y[out] - up * y[to]) / self.pivot[out]
        return y


def whole(indptr: np.ndarray, indices: np.ndarray, data: np.ndarray):
    """A direct solver of a matrix without leaves: dense while small, then banded; where a symmetric one's band is over BAND_BYTES, conjugate gradients."""
    n = len(indptr) - 1
    rows = np.repeat(np.arange(n), np.diff(indptr))
    if n <= DENSE:
        a = np.zeros((n, n))
        np.add.at(a, (rows, indices), data)
        return Dense(a)
    order = bandwidth_order(indptr, indices)
    place = np.empty(n, np.int64)
    place[order] = np.arange(n)
    band = int(np.abs(place[rows] - place[indices]).max())
    if 8 * (n + band) * (2 * band + 1) > BAND_BYTES:
        turned = np.lexsort((rows, indices))
        if np.array_equal(rows[turned], indices) and np.array_equal(indices[turned], rows) and np.allclose(data[turned], data, rtol=1e-12, atol=0):
            return ExactCG(rows, indices, data, n)
    return Banded(indptr, indices, data, order)


def factor(indptr: np.ndarray, indices: np.ndarray, data: np.ndarray, kind: str = "direct", rtol: float = 0.1):
    """A solver for one matrix in row form: direct (dense while small, else leaves first and then the rest) or cg_ic."""
    n = len(indptr) - 1
    if kind == "cg_ic":
        return IncompleteCG(indptr, indices, data, rtol)
    if kind != "direct":
        raise ValueError(f"no solver {kind}")
    if n > DENSE:
        return Eliminated(indptr, indices, data)
    a = np.zeros((n, n))
    np.add.at(a, (np.repeat(np.arange(n), np.diff(indptr)), indices), data)
    return Dense(a)


def kept(key: tuple, make):
    """make() once a process and key; the oldest go beyond KEPT_BYTES."""
    if key not in _KEPT:
        _KEPT[key] = make()
        while len(_KEPT) > 1 and sum(f.size for f in _KEPT.values()) > KEPT_BYTES:
            _KEPT.popitem(last=False)
    _KEPT.move_to_end(key)
    return _KEPT[key]


def gauss_seidel(a: tuple[np.ndarray, np.ndarray, np.ndarray], x: np.ndarray, r: np.ndarray, backward: bool = False) -> None:
    """One sweep on (indptr, indices, data), in place."""
    indptr, indices, data = a
    for i in range(len(r) - 1, -1, -1) if backward else range(len(r)):
        at = slice(indptr[i], indptr[i + 1])
        j, v = indices[at], data[at]
        d = v[j == i].sum()
        x[i] += (r[i] - v @ x[j]) / d


def to_csr(n: int, rows: np.ndarray, cols: np.ndarray, vals: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    key = rows * n + cols
    unique, inverse = np.unique(key, return_inverse=True)
    data = np.bincount(inverse, weights=vals, minlength=len(unique))
    r = unique // n if n else unique
    return np.searchsorted(r, np.arange(n + 1)), unique % n if n else unique, data


class VCycle:
    """Multigrid by pairwise aggregation of a lattice's or graph's neighbours, with one sweep before and one after."""

    def __init__(self, indptr: np.ndarray, indices: np.ndarray, data: np.ndarray, pre: int = 1, post: int = 1, coarsest: int = 64):
        self.pre, self.post = pre, post
        self.levels: list[tuple[tuple[np.ndarray, np.ndarray, np.ndarray], np.ndarray | None]] = []
        a = (indptr, indices, data)
        while len(a[0]) - 1 > coarsest:
            group = self._pairs(a)
            if group.max() + 1 >= 0.9 * len(group):
                break
            self.levels.append((a, group))
            rows = np.repeat(np.arange(len(group)), np.diff(a[0]))
            a = to_csr(int(group.max()) + 1, group[rows], group[a[1]], a[2])
        self.levels.append((a, None))
        self.last = factor(*a)
        self.size = sum(x[2].nbytes for x, _ in self.levels) + self.last.size

    @staticmethod
    def _pairs(a: tuple[np.ndarray, np.ndarray, np.ndarray]) -> np.ndarray:
        indptr, indices, data = a
        group, count = np.full(len(indptr) - 1, -1), 0
        for i in range(len(group)):
            if group[i] < 0:
                at = slice(indptr[i], indptr[i + 1])
                free = [(v, j) for j, v in zip(indices[at], data[at], strict=True) if j != i and group[j] < 0 and v < 0]
                group[i] = count
                if free:
                    group[min(free)[1]] = count
                count += 1
        return group

    def cycle(self, r: np.ndarray, level: int = 0) -> np.ndarray:
        a, group = self.levels[level]
        if group is None:
            return self.last.solve(r)
        x = np.zeros_like(r)
        for _ in range(self.pre):
            gauss_seidel(a, x, r)
        rows = np.repeat(np.arange(len(r)), np.diff(a[0]))
        rest = r - np.bincount(rows, weights=a[2] * x[a[1]], minlength=len(r))
        x += self.cycle(np.bincount(group, weights=rest, minlength=int(group.max()) + 1), level + 1)[group]
        for _ in range(self.post):
            gauss_seidel(a, x, r, backward=True)
        return x

    def solve(self, r: np.ndarray) -> np.ndarray:
        """One cycle: an approximate solve."""
        return self.cycle(r)


def lattice_interpolation(shape: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray, np.ndarray, tuple[int, ...]]:
    """(fine, coarse, weight) and the shape of the coarse lattice: multilinear, coarse nodes at every other fine one, zero outside."""
    small = tuple(max(1, n // 2) for n in shape)
    fine, coarse, weight = np.zeros(1, np.int64), np.zeros(1, np.int64), np.ones(1)
    for n, m in zip(shape, small, strict=True):
        x = np.arange(n)
        if n == 1:
            at, to, w = x, x, np.ones(1)
        else:
            left, right = (x - 1) // 2, x // 2  # coarse node c lies on fine node 2 c + 1
            both = x % 2 == 0
            at = np.concatenate([x[~both], x[both], x[both]])
            to = np.concatenate([left[~both], left[both], right[both]])
            w = np.concatenate([np.ones((~both).sum()), np.full(2 * both.sum(), 0.5)])
            ok = (to >= 0) & (to < m)
            at, to, w = at[ok], to[ok], w[ok]
        fine = (fine[:, None] * n + at[None, :]).ravel()
        coarse = (coarse[:, None] * m + to[None, :]).ravel()
        weight = (weight[:, None] * w[None, :]).ravel()
    return fine, coarse, weight, small


class LatticeMultigrid:
    """Geometric multigrid on a lattice: multilinear transfer between nested lattices, Galerkin coarse matrices, Gauss-Seidel sweeps."""

    def __init__(self, indptr: np.ndarray, indices: np.ndarray, data: np.ndarray, shape: tuple[int, ...], pre: int = 1, post: int = 1, coarsest: int = 32, cycles: int = 1):
        self.pre, self.post, self.cycles = pre, post, cycles
        self.levels, a = [], (indptr, indices, data)
        while len(a[0]) - 1 > coarsest and max(shape) > 2:
            fine, coarse, weight, small = lattice_interpolation(shape)
            n, m = len(a[0]) - 1, int(np.prod(small))
            order = np.argsort(fine, kind="stable")
            fine, coarse, weight = fine[order], coarse[order], weight[order]
            first = np.searchsorted(fine, np.arange(n + 1))
            self.levels.append((a, fine, coarse, weight))
            rows = np.repeat(np.arange(n), np.diff(a[0]))
            # Each entry meets the interpolation of its row and of its column.
            left, right = np.diff(first)[rows], np.diff(first)[a[1]]
            each = np.repeat(np.arange(len(rows)), left * right)
            within = np.arange(len(each)) - np.repeat(np.cumsum(left * right) - left * right, left * right)
            i, j = first[rows[each]] + within // right[each], first[a[1][each]] + within % right[each]
            a, shape = to_csr(m, coarse[i], coarse[j], a[2][each] * weight[i] * weight[j]), small
        self.last, self.end = factor(*a), a
        self.size = sum(x[0][2].nbytes for x in self.levels) + self.last.size

    def cycle(self, r: np.ndarray, level: int = 0) -> np.ndarray:
        if level == len(self.levels):
            return self.last.solve(r)
        a, fine, coarse, weight = self.levels[level]
        x = np.zeros_like(r)
        for _ in range(self.pre):
            gauss_seidel(a, x, r)
        rows = np.repeat(np.arange(len(r)), np.diff(a[0]))
        rest = r - np.bincount(rows, weights=a[2] * x[a[1]], minlength=len(r))
        m = len(self.levels[level + 1][0][0]) - 1 if level + 1 < len(self.levels) else len(self.end[0]) - 1
        x += np.bincount(fine, weights=weight * self.cycle(np.bincount(coarse, weights=weight * rest[fine], minlength=m), level + 1)[coarse], minlength=len(r))
        for _ in range(self.post):
            gauss_seidel(a, x, r, backward=True)
        return x

    def solve(self, r: np.ndarray) -> np.ndarray:
        """`cycles` V-cycles."""
        x = self.cycle(r)
        a = self.levels[0][0] if self.levels else self.end
        rows = np.repeat(np.arange(len(r)), np.diff(a[0]))
        for _ in range(self.cycles - 1):
            x += self.cycle(r - np.bincount(rows, weights=a[2] * x[a[1]], minlength=len(r)))
        return x


def green_1d(n: int) -> np.ndarray:
    """The inverse of the chain with 2 on the diagonal and -1 beside it."""
    i = np.arange(1, n + 1)
    return np.minimum.outer(i, i) * (n + 1 - np.maximum.outer(i, i)) / (n + 1)
