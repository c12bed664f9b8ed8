"""Solvers of the block problem, on the fast tier.

X holds a row for each column of the block. A solver returns the change of alpha and of v. The local model needs nothing
but X, alpha, v and the gradient at v: for quadratic f it is the problem itself, else an upper bound of it.
"""

from __future__ import annotations

import math
import time
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np

from ..functions.objectives import ElasticNet, LassoBoxed, Objective, RidgeDual, RidgePrimal, total  # noqa: F401

#: Least number of coordinates that a pass looks at together, to pass over those that rest.
LOOK = 64
#: Rows whose linear steps are solved together, and such groups that are made ready at once.
CHAIN, CHAINS = 32, 64


@dataclass
class Solved:
    delta: np.ndarray
    dv: np.ndarray
    passes: int
    seconds: float


class SparseRows:
    """Rows of a matrix of which only entries other than zero are held; it takes an array's place in passes."""

    __array_ufunc__ = None  # an array times these rows is their own product

    def __init__(self, ptr: np.ndarray, idx: np.ndarray, vals: np.ndarray, d: int):
        self.ptr, self.idx, self.vals, self.shape = ptr, idx, vals, (len(ptr) - 1, d)
        self.nbytes, self._norms = ptr.nbytes + idx.nbytes + vals.nbytes, None

    @classmethod
    def of(cls, row: np.ndarray, column: np.ndarray, vals: np.ndarray, n: int, d: int) -> SparseRows:
        order = np.lexsort((column, row))
        return cls(np.concatenate(([0], np.cumsum(np.bincount(row, minlength=n)))), column[order].astype(np.int32), vals[order].astype(np.float64), d)

    def __len__(self) -> int:
        return self.shape[0]

    def spans(self) -> tuple[list[int], list[int]]:
        """Where each row's entries begin and end."""
        return self.ptr[:-1].tolist(), self.ptr[1:].tolist()

    def __getitem__(self, at: np.ndarray) -> SparseRows:
        at = np.flatnonzero(at) if at.dtype == bool else at
        if len(at) == 1:
            a, b = self.ptr[at[0]], self.ptr[at[0] + 1]
            return SparseRows(np.array([0, b - a]), self.idx[a:b], self.vals[a:b], self.shape[1])
        count = self.ptr[at + 1] - self.ptr[at]
        ptr = np.concatenate(([0], np.cumsum(count)))
        idx, vals = np.empty(ptr[-1], self.idx.dtype), np.empty(ptr[-1], self.vals.dtype)
        for a, b in _parts(ptr):
            take = np.repeat(self.ptr[at[a:b]] - ptr[a:b], count[a:b]) + np.arange(ptr[a], ptr[b])
            idx[ptr[a] : ptr[b]], vals[ptr[a] : ptr[b]] = self.idx[take], self.vals[take]
        return SparseRows(ptr, idx, vals, self.shape[1])

    def __matmul__(self, w: np.ndarray) -> np.ndarray:
        if len(self) == 1:
            return np.array([self.vals @ w[self.idx]])
        return self._sums(lambda cells: self.vals[cells] * w.take(self.idx[cells]))

    def __rmatmul__(self, a: np.ndarray) -> np.ndarray:
        out = np.zeros(self.shape[1])
        for i, j in _parts(self.ptr):
            cells = slice(self.ptr[i], self.ptr[j])
            out += np.bincount(self.idx[cells], np.repeat(a[i:j], np.diff(self.ptr[i : j + 1])) * self.vals[cells], self.shape[1])
        return out

    def _sums(self, values: Callable[[slice], np.ndarray]) -> np.ndarray:
        """Sum of each row's values, a bounded number of entries at a time, few enough to stay in a processor's cache."""
        out = np.zeros(len(self))
        for i, j in _small_parts(self.ptr):
            begin = self.ptr[i:j]
            some = begin < self.ptr[i + 1 : j + 1]
            if some.any():
                out[i:j][some] = np.add.reduceat(values(slice(self.ptr[i], self.ptr[j])), begin[some] - self.ptr[i])
        return out

    def norms(self) -> np.ndarray:
        if self._norms is None:
            self._norms = self._sums(lambda cells: self.vals[cells] * self.vals[cells])
        return self._norms

    def joined(self, other: SparseRows) -> SparseRows:
        return SparseRows(np.concatenate((self.ptr, self.ptr[-1] + other.ptr[1:])), np.concatenate((self.idx, other.idx)), np.concatenate((self.vals, other.vals)), self.shape[1])


class StoredRows(SparseRows):
    """Sparse rows in files of this machine (name.ptr, name.idx, name.vals), read where they are asked for."""

    def __init__(self, path: str, d: int):
        self.path = path
        idx, vals = (np.memmap(f"{path}.{part}", kind, "r").view(np.ndarray) for part, kind in (("idx", np.int32), ("vals", np.float64)))
        super().__init__(np.fromfile(f"{path}.ptr", np.int64), idx, vals, d)

    def __getitem__(self, at: np.ndarray) -> PickedRows:
        return PickedRows(self, np.flatnonzero(at) if at.dtype == bool else at)


class PickedRows(SparseRows):
    """Some of the rows in files, left there: only a bounded part of them is copied at a time."""

    def __init__(self, whole: StoredRows, at: np.ndarray):
        self.whole, self.at, self.idx, self.vals, self.shape = whole, at, whole.idx, whole.vals, (len(at), whole.shape[1])
        self.begin, self.end = whole.ptr[at], whole.ptr[at + 1]
        self.nbytes = 12 * int((self.end - self.begin).sum())

    def spans(self) -> tuple[list[int], list[int]]:
        return self.begin.tolist(), self.end.tolist()

    def __getitem__(self, at: np.ndarray) -> PickedRows:
        return PickedRows(self.whole, self.at[at])

    def _copies(self):
        for i, j in _small_parts(np.concatenate(([0], np.cumsum(self.end - self.begin)))):
            yield i, j, SparseRows.__getitem__(self.whole, self.at[i:j])

    def __matmul__(self, w: np.ndarray) -> np.ndarray:
        return np.concatenate([np.zeros(0), *(rows @ w for _, _, rows in self._copies())])

    def __rmatmul__(self, a: np.ndarray) -> np.ndarray:
        return sum((a[i:j] @ rows for i, j, rows in self._copies()), np.zeros(self.shape[1]))

    def norms(self) -> np.ndarray:
        return self.whole.norms()[self.at]

    def joined(self, other: PickedRows) -> PickedRows:
        return PickedRows(self.whole, np.concatenate((self.at, other.at)))


class Resting:
    """Products of all rows with an earlier gradient w, which tell the rows that rest as long as the gradient is near it. Passes over the same rows may share one."""

    def __init__(self):
        self.w = self.u = None
        self.due, self.vain = False, 0


def _parts(ptr: np.ndarray, entries: int = 1 << 22) -> list[tuple[int, int]]:
    """Ranges of rows of at most so many entries, a row at least."""
    return _split(ptr, entries)


def _split(ptr: np.ndarray, entries: int) -> list[tuple[int, int]]:
    ends = [0]
    while ends[-1] < len(ptr) - 1:
        ends.append(max(ends[-1] + 1, int(np.searchsorted(ptr, ptr[ends[-1]] + entries, "right")) - 1))
    return list(zip(ends, ends[1:]))


def _small_parts(ptr: np.ndarray, entries: int = 1 << 16) -> list[tuple[int, int]]:
    """Parts that stay in a processor's cache."""
    return [(a + i, a + j) for a, b in _parts(ptr) for i, j in _split(ptr[a : b + 1], entries)]


class PairRows:
    """Centred rows of length 1 that are base rows or products of two of them, of which only the base is held; it takes an array's place in passes."""

    __array_ufunc__ = None

    def __init__(self, base: np.ndarray, a: np.ndarray, b: np.ndarray, mean: np.ndarray, scale: np.ndarray):
        self.base, self.a, self.b, self.mean, self.scale, self.shape, self.nbytes = base, a, b, mean, scale, (len(a), base.shape[1]), base.nbytes

    @classmethod
    def of(cls, e: np.ndarray) -> PairRows:
        """All rows of e, then their products of pairs i <= j."""
        base, d = np.concatenate((e, np.ones((1, e.shape[1])))), e.shape[1]
        i, j = np.triu_indices(len(e))
        a, b = np.concatenate((np.arange(len(e)), i)), np.concatenate((np.full(len(e), len(e)), j))
        mean, norm = ((base @ base.T) / d)[a, b], np.zeros(len(a))
        for p in range(len(e)):
            own = np.flatnonzero(a == p)
            x = base[b[own]] * base[p] - mean[own, None]
            norm[own] = np.sqrt(np.einsum("ij,ij->i", x, x))
        return cls(base, a, b, mean, np.where(norm > 0, 1 / np.where(norm > 0, norm, 1.0), 0.0))

    def __len__(self) -> int:
        return self.shape[0]

    def __getitem__(self, at: np.ndarray) -> PairRows:
        return PairRows(self.base, self.a[at], self.b[at], self.mean[at], self.scale[at])

    def _row(self) -> np.ndarray:
        return (self.base[self.a[0]] * self.base[self.b[0]] - self.mean[0]) * self.scale[0]

    def __matmul__(self, w: np.ndarray) -> np.ndarray:
        if len(self) == 1:
            return np.array([self._row() @ w])
        return (((self.base * w) @ self.base.T)[self.a, self.b] - self.mean * w.sum()) * self.scale

    def __rmatmul__(self, alpha: np.ndarray) -> np.ndarray:
        if len(self) == 1:
            return alpha[0] * self._row()
        s, weight = alpha * self.scale, np.zeros((len(self.base), len(self.base)))
        np.add.at(weight, (self.a, self.b), s)
        return np.einsum("ij,ij->j", self.base, weight @ self.base) - s @ self.mean

    def norms(self) -> np.ndarray:
        return (self.scale > 0).astype(float)

    def joined(self, other: PairRows) -> PairRows:
        return PairRows(self.base, *(np.concatenate((p, q)) for p, q in ((self.a, other.a), (self.b, other.b), (self.mean, other.mean), (self.scale, other.scale))))


def squares(x: np.ndarray | SparseRows | PairRows) -> np.ndarray:
    """Squared length of each row."""
    return np.einsum("ij,ij->i", x, x) if isinstance(x, np.ndarray) else x.norms()


def stacked(a: np.ndarray | SparseRows | PairRows, b: np.ndarray | SparseRows | PairRows) -> np.ndarray | SparseRows | PairRows:
    return np.concatenate((a, b)) if isinstance(a, np.ndarray) else a.joined(b)


def op_norm_sq(x: np.ndarray, iterations: int = 100, seed: int = 0) -> float:
    """Squared operator norm of the block by power iteration."""
    if not x.size:
        return 0.0
    p = np.random.default_rng(seed).standard_normal(x.shape[1])
    value = 0.0
    for _ in range(iterations):
        q = x.T @ (x @ p)
        n = float(np.linalg.norm(q))
        if n == 0:
            return 0.0
        p, old, value = q / n, value, n
        if abs(value - old) <= 1e-10 * value:
            break
    return value


def _shifted(x: np.ndarray, lam: float, r: np.ndarray) -> np.ndarray:
    """Solution of (x x' + lam) z = r; the system is of the shorter side of x, so that a block of many short columns makes no square of its own size."""
    if len(x) <= x.shape[1]:
        return np.linalg.solve(x @ x.T + lam * np.eye(len(x)), r)
    return (r - x @ np.linalg.solve(x.T @ x + lam * np.eye(x.shape[1]), x.T @ r)) / lam


def exact(x: np.ndarray, alpha: np.ndarray, v: np.ndarray, obj: Objective, y: np.ndarray | float = 0.0, tolerance: float = 1e-12, most: int = 5000) -> Solved:
    """The block's optimum: a linear system for ridge, else passes until the block's gap is below the tolerance times its first value."""
    began = time.perf_counter()
    w = obj.grad(v)
    if isinstance(obj, RidgePrimal | RidgeDual):
        u = x @ w
        if isinstance(obj, RidgePrimal):
            delta = _shifted(x, obj.lam, -(u + obj.lam * alpha))
        else:
            delta = _shifted(x, obj.lam, obj.lam * (y - alpha - u))
        return Solved(delta, x.T @ delta, 0, time.perf_counter() - began)
    a, now, first, k = alpha.copy(), v.copy(), None, 0
    for k in range(1, most + 1):
        s = passes(x, a, now, obj, y, 1, seed=k)
        a, now = a + s.delta, now + s.dv
        gap = float(np.sum(obj.gap(a, x @ obj.grad(now), y)))
        first = gap if first is None else first
        if gap <= tolerance * max(1.0, first):
            break
    return Solved(a - alpha, now - v, k, time.perf_counter() - began)


def passes(x: np.ndarray, alpha: np.ndarray, v: np.ndarray, obj: Objective, y: np.ndarray | float = 0.0, k: int = 2, seed: int = 0, width: int = 1, damping: float = 1.0, sigma: float = 1.0, model: bool = False, seconds: float | None = None, tolerance: float = 0.0, cyclic: bool = False, rest: Resting | None = None) -> Solved:
    """Randomised passes over the coordinates of the block.

    width: how many coordinates are updated from the same residual (their products are one matrix product); damping then
    scales their steps. sigma: curvature factor for several workers whose changes are added. model: for non-quadratic f,
    keep the gradient at v and its quadratic bound instead of fresh gradients. Ends after k passes, after `seconds`, or
    once the block's gap is at most the tolerance.
    """
    began = time.perf_counter()
    rng = np.random.default_rng(seed)
    m, q = len(x), obj.smooth * sigma * squares(x)
    a, dv, target = alpha.copy(), np.zeros_like(v), np.broadcast_to(np.asarray(y, float), (m,))
    exact_gradient = not (obj.quadratic or model)
    w, done = obj.grad(v), 0
    if width == 1 and not exact_gradient:
        return _single(x, alpha, v, obj, q, target, k, rng, sigma, seconds, tolerance, cyclic, began, rest or Resting())
    sparse = width == 1 and isinstance(x, SparseRows) and hasattr(obj, "grad_at")
    for _ in range(k):
        order = np.arange(m) if cyclic else rng.permutation(m)
        if sparse:
            _fresh(x, order, a, v, dv, w, obj, q, target)
        for at in range(0, 0 if sparse else m, width):
            g = order[at : at + width]
            u = x[g] @ w
            step = damping * obj.step(a[g], u, q[g], target[g]) if width > 1 else obj.step(a[g], u, q[g], target[g])
            if not step.any():
                continue
            a[g] += step
            change = step @ x[g]
            dv += change
            w = obj.grad(v + dv) if exact_gradient else w + (obj.smooth * sigma) * change
        done += 1
        if seconds is not None and time.perf_counter() - began > seconds:
            break
        if tolerance and float(np.sum(obj.gap(a, x @ (obj.grad(v + dv) if not obj.quadratic or sigma != 1 else w), target))) <= tolerance:
            break
    return Solved(a - alpha, dv, done, time.perf_counter() - began)


def _single(x: np.ndarray | SparseRows, alpha: np.ndarray, v: np.ndarray, obj: Objective, q: np.ndarray, target: np.ndarray, k: int, rng: np.random.Generator, sigma: float, seconds: float | None, tolerance: float, cyclic: bool, began: float, rest: Resting) -> Solved:
    """Passes of one coordinate after the other under a gradient that is linear in the change: plain numbers but for the product and the update of the gradient.

    Where a model's coordinates can rest, those whose step is 0 wherever the gradient may have gone meanwhile are passed over; the others' steps are what they would be without that.
    Of short dense rows the next ones are looked at together, of sparse ones all, by their products with an earlier gradient.
    """
    sparse, scale, m = isinstance(x, SparseRows), obj.smooth * sigma, len(x)
    a, w, done = np.array(alpha, float), np.array(obj.grad(v), float), 0
    length = np.sqrt(q / scale)
    begin, end = x.spans() if sparse else ([], [])

    def in_turn(ids: np.ndarray, before: np.ndarray, room: float) -> tuple[int, float]:
        """Steps until the gradient is further than room from where it was: how many coordinates had their turn, and how far it is. before: their products then."""
        own, way, n, now = a[ids].tolist(), 0.0, 0, w
        for i, curve, y, u0 in zip(ids.tolist(), q[ids].tolist(), target[ids].tolist(), before.tolist()):
            row = x[i]
            u = float(row @ now)
            step = obj.step_one(own[n], u, curve, y)
            n += 1
            if step:
                own[n - 1] += step
                now += (scale * step) * row
                way += scale * step * (2 * (u - u0) + step * curve)  # squared, of the change so far and this one
                if way > room * room:
                    break
        a[ids[:n]] = own[:n]
        return n, math.sqrt(max(way, 0.0))

    def sparse_turns(ids: np.ndarray, before: np.ndarray, way: float, room: float) -> tuple[list[float], int, float]:
        """The same for sparse rows, from a gradient whose squared distance is way: products of those that had their turn, how many didn't move, and the squared distance after them."""
        own, seen, still, now, cells, vals = a[ids].tolist(), [], 0, w, x.idx, x.vals
        for n, (i, curve, y, u0) in enumerate(zip(ids.tolist(), q[ids].tolist(), target[ids].tolist(), before.tolist())):
            at, row = cells[begin[i] : end[i]].astype(np.intp), vals[begin[i] : end[i]]
            there = now[at]
            u = float(row @ there)
            step = obj.step_one(own[n], u, curve, y)
            seen.append(u)
            if step:
                own[n] += step
                now[at] = there + (scale * step) * row  # a row's places are different ones
                way += scale * step * (2 * (u - u0) + step * curve)
                if way > room * room:
                    break
            else:
                still += 1
        a[ids[: len(seen)]] = own[: len(seen)]
        return seen, still, max(way, 0.0)

    def sparse_pass(order: np.ndarray) -> None:
        nonlocal size
        if not obj.rests or m < 16 * LOOK:
            sparse_turns(order, np.zeros(m), 0.0, math.inf)
            return
        size, old, every = float(np.linalg.norm(w)), w.copy(), np.arange(m)
        if rest.due:
            rest.w, rest.u, rest.due, rest.vain = old, x @ w, False, 0
        if rest.u is None:
            seen, _, _ = sparse_turns(order, np.zeros(m), 0.0, math.inf)
            moved, u = float(np.linalg.norm(w - old)), np.empty(m)
            u[order] = seen
            rest.due = len(may_step(every, u, moved)) < 0.6 * m
            return
        way, at = float(np.sum((w - rest.w) ** 2)), 0
        room = 1.1 * math.sqrt(way) + 1e-9 * size
        while at < m:
            size = float(np.linalg.norm(w))
            left = order[at:]
            may = may_step(left, rest.u[left], room)
            seen, still, way = sparse_turns(left[may], rest.u[left[may]], way, room)
            rest.vain += still
            at = m if way <= room * room else at + int(may[len(seen) - 1]) + 1
            room = 2 * math.sqrt(way)
        # products anew cost as much as some two fifths of all turns
        rest.due = rest.vain > 0.4 * m

    def may_step(ids: np.ndarray, u: np.ndarray, reach: float) -> np.ndarray:
        """Places of ids whose step isn't 0 for all products within reach of u: a step falls as its product rises, so the ends tell. What rounding may add is counted in."""
        r, both = (reach + 1e-10 * size) * length[ids] + 1e-12, np.concatenate((ids, ids))
        return np.flatnonzero((obj.step(a[both], np.concatenate((u - r, u + r)), q[both], target[both]) != 0).reshape(2, -1).any(axis=0))

    places = _places(x) if sparse and isinstance(obj, RidgeDual) else None
    # of long rows a product together costs as much as one by one
    look, first, size = obj.rests and m >= 16 * LOOK and not sparse and x.shape[1] <= 4 * LOOK, 4 * LOOK, 0.0
    blind, again, room, wide = first if look else m, first, 0.0, LOOK
    for _ in range(k):
        order, at = np.arange(m) if cyclic else rng.permutation(m), 0
        if places is not None:
            _chained(*places, order, a, w, q, target, scale)
        elif sparse:
            sparse_pass(order)
        while at < m and not sparse:
            if blind:  # nearly all step, so that a look ahead costs more than it saves
                part, old = order[at : at + blind], w.copy() if look else w
                in_turn(part, np.zeros(len(part)), math.inf)
                at, room, blind = at + len(part), float(np.linalg.norm(w - old)), 0 if look else m
                continue
            part, size = order[at : at + wide], float(np.linalg.norm(w))
            before = x[part] @ w
            may = may_step(part, before, room)
            n, moved = in_turn(part[may], before[may], room)
            whole, share = moved <= room, len(may) / len(part)
            at += len(part) if whole else int(may[n - 1]) + 1
            blind, again = (again, min(2 * again, m)) if share > 0.8 and wide == LOOK else (0, first)
            room = 2 * moved if moved else room / 2
            wide = min(2 * wide, 32 * LOOK) if whole and share < 0.1 else max(wide // 2, LOOK) if share > 0.3 or not whole else wide
        done += 1
        if seconds is not None and time.perf_counter() - began > seconds:
            break
        if tolerance:
            now = x @ (w if obj.quadratic and sigma == 1 else obj.grad(v + (a - alpha) @ x))
            if float(np.sum(obj.gap(a, now, target))) <= tolerance:
                break
    delta = a - alpha
    changed = np.flatnonzero(delta)
    dv = delta[changed] @ x[changed] if sparse and 2 * len(changed) < m else delta @ x
    return Solved(delta, dv, done, time.perf_counter() - began)


def _places(x: SparseRows) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    """Indices and values as matrices and which places differ in their index, if rows are short and of one length and no index is at two places."""
    m = len(x)
    if type(x) is not SparseRows or m < 2 * CHAIN or x.shape[1] > 4096:
        return None
    many = len(x.idx) // m
    if not 0 < many <= 32 or (np.diff(x.ptr) != many).any():
        return None
    idx, vals = x.idx.reshape(m, many), x.vals.reshape(m, many)
    low, high = idx.min(axis=0), idx.max(axis=0)
    by = np.argsort(low)
    return (idx, vals, low < high) if (high[by][:-1] < low[by][1:]).all() else None


def _chained(idx: np.ndarray, vals: np.ndarray, differ: np.ndarray, order: np.ndarray, a: np.ndarray, w: np.ndarray, q: np.ndarray, target: np.ndarray, scale: float) -> None:
    """One pass of a dual ridge's steps, each counting all steps before it: a step is linear in the product, so those of some rows in turn solve a triangular system. Changes a and w."""
    d, many = len(w), idx.shape[1]
    for at in range(0, len(order), CHAIN * CHAINS):
        ids = order[at : at + CHAIN * CHAINS]
        more = -len(ids) % CHAIN  # rows of zeros fill the last group
        n = (len(ids) + more) // CHAIN
        i = np.pad(idx[ids], ((0, more), (0, 0))).astype(np.intp).reshape(n, CHAIN, many)
        x = np.pad(vals[ids], ((0, more), (0, 0))).reshape(n, CHAIN, many)
        curve, want = np.pad(q[ids], (0, more)), np.pad(np.where(q[ids] > 0, target[ids] - a[ids], 0.0), (0, more))
        same = x[:, :, ~differ]
        products = same @ same.transpose(0, 2, 1)
        for p in np.flatnonzero(differ):
            c, z = i[:, :, p], x[:, :, p]
            products += (c[:, :, None] == c[:, None, :]) * (z[:, :, None] * z[:, None, :])
        system = np.tril(products, -1) * scale
        system[:, range(CHAIN), range(CHAIN)] = curve.reshape(n, CHAIN) + 1.0
        steps = np.empty((n, CHAIN))
        for own, step, b, j, z in zip(np.linalg.inv(system), steps, want.reshape(n, CHAIN), i, x):
            step[:] = own @ (b - np.einsum("ij,ij->i", w.take(j), z))
            w += np.bincount(j.ravel(), ((scale * step)[:, None] * z).ravel(), d)
        a[ids] += steps.ravel()[: len(ids)]


def _fresh(x: SparseRows, order: np.ndarray, a: np.ndarray, v: np.ndarray, dv: np.ndarray, w: np.ndarray, obj: Objective, q: np.ndarray, target: np.ndarray) -> None:
    """One pass whose gradient is fresh for each coordinate: only its places change, so only there it is taken again. Changes a, dv and w."""
    begin, end = x.spans()
    for i in order.tolist():
        at, row = x.idx[begin[i] : end[i]], x.vals[begin[i] : end[i]]
        step = obj.step_one(float(a[i]), float(row @ w[at]), float(q[i]), float(target[i]))
        if step:
            a[i] += step
            dv[at] += step * row
            w[at] = obj.grad_at(v[at] + dv[at], at)


def guarded(x: np.ndarray, alpha: np.ndarray, v: np.ndarray, obj: Objective, y: np.ndarray | float = 0.0, **options) -> Solved:
    """Wide passes whose damping is halved until the objective doesn't rise."""
    before, damping = total(obj, v, alpha, y), options.pop("damping", 1.0)
    while True:
        s = passes(x, alpha, v, obj, y, damping=damping, **options)
        if total(obj, v + s.dv, alpha + s.delta, y) <= before + 1e-12 * abs(before):
            return s
        if damping < 1e-3:
            return Solved(np.zeros_like(alpha), np.zeros_like(v), 0, s.seconds)
        damping /= 2


def proximal(x: np.ndarray, alpha: np.ndarray, v: np.ndarray, obj: Objective, y: np.ndarray | float = 0.0, norm_sq: float | None = None) -> Solved:
    """One step for all coordinates at once, at the inverse of L times the block's squared norm."""
    began = time.perf_counter()
    q = np.full(len(x), obj.smooth * (norm_sq if norm_sq is not None else op_norm_sq(x)))
    delta = obj.step(alpha, x @ obj.grad(v), q, y)
    return Solved(delta, x.T @ delta, 1, time.perf_counter() - began)


SOLVERS: dict[str, Callable] = {"exact": exact, "passes": passes, "guarded": guarded, "proximal": proximal}
