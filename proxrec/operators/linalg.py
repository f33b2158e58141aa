"""Symmetric operators on items and the eigen-solvers that need only their products."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np


#: Residuals, as a share of the largest value, that rounding alone may leave.
ROUNDING = 1e-7

#: Bytes of the basis and its images, and of one block, that a block solve holds on the driver.
BASIS_BYTES, BLOCK_BYTES = 200_000_000, 24_000_000


class Csr:
    """Rows of a sparse matrix; products by segment sums (no SciPy)."""

    def __init__(self, row: np.ndarray, column: np.ndarray, value: np.ndarray, shape: tuple[int, int]):
        order = np.lexsort((column, row))
        self.row, self.column, self.value, self.shape = row[order], column[order], value[order], shape
        back = np.argsort(self.column, kind="stable")
        self.t_row, self.t_column, self.t_value = self.row[back], self.column[back], self.value[back]

        self.first, self.t_first = self._starts(self.row), self._starts(self.t_column)

    @staticmethod
    def _starts(keys: np.ndarray) -> np.ndarray:
        return np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, np.int64)

    @staticmethod
    def _product(keys: np.ndarray, first: np.ndarray, value: np.ndarray, x: np.ndarray, at: np.ndarray, n: int) -> np.ndarray:
        out = np.zeros((n, x.shape[1]))
        if len(first) and x.shape[1] == 1:
            out[keys[first], 0] = np.add.reduceat(value * x[:, 0][at], first)
        elif len(first):
            out[keys[first]] = np.add.reduceat(value[:, None] * x[at], first, axis=0)
        return out

    def dot(self, x: np.ndarray) -> np.ndarray:
        return self._product(self.row, self.first, self.value, x, self.column, self.shape[0])

    def tdot(self, y: np.ndarray) -> np.ndarray:
        return self._product(self.t_column, self.t_first, self.t_value, y, self.t_row, self.shape[1])


class DenseOperator:
    def __init__(self, a: np.ndarray):
        self.a, self.m, self.passes = a, len(a), 0

    def apply(self, x: np.ndarray) -> np.ndarray:
        self.passes += 1
        return self.a @ x


class LocalOperator:
    """g (R'R / scale - shift shift') g with R sparse on the driver: cosine (shift 0) and Pearson (shift the means, scale n)."""

    def __init__(self, r: Csr, g: np.ndarray, scale: float = 1.0, shift: np.ndarray | None = None):
        self.r, self.g, self.scale, self.shift, self.m, self.passes = r, g[:, None], scale, shift, r.shape[1], 0

    def gram(self, x: np.ndarray) -> np.ndarray:
        return self.r.tdot(self.r.dot(x))

    def apply(self, x: np.ndarray) -> np.ndarray:
        self.passes += 1
        z = self.g * x
        y = self.gram(z) / self.scale
        if self.shift is not None:
            y = y - self.shift[:, None] * (self.shift @ z)
        return self.g * y


class PairsOperator:
    """S K S from a sparse symmetric K on the driver."""

    def __init__(self, k: Csr, s: np.ndarray):
        self.k, self.s, self.m, self.passes = k, s[:, None], k.shape[0], 0

    def apply(self, x: np.ndarray) -> np.ndarray:
        self.passes += 1
        return self.s * self.k.dot(self.s * x)


class FilteredOperator:
    """A Chebyshev polynomial of an operator that damps the spectrum within an interval; eigenvectors stay."""

    def __init__(self, op, low: float, high: float, degree: int = 6):
        self.op, self.degree, self.m = op, degree, op.m
        self.centre, self.half = (low + high) / 2, (high - low) / 2

    @property
    def passes(self) -> int:
        return self.op.passes

    def apply(self, x: np.ndarray) -> np.ndarray:
        step = lambda y: (self.op.apply(y) - self.centre * y) / self.half
        before, now = x, step(x)
        for _ in range(self.degree - 1):
            before, now = now, 2 * step(now) - before
        return now


@dataclass
class Trace:
    """What a solve has cost and how well it ended."""

    steps: int = 0
    passes: int = 0
    product_s: float = 0.0
    orth_s: float = 0.0
    tri_s: float = 0.0
    residuals: list[float] = field(default_factory=list)
    path: str = ""

    def shares(self) -> dict[str, float]:
        total = max(1e-12, self.product_s + self.orth_s + self.tri_s)
        return {"product": self.product_s / total, "orthogonalisation": self.orth_s / total, "tridiagonal": self.tri_s / total}


@dataclass
class Eigen:
    values: np.ndarray
    vectors: np.ndarray
    trace: Trace


def ritz(diag: np.ndarray, off: np.ndarray, beta: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Values, vectors and residual norms of the tridiagonal problem, by value from the largest."""
    t = np.diag(diag) + np.diag(off, 1) + np.diag(off, -1)
    values, vectors = np.linalg.eigh(t)
    values, vectors = values[::-1], vectors[:, ::-1]
    return values, vectors, np.abs(beta * vectors[-1])


def _order(values: np.ndarray, which: str) -> np.ndarray:
    return np.argsort(-np.abs(values) if which == "LM" else -values, kind="stable")


def lanczos(op, f: int, tol: float = 1e-8, max_steps: int | None = None, seed: int = 1, which: str = "LA", reorth: str = "full", check_every: int = 10, allow_partial: bool = False) -> Eigen:
    """The f leading eigenpairs. reorth: none (three terms only), full, or twice. A zero residual restarts with a fresh orthogonal vector.

    Without ``max_steps`` it goes on until the residuals reach tol, at the latest when the basis spans the space; an end before that is an
    error unless ``allow_partial``.
    """
    m = op.m
    f = min(f, m)
    most = min(m, max_steps or m)
    rng, trace = np.random.default_rng(seed), Trace(path=f"lanczos-{reorth}")
    q = np.zeros((m, min(most, 2 * f + 50)), order="F")
    diag, off = np.zeros(most), np.zeros(most)
    r = rng.standard_normal(m)
    beta = np.linalg.norm(r)
    scale = 0.0
    for j in range(most):
        if j == q.shape[1]:
            q = np.hstack([q, np.zeros((m, min(most, 2 * j) - j), order="F")])
        q[:, j] = r / beta
        t0 = time.perf_counter()
        r = op.apply(q[:, j : j + 1])[:, 0]
        t1 = time.perf_counter()
        if j and off[j - 1]:
            r = r - q[:, j - 1] * off[j - 1]
        diag[j] = q[:, j] @ r
        r = r - q[:, j] * diag[j]
        for _ in range({"none": 0, "full": 1, "twice": 2}[reorth]):
            r = r - q[:, : j + 1] @ (q[:, : j + 1].T @ r)
        beta = np.linalg.norm(r)
        trace.product_s, trace.orth_s = trace.product_s + t1 - t0, trace.orth_s + time.perf_counter() - t1
        scale = max(scale, abs(diag[j]) + beta)
        broke = beta <= 1e-13 * max(scale, 1e-300)
        trace.steps = j + 1
        if j + 1 >= f and ((j + 1) % check_every == 0 or j + 1 == most or broke):
            t2 = time.perf_counter()
            values, xi, delta = ritz(diag[: j + 1], off[:j], 0.0 if broke else beta)
            lead = _order(values, which)[:f]
            trace.tri_s += time.perf_counter() - t2
            trace.residuals = delta[lead].tolist()
            full = j + 1 == m
            if full or (max(trace.residuals) <= tol * max(abs(values).max(), 1e-300) and not (broke and reorth == "none")):
                # an invariant subspace found by breakdown may lack copies of an eigenvalue, so go on unless it is the whole space
                if not broke or full:
                    trace.passes = op.passes
                    return Eigen(values[lead], q[:, : j + 1] @ xi[:, lead], trace)
        if broke:
            off[j] = 0.0
            r = rng.standard_normal(m)
            for _ in range(2):
                r = r - q[:, : j + 1] @ (q[:, : j + 1].T @ r)
            beta = np.linalg.norm(r)
            if beta <= 1e-10:
                break
        else:
            off[j] = beta
    trace.passes = op.passes
    if not allow_partial:
        raise ArithmeticError(f"not converged in {trace.steps} steps; residuals {trace.residuals}")
    values, xi, delta = ritz(diag[: trace.steps], off[: trace.steps - 1], beta)
    lead = _order(values, which)[:f]
    trace.residuals = delta[lead].tolist()
    return Eigen(values[lead], q[:, : trace.steps] @ xi[:, lead], trace)


def settled(trace: Trace, done: bool, allow_partial: bool) -> None:
    if not done and not allow_partial:
        raise ArithmeticError(f"{trace.path}: not converged in {trace.steps} steps; largest residual {max(trace.residuals):.3g}")


def thick_restart_lanczos(op, f: int, width: int | None = None, tol: float = 1e-8, restarts: int = 200, seed: int = 1, allow_partial: bool = False) -> Eigen:
    """Lanczos in a basis of at most ``width`` vectors, restarted with the leading Ritz vectors; running out of restarts is an error unless allowed."""
    m = op.m
    f = min(f, m)
    width = min(m, width or max(2 * f + 10, f + 20))
    rng, trace = np.random.default_rng(seed), Trace(path="thick-restart")
    basis = np.linalg.qr(rng.standard_normal((m, 1)))[0]
    done = False
    for _ in range(restarts):
        t0 = time.perf_counter()
        images = op.apply(basis)
        trace.product_s += time.perf_counter() - t0
        while basis.shape[1] < width:
            t1 = time.perf_counter()
            r = images[:, -1]
            for _ in range(2):
                r = r - basis @ (basis.T @ r)
            norm = np.linalg.norm(r)
            if norm <= 1e-12 * max(1.0, np.linalg.norm(images[:, -1])):
                r = rng.standard_normal(m)
                for _ in range(2):
                    r = r - basis @ (basis.T @ r)
                norm = np.linalg.norm(r)
            basis = np.hstack([basis, (r / norm)[:, None]])
            t2 = time.perf_counter()
            images = np.hstack([images, op.apply(basis[:, -1:])])
            trace.orth_s, trace.product_s = trace.orth_s + t2 - t1, trace.product_s + time.perf_counter() - t2
            trace.steps += 1
        small = basis.T @ images
        values, xi = np.linalg.eigh((small + small.T) / 2)
        values, xi = values[::-1][:f], xi[:, ::-1]
        vectors = basis @ xi[:, :f]
        residual = images @ xi[:, :f] - vectors * values
        trace.residuals = np.linalg.norm(residual, axis=0).tolist()
        done = max(trace.residuals) <= tol * max(abs(values[0]), 1e-300) or width == m
        if done:
            break
        extra = residual[:, int(np.argmax(trace.residuals))]
        kept = basis @ xi[:, : min(width - 2, f + 5)]
        extra = extra - kept @ (kept.T @ extra)
        basis = np.hstack([kept, (extra / np.linalg.norm(extra))[:, None]])
    trace.passes = op.passes
    settled(trace, done, allow_partial)
    return Eigen(values, vectors, trace)


def block_subspace(op, f: int, oversample: int = 20, passes: int = 200, tol: float = 1e-10, seed: int = 1, allow_partial: bool = False) -> Eigen:
    """Block Krylov iteration from a random block: few products of many columns each, for operators whose passes are dear.

    Ends when the residuals reach tol, or stand below ROUNDING with values that no longer move; running out of passes is an error unless allowed.
    For many items the basis restarts earlier and the block is narrower, so that both keep to their bytes, with a few columns more than f at least.
    """
    f = min(f, op.m)
    width = min(op.m, max(f + min(oversample, 4), min(f + oversample, BLOCK_BYTES // (8 * op.m))))
    most = max(2 * width, min(8 * width, BASIS_BYTES // (16 * op.m)))
    trace = Trace(path="block-subspace")
    block = np.random.default_rng(seed).standard_normal((op.m, width))
    basis = image = np.zeros((op.m, 0))
    before = np.full(f, np.inf)
    done = False
    for _ in range(passes):
        t0 = time.perf_counter()
        for _ in range(2):
            block = block - basis @ (basis.T @ block)
            u, s, _ = np.linalg.svd(block, full_matrices=False)
            block = u[:, s > 1e-10 * max(s[0], 1e-300)]
        t1 = time.perf_counter()
        fresh = op.apply(block)
        trace.orth_s, trace.product_s = trace.orth_s + t1 - t0, trace.product_s + time.perf_counter() - t1
        trace.steps += 1
        basis = np.hstack([basis, block])
        image = np.hstack([image, fresh])
        small = basis.T @ image
        values, xi = np.linalg.eigh((small + small.T) / 2)
        values, xi = values[::-1], xi[:, ::-1]
        vectors = basis @ xi[:, :f]
        trace.residuals = np.linalg.norm(image @ xi[:, :f] - vectors * values[:f], axis=0).tolist()
        top = max(abs(values[0]), 1e-300)
        still = np.abs(values[:f] - before).max() <= 1e-15 * top and max(trace.residuals) <= ROUNDING * top
        done = max(trace.residuals) <= tol * top or still or basis.shape[1] >= op.m
        if done:
            break
        before = values[:f].copy()
        block = fresh
        if basis.shape[1] > most:
            block = image @ xi[:, :width]
            kept = xi[:, : min(2 * width, max(width, most - width))]
            basis = basis @ kept
            image = image @ kept
    trace.passes = op.passes
    settled(trace, done, allow_partial)
    return Eigen(values[:f], vectors, trace)


def filtered_lanczos(op, f: int, tol: float = 1e-8, degree: int = 8, seed: int = 1, allow_partial: bool = False) -> Eigen:
    """Lanczos on a Chebyshev filter of a positive semi-definite operator: a short run bounds the unwanted part of the spectrum, which the filter damps."""
    f = min(f, op.m)
    look = lanczos(op, min(op.m, f + 1), tol=0.0, max_steps=min(op.m, 3 * f + 30), seed=seed, allow_partial=True)
    if look.trace.steps == op.m:
        return Eigen(look.values[:f], look.vectors[:, :f], look.trace)
    high = 0.95 * max(look.values[-1], 1e-12 * max(look.values[0], 1e-300))
    scale = lambda x: np.cosh(degree * np.arccosh(max(1.0, 2 * x / high - 1)))
    # the filter stretches the spectrum, so residuals are asked of the operator itself
    inner = tol
    for _ in range(6):
        found = lanczos(FilteredOperator(op, 0.0, high, degree), f, inner, seed=seed, allow_partial=allow_partial)
        values = np.einsum("ij,ij->j", found.vectors, images := op.apply(found.vectors))
        residuals = np.linalg.norm(images - found.vectors * values, axis=0)
        if residuals.max() <= tol * values.max() or inner < 1e-15:
            break
        inner *= min(0.1, scale(values.min()) / scale(values.max()))
    order = np.argsort(-values, kind="stable")
    found.trace.path, found.trace.residuals, found.trace.passes = "filtered", residuals[order].tolist(), op.passes
    settled(found.trace, residuals.max() <= max(tol, ROUNDING) * values.max(), allow_partial)
    return Eigen(values[order], found.vectors[:, order], found.trace)


def dense_eigh(a: np.ndarray, f: int, which: str = "LA") -> Eigen:
    if len(a) > 10_000:
        raise MemoryError(f"{len(a)} items are too many for a dense solve")
    values, vectors = np.linalg.eigh((a + a.T) / 2)
    lead = _order(values, which)[: min(f, len(a))]
    return Eigen(values[lead], vectors[:, lead], Trace(path="dense"))


def factor_eigh(w: np.ndarray, f: int) -> Eigen:
    """The f leading eigenpairs of w'w from the smaller of its two products, for matrices that the driver holds densely."""
    n, m = w.shape
    if n >= m:
        return dense_eigh(w.T @ w, f)
    values, u = np.linalg.eigh(w @ w.T)
    lead = np.argsort(-values, kind="stable")[: min(f, n)]
    values, u = np.maximum(values[lead], 0), u[:, lead]
    good = values > 1e-14 * max(values[0], 1e-300)
    vectors = np.zeros((m, len(values)))
    vectors[:, good] = w.T @ u[:, good] / np.sqrt(values[good])
    return Eigen(values, vectors, Trace(path="factor"))
