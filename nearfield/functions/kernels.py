"""Dense matrix functions of one submatrix, in numpy: precisions, iterations, direct solvers, purification.

Kernels take one matrix or a stack of equal-sized ones (the last two axes are the matrix): small matrices are done many
at a time. In a stack an iteration with a residual rule goes on until the slowest has met it.

Every kernel multiplies through :class:`Precision`, so accuracy at a narrow operand format is that of the format; the
speed of narrow formats is not (a CPU has none), and flops are counted, not timed, here.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np


class KernelError(ValueError):
    """The input of a kernel does not meet its conditions."""


# ---- formats


def _keep_bits(x: np.ndarray, bits: int) -> np.ndarray:
    """float32 values rounded to so many mantissa bits, ties to even."""
    drop = 23 - bits
    raw = np.ascontiguousarray(x, np.float32).view(np.uint32)
    half = np.uint32((1 << (drop - 1)) - 1) + ((raw >> np.uint32(drop)) & np.uint32(1))
    return ((raw + half) & np.uint32(0xFFFFFFFF ^ ((1 << drop) - 1))).view(np.float32)


_FORMATS: dict[str, Callable[[np.ndarray], np.ndarray]] = {
    "fp64": lambda x: np.asarray(x, np.float64),
    "fp32": lambda x: np.asarray(x, np.float32),
    "tf32": lambda x: _keep_bits(x, 10),
    "bf16": lambda x: _keep_bits(x, 7),
    "half": lambda x: np.asarray(x, np.float32).astype(np.float16).astype(np.float32),
}


@dataclass
class Precision:
    """Operands are rounded to ``operand``, products added in fp32 (fp64 for fp64); ``stored`` also rounds results."""

    operand: str = "fp64"
    stored: bool = False
    gemms: int = field(default=0, compare=False)

    def __post_init__(self):
        if self.operand not in _FORMATS:
            raise KernelError(f"no such format: {self.operand}")

    @property
    def dtype(self):
        return np.float64 if self.operand == "fp64" else np.float32

    def round(self, x: np.ndarray) -> np.ndarray:
        return _FORMATS[self.operand](x)

    def gemm(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """One product; the last two axes are the matrix, others a batch."""
        self.gemms += 1
        out = self.round(a) @ self.round(b)
        return self.round(out) if self.stored else out


# ---- norms of what a matrix stands for


def _eye_like(a: np.ndarray) -> np.ndarray:
    return np.eye(a.shape[-1], dtype=a.dtype)


def _turn(a: np.ndarray) -> np.ndarray:
    return np.swapaxes(a, -1, -2)


class Plain:
    """Matrices that stand for themselves."""

    def size(self, a: np.ndarray):
        return a.shape[-1]

    def norm(self, a: np.ndarray):
        """Frobenius norm of each matrix."""
        return np.sqrt((a.astype(np.float64) ** 2).sum(axis=(-2, -1)))

    def rows(self, a: np.ndarray):
        """Largest sum of a row's absolute values, of each matrix."""
        return np.abs(a).sum(axis=-1).max(axis=-1)


PLAIN = Plain()


class Twins(Plain):
    """Matrices reduced by classes of like rows: rows that can be exchanged without changing the matrix.

    Such a matrix acts on a class's sum and on its differences apart. Class p has two places: 2 p holds the matrix
    between normed sums of classes, 2 p + 1 the number that multiplies each of its ``counts`` - 1 differences. Products,
    solves and functions of the reduced matrix are those of the full one, reduced; sizes and norms need the counts.
    """

    def __init__(self, counts: np.ndarray):
        self.counts = np.asarray(counts, np.float64)

    @classmethod
    def of(cls, twins: np.ndarray) -> Twins:
        """From a matrix with counts - 1 at the places 2 p + 1 of the diagonal."""
        return cls(np.diagonal(twins, axis1=-2, axis2=-1)[..., 1::2] + 1)

    def entries(self, a: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(entry between different rows of classes p and q, what a diagonal entry of class p has more)."""
        n, more = np.maximum(self.counts, 1), np.diagonal(a, axis1=-2, axis2=-1)[..., 1::2].astype(np.float64)
        off = a[..., 0::2, 0::2] / np.sqrt(n[..., :, None] * n[..., None, :])
        return off - np.eye(n.shape[-1]) * (more / n)[..., None], more

    def size(self, a: np.ndarray):
        return self.counts.sum(axis=-1)

    def norm(self, a: np.ndarray):
        some = np.minimum(self.counts, 1)
        sums = (a[..., 0::2, 0::2].astype(np.float64) ** 2 * some[..., :, None] * some[..., None, :]).sum(axis=(-2, -1))
        apart = np.diagonal(a, axis1=-2, axis2=-1)[..., 1::2].astype(np.float64)
        return np.sqrt(sums + (np.maximum(self.counts - 1, 0) * apart**2).sum(axis=-1))

    def rows(self, a: np.ndarray):
        off, more = self.entries(a)
        own = np.diagonal(off, axis1=-2, axis2=-1)
        total = (np.abs(off) * self.counts[..., None, :]).sum(axis=-1) - np.abs(own) + np.abs(own + more)
        return np.where(self.counts > 0, total, 0.0).max(axis=-1)


# ---- when to stop


@dataclass(frozen=True)
class StopRule:
    """A fixed number of steps, or until norm(X X - I) / sqrt(n) <= tol, looked at every ``every`` steps."""

    steps: int = 60
    tol: float | None = None
    every: int = 1

    @classmethod
    def fixed(cls, steps: int) -> StopRule:
        return cls(steps)

    @classmethod
    def residual(cls, tol: float, every: int = 1, most: int = 100) -> StopRule:
        return cls(most, tol, every)

    def met(self, step: int, miss: np.ndarray, space: Plain = PLAIN) -> bool:
        """``miss``: I - X X of this step."""
        return self.tol is not None and step % self.every == 0 and bool(np.all(space.norm(miss) <= self.tol * np.sqrt(space.size(miss))))


@dataclass
class Report:
    """What an iteration did: steps, products, and the last residual norm(X X - I) / sqrt(n); of a stack one each."""

    steps: int = 0
    gemms: int = 0
    residual: float | np.ndarray = np.nan


def _each(c) -> np.ndarray:
    """A number for each matrix, to multiply the matrices with."""
    return np.asarray(c)[..., None, None]


def _miss(x: np.ndarray, space: Plain = PLAIN):
    """norm(X X - I) / sqrt(n) of each matrix."""
    return space.norm(x @ x - _eye_like(x)) / np.maximum(1.0, np.sqrt(space.size(x)))


def checked(a, symmetric: bool = False) -> np.ndarray:
    a = np.asarray(a, np.float64)
    if a.ndim < 2 or a.shape[-1] != a.shape[-2]:
        raise KernelError("not square")
    if not np.isfinite(a).all():
        raise KernelError("not finite")
    if symmetric and a.size and np.abs(a - np.swapaxes(a, -1, -2)).max() > 1e-8 * max(1.0, np.abs(a).max()):
        raise KernelError("not symmetric")
    return a


# ---- scaling before iterating


def scale_of(a: np.ndarray, how: str = "norms", space: Plain = PLAIN):
    """A number at least the spectral radius: sqrt(norm1 * norminf), the Frobenius norm, or a few power steps (times 1.1)."""
    if not a.size:
        return 1.0
    if how == "norms":
        c = np.sqrt(space.rows(_turn(a)) * space.rows(a))
    elif how == "fro":
        c = space.norm(a)
    elif how == "power":
        v = np.broadcast_to((np.cos(np.arange(a.shape[-1])) + 1.5)[:, None], (*a.shape[:-1], 1))
        for _ in range(12):
            v = _turn(a) @ (a @ (v / np.maximum(_each(PLAIN.norm(v)), 1e-300)))
        c = 1.1 * np.sqrt(PLAIN.norm(v))
    else:
        raise KernelError(f"no such scaling: {how}")
    return np.where(c > 0, c, 1.0) if a.ndim > 2 else float(c) or 1.0


# ---- sign

#: Coefficients of (1 - t)^(-1/2) by powers of t: each is the one before times (2 k - 1) / (2 k).
def binomial(order: int) -> list[float]:
    out = [1.0]
    for k in range(1, order):
        out.append(out[-1] * (2 * k - 1) / (2 * k))
    return out


def sign(a, order: int = 2, stop: StopRule | None = None, precision: Precision | None = None, scale: str = "norms", report: Report | None = None, space: Plain = PLAIN) -> np.ndarray:
    """Matrix sign by X <- X p(I - X X) with the first ``order`` terms of the binomial series; order 2 is cubic.

    Needs a real spectrum without zero. ``scale`` brings the spectrum within [-1, 1] first; None leaves it, and then
    norm(A A - I) < 1 is required.
    """
    a = checked(a)
    p, stop, report = precision or Precision(), stop or StopRule.residual(1e-12), report if report is not None else Report()
    if order < 2:
        raise KernelError("the order is at least 2")
    if scale is None:
        if a.size and np.max(np.linalg.norm(a @ a - _eye_like(a), 2, axis=(-2, -1))) >= 1:
            raise KernelError("norm(A A - I) is not below 1")
        x = a.astype(p.dtype)
    else:
        x = (a / _each(scale_of(a, scale, space))).astype(p.dtype)
    before, eye, b = p.gemms, _eye_like(x), binomial(order)
    for step in range(1, stop.steps + 1):
        miss = eye - p.gemm(x, x)
        if stop.met(step, miss, space):
            break
        poly = b[-1] * miss + b[-2] * eye
        for c in b[-3::-1]:
            poly = p.gemm(poly, miss) + c * eye
        x = p.gemm(x, poly)
        report.steps = step
    report.gemms = p.gemms - before
    x = x.astype(np.float64)
    report.residual = _miss(x, space)
    if stop.tol is not None and not np.all(report.residual < max(1e-2, 10 * stop.tol)):
        raise KernelError("the sign iteration did not converge: an eigenvalue is zero, or not real")
    return x


def sign_pade(a, terms: int = 1, stop: StopRule | None = None, report: Report | None = None, space: Plain = PLAIN) -> np.ndarray:
    """Matrix sign by the principal Pade family in partial fractions: ``terms`` poles, one solve each a step.

    With m = 2 * terms poles placed by cos^2 of equidistant angles, X <- X / terms * sum 1 / (s_i (X X + t_i I)).
    """
    a = checked(a)
    stop, report = stop or StopRule.residual(1e-12, most=60), report if report is not None else Report()
    x = a / _each(scale_of(a, space=space))
    eye = _eye_like(a)
    angle = (2 * np.arange(1, terms + 1) - 1) * np.pi / (4 * terms)
    s = np.cos(angle) ** 2
    for step in range(1, stop.steps + 1):
        square = x @ x
        if stop.met(step, eye - square, space):
            break
        x = sum(np.linalg.solve(c * square + (1 - c) * eye, x) for c in s) / terms
        report.steps = step
    report.residual = _miss(x, space)
    return x


def sign_exact(a, symmetric: bool | None = None) -> np.ndarray:
    """Matrix sign by an eigensolver (of any real spectrum)."""
    a = checked(a)
    if symmetric or symmetric is None and np.allclose(a, _turn(a), atol=1e-13):
        w, v = np.linalg.eigh(a)
        return (v * np.sign(w)[..., None, :]) @ _turn(v)
    w, v = np.linalg.eig(a)
    return np.real((v * np.sign(w.real)[..., None, :]) @ np.linalg.inv(v))


# ---- roots and inverses


def coupled_roots(s, stop: StopRule | None = None, precision: Precision | None = None, report: Report | None = None, space: Plain = PLAIN) -> tuple[np.ndarray, np.ndarray]:
    """(S^(1/2), S^(-1/2)) of a symmetric positive definite matrix by one coupled iteration of both."""
    s = checked(s)
    p, stop, report = precision or Precision(), stop or StopRule.residual(1e-12), report if report is not None else Report()
    c = space.rows(s) if s.size else 1.0
    if not np.all(c > 0):
        raise KernelError("not positive definite")
    c = _each(c)
    y = (s / c).astype(p.dtype)
    eye = _eye_like(y)
    z, before = eye.copy(), p.gemms
    for step in range(1, stop.steps + 1):
        v = p.gemm(z, y)
        if stop.met(step, eye - v, space):
            break
        t = 1.5 * eye - 0.5 * v
        y, z = p.gemm(y, t), p.gemm(t, z)
        report.steps = step
    y, z = y.astype(np.float64), z.astype(np.float64)
    report.gemms = p.gemms - before
    report.residual = space.norm(z @ y - _eye_like(s)) / np.maximum(1.0, np.sqrt(space.size(s)))
    if not np.isfinite(report.residual).all() or stop.tol is not None and not np.all(report.residual < max(1e-2, 10 * stop.tol)):
        raise KernelError("the coupled iteration did not converge: the matrix is not positive definite")
    return y * np.sqrt(c), z / np.sqrt(c)


def inverse(s, how: str = "coupled", stop: StopRule | None = None, precision: Precision | None = None, report: Report | None = None, space: Plain = PLAIN) -> np.ndarray:
    """Inverse: the square of the coupled iteration's inverse root, or a Cholesky or LU solve."""
    if how == "coupled":
        p = precision or Precision()
        z = coupled_roots(s, stop, p, report, space)[1].astype(p.dtype)
        out = p.gemm(z, z).astype(np.float64)
        if report is not None:
            report.gemms += 1
        return out
    s = checked(s)
    try:
        if how == "cholesky":
            lower = np.linalg.inv(np.linalg.cholesky(s))
            return _turn(lower) @ lower
        if how == "lu":
            return np.linalg.inv(s)
    except np.linalg.LinAlgError as e:
        raise KernelError(f"{how}: {e}") from e
    raise KernelError(f"no such inverse: {how}")


def inverse_root(a, p: int, steps: int = 100, tol: float = 1e-12, space: Plain = PLAIN) -> np.ndarray:
    """A^(-1/p) of a symmetric positive definite matrix: Z <- Z ((p + 1) I - Z^p A) / p, after scaling."""
    a = checked(a)
    c = _each(space.rows(a) if a.size else 1.0)
    b, eye, n = a / c, _eye_like(a), space.size(a)
    z = np.broadcast_to(eye, a.shape).copy()
    for _ in range(steps):
        m = np.linalg.matrix_power(z, p) @ b
        if np.all(space.norm(m - eye) <= tol * np.sqrt(n)):
            break
        z = z @ ((p + 1) * eye - m) / p
    if not np.isfinite(z).all() or np.any(space.norm(np.linalg.matrix_power(z, p) @ b - eye) > 1e-6 * np.maximum(1, n)):
        raise KernelError("the root iteration did not converge: the matrix is not positive definite")
    return z / c ** (1 / p)


def polynomial(a, coefficients) -> np.ndarray:
    """c0 I + c1 A + c2 A A + ..., by Horner."""
    a = checked(a)
    out = np.zeros_like(a)
    eye = _eye_like(a)
    for c in reversed(list(coefficients)):
        out = out @ a + c * eye
    return out


def spectral(a, f: Callable[[np.ndarray], np.ndarray]) -> np.ndarray:
    """f of a symmetric matrix by its eigenvectors."""
    w, v = np.linalg.eigh(checked(a, symmetric=True))
    return (v * f(w)[..., None, :]) @ _turn(v)


# ---- the registry of matrix functions


@dataclass(frozen=True)
class MatFn:
    """A named matrix function of one submatrix; ``MatFn.sign(mu)(a)`` and so on.

    ``stacks``: whether the function also takes a stack of equal-sized matrices; ``norms``: whether ``call`` takes the
    space too, as it scales or stops by norms.
    """

    name: str
    call: Callable[..., np.ndarray]
    stacks: bool = True
    norms: bool = False

    def __call__(self, a: np.ndarray, space: Plain = PLAIN) -> np.ndarray:
        return self.call(a, space) if self.norms else self.call(a)

    @staticmethod
    def sign(mu: float = 0.0, order: int = 2, stop: StopRule | None = None, operand: str = "fp64", solver: str = "iterate") -> MatFn:
        if solver == "exact":
            return MatFn("sign", lambda a: sign_exact(a - mu * np.eye(a.shape[-1])))
        if solver == "pade":
            return MatFn("sign", lambda a, space: sign_pade(a - mu * np.eye(a.shape[-1]), order, stop, space=space), norms=True)
        return MatFn("sign", lambda a, space: sign(a - mu * np.eye(a.shape[-1]), order, stop, Precision(operand), space=space), norms=True)

    @staticmethod
    def inverse(how: str = "coupled", stop: StopRule | None = None, operand: str = "fp64") -> MatFn:
        return MatFn("inverse", lambda a, space: inverse(a, how, stop, Precision(operand), space=space), norms=True)

    @staticmethod
    def inv_sqrt(stop: StopRule | None = None) -> MatFn:
        return MatFn("inv_sqrt", lambda a, space: coupled_roots(a, stop, space=space)[1], norms=True)

    @staticmethod
    def sqrt(stop: StopRule | None = None) -> MatFn:
        return MatFn("sqrt", lambda a, space: coupled_roots(a, stop, space=space)[0], norms=True)

    @staticmethod
    def root(p: int) -> MatFn:
        return MatFn(f"root{p}", lambda a, space: a @ np.linalg.matrix_power(inverse_root(a, p, space=space), p - 1), norms=True)

    @staticmethod
    def poly(coefficients) -> MatFn:
        own = tuple(coefficients)
        return MatFn("poly", lambda a: polynomial(a, own))

    @staticmethod
    def spectral(f: Callable[[np.ndarray], np.ndarray], name: str = "spectral") -> MatFn:
        return MatFn(name, lambda a: spectral(a, f))


# ---- purification of a pair


@dataclass(frozen=True)
class Purification:
    """How a pair of submatrices becomes a density matrix.

    ``inverse``: coupled, cholesky or lu; ``solver``: iterate, pade, exact (all: sign), or eigen (the generalised
    eigenproblem); fixed steps if ``k_inverse`` or ``k_sign`` is given, else by residual ``tol``.
    """

    mu: float = 0.0
    inverse: str = "coupled"
    solver: str = "iterate"
    order: int = 2
    k_inverse: int | None = None
    k_sign: int | None = None
    tol: float = 1e-12
    operand: str = "fp64"
    pad: int = 1

    @property
    def stacks(self) -> bool:
        """Whether a stack takes the same steps as its matrices one by one."""
        iterates = self.inverse == "coupled" and self.k_inverse is None or self.solver in ("iterate", "pade") and self.k_sign is None
        return self.solver == "eigen" or not iterates

    def stop(self, k: int | None) -> StopRule:
        floor = {"fp64": self.tol, "fp32": max(self.tol, 1e-5), "tf32": 5e-3, "bf16": 3e-2, "half": 5e-3}[self.operand]
        return StopRule.fixed(k) if k is not None else StopRule.residual(floor, most=60)


def padded_twins(h: np.ndarray, s: np.ndarray, to: int, mu: float, space: Twins) -> tuple[np.ndarray, np.ndarray, Twins]:
    """``padded`` of reduced matrices: the functions added are one more class, which may be empty."""
    n, size = h.shape[-1], space.size(h)
    more = -(-size // to) * to - size
    if not np.any(more):
        return h, s, space
    big_h, big_s = np.zeros((*h.shape[:-2], n + 2, n + 2)), np.broadcast_to(np.eye(n + 2), (*h.shape[:-2], n + 2, n + 2)).copy()
    big_h[..., :n, :n], big_s[..., :n, :n] = h, s
    big_h[..., range(n, n + 2), range(n, n + 2)] = np.asarray(mu + np.maximum(1.0, space.rows(_turn(h))))[..., None]
    return big_h, big_s, Twins(np.concatenate([space.counts, np.asarray(more)[..., None]], axis=-1))


def padded(h: np.ndarray, s: np.ndarray, to: int, mu: float) -> tuple[np.ndarray, np.ndarray]:
    """The pair grown to a multiple of ``to`` by functions that couple to nothing and lie as far from mu as h's norm."""
    n = h.shape[-1]
    m = -(-n // to) * to
    if m == n:
        return h, s
    big_h, big_s = np.zeros((*h.shape[:-2], m, m)), np.broadcast_to(np.eye(m), (*h.shape[:-2], m, m)).copy()
    big_h[..., :n, :n], big_s[..., :n, :n] = h, s
    big_h[..., range(n, m), range(n, m)] = (mu + np.maximum(1.0, np.abs(h).sum(axis=-2).max(axis=-1, initial=1.0)))[..., None]
    return big_h, big_s


def generalised_eigen(h: np.ndarray, s: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(e, C) with H C = S C e and C' S C = I."""
    try:
        back = np.linalg.inv(np.linalg.cholesky(checked(s, symmetric=True)))
    except np.linalg.LinAlgError as e:
        raise KernelError(f"the overlap is not positive definite: {e}") from e
    e, v = np.linalg.eigh(back @ h @ _turn(back))
    return e, _turn(back) @ v


def purify(h, s, how: Purification, with_w: bool = True, space: Plain = PLAIN) -> tuple[np.ndarray, np.ndarray | None, dict]:
    """(D, W, what was done) of one pair: D = (I - sign(S^-1 H - mu I)) S^-1 / 2 and W = D H D."""
    h, s = checked(h), checked(s)
    n = h.shape[-1]
    done = {"k_inverse": 0, "k_sign": 0, "residual": 0.0, "gemms": 0}
    if how.solver == "eigen":
        e, c = generalised_eigen(h, s)
        filled = e < how.mu
        if h.ndim == 2:
            e, c, filled = e[filled], c[:, filled], 1.0
        d = (c * np.asarray(filled)[..., None, :] if h.ndim > 2 else c) @ _turn(c)
        return d, ((c * (e * filled)[..., None, :]) @ _turn(c) if with_w else None), done
    if isinstance(space, Twins):
        big_h, big_s, space = padded_twins(h, s, how.pad, how.mu, space)
    else:
        big_h, big_s = padded(h, s, how.pad, how.mu)
    p, r_inverse, r_sign = Precision(how.operand), Report(), Report()
    inv = inverse(big_s, how.inverse, how.stop(how.k_inverse), p, r_inverse, space)
    eye = _eye_like(big_h)
    a = p.gemm(inv.astype(p.dtype), big_h.astype(p.dtype)).astype(np.float64) - how.mu * eye
    if how.solver == "iterate":
        x = sign(a, how.order, how.stop(how.k_sign), p, report=r_sign, space=space)
    elif how.solver == "pade":
        x = sign_pade(a, how.order, how.stop(how.k_sign), r_sign, space)
    elif how.solver == "exact":
        x = sign_exact(a, symmetric=False)
    else:
        raise KernelError(f"no such solver: {how.solver}")
    d = 0.5 * p.gemm((eye - x).astype(p.dtype), inv.astype(p.dtype)).astype(np.float64)
    w = p.gemm(p.gemm(d.astype(p.dtype), big_h.astype(p.dtype)), d.astype(p.dtype)).astype(np.float64)[..., :n, :n] if with_w else None
    done |= {"k_inverse": r_inverse.steps, "k_sign": r_sign.steps, "residual": r_sign.residual, "gemms": p.gemms}
    return d[..., :n, :n], w, done


def spectral_weights(h, s, own, times: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(levels, weight of the owned functions in each): the owned part of an electron count at any potential.

    ``times``: how many functions each place stands for, if not one.
    """
    e, c = generalised_eigen(checked(h), checked(s))
    own = np.asarray(own)
    return e, (c[own] * (np.asarray(s)[own] @ c) * (1.0 if times is None else times[own, None])).sum(axis=0)


def batched(function: Callable[[np.ndarray], np.ndarray], matrices: list[np.ndarray]) -> list[np.ndarray]:
    """Apply a kernel that takes a stack to matrices of many sizes: equal sizes together."""
    out: list[np.ndarray | None] = [None] * len(matrices)
    by: dict[int, list[int]] = {}
    for i, m in enumerate(matrices):
        by.setdefault(len(m), []).append(i)
    for places in by.values():
        for i, r in zip(places, function(np.stack([matrices[i] for i in places])), strict=True):
            out[i] = r
    return out  # type: ignore[return-value]
