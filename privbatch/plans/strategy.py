"""Strategies, their errors, and the spectral lower bound (P = 1 throughout unless given)."""

from __future__ import annotations

import numpy as np

from .workload import kron, spectrum_all_range

# ---- baselines ------------------------------------------------------------------------------


def identity(n: int) -> np.ndarray:
    return np.eye(n)


def hierarchical(n: int, fanout: int = 2) -> np.ndarray:
    """Counts of the whole domain, its fanout parts and so on down to single cells; ragged where n is no power."""
    rows, level = [], [(0, n)]
    while True:
        rows += level
        if all(b - a == 1 for a, b in level):
            break
        nxt = []
        for a, b in level:
            cuts = np.unique(np.linspace(a, b, min(fanout, b - a) + 1).round().astype(int))
            nxt += list(zip(cuts[:-1], cuts[1:], strict=True))
        level = nxt
    out = np.zeros((len(rows), n))
    for r, (a, b) in enumerate(rows):
        out[r, a:b] = 1
    return out


def haar(n: int) -> np.ndarray:
    """Total row, then +1/-1 rows of halving support; n is a power of two (pad with public empty cells)."""
    if n & (n - 1):
        raise ValueError("n must be a power of two")
    rows = [np.ones(n)]
    s = n
    while s > 1:
        for a in range(0, n, s):
            r = np.zeros(n)
            r[a : a + s // 2], r[a + s // 2 : a + s] = 1, -1
            rows.append(r)
        s //= 2
    return np.array(rows)


def haar_iso(dims: tuple[int, ...]) -> np.ndarray:
    """Isotropic wavelet on equal power-of-two axes: all sign patterns of one scale at a time."""
    from itertools import product

    n, rows = int(np.prod(dims)), [np.ones(int(np.prod(dims)))]
    s = max(dims)
    while s > 1:
        for corner in product(*[range(0, d, s) for d in dims]):
            for pattern in product((0, 1), repeat=len(dims)):
                if any(pattern):
                    axes = []
                    for d, a, p in zip(dims, corner, pattern, strict=True):
                        v = np.zeros(d)
                        v[a : a + s] = 1
                        if p:
                            v[a + s // 2 : a + s] = -1
                        axes.append(v)
                    rows.append(kron([v[None, :] for v in axes]).ravel())
        s //= 2
    assert len(rows) == n
    return np.array(rows)


def hierarchical_iso(dims: tuple[int, ...]) -> np.ndarray:
    """Counts of boxes that halve along all axes at once, down to single cells; equal power-of-two axes."""
    from itertools import product

    rows, s = [], max(dims)
    while s:
        for corner in product(*[range(0, d, s) for d in dims]):
            rows.append(kron([((np.arange(d) >= a) & (np.arange(d) < a + s)).astype(float)[None, :] for d, a in zip(dims, corner, strict=True)]).ravel())
        s //= 2
    return np.array(rows)


def tree_levels(n: int) -> list[list[tuple[tuple[int, int], ...]]]:
    """The binary tree as levels of boxes, single cells first: a point of the space that the level search looks through."""
    return [[((a, a + s),) for a in range(0, n, s)] for s in (1 << k for k in range(n.bit_length()))]


def haar_levels(n: int) -> list[list[tuple[tuple[int, int], ...]]]:
    """Levels with the wavelet's Gram matrix: single cells twice, then intervals of 2, 4 and so on up to half the domain."""
    return [[((a, a + s),) for a in range(0, n, s)] for s in (1, *(1 << k for k in range(n.bit_length() - 1)))]


# ---- measures ---------------------------------------------------------------------------------


def l2(a: np.ndarray) -> float:
    return float(np.sqrt((a * a).sum(axis=0).max()))


def l1(a: np.ndarray) -> float:
    return float(np.abs(a).sum(axis=0).max())


def trace_error(gram: np.ndarray, strategy: np.ndarray, tol: float = 1e-9) -> float:
    """tr(G M^+) for the Gram matrices of workload and strategy; an error if the strategy leaves a query open.

    The rank of M is read off its spectrum, and what the workload has outside is compared with the
    whole of it, so that neither scale matters.
    """
    values, vectors = np.linalg.eigh((strategy + strategy.T) / 2)
    kept = values > tol * max(values[-1], 0)
    inside = vectors[:, kept]
    own = np.einsum("ik,ik->k", inside, gram @ inside)
    if np.trace(gram) - own.sum() > 1e-7 * np.trace(gram):
        raise ValueError("the strategy does not support the workload")
    return float((own / values[kept]).sum())


def supports(a: np.ndarray, gram: np.ndarray) -> bool:
    """Whether every workload query is a combination of strategy rows."""
    try:
        trace_error(gram, a.T @ a)
    except ValueError:
        return False
    return True


def total_error(gram: np.ndarray, a: np.ndarray, p: float = 1.0) -> float:
    """P ||A||^2 tr(W'W (A'A)^+), the summed mean squared error of the workload."""
    return p * l2(a) ** 2 * trace_error(gram, a.T @ a)


def average_error(gram: np.ndarray, a: np.ndarray, queries: int, p: float = 1.0) -> tuple[float, float]:
    """(mean squared error of a query on average, its root)."""
    mean = total_error(gram, a, p) / queries
    return mean, float(np.sqrt(mean))


def error_ratio(gram: np.ndarray, a: np.ndarray) -> float:
    """Total error over the spectral bound."""
    return total_error(gram, a) / bound_of_gram(gram)


def total_error_pure(gram: np.ndarray, a: np.ndarray, eps: float = 1.0) -> float:
    """The same under the eps-only notion: Laplace noise and L1 sensitivity."""
    return 2 * l1(a) ** 2 / eps**2 * trace_error(gram, a.T @ a)


def query_error(w: np.ndarray, a: np.ndarray, p: float = 1.0) -> float:
    return p * l2(a) ** 2 * float(w @ np.linalg.pinv(a.T @ a, hermitian=True) @ w)


def bound_of_spectrum(values: np.ndarray, p: float = 1.0) -> float:
    return p * float(np.sqrt(np.clip(values, 0, None)).sum()) ** 2 / len(values)


def bound_of_gram(gram: np.ndarray, p: float = 1.0) -> float:
    return bound_of_spectrum(np.linalg.eigvalsh(gram), p)


def bound_of_rows(w: np.ndarray, p: float = 1.0) -> float:
    """From the singular values of the workload itself."""
    return p * float(np.linalg.svd(w, compute_uv=False).sum()) ** 2 / w.shape[1]


def bound_all_range(dims: tuple[int, ...]) -> float:
    """In closed form: the bound of a product workload is the product of the bounds."""
    return float(np.prod([bound_of_spectrum(spectrum_all_range(n)) for n in dims]))


def bound_merged(gram: np.ndarray) -> float:
    """After merging cells with equal workload columns: still valid, never lower."""
    _, first = np.unique(gram.round(9), axis=0, return_index=True)
    keep = np.sort(first)
    return bound_of_gram(gram[np.ix_(keep, keep)])


def agnostic_root(a: float, b: float, n: int) -> tuple[float, float]:
    """alpha, beta of the strategy alpha I + beta J that attains the bound for the Gram matrix a I + b J."""
    alpha = a**0.25
    return alpha, ((a + n * b) ** 0.25 - alpha) / n


def spectral_strategy(gram: np.ndarray) -> np.ndarray:
    """A with A'A = G^(1/2); attains the bound whenever G^(1/2) has a constant diagonal."""
    values, vectors = np.linalg.eigh(gram)
    return np.clip(values, 0, None)[:, None] ** 0.25 * vectors.T


def column_norms(a: np.ndarray) -> np.ndarray:
    return (a * a).sum(axis=0)


def is_column_uniform(a: np.ndarray, tol: float = 1e-9) -> bool:
    c = column_norms(a)
    return bool(c.max() - c.min() <= tol * max(1.0, c.max()))


def complete_columns(a: np.ndarray) -> np.ndarray:
    """One-cell rows that bring every column to the largest norm: same sensitivity, never more error."""
    gap = column_norms(a).max() - column_norms(a)
    extra = np.diag(np.sqrt(np.clip(gap, 0, None)))
    return np.concatenate([a, extra[gap > 1e-12]])


def merge_redundant(a: np.ndarray) -> np.ndarray:
    """Rows that are multiples of one another become one; their weights add in squares."""
    size = np.linalg.norm(a, axis=1)
    unit = a[size > 0] / size[size > 0, None]
    unit *= np.sign(unit[np.arange(len(unit)), (unit != 0).argmax(axis=1)])[:, None]
    rows, where = np.unique(unit.round(10), axis=0, return_inverse=True)
    return rows * np.sqrt(np.bincount(where.ravel(), weights=size[size > 0] ** 2))[:, None]


def compare(a: np.ndarray, b: np.ndarray, tol: float = 1e-9) -> str:
    """Which strategy answers every query at least as well: 'first', 'second', 'equal' or 'neither'."""
    d = l2(a) ** 2 * np.linalg.inv(a.T @ a) - l2(b) ** 2 * np.linalg.inv(b.T @ b)
    v = np.linalg.eigvalsh(d)
    lo, hi = v.min() >= -tol, v.max() <= tol
    return "equal" if lo and hi else "first" if hi else "second" if lo else "neither"


def exact_optimum(gram: np.ndarray, steps: int = 400) -> tuple[float, float]:
    """(certified lower bound, attained error) for small n, by ascent on cell multipliers.

    For weights m on the cells the value (tr (sqrt(m) G sqrt(m))^(1/2))^2 / sum(m) is a lower bound;
    equal weights give the spectral bound.  The matching strategy is completed and evaluated.
    """
    n = len(gram)
    if n > 64:
        raise ValueError("exact_optimum is for n <= 64")
    m, best, attained = np.ones(n), 0.0, np.inf
    for _ in range(steps):
        s = np.sqrt(m)
        values, vectors = np.linalg.eigh(s[:, None] * gram * s[None, :])
        root = np.sqrt(np.clip(values, 0, None))
        best = max(best, root.sum() ** 2 / m.sum())
        x = (vectors * root) @ vectors.T / np.outer(s, s)
        diag = np.diag(x)
        lam, vec = np.linalg.eigh((x + x.T) / 2)
        a = np.sqrt(np.clip(lam, 1e-14, None))[:, None] * vec.T
        attained = min(attained, total_error(gram, complete_columns(a)) if lam.min() > 1e-12 else np.inf)
        m = m * (diag / diag.mean()) ** 0.5
        m /= m.mean()
    return float(best), float(attained)


def split_budget(errors: list[float]) -> list[float]:
    """Weights w with sum of squares one that minimise the sum of errors / w^2."""
    w = np.array(errors, float) ** 0.25
    return (w / np.sqrt((w * w).sum())).tolist()


def balance(gram: np.ndarray, parts: list[np.ndarray], start: list[float], steps: int = 200) -> list[float]:
    """Squared weights of sum one that minimise tr(G (sum w_k M_k)^+), by multiplicative steps from ``start``.

    At the optimum every part with weight lowers the error at the same rate.
    """
    w = np.array(start, float) ** 2
    for _ in range(steps):
        inv = np.linalg.pinv(sum(a * m for a, m in zip(w, parts, strict=True)), rcond=1e-11, hermitian=True)
        rate = np.array([(inv @ gram @ inv * m).sum() for m in parts])
        new = w * np.sqrt(np.clip(rate, 0, None))
        new /= new.sum()
        if np.abs(new - w).max() < 1e-9:
            break
        w = new
    return w.tolist()
