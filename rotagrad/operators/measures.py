"""Accuracy, flatness, cost and security measures (driver-side on d x d or block moments)."""

from __future__ import annotations

import itertools
import math

import numpy as np

from rotagrad.functions.prf import log2_factorial
from rotagrad.operators.gradient import Moments
from rotagrad.operators.solver import draw


def block_scores(m: Moments) -> np.ndarray:
    """Leverage of each block divided by d: trace(G^-1 G_k) / d; sums to 1."""
    g = m.m[:, :-1, :-1]
    inverse = np.linalg.pinv(g.sum(axis=0))
    return np.einsum("ij,kji->k", inverse, g) / m.d


def flatness(scores: np.ndarray, delta: float = 0.1, tau: int = 1) -> dict:
    """Spread of the block scores beside the printed bound, tau rho with rho = sqrt(log(2 tau / delta) / 2); vacuous above 1."""
    k = len(scores)
    bound = tau * math.sqrt(math.log(2 * tau / delta) / 2)
    return {"max_k": float(scores.max() * k), "min_k": float(scores.min() * k), "distance": float(np.abs(scores - 1 / k).max()), "bound": bound, "vacuous": bound >= 1}


def measured_bounds(m: Moments, q: int, key: str = "draw") -> dict:
    """A frozen draw against its bounds: distortion eps over the span of [A b], ratio of residuals with its bound
    (1 + eps) / (1 - eps), and the gap of the solutions with its bound eps times the residual (in the norm of A)."""
    from rotagrad.operators.solver import exact, frozen_solve

    total, own = m.total(), list(draw(key, 0, m.blocks, q, "without"))
    root = np.linalg.inv(np.linalg.cholesky(total))
    eps = float(np.abs(np.linalg.eigvalsh(root @ (m.m[own].sum(axis=0) * m.blocks / q) @ root.T) - 1).max())
    best, x = exact(m), frozen_solve(m, q, key)
    cost = lambda y: float(np.append(y, -1) @ total @ np.append(y, -1))
    gap = best - x
    ratio, limit = cost(x) / cost(best), solution_bounds(min(eps, 0.999999), math.sqrt(cost(best)))
    return {"eps": eps, "ratio": ratio, "ratio_bound": limit[0], "gap": math.sqrt(max(float(gap @ total[:-1, :-1] @ gap), 0.0)), "gap_bound": limit[1] / (1 - min(eps, 0.999999))}


def measured_gradient_error(m: Moments, code: np.ndarray, responders: list[int], x: np.ndarray) -> tuple[float, float]:
    """(error, bound) of a decoded gradient: optimal coefficients of the responders against the sum over all blocks."""
    from rotagrad.operators.coding import optimal_decode

    parts = np.stack([2 * (b[:-1, :-1] @ x - b[:-1, -1]) for b in m.m])
    weights = optimal_decode(code, responders) @ code[responders]
    total, y = m.total(), np.append(x, -1)
    sigma, residual = math.sqrt(np.linalg.eigvalsh(total[:-1, :-1])[-1]), math.sqrt(max(float(y @ total @ y), 0.0))
    return float(np.linalg.norm(weights @ parts - parts.sum(axis=0))), gradient_error_bound(decode_error(code, responders), m.blocks, sigma, residual)


def embedding_distortion(m: Moments, q: int, t: int = 0, key: str = "draw") -> float:
    """Spectral distance of the sketched basis' Gram matrix from the identity."""
    g = m.m[:, :-1, :-1]
    root = np.linalg.inv(np.linalg.cholesky(g.sum(axis=0)))
    own = list(draw(key, t, m.blocks, q, "without"))
    s = root @ (g[own].sum(axis=0) * m.blocks / q) @ root.T
    return float(np.abs(np.linalg.eigvalsh(s) - 1).max())


def condition(m: Moments, q: int, t: int = 0, key: str = "draw") -> tuple[float, float]:
    """Condition numbers of the matrix and of one sketch of it."""
    g = m.m[:, :-1, :-1]
    own = list(draw(key, t, m.blocks, q, "without"))
    return math.sqrt(np.linalg.cond(g.sum(axis=0))), math.sqrt(np.linalg.cond(g[own].sum(axis=0)))


def gradient_bias(m: Moments, q: int, draws: int, x: np.ndarray, sampling: str = "without", scale: bool = True, key: str = "draw") -> tuple[float, float]:
    """(relative error, ratio along the full gradient) of the mean sketched gradient."""
    full = m.total()
    g = 2 * (full[:-1, :-1] @ x - full[:-1, -1])
    mean = np.zeros(m.d)
    for t in range(draws):
        for b, w in draw(key, t, m.blocks, q, sampling).items():
            mean += w * (m.blocks / q if scale else 1.0) * 2 * (m.m[b, :-1, :-1] @ x - m.m[b, :-1, -1]) / draws
    return float(np.linalg.norm(mean - g) / np.linalg.norm(g)), float(mean @ g / (g @ g))


def decode_error(code: np.ndarray, responders: list[int]) -> float:
    """||I - pinv(G) G||_2 over the responders' rows: 0 when each block's own gradient can be decoded."""
    g = code[responders]
    return float(np.linalg.norm(np.eye(code.shape[1]) - np.linalg.pinv(g) @ g, 2))


def gradient_error_bound(error: float, blocks: int, sigma: float, residual: float) -> float:
    return 2 * math.sqrt(blocks) * error * sigma * residual


def solution_bounds(eps: float, residual: float) -> tuple[float, float]:
    return (1 + eps) / (1 - eps), eps * residual


def q_required(d: int, tau: int, eps: float, delta: float, n: int, hadamard: bool = False, constant: float = 1.0) -> float:
    base = constant * d / tau * math.log(2 * d / delta) / eps**2
    return base * math.log(n * d / delta) if hadamard else base


def op_counts(n: int, d: int, k: int = 2, s: int = 1, m: int = 12) -> dict[str, float]:
    return {"hadamard": n * d * math.log2(n), "kronecker": n * d * k * math.log(n, k), "dense": float(n) * n * d, "exact": float(n) * d * d, "decode": float((s + 1) * -(-m // (s + 1)))}


def key_bits(n: int) -> dict[str, float]:
    """Bits of the key; the scrambled family has fewer different matrices than keys."""
    return {"sign_hadamard": float(n), "scrambled": n + log2_factorial(n), "scrambled_distinct": n + log2_factorial(n - 1), "rademacher": float(n) * n}


def repeat_probability(k: int, q: int) -> tuple[float, float]:
    """(exact, printed) chance that a given block is drawn at least twice."""
    return 1 - (1 - 1 / k) ** q - q / k * (1 - 1 / k) ** (q - 1), (q - 1) / k**2


def signed_permutations(n: int) -> list[np.ndarray]:
    out = []
    for p in itertools.permutations(range(n)):
        for s in itertools.product((1, -1), repeat=n):
            m = np.zeros((n, n), int)
            for i, j in enumerate(p):
                m[i, j] = s[i]
            out.append(m)
    return out
