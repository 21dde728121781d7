"""Descent over sketched blocks, its step sizes and its baselines, in moments mode.

A block enters a step only through its moments, so after one pass over the rows every step
costs O(q d^2) on the driver and no job.  The response is column d of the moments.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rotagrad.functions import prf
from rotagrad.functions.vec import dot, literal
from rotagrad.operators.gradient import Moments


@dataclass(frozen=True)
class Fixed:
    """A multiple of 2 / sigma_max^2 (or an absolute step when unit is False)."""

    value: float
    unit: bool = True

    def xi(self, t: int, run: Run, x: np.ndarray, g: np.ndarray) -> float:
        return self.value * (run.unit if self.unit else 1.0)


@dataclass(frozen=True)
class Decay:
    """c / (t + 1) or c / sqrt(t + 1), in units of 2 / sigma_max^2."""

    value: float
    root: bool = False

    def xi(self, t: int, run: Run, x: np.ndarray, g: np.ndarray) -> float:
        return self.value * run.unit / (math.sqrt(t + 1) if self.root else t + 1)


@dataclass(frozen=True)
class LineSearch:
    """The exact minimiser along the full gradient ("full") or along this draw's own ("sketch")."""

    source: str = "full"

    def xi(self, t: int, run: Run, x: np.ndarray, g: np.ndarray) -> float:
        m = run.total if self.source == "full" else run.drawn
        gram, cross = m[:-1, :-1], m[:-1, -1]
        e = gram @ x - cross
        full = 2 * e
        bottom = full @ gram @ full
        return float(full @ e / bottom) if bottom > 0 else 0.0  # a zero step ends the run


@lru_cache(maxsize=4096)
def _answers(key: str, t: int, blocks: int) -> tuple[int, ...]:
    """Blocks by keyed latency, the first to answer first."""
    return tuple(sorted(range(blocks), key=lambda b: (-math.log(prf.uniform(key, t, b)), b)))


def permuted(key: str, t: int, blocks: int, q: int) -> list[int]:
    """q different blocks without ranking all of them: the places of 0 .. q - 1 under a keyed bijection
    (walked along its cycles where it leaves the blocks)."""
    bits = max(1, (blocks - 1).bit_length())
    out = []
    for i in range(q):
        b = prf.feistel_place(f"{key}:{t}", bits, i)
        while b >= blocks:
            b = prf.feistel_place(f"{key}:{t}", bits, b)
        out.append(b)
    return out


def draw(key: str, t: int, blocks: int, q: int, sampling: str, scores: np.ndarray | None = None) -> dict[int, float]:
    """block -> multiplicity (times an importance weight) of step t."""
    if sampling == "with":
        out: dict[int, float] = {}
        for i in range(q):
            b = prf.digits(key, t, i) % blocks
            out[b] = out.get(b, 0) + 1
        return out
    if sampling == "leverage":
        p = scores / scores.sum()
        edges, out = np.cumsum(p), {}
        for i in range(q):
            b = min(int(np.searchsorted(edges, prf.uniform(key, t, i))), blocks - 1)
            out[b] = out.get(b, 0) + 1 / (blocks * p[b])
        return out
    if sampling == "permuted":
        return dict.fromkeys(permuted(key, t, blocks, q), 1.0)
    # Without replacement: the q least keyed latencies answer first.
    return dict.fromkeys(_answers(key, t, blocks)[:q], 1.0)


@dataclass
class Run:
    moments: Moments
    q: int | list[int]
    step: object
    sampling: str = "without"
    block_scale: str = "sqrt_K_over_q"
    key: str = "draw"
    resample: bool = True
    reg: float = 0.0
    reference: np.ndarray | None = None
    tol: float = 0.0
    scores: np.ndarray | None = None
    #: Blocks and weights of each step as given, instead of draws (partial stragglers, decoded codes).
    given: Callable[[int], dict[int, float]] | None = None
    history: list = field(default_factory=list)

    def __post_init__(self):
        self.total = self.moments.total()
        self.gram, self.cross, self.bb = self.total[:-1, :-1], self.total[:-1, -1], self.total[-1, -1]
        self.unit = 2 / max(float(np.linalg.eigvalsh(self.gram)[-1]), 1e-300)
        self.best = exact(self.moments) if self.reference is None else self.reference
        self.drawn = self.total

    def objective(self, x: np.ndarray) -> float:
        return float(x @ self.gram @ x - 2 * self.cross @ x + self.bb)

    def record(self, t: int, x: np.ndarray, xi: float) -> None:
        far = np.linalg.norm(self.best - x) / math.sqrt(self.moments.rows)
        self.history.append((t, [float(v) for v in x], float(xi), self.objective(x), math.log10(max(far, 1e-17)) if np.isfinite(far) else float("inf")))

    def go(self, steps: int, x0: np.ndarray | None = None) -> np.ndarray:
        k, d = self.moments.blocks, self.moments.d
        x = np.zeros(d) if x0 is None else np.array(x0, float)
        self.record(0, x, 0.0)
        for t in range(steps):
            q = self.q if isinstance(self.q, int) else self.q[min(t, len(self.q) - 1)]
            if self.given is not None:
                own = self.given(t)
                ids, w = np.array(list(own), int), np.array(list(own.values()), float)
                self.drawn = np.tensordot(w, self.moments.m[ids], 1)
            elif q < k or self.sampling != "without":
                own = draw(self.key, t if self.resample else 0, k, q, self.sampling, self.scores)
                ids, w = np.array(list(own)), np.array(list(own.values()))
                self.drawn = np.tensordot(w * (k / q if self.block_scale != "none" else 1.0), self.moments.m[ids], 1)
            else:
                self.drawn = self.total
            g = 2 * (self.drawn[:-1, :-1] @ x - self.drawn[:-1, -1]) + 2 * self.reg * x
            xi = self.step.xi(t, self, x, g)
            # Without block scaling the expected sketched gradient is q/K times the full one.
            move = xi * g * (k / q if self.block_scale == "none" else 1.0)
            x = x - move
            self.record(t + 1, x, xi)
            if xi == 0 or np.linalg.norm(move) <= self.tol * 1e-300 or (self.tol and np.linalg.norm(move) < self.tol) or not np.isfinite(x).all() or np.abs(x).max() > 1e150:
                break
        return x


def exact(m: Moments) -> np.ndarray:
    """The least-squares solution from the moments (pseudo-inverse when columns repeat)."""
    t = m.total()
    return np.linalg.lstsq(t[:-1, :-1], t[:-1, -1], rcond=None)[0]


def check_draw(q: int, tau: int, d: int) -> None:
    if q * tau <= d:
        raise ValueError(f"{q} blocks of {tau} rows cannot span {d} columns")


def sketched_descent(m: Moments, q, steps: int, step, **options) -> Run:
    run = Run(m, q, step, **options)
    run.go(steps)
    return run


def plain_descent(m: Moments, steps: int, step, **options) -> Run:
    return sketched_descent(m, m.blocks, steps, step, **options)


def fixed_sweep(m: Moments, q: int, steps: int, multipliers: tuple[float, ...], x0: np.ndarray | None = None, key: str = "draw", of: Run | None = None) -> list[float]:
    """Last log residuals of runs with several constant steps over the same draws: one pass, x is d x runs.

    Step unit and reference solution are those of ``of`` (the matrix itself), which projections do not keep.
    """
    run = Run(m, q, Fixed(1.0), key=key)
    if of is not None:
        run.unit, run.best = of.unit, of.best
    x = np.zeros((m.d, len(multipliers))) if x0 is None else np.repeat(np.array(x0, float)[:, None], len(multipliers), axis=1)
    live = np.ones(len(multipliers), bool)
    for t in range(steps):
        s = m.m[list(draw(key, t, m.blocks, q, "without"))].sum(axis=0) * (m.blocks / q) if q < m.blocks else run.total
        move = run.unit * np.array(multipliers) * 2 * (s[:-1, :-1] @ x - s[:-1, -1:])
        x = np.where(live, x - move, x)
        live &= np.isfinite(x).all(axis=0) & (np.abs(x).max(axis=0) <= 1e150)  # the rest has diverged
        if not live.any():
            break
    far = np.linalg.norm(run.best[:, None] - x, axis=0) / math.sqrt(m.rows)
    return [math.log10(max(v, 1e-17)) if np.isfinite(v) else float("inf") for v in far]


def frozen_solve(m: Moments, q: int, key: str = "draw") -> np.ndarray:
    """One draw, then the exact solution of the small system."""
    own = draw(key, 0, m.blocks, q, "without")
    t = m.m[list(own)].sum(axis=0)
    return np.linalg.lstsq(t[:-1, :-1], t[:-1, -1], rcond=None)[0]


def averaged_solution(m: Moments, q: int, n: int, key: str = "draw") -> np.ndarray:
    return np.mean([frozen_solve(m, q, f"{key}:{i}") for i in range(n)], axis=0)


SCHEMA = "run string, t int, x array<double>, xi double, objective double, log_residual double"


def history(spark: SparkSession, runs: dict[str, Run]) -> DataFrame:
    return spark.createDataFrame([(name, *row) for name, r in runs.items() for row in r.history], SCHEMA)


def row_pass_descent(mat: DataFrame, tau: int, blocks: int, q: int, steps: int, xi: float, d: int, key: str = "draw") -> list[tuple[int, list[float]]]:
    """Descent without moments: a job per step over the rows of the drawn blocks only.

    For blocks whose moments exceed the driver.  x travels as a literal and d sums come back.
    """
    rows = mat.select(F.expr(f"row_id div {tau}").alias("block_id"), "features", "label")
    x = np.zeros(d)
    out = [(0, x.tolist())]
    for t in range(steps):
        own = list(draw(key, t, blocks, q, "without"))
        x = x - xi * blocks / q * row_gradient(rows.filter(F.col("block_id").isin(own)), x)
        out.append((t + 1, x.tolist()))
    return out


def row_gradient(rows: DataFrame, x: np.ndarray) -> np.ndarray:
    """2 A'(Ax - b) over rows (features, label)."""
    residual = dot(F.col("features"), literal(x)) - F.col("label")
    got = rows.select(residual.alias("e"), "features").agg(*[F.sum(F.col("e") * F.col("features")[j]).alias(str(j)) for j in range(len(x))]).first()
    return 2 * np.array([v or 0.0 for v in got])


def stored_blocks(stored: DataFrame, own: list[int], buckets: int) -> DataFrame:
    """The drawn blocks of rows that ``write_blocks`` stored (block_id, v, block_bucket): the filter on the partition column prunes files."""
    return stored.filter(F.col("block_bucket").isin(sorted({b % buckets for b in own})) & F.col("block_id").isin(own))


def stored_descent(stored: DataFrame, blocks: int, buckets: int, q: int, steps: int, step, d: int, rows: int, **options) -> Run:
    """Sketched descent over stored rotated blocks, a pruned job per step and no moments of blocks.

    Only the d x d total is summed once, for the step (line search included) and the reference.
    """
    from rotagrad.operators import gradient

    total = np.zeros((1, d + 1, d + 1))
    for r in gradient.block_moments(stored.select(F.lit(0).cast("bigint").alias("row_id"), "v"), 1, d + 1).collect():
        total[0] = np.array(r.m).reshape(d + 1, d + 1)
    run = Run(Moments(total, rows), q, step, **options)
    split = stored.select("block_id", "block_bucket", F.slice("v", 1, d).alias("features"), F.col("v")[d].alias("label"))
    x = np.zeros(d)
    run.record(0, x, 0.0)
    for t in range(steps):
        own = draw(run.key, t if run.resample else 0, blocks, q, "permuted" if run.sampling == "permuted" else "without")
        g = blocks / q * row_gradient(stored_blocks(split, list(own), buckets), x)
        xi = run.step.xi(t, run, x, g)
        x = x - xi * g
        run.record(t + 1, x, xi)
        if xi == 0:
            break
    return run
