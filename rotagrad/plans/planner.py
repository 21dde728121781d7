"""A small plan of a sketched regression and the rewrites that precede any job."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame

from rotagrad.operators import gradient, solver
from rotagrad.operators.rotation import Identity, Rotation
from rotagrad.sources import matrices


@dataclass(frozen=True)
class SketchPlan:
    rotation: Rotation
    blocks: int
    q: int
    step: object
    steps: int
    d: int
    must_protect: bool = False
    sampling: str = "without"


def cancel_rotation(plan: SketchPlan) -> SketchPlan:
    """If every block answers, an orthonormal rotation cancels in each step: leave it out unless storage is protected."""
    if plan.q == plan.blocks and plan.sampling == "without" and plan.rotation.orthonormal and not plan.must_protect:
        return replace(plan, rotation=Identity())
    return plan


def use_moments(plan: SketchPlan, n: int) -> bool:
    """Moments pay when a block has more rows than columns and all fit the driver."""
    return plan.d + 1 < plan.rotation.height(n) // plan.blocks and plan.blocks * (plan.d + 1) ** 2 * 8 <= gradient.DRIVER_BYTES


def execute(plan: SketchPlan, mat: DataFrame, n: int | None = None, folder: str | None = None, buckets: int = 64, **options) -> solver.Run:
    """Moments where they pay; otherwise the rotated blocks are stored in ``folder`` and each step reads those drawn."""
    n = n if n is not None else mat.count()
    plan = cancel_rotation(plan)
    tau = -(-plan.rotation.height(n) // plan.blocks)
    solver.check_draw(plan.q, tau, plan.d)
    if use_moments(plan, n) or folder is None:
        m = gradient.moments(mat, plan.rotation, plan.blocks, plan.d, n)
        return solver.sketched_descent(m, plan.q, plan.steps, plan.step, sampling=plan.sampling, **options)
    rotated = gradient.with_blocks(plan.rotation.apply(gradient.stacked(mat), n, plan.d + 1), tau)
    matrices.write_blocks(rotated.select("block_id", "v"), folder, buckets)
    return solver.stored_descent(mat.sparkSession.read.parquet(folder), plan.blocks, buckets, plan.q, plan.steps, plan.step, plan.d, n, sampling=plan.sampling, **options)
