"""Findings of round 3: dense kinds keep all cores at work."""

import threading

import numpy as np
import pytest

from rotagrad import queries as engine
from rotagrad.functions import prf
from rotagrad.operators import rotation


@pytest.mark.parametrize("kind", ["gaussian", "rademacher"])
def test_parts_of_a_tall_projection_are_dealt_one_to_a_task(spark, kind):
    """Sampled range bounds gave some tasks two parts and others none, which took twice the time."""
    n = rotation.DENSE_LIMIT + 100
    x = np.random.default_rng(1).standard_normal((n, 2))
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "row_id bigint, v array<double>")
    out = rotation.Dense("k", kind).apply(rows, n, 2)
    assert "rangepartitioning" not in out._jdf.queryExecution().toString().lower()
    parts = spark.sparkContext.defaultParallelism
    per_task = out.rdd.mapPartitions(lambda part: [[r.row_id for r in part]]).collect()
    assert len(per_task) == parts and sorted(i for own in per_task for i in own) == list(range(n))
    assert all({i // rotation.ROWS % parts for i in own} == {p} for p, own in enumerate(per_task))


@pytest.mark.parametrize("name", ["sketched_descent", "flatness_by_rotation", "residual_cube", "measured_properties"])
def test_rotations_of_a_comparison_run_at_once(spark, sf, monkeypatch, name):
    """One after the other, they left cores idle while the product of reflections had one task."""
    real, both, seen = engine.part_moments, threading.Barrier(2), []

    def meeting(*a, **k):
        seen.append(1)
        if len(seen) <= 2:
            both.wait(timeout=20)
        return real(*a, **k)

    monkeypatch.setattr(engine, "part_moments", meeting)
    assert engine.QUERIES[name](spark, sf).count() > 0 and len(seen) >= 6


def test_together_keeps_order_and_errors():
    assert list(engine.together(lambda i: i * i, range(10)).items()) == [(i, i * i) for i in range(10)]
    with pytest.raises(ZeroDivisionError):
        engine.together(lambda i: 1 / i, (1, 0))


def test_keyed_generators():
    """The default draws are what they were; another generator repeats by key too."""
    assert prf.rng("a").standard_normal() == prf.rng("a", np.random.PCG64).standard_normal()
    assert (prf.rng("a", np.random.SFC64).bytes(8) == prf.rng("a", np.random.SFC64).bytes(8)) and prf.rng("a", np.random.SFC64).bytes(8) != prf.rng("b", np.random.SFC64).bytes(8)


def test_together_is_what_one_after_the_other_gives(spark, sf, monkeypatch):
    at_once = {tuple(r) for r in engine.QUERIES["flatness_by_rotation"](spark, sf).collect()}
    monkeypatch.setattr(engine, "AT_ONCE", 1)
    alone = {tuple(r) for r in engine.QUERIES["flatness_by_rotation"](spark, sf).collect()}
    assert {r[0] for r in at_once} == {r[0] for r in alone}
    for name, *values in at_once:
        assert np.allclose(values, next(r[1:] for r in alone if r[0] == name), rtol=1e-9)
