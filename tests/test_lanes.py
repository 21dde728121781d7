"""Scale path, codes, measured bounds, edge rows of the transform, streams and sinks."""

import datetime as dt
import math

import numpy as np
import pytest

from rotagrad import lane_queries as lanes
from rotagrad import queries as engine
from rotagrad.operators import gradient, measures, rotation, solver
from rotagrad.plans import planner
from rotagrad.sources import matrices as src
from rotagrad.streaming import events as ev


def test_repeated_ids_add_up_and_bad_rows_are_refused(spark):
    rows = spark.createDataFrame([(0, [1]), (0, [1]), (1, [5])], "row_id bigint, v array<bigint>").coalesce(1)
    got = {r.row_id: r.v for r in rotation.SignHadamard(None, False).apply(rows, 2, 1).collect()}
    assert got == {0: [7], 1: [-3]}
    for bad in ([(0, [1, 2]), (1, [3])], [(0, None)], [(None, [1])], [(-1, [1])]):
        frame = spark.createDataFrame(bad, "row_id bigint, v array<bigint>").coalesce(1)
        with pytest.raises(Exception):
            rotation.SignHadamard(None, False).apply(frame, 2, len(bad[0][1] or [1])).collect()
    tall = rotation.Dense("k", "gaussian").apply(spark.createDataFrame([(0, [1.0]), (0, [1.0])], "row_id bigint, v array<double>"), 2, 1).collect()
    assert np.allclose([r.v[0] for r in sorted(tall, key=lambda r: r.row_id)], 2 * rotation.Dense("k", "gaussian").matrix(2)[:, 0])


def test_sorted_permutation_is_a_rotation(spark):
    rng = np.random.default_rng(2)
    x = rng.standard_normal((13, 3))
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "row_id bigint, v array<double>")
    r = rotation.Scrambled("s", perm="sort")
    out = r.apply(rows, 13, 3)
    y = np.array([v.v for v in out.collect()])
    assert len(y) == 16 and np.allclose(y.T @ y, x.T @ x)
    back = {v.row_id: v.v for v in r.inverse(out, 13, 3).collect()}
    assert all(np.allclose(back[i], x[i]) for i in range(13))


def test_stored_blocks_equal_moments_and_prune_files(spark, sf, tmp_path, monkeypatch):
    rows = engine.QUERIES["planned_row_pass"](spark, sf).collect()
    by = {(r.run, r.t): r.x for r in rows}
    assert len(by) == 12 and all(np.allclose(by["moments", t], by["stored", t], atol=1e-9) for t in range(6))
    n = src.read(spark, sf, "orders").count()
    rotated = gradient.with_blocks(rotation.SignHadamard("p").apply(gradient.stacked(src.orders(spark, sf)), n, 9), 128)
    src.write_blocks(rotated.select("block_id", "v"), f"{tmp_path}/b", 4)
    read = solver.stored_blocks(spark.read.parquet(f"{tmp_path}/b"), [1, 5], 4)
    plan = read._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(block_bucket" in plan.replace("PartitionFilters: [block_bucket", "PartitionFilters: [isnotnull(block_bucket") and len(read.inputFiles()) >= 1
    assert {r.block_id for r in read.select("block_id").distinct().collect()} == {1, 5}
    plan = planner.SketchPlan(rotation.SignHadamard("p"), 16, 8, solver.LineSearch(), 1, 8)
    monkeypatch.setattr(gradient, "DRIVER_BYTES", 0)
    with pytest.raises(ValueError):
        planner.execute(plan, src.orders(spark, sf), n)


def test_permuted_draws():
    for blocks, q in ((64, 64), (100, 37), (5, 5), (1, 1)):
        own = solver.permuted("k", 3, blocks, q)
        assert len(set(own)) == q and all(0 <= b < blocks for b in own)
    seen = np.zeros(12)
    for t in range(600):
        seen[solver.permuted("k", t, 12, 6)] += 1
    assert abs(seen / 600 - 0.5).max() < 0.1


def test_sweep_equals_single_runs(spark, sf):
    m = engine.lane_moments(spark, sf, 6)
    for x0 in (None, [1.0, -2.0]):
        got = solver.fixed_sweep(m, 3, 40, (0.05, 0.2, 1.4), x0)
        for mult, last in zip((0.05, 0.2, 1.4), got):
            run = solver.Run(m, 3, solver.Fixed(mult))
            run.go(40, x0)
            assert last == pytest.approx(run.history[-1][4], abs=1e-6)


def test_bounds_hold_and_properties_are_measured(spark, sf):
    for r in engine.QUERIES["measured_bounds"](spark, sf).collect():
        assert r.eps >= 1 or (r.ratio <= r.ratio_bound + 1e-9 and r.gap <= r.gap_bound + 1e-9)
        assert r.q < engine.shape(spark, sf)[1] or r.eps < 1e-9
    for r in engine.QUERIES["measured_gradient_errors"](spark, sf).collect():
        assert r.error <= r.bound + 1e-6
    rows = {r.rotation: r for r in engine.QUERIES["measured_properties"](spark, sf).collect()}
    for name, r in rows.items():
        assert (r.gram_gap < 1e-9) == rotation.by_name(name).orthonormal and r.max_k >= 1 - 1e-9
        assert r.bias < 0.5 or not rotation.by_name(name).orthonormal
    assert measures.flatness(np.array([0.5, 0.5]), 0.1, 4)["bound"] == pytest.approx(4 * math.sqrt(math.log(80) / 2))


def test_protected_inverse_of_64_columns(spark, sf):
    got = np.zeros((64, 64))
    for r in engine.QUERIES["secure_inverse_64"](spark, sf).collect():
        got[:, r.i] = r.column
    mat = src.vectors(spark, sf, 64)
    a = gradient.moments(mat, rotation.Identity(), 1, 64).total()[:-1, :-1] / mat.count() + np.eye(64) / 64
    assert np.abs(a @ got - np.eye(64)).max() < 1e-3


def test_sparse_descent_reaches_the_neighbourhood(spark, sf):
    rows = {(r.run, r.t): r.log_residual for r in engine.QUERIES["sparse_descent"](spark, sf).collect()}
    assert all(rows[name, 50] < rows[name, 0] - 0.5 for name in ("plain", "sign_hadamard", "scrambled"))


def test_sampled_product_error_falls(spark, sf):
    rows = sorted((r.c, r.error) for r in engine.QUERIES["column_row_error"](spark, sf).collect())
    assert rows[0][1] > rows[2][1]
    assert {r.kind for r in lanes.sampled_rotated_product(spark, sf).collect()} == {"plain", "rotated"}


def answers(spark, folder, rows):
    frame = spark.createDataFrame([(t, s, float(v), dt.datetime(2024, 1, 1) + dt.timedelta(seconds=at)) for t, s, v, at in rows], "t int, server_id bigint, latency double, ts timestamp")
    frame.coalesce(1).write.mode("append").parquet(folder)
    return frame.schema


def drained(stream, name, checkpoint, mode="append"):
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)


def test_deadline_and_dedup_in_streams(spark, tmp_path):
    folder = f"{tmp_path}/in"
    schema = answers(spark, folder, [(0, 1, 0.1, 0), (0, 1, 0.1, 0), (0, 2, 0.2, 5), (0, 3, 0.3, 90), (1, 4, 0.1, 10)])
    stream = spark.readStream.schema(schema).parquet(folder)
    got = drained(ev.first_answers_by_deadline(stream, 3), "by_deadline", f"{tmp_path}/c1").collect()
    assert sorted((r.t, r.server_id, r["rank"]) for r in got) == [(0, 1, 1), (0, 2, 2), (1, 4, 1)]  # server 3 came after the deadline
    once = drained(ev.once_within(stream), "once_within", f"{tmp_path}/c2").collect()
    assert sorted((r.t, r.server_id) for r in once) == [(0, 1), (0, 2), (0, 3), (1, 4)]


def test_history_and_sketch_sinks(spark, sf, tmp_path):
    m = engine.lane_moments(spark, sf, 6)
    for name, steps in (("a", 3), ("b", 4), ("a", 5)):
        src.append_history(solver.history(spark, {name: solver.plain_descent(m, steps, solver.Fixed(0.1))}), f"{tmp_path}/h")
    counts = {r.run: r["count"] for r in spark.read.parquet(f"{tmp_path}/h").groupBy("run").count().collect()}
    assert counts == {"a": 6, "b": 5}
    rows = gradient.with_blocks(gradient.stacked(src.orders(spark, sf)), 100)
    own = list(solver.draw("draw", 0, 15, 7, "without"))
    src.write_sketch(rows, own, math.sqrt(15 / 7), f"{tmp_path}/s")
    stored = spark.read.parquet(f"{tmp_path}/s")
    assert stored.count() == 700
    v = np.array([r.v for r in stored.collect()])
    full = gradient.moments(src.orders(spark, sf), rotation.Identity(), 15, 8)
    assert np.allclose(v.T @ v, full.m[own].sum(axis=0) * 15 / 7)
    x = np.linalg.lstsq(v[:, :-1], v[:, -1], rcond=None)[0]
    assert np.allclose(x, solver.frozen_solve(full, 7), atol=1e-6)
