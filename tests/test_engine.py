"""Definitions, invariants, draws, descent, codes and protection of the engine."""

import itertools
import math

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from rotagrad.functions import prf, sqlapi, vec
from rotagrad.operators import coding, gradient, measures, rotation, solver, tasks
from rotagrad.plans import planner
from rotagrad.sources import matrices as src
from rotagrad.streaming import events as ev

WALSH = np.array([[(-1) ** bin(i & j).count("1") for j in range(16)] for i in range(16)])


def frame(spark, x):
    return spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "row_id bigint, v array<double>")


def collect(df):
    return np.array([r.v for r in df.orderBy("row_id").collect()])


def random_matrix(seed, n, d):
    return np.random.default_rng(seed).standard_normal((n, d))


def matrix(spark, a, b):
    return spark.createDataFrame([(i, [float(v) for v in r], float(y)) for i, (r, y) in enumerate(zip(a, b))], "row_id bigint, features array<double>, label double")


def test_kron_apply_is_the_dense_product():
    base = np.array(rotation.reflection(3))
    x = random_matrix(1, 27, 2)
    assert np.allclose(rotation.kron_apply(x, base, 3), np.kron(base, np.kron(base, base)) @ x)


def test_hadamard_matches_its_definition_at_any_stage_width(spark):
    x = random_matrix(2, 13, 3)
    padded = np.vstack([x, np.zeros((3, 3))])
    for group in (2, 4, 1 << 13):
        r = rotation.SignHadamard(None, group_rows=group)
        assert np.allclose(collect(r.apply(frame(spark, x), 13, 3)), WALSH @ padded / 4)


@pytest.mark.parametrize("name", ["identity", "orthonormal", "sign_hadamard", "scrambled", "kronecker", "super_block"])
def test_rotations_keep_moments_and_projections_do_not(spark, name):
    x = random_matrix(3, 20, 3)
    y = collect(rotation.by_name(name).apply(frame(spark, x), 20, 3))
    assert np.allclose(y.T @ y, x.T @ x)
    for other in ("gaussian", "rademacher"):
        z = collect(rotation.by_name(other).apply(frame(spark, x), 20, 3))
        assert not np.allclose(z.T @ z, x.T @ x, rtol=1e-3)


@pytest.mark.parametrize("name", ["orthonormal", "sign_hadamard", "scrambled", "kronecker"])
def test_inverse_undoes(spark, name):
    x = random_matrix(4, 11, 2)
    r = rotation.by_name(name)
    back = collect(r.inverse(r.apply(frame(spark, x), 11, 2), 11, 2))
    assert np.allclose(back[:11], x) and np.allclose(back[11:], 0)


def test_dense_limit():
    with pytest.raises(ValueError):
        rotation.Dense("k").matrix(rotation.DENSE_LIMIT + 1)


@pytest.mark.parametrize("bits", [1, 3, 10, 11])
def test_feistel_is_a_keyed_bijection(spark, bits):
    ids = spark.range(1 << bits)
    got = [r[0] for r in ids.select(prf.feistel("a", bits, "id")).collect()]
    assert sorted(got) == list(range(1 << bits))
    assert [prf.feistel_inverse("a", bits, y) for y in got] == list(range(1 << bits))
    if bits > 3:
        assert got != [r[0] for r in ids.select(prf.feistel("b", bits, "id")).collect()]


def test_keyed_digits_agree_in_three_engines(spark):
    here = [prf.digits("k", i, 2) for i in range(50)]
    assert here == [r[0] for r in spark.range(50).select(F.expr(prf.SPARK.digits("k", "id", "2"))).collect()]
    assert here == [r[0] for r in duckdb.sql(f"SELECT {prf.DUCK.digits('k', 'i', '2')} FROM range(50) r(i) ORDER BY i").fetchall()]


def test_t_quantiles():
    assert duckdb.sql(f"SELECT {prf.t_quantile('0.9::DOUBLE', 1)}").fetchall()[0][0] == pytest.approx(3.0776835)
    assert duckdb.sql(f"SELECT {prf.t_quantile('0.9::DOUBLE', 2)}").fetchall()[0][0] == pytest.approx(1.8856181)
    assert duckdb.sql(f"SELECT {prf.t_quantile('0.9::DOUBLE', 4)}").fetchall()[0][0] == pytest.approx(1.5332063)


def moments_of(spark, a, b, blocks, r=None):
    return gradient.moments(matrix(spark, a, b), r or rotation.Identity(), blocks, a.shape[1])


@pytest.fixture(scope="module")
def problem(spark):
    a = random_matrix(5, 96, 3) * np.array([1, 2, 3])
    b = a @ [1, -1, 0.5] + random_matrix(6, 96, 1)[:, 0]
    return a, b, moments_of(spark, a, b, 6)


def test_moments_and_exact_solution(problem):
    a, b, m = problem
    assert np.allclose(m.total(), np.column_stack([a, b]).T @ np.column_stack([a, b]))
    assert np.allclose(solver.exact(m), np.linalg.lstsq(a, b, rcond=None)[0])


def test_unbiased_over_all_responder_sets(problem):
    _, _, m = problem
    x = np.array([0.3, 0.1, -2])
    g = [2 * (k[:-1, :-1] @ x - k[:-1, -1]) for k in m.m]
    sets = list(itertools.combinations(range(6), 3))
    mean = sum(sum(g[i] for i in s) for s in sets) / len(sets)
    assert np.allclose(mean, sum(g) / 2)  # q/K of the gradient without the block scale
    assert measures.gradient_bias(m, 6, 1, x)[0] < 1e-12


def test_steps_replay_in_numpy(problem):
    _, _, m = problem
    run = solver.sketched_descent(m, 3, 10, solver.Fixed(0.1))
    x = np.zeros(3)
    for t in range(10):
        own = list(solver.draw("draw", t, 6, 3, "without"))
        s = 2 * m.m[own].sum(axis=0)
        x = x - 0.1 * run.unit * 2 * (s[:-1, :-1] @ x - s[:-1, -1])
    assert np.allclose(run.history[-1][1], x, atol=1e-12)
    same = solver.sketched_descent(m, 3, 10, solver.Fixed(0.1), block_scale="none")
    assert np.allclose(same.history[-1][1], x)


def test_step_limit(problem):
    _, _, m = problem
    assert solver.plain_descent(m, 400, solver.Fixed(0.45)).history[-1][4] < -6
    assert solver.plain_descent(m, 200, solver.Fixed(1.05)).history[-1][4] > 3


def test_line_search_is_the_minimum_and_stops_at_the_optimum(problem):
    _, _, m = problem
    run = solver.plain_descent(m, 30, solver.LineSearch())
    values = [h[3] for h in run.history]
    assert all(b <= a + 1e-9 for a, b in zip(values, values[1:]))
    x, xi = np.array(run.history[0][1]), run.history[1][2]
    g = 2 * (run.gram @ x - run.cross)
    assert run.objective(x - xi * g) <= min(run.objective(x - xi * f * g) for f in (0.9, 0.99, 1.01, 1.1))
    still = solver.Run(m, 6, solver.LineSearch())
    still.go(5, solver.exact(m))
    assert len(still.history) <= 6 and still.history[-1][4] < -10


def test_repeat_probability_and_draws():
    right, printed = measures.repeat_probability(100, 50)
    assert right == pytest.approx(0.0894, abs=1e-4) and printed == pytest.approx(0.0049)
    twice = np.mean([any(w > 1 for b, w in solver.draw("r", t, 12, 6, "with").items() if b == 0) for t in range(3000)])
    assert twice == pytest.approx(measures.repeat_probability(12, 6)[0], abs=0.02)
    assert all(len(solver.draw("r", t, 12, 6, "without")) == 6 for t in range(20))


def test_distortion_falls_with_q(spark):
    a, b = random_matrix(7, 256, 3), random_matrix(8, 256, 1)[:, 0]
    m = moments_of(spark, a, b, 16, rotation.SignHadamard("k"))
    values = [measures.embedding_distortion(m, q) for q in (4, 12, 16)]
    assert values[0] > values[1] > values[2] and values[2] < 1e-9


def test_flattening_and_ordering_of_methods(spark):
    """Heavy tails, two degrees of freedom, fresh salts: what the experiments assert at step 50."""
    n, d, k, q = 2048, 40, 128, 64
    end = {}
    for salt in range(11, 15):
        rng = prf.rng(f"t:{salt}")
        u = rng.random((n, d))
        a = (2 * u - 1) / np.sqrt(2 * u * (1 - u))
        b = a @ (rng.random(d) * 2 - 1) + rng.standard_normal(n)
        v = np.column_stack([a, b])
        h = rotation.kron_apply(v * rng.choice([-1, 1], n)[:, None], np.array(rotation.HADAMARD), 11) / math.sqrt(n)
        kinds = {"identity": v, "hadamard": h, "scrambled": h[rng.permutation(n)], "gaussian": rng.standard_normal((n, n)) @ v / math.sqrt(n), "rademacher": rng.choice([-1.0, 1.0], (n, n)) @ v / math.sqrt(n)}
        ms = {name: gradient.Moments(np.einsum("kti,ktj->kij", x.reshape(k, -1, d + 1), x.reshape(k, -1, d + 1)), n) for name, x in kinds.items()}
        best = solver.exact(ms["identity"])
        for name, m in ms.items():
            end.setdefault(name, []).append(solver.sketched_descent(m, q, 50, solver.LineSearch(), reference=best).history[-1][4])
        end.setdefault("frozen", []).append(solver.sketched_descent(ms["scrambled"], q, 50, solver.LineSearch(), resample=False, reference=best).history[-1][4])
        flat = [measures.flatness(measures.block_scores(ms[x]))["max_k"] for x in ("identity", "hadamard")]
        assert flat[1] < 1.3 < flat[0]
    mean = {k: np.mean(v) for k, v in end.items()}
    for rotated in ("hadamard", "scrambled"):
        assert mean[rotated] < mean["identity"] and mean[rotated] < mean["gaussian"] - 0.1 and mean[rotated] < mean["rademacher"] - 0.1
    assert mean["scrambled"] < mean["frozen"]


def test_codes():
    code = coding.as_matrix(coding.fractional_repetition(12, 2), 12)


    def gap(own):
        return np.abs(coding.optimal_decode(code, own) @ code[own] - 1).max()

    assert all(gap([i for i in range(12) if i not in lost]) < 1e-9 for lost in itertools.combinations(range(12), 2))
    assert gap(list(range(3, 12))) > 0.5  # a whole group is lost
    assert measures.decode_error(np.eye(4), [0, 1, 2, 3]) < 1e-12 < measures.decode_error(np.eye(4), [0, 1])
    with pytest.raises(ValueError):
        coding.fractional_repetition(12, 4)


def test_secrecy_of_a_group_and_failure_of_a_family():
    group = measures.signed_permutations(2)
    for m in group:
        ciphers = {(p @ m).tobytes() for p in group}
        assert len(ciphers) == len(group)
    h = np.array([[1, 1], [1, -1]])
    keys = [h @ np.diag(s) for s in itertools.product((1, -1), repeat=2)]
    assert sum((k == h).all() for k in keys) == 1 and sum((k @ h == h).all() for k in keys) == 0


def test_planner_cancels_only_what_cancels(spark):
    plan = planner.SketchPlan(rotation.SignHadamard("k"), 4, 4, solver.LineSearch(), 5, 2)
    assert planner.cancel_rotation(plan).rotation.name == "identity"
    assert planner.cancel_rotation(planner.SketchPlan(rotation.Dense("k", "gaussian"), 4, 4, None, 5, 2)).rotation.name == "gaussian"
    with pytest.raises(ValueError):
        solver.check_draw(1, 2, 3)


def test_edge_matrices(spark):
    for a, b, blocks in ((np.ones((5, 1)), np.zeros(5), 8), (np.ones((4, 2)), np.arange(4.0), 2), (random_matrix(1, 1, 1), np.ones(1), 1)):
        m = moments_of(spark, a, b, blocks, rotation.SignHadamard("k"))
        assert np.isfinite(solver.plain_descent(m, 5, solver.LineSearch()).history[-1][3])


def test_protected_product_inverse_and_logistic(spark):
    a = np.eye(4) + 0.1 * random_matrix(9, 4, 4)
    q = rotation.Dense("q").matrix(4)
    assert np.abs(a @ tasks.secure_inverse(a, q, 800) - np.eye(4)).max() < 1e-6
    x = random_matrix(10, 80, 2)
    y = (x[:, 0] + 0.3 * x[:, 1] > 0).astype(float)
    mat = matrix(spark, x, y)
    plain = tasks.logistic(mat, 2, 6, 1.0)
    assert np.allclose(plain, tasks.logistic(mat, 2, 6, 1.0, rotation.Dense("f").matrix(2)), atol=1e-9)
    assert np.allclose(plain, tasks.logistic_two_round(mat, 2, 6, 1.0, rotation.SignHadamard("r"), 80), atol=1e-9)


def test_stage_plans(spark):
    x = frame(spark, random_matrix(1, 64, 2))
    plan = rotation.SignHadamard("k", group_rows=8).apply(x, 64, 2)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 2 and "Cartesian" not in plan


def test_dense_ids_and_blocks_on_disk(spark, tmp_path):
    rows = src.dense_row_ids(spark.range(1000).select((F.col("id") * 7919 % 1009).alias("k")), ["k"])
    got = sorted((r.k, r.row_id) for r in rows.collect())
    assert [i for _, i in got] == list(range(1000))
    blocks = gradient.with_blocks(frame(spark, random_matrix(1, 32, 2)), 4)
    src.write_blocks(blocks, str(tmp_path / "b"), 4)
    read = spark.read.parquet(str(tmp_path / "b")).filter("block_bucket = 1")
    assert read.count() == 8 and "PartitionFilters: [isnotnull(block_bucket" in read._jdf.queryExecution().toString()
    frame(spark, random_matrix(1, 3, 2)).select("row_id").write.json(str(tmp_path / "j"))
    assert src.read_any(spark, "json", str(tmp_path / "j"), "row_id bigint").count() == 3


def test_regression_from_sql_equals_the_solver(spark):
    sqlapi.register(spark)
    mat = matrix(spark, random_matrix(5, 50, 3), random_matrix(6, 50, 1)[:, 0])
    mat.createOrReplaceTempView("small_matrix")
    got = spark.sql("SELECT * FROM sketched_regression(TABLE(SELECT * FROM small_matrix), 8, 4, 12, 'k1')").collect()
    m = gradient.moments(mat, rotation.Scrambled("k1"), 8, 3, 50)
    want = solver.sketched_descent(m, 4, 12, solver.LineSearch()).history
    assert len(got) == 13 and [r.t for r in got] == [h[0] for h in want]
    assert all(np.allclose(r.x, h[1]) and np.isclose(r.objective, h[3]) for r, h in zip(got, want))
    assert spark.sql("SELECT * FROM sketched_regression(TABLE(SELECT * FROM small_matrix WHERE row_id < 0), 8, 4, 12, 'k1')").count() == 0
    with pytest.raises(Exception, match="null in a matrix row"):
        spark.sql("SELECT * FROM sketched_regression(TABLE(SELECT row_id, features, cast(null AS double) AS label FROM small_matrix), 8, 4, 12, 'k1')").collect()


@pytest.mark.parametrize("how", ["qr_sign", "gram_schmidt", "reflections"])
def test_every_construction_of_the_uniform_rotation(how):
    r = rotation.Dense("k9", how=how)
    m = r.product(np.eye(70), False)
    assert np.allclose(m.T @ m, np.eye(70)) and np.allclose(r.product(np.eye(70), True), m.T)
    # Entries of a uniform matrix have mean 0 and variance 1/N, on the diagonal too.
    assert abs(m.mean()) < 0.01 and abs(np.diag(m).mean()) < 5 / 70


def test_permutations_are_undone_without_a_shuffle(spark):
    for bits in (1, 2, 5, 8):
        ids = spark.range(1 << bits).select(prf.feistel("p", bits, "id").alias("row_id"), "id")
        back = ids.select("row_id", prf.unfeistel("p", bits).alias("back"), "id").collect()
        assert all(r.back == r.id for r in back) and sorted(r.row_id for r in back) == list(range(1 << bits))
    r = rotation.SignedPermutation("p")
    rows = spark.createDataFrame([(i, [float(i), 1.0]) for i in range(37)], "row_id long, v array<double>")
    out = r.inverse(r.apply(rows, 37, 2), 37, 2)
    assert "Exchange" not in out._jdf.queryExecution().toString() and sorted(map(tuple, ((i, *v) for i, v in out.collect()))) == [(i, float(i), 1.0) for i in range(37)]


def test_sql_functions_and_vectors(spark):
    sqlapi.register(spark)
    rows = spark.sql("SELECT * FROM draw_blocks(6, 3, 4, 'draw', 'without')").collect()
    assert len(rows) == 12 and {r.weight for r in rows} == {2.0}
    assert spark.sql("SELECT hadamard_entry(3, 5)").first()[0] == -1
    a, b = F.array(F.lit(1.0), F.lit(2.0)), F.array(F.lit(3.0), F.lit(4.0))
    got = spark.range(1).select(vec.dot(a, b), vec.axpy(2.0, a, b), vec.norm2(b)).first()
    assert got[0] == 11 and got[1] == [5, 8] and got[2] == 5


def test_minibatch_stream_skips_replays(spark, sf):
    batch = src.read(spark, sf, "events")
    sink = ev.MinibatchDescent(0.3)
    for i in range(3):
        sink(batch, i)
    x = list(sink.x)
    sink(batch, 2)
    assert sink.x == x and sink.seen == 3 * batch.count() and x[0] > 0
    answers = spark.createDataFrame([(0, 1, 0.5), (0, 1, 0.4), (0, 2, 0.1), (0, 3, 0.9)], "t int, server_id bigint, latency double")
    assert [r.server_id for r in ev.responders(answers, 2).orderBy("rank").collect()] == [2, 1]


def test_stateful_collector_equals_the_batch(spark, tmp_path):
    rows = [(t, (7 * t + 3 * s) % 9, float((5 * s + t) % 11)) for t in range(4) for s in range(9)]
    answers = spark.createDataFrame(rows + rows[:5], "t int, server_id bigint, latency double")
    answers.coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = ev.source(spark, str(tmp_path / "in"), answers.schema)
    query = ev.first_answers(stream, 3).writeStream.format("memory").queryName("first_answers").outputMode("append").option("checkpointLocation", str(tmp_path / "ckpt")).trigger(availableNow=True).start()
    query.awaitTermination()
    got = {(r.t, r.server_id) for r in spark.table("first_answers").collect()}
    assert got == {(r.t, r.server_id) for r in ev.responders(answers, 3).collect()}


def test_row_pass_and_moments_take_the_same_steps(spark, problem):
    a, b, m = problem
    run = solver.sketched_descent(m, 3, 4, solver.Fixed(0.1))
    path = solver.row_pass_descent(matrix(spark, a, b), 16, 6, 3, 4, 0.1 * run.unit, 3)
    assert np.allclose(path[-1][1], run.history[-1][1])
