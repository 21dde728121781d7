"""Queries over whole tables against matrices written out, and dense kinds taller than their held matrix."""

import numpy as np
import pytest

from rotagrad import queries as engine
from rotagrad.functions import prf
from rotagrad.operators import rotation
from rotagrad.sources import matrices as src


def collected(df, width=4):
    rows = sorted(df.collect(), key=lambda r: r.row_id)
    return np.array([r.row_id for r in rows]), np.array([[r[f"v{j}"] for j in range(width)] for r in rows])


@pytest.fixture(scope="module")
def customers(spark, sf):
    rows = src.customers_all(spark, sf).orderBy("row_id").collect()
    assert len(rows) == 150 and [r.row_id for r in rows] == list(range(150))
    return np.array([r.v for r in rows])


def test_scrambled_and_kronecker_take_all_customers(spark, sf, customers):
    h, k = np.array([[1]]), np.array([[1]])
    for _ in range(8):
        h = np.kron(h, np.array(rotation.HADAMARD))
    for _ in range(5):
        k = np.kron(k, np.array(engine.THREE))
    ids, got = collected(engine.QUERIES["kronecker_rotation"](spark, sf))
    assert len(ids) == 243 and (got == k[:, :150] @ customers).all()
    s = {r[0]: r[1] for r in spark.range(150).select("id", prf.keyed_sign("k1", "id").alias("s")).collect()}
    place = {r[0]: r[1] for r in spark.range(256).select("id", prf.feistel("k1", 8, "id").alias("p")).collect()}
    want = h[:, :150] @ (customers * np.array([s[i] for i in range(150)])[:, None])
    ids, got = collected(engine.QUERIES["scrambled_rotation"](spark, sf))
    assert len(ids) == 256 and all((got[place[i]] == want[i]).all() for i in range(256))


def test_queries_without_bound_sql_see_every_row(spark, sf):
    for name, n in (("feistel_permutation", 200), ("gaussian_rotation", 150), ("rademacher_rotation", 150)):
        rows = engine.QUERIES[name](spark, sf).collect()
        assert len({r.row_id for r in rows}) == len(rows) == n
    places = [r.place for r in engine.QUERIES["feistel_permutation"](spark, sf).collect()]
    assert len(set(places)) == 200 and max(places) < 256


@pytest.mark.parametrize("kind", ["gaussian", "rademacher"])
def test_projections_take_all_customers(spark, sf, customers, kind):
    ids, got = collected(engine.QUERIES[f"{kind}_rotation"](spark, sf))
    assert (ids == np.arange(150)).all() and np.allclose(got, rotation.Dense("k1", kind).matrix(150) @ customers)


@pytest.mark.parametrize("make", [lambda: rotation.Scrambled("k", group_rows=16), lambda: rotation.Kronecker(rotation.reflection(3), "k", group_rows=27)])
def test_inverse_over_many_groups(spark, sf, customers, make):
    """More index digits than one group holds, with several groups in every stage."""
    r = make()
    assert len(r.plan(150)) >= 2
    rows, n = engine.all_customers(spark, sf, real=True)
    ids, got = collected(engine.wide(r.inverse(r.apply(rows, n, 4), n, 4), engine.V4, "double").filter("row_id < 150"))
    assert len(ids) == 150 and np.allclose(got, customers)


@pytest.mark.parametrize("kind", ["orthonormal", "gaussian", "rademacher"])
def test_tall_dense_kinds_in_panels(monkeypatch, kind):
    monkeypatch.setattr(rotation, "DENSE_LIMIT", 8)
    monkeypatch.setattr(rotation, "PANEL", 1000)
    r, n = rotation.Dense("k", kind), 150
    m = r.product(np.eye(n), False)
    assert np.allclose(r.product(np.eye(n), True), m.T)
    x = np.random.default_rng(1).standard_normal((n, 3))
    assert np.allclose(r.product(x, False), m @ x) and np.linalg.matrix_rank(m) == n
    if kind == "orthonormal":
        assert np.allclose(m @ m.T, np.eye(n)) and abs(np.mean(m**4) * n * n - 3 * n / (n + 2)) < 0.1
    else:
        assert abs((m**2).mean() * n - 1) < 0.05 and len({tuple(row) for row in m}) == n


def test_rotations_of_a_comparison_see_the_same_rows(spark, tmp_path):
    """More parts than a dense matrix is held for: no kind takes a prefix, and sums of squares stay where they must."""
    n = rotation.DENSE_LIMIT + 100
    spark.range(n).withColumnRenamed("id", "p_partkey").write.parquet(f"{tmp_path}/part.parquet")
    found = {name: engine.part_moments(spark, str(tmp_path), name, blocks=8, d=4) for name in ("identity", "orthonormal", "gaussian", "rademacher")}
    assert {m.rows for m in found.values()} == {n}
    whole = found["identity"].total()
    assert np.allclose(found["orthonormal"].total(), whole, rtol=1e-8, atol=1e-8 * np.abs(whole).max())
