"""Findings of round 2: larger ids and sums, fractions of a second."""

import datetime as dt

import duckdb
import numpy as np
import pytest

from rotagrad import lane_queries as lanes
from rotagrad import queries as engine
from rotagrad.operators import rotation
from test_queries import canonical


def against_sql(spark, folder, name, tables):
    con = duckdb.connect()
    for t in tables:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{folder}/{t}.parquet/*.parquet')")
    got = engine.QUERIES[name](spark, folder)
    want = con.sql(engine.SQL[name])
    assert sorted(got.columns) == sorted(want.columns)
    return canonical(tuple(r[c] for c in want.columns) for r in got.collect()) == canonical(want.fetchall())


@pytest.fixture(scope="module")
def tall(spark, tmp_path_factory):
    """Few rows whose ids lie beyond the heights that the SQL writes out."""
    folder = str(tmp_path_factory.mktemp("tall"))
    far = "case when id < 30 then id when id < 60 then id + 40000 else id + 1000000 end"
    spark.range(90).selectExpr(f"{far} as p_partkey", "cast(id * 7 % 50 as int) as p_size", "900 + id * 13.5 as p_retailprice").selectExpr("p_partkey", "p_size", "cast(p_retailprice as double) p_retailprice").write.parquet(f"{folder}/part.parquet")
    return folder


@pytest.mark.parametrize("name", ["sketched_descent_lane", "sketch_step_lane", "stored_row_pass", "flatness_lane", "embedding_distortion_lane", "block_score_table", "frozen_solve_lane", "leverage_sampling_lane"])
def test_lanes_take_parts_beyond_their_height(spark, tall, name):
    assert against_sql(spark, tall, name, ["part"])


def test_sliding_windows_take_the_nearest_second(spark, tmp_path):
    day = dt.datetime(2024, 1, 2)
    rows = [(i, day + dt.timedelta(hours=6 * i, seconds=s), i, 1.5 + i) for i, s in enumerate((-0.3, -0.5, 0.5, -0.6, 20.25))]
    spark.createDataFrame(rows, "event_id bigint, ts timestamp_ntz, user_id bigint, value double").write.parquet(f"{tmp_path}/events.parquet")
    assert against_sql(spark, str(tmp_path), "event_sliding_moments", ["events"])


def test_signed_permutation_beyond_its_places(spark, tmp_path):
    n = (1 << engine.PLACES) + 50
    spark.range(n).selectExpr("id as o_orderkey", "date'1995-01-01' as o_orderdate", "'1-X' as o_orderpriority", "id as o_custkey", "cast(id as double) as o_totalprice").write.parquet(f"{tmp_path}/orders.parquet")
    assert against_sql(spark, str(tmp_path), "signed_permutation", ["orders"])
    assert engine.signed_permutation(spark, str(tmp_path)).select("row_id").distinct().count() == n


@pytest.fixture(scope="module")
def rich(spark, tmp_path_factory):
    """Customers whose sums of squares times the height exceed 64 bits."""
    folder = str(tmp_path_factory.mktemp("rich"))
    spark.range(2000).selectExpr("id as c_custkey", "id % 25 as c_nationkey", "cast(1500000 + id * 100 as double) as c_acctbal").write.parquet(f"{folder}/customer.parquet")
    return folder


def test_gram_from_rotated_beyond_64_bits(spark, rich):
    rows = [(1, i % 25, 1500000 + i * 100, i % 25 % 3) for i in range(2000)]
    got = engine.gram_from_rotated(spark, rich).first()
    want = {f"m{i}{j}": 2048 * sum(r[i] * r[j] for r in rows) for i in range(4) for j in range(i, 4)}
    assert want["m22"] > 1 << 63 and {c: int(got[c]) for c in want} == want


def test_exact_recovery_beyond_64_bits(spark, rich):
    assert engine.exact_recovery_gap(spark, rich).first()[0] == 0


ON_TABLES = ["adaptive_repetition", "comm_cost", "coordinate_bound", "gradient_error_bound", "hadamard_entry_table", "key_bits", "op_counts", "optimal_decode_error", "property_matrix", "q_required", "repeat_probability", "repetition_code"]


@pytest.mark.parametrize("name", ON_TABLES)
def test_queries_read_their_table(spark, tmp_path, name):
    """Each was a form over made-up numbers and did without a table."""
    with pytest.raises(Exception):
        engine.QUERIES[name](spark, str(tmp_path)).collect()


@pytest.mark.parametrize("kind", ["gaussian", "rademacher"])
def test_tall_projections_are_made_in_many_tasks(spark, kind):
    n = rotation.DENSE_LIMIT + 100
    x = np.random.default_rng(1).standard_normal((n, 3))
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "row_id bigint, v array<double>")
    out = rotation.Dense("k", kind).apply(rows, n, 3)
    got = {r.row_id: r.v for r in out.collect()}
    assert len(got) == n and np.allclose([got[i] for i in range(n)], rotation.Dense("k", kind).product(x, False))
    assert out.rdd.mapPartitions(lambda part: [any(True for _ in part)]).filter(bool).count() > 1


def test_groups_of_reflections_are_made_ahead(monkeypatch):
    monkeypatch.setattr(rotation, "DENSE_LIMIT", 8)
    monkeypatch.setattr(rotation, "PANEL", 1000)
    r, x = rotation.Dense("k"), np.random.default_rng(1).standard_normal((150, 3))
    whole = r.product(x, False)
    monkeypatch.setattr(rotation, "AHEAD", 1)
    assert (r.product(x, False) == whole).all() and np.allclose(r.product(whole, True), x)


@pytest.mark.parametrize("name", ["sketched_descent", "residual_cube", "measured_properties"])
def test_rotations_of_a_comparison_share_one_matrix(spark, sf, monkeypatch, name):
    """Each rotation made the hashed matrix anew, in one task for a small file."""
    made = []
    real = engine.src.part_heavy
    monkeypatch.setattr(engine.src, "part_heavy", lambda *a, **k: made.append(real(*a, **k)) or made[-1])
    assert engine.QUERIES[name](spark, sf).count() > 0
    assert len(made) == 1 and made[0].rdd.getNumPartitions() == spark.sparkContext.defaultParallelism


@pytest.mark.parametrize("n", [2, 65, 150, 1100])
def test_reflections_in_groups_and_pieces(monkeypatch, n):
    """Groups smaller than the matrix, several pieces each, against the explicit matrix."""
    monkeypatch.setattr(rotation, "HELD", 16 * n)
    r = rotation.Dense("k", how="reflections")
    m = r.product(np.eye(n), False)
    assert np.allclose(m @ m.T, np.eye(n)) and np.allclose(r.product(np.eye(n), True), m.T)
    x = np.random.default_rng(1).standard_normal((n, 3))
    assert np.allclose(r.product(x, False), m @ x)
