"""Rotations of 64 customers and 1024 places against SQL that sums over all pairs of ids."""

import pytest
from pyspark.sql import functions as F

from rotagrad.functions import prf
from rotagrad.functions.prf import DUCK, SPARK
from rotagrad.operators import gradient, rotation
from rotagrad.queries import THREE, V4, _mean_over_sets, _walsh, wide
from rotagrad.sources import matrices as src
from test_queries import canonical, duck  # noqa: F401

QUERIES, SQL = {}, {}


def query(sql):
    def add(f):
        QUERIES[f.__name__], SQL[f.__name__] = f, sql
        return f

    return add


SEVEN = """f7 AS (SELECT c_custkey AS row_id, 1::BIGINT AS v0, c_nationkey::BIGINT AS v1, floor(c_acctbal)::BIGINT AS v2, (c_nationkey % 3)::BIGINT AS v3
  FROM customer WHERE c_custkey < 64)"""


def customers_exact(spark, sf):
    return src.customers_all(spark, sf).filter("row_id < 64")


def every_64():
    return F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(63).cast("bigint")))


@query(f"SELECT p_partkey AS row_id, {DUCK.feistel('perm', 'p_partkey', 10)} AS place FROM part WHERE p_partkey < 1024")
def feistel_permutation(spark, sf):
    return src.read(spark, sf, "part").filter("p_partkey < 1024").select(F.col("p_partkey").alias("row_id"), prf.feistel("perm", 10, "p_partkey").alias("place"))


@query(f"WITH {SEVEN} {_walsh('f7', 'range(64)', V4)}")
def hadamard_defining_sum(spark, sf):
    rows = wide(customers_exact(spark, sf), V4)
    parity = 1 - 2 * (F.bit_count(F.col("i").bitwiseAND(F.col("row_id"))) % 2)
    # The definition itself: each of 64 rows goes to 64 sums.
    return rows.withColumn("i", every_64()).groupBy("i").agg(*[F.sum(parity * F.col(c)).cast("bigint").alias(c) for c in V4]).withColumnRenamed("i", "row_id")


@query(f"WITH {SEVEN} SELECT i AS row_id, " + ", ".join(f"coalesce(64 * {c}, 0)::BIGINT AS {c}" for c in V4) + " FROM range(64) r(i) LEFT JOIN f7 ON i = row_id")
def hadamard_involution(spark, sf):
    r = rotation.SignHadamard(None, False)
    return wide(r.apply(r.apply(customers_exact(spark, sf), 64, 4), 64, 4), V4)


@query(f"WITH {SEVEN}, hd AS ({_walsh('f7', 'range(64)', V4, sign=DUCK.sign('k1', 'f7.row_id'))}) SELECT {DUCK.feistel('k1', 'row_id', 6)} AS row_id, v0, v1, v2, v3 FROM hd")
def scrambled_rotation(spark, sf):
    return wide(rotation.Scrambled("k1", False).apply(customers_exact(spark, sf), 64, 4), V4)


def _kron_sql() -> str:
    pick = "(CASE (o.i // {p}) % 3 * 3 + (row_id // {p}) % 3 " + " ".join(f"WHEN {3 * a + b} THEN {THREE[a][b]}" for a in range(3) for b in range(3)) + " END)"
    entry = " * ".join(pick.format(p=3**k) for k in range(4))
    return f"WITH {SEVEN} SELECT o.i AS row_id, " + ", ".join(f"CAST(sum({entry} * {c}) AS BIGINT) AS {c}" for c in V4) + " FROM range(81) o(i), f7 GROUP BY o.i"


@query(_kron_sql())
def kronecker_rotation(spark, sf):
    return wide(rotation.Kronecker(THREE, None).apply(customers_exact(spark, sf), 64, 4), V4)


@query(f"WITH {SEVEN} SELECT o.i AS row_id, " + ", ".join(f"CAST(sum({DUCK.sign('rad', 'o.i * 64 + row_id')} * {c}) AS BIGINT) AS {c}" for c in V4) + " FROM range(64) o(i), f7 GROUP BY o.i")
def rademacher_rotation(spark, sf):
    rows = wide(customers_exact(spark, sf), V4)
    s = F.expr(SPARK.sign("rad", "i * 64 + row_id"))
    return rows.withColumn("i", every_64()).groupBy("i").agg(*[F.sum(s * F.col(c)).cast("bigint").alias(c) for c in V4]).withColumnRenamed("i", "row_id")


def _round_trip(spark, sf, r):
    rows = customers_exact(spark, sf).select("row_id", F.transform("v", lambda x: x.cast("double")).alias("v"))
    back = wide(r.inverse(r.apply(rows, 64, 4), 64, 4), V4, "double").filter("row_id < 64")
    return back.select("row_id", *[(F.round(c, 6) + F.lit(0.0)).alias(c) for c in V4])


_SEVEN_REAL = f"WITH {SEVEN} SELECT i AS row_id, " + ", ".join(f"coalesce({c}, 0)::DOUBLE AS {c}" for c in V4) + " FROM range(64) r(i) LEFT JOIN f7 ON i = row_id"


@query(_SEVEN_REAL)
def sign_hadamard_inverse(spark, sf):
    return _round_trip(spark, sf, rotation.SignHadamard("k1"))


@query(_SEVEN_REAL)
def scrambled_inverse(spark, sf):
    return _round_trip(spark, sf, rotation.Scrambled("k1"))


@query(_SEVEN_REAL)
def kronecker_inverse(spark, sf):
    return _round_trip(spark, sf, rotation.Kronecker(rotation.reflection(3), "k1"))


@query(_SEVEN_REAL)
def dense_rotation(spark, sf):
    return _round_trip(spark, sf, rotation.Dense("k1"))


@query(_SEVEN_REAL)
def givens_rotation(spark, sf):
    return _round_trip(spark, sf, rotation.Kronecker(rotation.givens(0.7), "k1"))


@query(f"WITH {SEVEN}, hd AS ({_walsh('f7', 'range(64)', V4, sign=DUCK.sign('k1', 'f7.row_id'))}) SELECT row_id AS block_id, v0 * v0 AS g00, v0 * v1 AS g01, v1 * v1 AS g11 FROM hd")
def row_sampled_hadamard(spark, sf):
    rows = rotation.SignHadamard("k1", False).apply(customers_exact(spark, sf), 64, 4)
    m = gradient.block_moments(rows, 1, 4)
    return m.select("block_id", *[F.col("m")[i].cast("bigint").alias(n) for n, i in (("g00", 0), ("g01", 1), ("g11", 5))])


@query(f"WITH {SEVEN} SELECT " + ", ".join(f"CAST(64 * sum(v{i} * v{j}) AS BIGINT) AS m{i}{j}" for i in range(4) for j in range(i, 4)) + " FROM f7")
def gram_from_rotated(spark, sf):
    rows = rotation.Scrambled("k1", False).apply(customers_exact(spark, sf), 64, 4)
    return rows.agg(*gradient.gram(rows, 4)).toDF(*[f"m{i}{j}" for i in range(4) for j in range(i, 4)])


@query(f"""WITH {SEVEN}, g AS (SELECT row_id // 11 AS b, {', '.join(f'sum(2 * v{j} * (v0 + 2 * v1 - v2 - v3)) AS g{j}' for j in range(3))} FROM f7 GROUP BY 1)
SELECT {', '.join(f'round(sum(g{j})::DOUBLE, 6) AS g{j}' for j in range(3))}, 20::BIGINT AS sets FROM g""")
def gradient_bias_enumerated(spark, sf):
    """The mean over all 20 responder sets of 3 of 6 blocks, scaled by K/q: the full gradient exactly."""
    return _mean_over_sets(spark, gradient.partial_gradients(customers_exact(spark, sf), [1, 2, -1], 11))


@pytest.mark.parametrize("name", sorted(SQL))
def test_small_against_sql(spark, sf, duck, name):  # noqa: F811
    got = QUERIES[name](spark, sf)
    columns = sorted(got.columns)
    want = duck.sql(SQL[name])
    assert columns == sorted(want.columns)
    assert canonical(tuple(r[c] for c in columns) for r in got.collect()) == canonical(tuple(r[want.columns.index(c)] for c in columns) for r in want.fetchall())
