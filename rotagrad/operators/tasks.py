"""Further tasks on rotated data: logistic regression, matrix products, inversion."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rotagrad.functions import prf
from rotagrad.functions.vec import dot, literal


def logistic(mat: DataFrame, d: int, steps: int, xi: float, feature_rotation: np.ndarray | None = None, penalty: float = 0.0) -> np.ndarray:
    """Descent on the mean log-loss with labels 0 or 1, one job per step.

    With ``feature_rotation`` the servers see rotated features and parameters only: inner
    products are kept, and the gradient's sum is decoded by the transpose.
    """
    rows = mat.select("features", "label")
    if feature_rotation is not None:
        columns = [dot(F.col("features"), literal(r)) for r in feature_rotation]
        rows = rows.select(F.array(*columns).alias("features"), "label")
    rows = rows.cache()
    n, x = rows.count(), np.zeros(d)
    for _ in range(steps):
        sent = feature_rotation @ x if feature_rotation is not None else x
        mean = 1 / (1 + F.exp(-dot(F.col("features"), literal(sent))))
        got = rows.select((mean - F.col("label")).alias("e"), "features").agg(*[F.sum(F.col("e") * F.col("features")[j]).alias(str(j)) for j in range(d)]).first()
        g = np.array([v or 0.0 for v in got])
        if feature_rotation is not None:
            g = feature_rotation.T @ g
        x = x - xi * (g / max(n, 1) + penalty * x)
    rows.unpersist()
    return x


def logistic_two_round(mat: DataFrame, d: int, steps: int, xi: float, rotation, n: int) -> np.ndarray:
    """Two trips a step: means go to the centre, the rotated residual meets the rotated matrix."""
    a = rotation.apply(mat.select("row_id", F.col("features").alias("v")), n, d).cache()
    x = np.zeros(d)
    for _ in range(steps):
        mean = 1 / (1 + F.exp(-dot(F.col("features"), literal(x))))
        residual = mat.select("row_id", F.array(mean - F.col("label")).alias("v"))
        r = rotation.apply(residual, n, 1).select("row_id", F.col("v")[0].alias("e"))
        got = a.join(r, "row_id").agg(*[F.sum(F.col("e") * F.col("v")[j]).alias(str(j)) for j in range(d)]).first()
        x = x - xi * np.array(got) / max(n, 1)
    a.unpersist()
    return x


def product(left: DataFrame, right: DataFrame) -> DataFrame:
    """(i, j, v) of left (i, k, v) times right (k, j, v): a join on the inner index and partial sums."""
    joined = left.select("i", "k", F.col("v").alias("a")).join(right.select("k", "j", F.col("v").alias("b")), "k")
    return joined.groupBy("i", "j").agg(F.sum(F.col("a") * F.col("b")).alias("v"))


def sampled_product(left: DataFrame, right: DataFrame, n: int, c: int, key: str) -> DataFrame:
    """c inner indices drawn with replacement by keyed hashes, weighted n / c."""
    own = left.sparkSession.range(c).select((F.expr(prf.SPARK.digits(key, "id")) % n).alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("times"))
    drawn = left.join(own, "k").select("i", "k", (F.col("v") * F.col("times") * (n / c)).alias("v"))
    return product(drawn, right)


def secure_inverse(a: np.ndarray, rotation: np.ndarray, steps: int) -> np.ndarray:
    """Inverse by descent on N least-squares problems over A Q' (Q orthonormal), decoded by Q'."""
    m = a @ rotation.T
    gram, x = m.T @ m, np.zeros_like(a)
    for _ in range(steps):
        e = gram @ x - m.T
        g = 2 * e
        bottom = np.einsum("ij,ij->j", g, gram @ g)
        xi = np.divide(np.einsum("ij,ij->j", g, e), bottom, out=np.zeros(len(a)), where=bottom > 0)
        x = x - g * xi
    return rotation.T @ x


#: Bytes of the matrix that every task of a distributed inversion holds.
INVERSE_BYTES = 64 << 20


def secure_inverse_columns(spark, a: np.ndarray, rotation: np.ndarray, steps: int) -> DataFrame:
    """(i, column): the inverse's columns, one least-squares problem each, spread over the cluster.

    Tasks get A Q' only (broadcast, at most ``INVERSE_BYTES``); the decoding by Q' is done on the way out.
    """
    if a.nbytes > INVERSE_BYTES:
        raise ValueError(f"a matrix of {a.nbytes} bytes; the limit is {INVERSE_BYTES}")
    shared = spark.sparkContext.broadcast((a @ rotation.T, rotation))

    def run(batches):
        import pandas as pd

        m, q = shared.value
        gram = m.T @ m
        for batch in batches:
            out = []
            for i in batch["id"]:
                x, c = np.zeros(len(m)), m[i]
                for _ in range(steps):
                    e = gram @ x - c
                    g = 2 * e
                    bottom = g @ gram @ g
                    if bottom <= 0:
                        break
                    x = x - g * (g @ e / bottom)
                out.append((int(i), (q.T @ x).tolist()))
            yield pd.DataFrame(out, columns=["i", "column"])

    return spark.range(len(a)).repartition(min(len(a), 64), "id").mapInPandas(run, "i bigint, column array<double>")
