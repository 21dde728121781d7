"""Gradient codes over (rotated) blocks, and simulated servers, as relations."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import window as W

from rotagrad.functions import prf


def latencies(spark: SparkSession, servers: int, steps: int, key: str = "latency") -> DataFrame:
    """(t, server_id, latency, rank): keyed exponential answers; ranked inside each step."""
    every = F.sequence(F.lit(0).cast("bigint"), F.lit(servers - 1).cast("bigint"))
    grid = spark.range(steps).select(F.col("id").cast("int").alias("t"), F.explode(every).alias("server_id"))
    u = prf.keyed_uniform(key, "t", "server_id")
    timed = grid.select("t", "server_id", F.round(-F.log(u), 9).alias("latency"))
    order = W.Window.partitionBy("t").orderBy("latency", "server_id")
    return timed.withColumn("rank", F.row_number().over(order).cast("int"))


def replicated(spark: SparkSession, blocks: int, steps: int, replicas: int, key: str = "replica") -> DataFrame:
    """(t, block_id, replica, latency): every block on several servers."""
    grid = spark.range(steps).select(F.col("id").cast("int").alias("t"), F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(blocks - 1).cast("bigint"))).alias("block_id"))
    grid = grid.withColumn("replica", F.explode(F.sequence(F.lit(0), F.lit(replicas - 1))))
    return grid.withColumn("latency", F.round(-F.log(prf.keyed_uniform(key, "t", "block_id", "replica")), 9))


def fractional_repetition(k: int, s: int) -> list[tuple[int, int, float]]:
    """K servers, s + 1 blocks each: groups of s + 1 servers hold the same blocks."""
    if k % (s + 1):
        raise ValueError("s + 1 must divide the number of servers")
    return [(server, server // (s + 1) * (s + 1) + j, 1.0) for server in range(k) for j in range(s + 1)]


def code_table(spark: SparkSession, code: list[tuple[int, int, float]]) -> DataFrame:
    return spark.createDataFrame(code, "server_id bigint, block_id bigint, coef double")


def as_matrix(code: list[tuple[int, int, float]], k: int) -> np.ndarray:
    out = np.zeros((k, k))
    for server, block, c in code:
        out[server, block] = c
    return out


def recover(code: DataFrame, partials: DataFrame, responders: DataFrame, d: int) -> DataFrame:
    """One answer per group of servers with equal blocks; the sum is exact if every group answers.

    partials: block_id, g0..; responders: server_id.
    """
    lead = code.groupBy("server_id").agg(F.min("block_id").alias("grp"))
    chosen = lead.join(responders, "server_id").groupBy("grp").agg(F.min("server_id").alias("server_id"))
    sums = [F.sum(F.col(f"g{j}") * F.col("coef").cast("bigint")).alias(f"g{j}") for j in range(d)]
    return code.join(chosen.select("server_id"), "server_id").join(partials, "block_id").agg(*sums)


def optimal_decode(code: np.ndarray, responders: list[int]) -> np.ndarray:
    """The coefficients of the responders that come nearest to the sum of all blocks."""
    return np.ones(code.shape[1]) @ np.linalg.pinv(code[responders])


def fixed_coefficient(k: int, q: int) -> float:
    return k / q


def adaptive_tolerance(stragglers: list[int], s: int) -> list[tuple[int, int, int]]:
    """(t, s, rounds of recoding so far): the code shrinks when fewer stragglers were seen than it allows."""
    out, rounds = [], 0
    for t, seen in enumerate(stragglers):
        if seen < s:
            s, rounds = max(1, seen), rounds + 1
        out.append((t, s, rounds))
    return out


def partial_work(times: DataFrame, blocks_per_server: int, deadline: float) -> DataFrame:
    """How many of its blocks each server has finished at the deadline; it works through them in order."""
    done = F.least(F.lit(blocks_per_server), F.floor(F.lit(deadline) / F.col("latency")).cast("int"))
    return times.select("t", "server_id", done.alias("done"))
