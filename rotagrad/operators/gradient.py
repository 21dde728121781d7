"""Blocks, their moments and their gradients."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rotagrad.operators.rotation import Rotation, as_lists, as_rows

#: Bytes of moments that may be brought to the driver at once.
DRIVER_BYTES = 256 << 20


def stacked(mat: DataFrame) -> DataFrame:
    """(row_id, v): features and label as one vector, so that the response is rotated alongside."""
    return mat.select("row_id", F.concat("features", F.array("label")).alias("v"))


def with_blocks(rows: DataFrame, tau: int) -> DataFrame:
    return rows.withColumn("block_id", F.expr(f"row_id div {tau}"))


def block_moments(rows: DataFrame, tau: int, width: int) -> DataFrame:
    """(block_id, m): sums of outer products of each block's rows, width x width flattened.

    Tasks sum what they see of a block before the shuffle; partial sums are added natively.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}

        def out() -> pa.RecordBatch:
            ids = sorted(sums)
            return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), as_lists(np.stack([sums[i].ravel() for i in ids]))], ["block_id", "m"])

        for batch in batches:
            if not batch.num_rows:
                continue
            block, v = batch.column(0).to_numpy() // tau, as_rows(batch.column(1)).astype(float)
            order = np.argsort(block, kind="stable")
            cuts = np.concatenate([[0], np.flatnonzero(np.diff(block[order])) + 1, [len(block)]])
            for a, b in zip(cuts[:-1], cuts[1:]):
                own = v[order[a:b]]
                k = int(block[order[a]])
                sums[k] = sums.get(k, 0) + own.T @ own
            if len(sums) * width * width * 8 > 1 << 25:
                yield out()
                sums.clear()
        if sums:
            yield out()

    parts = rows.select("row_id", "v").mapInArrow(run, "block_id bigint, m array<double>")
    add = F.aggregate(F.slice("ms", 2, F.size("ms")), F.col("ms")[0], lambda acc, x: F.zip_with(acc, x, lambda a, b: a + b))
    return parts.groupBy("block_id").agg(F.collect_list("m").alias("ms")).select("block_id", add.alias("m"))


@dataclass
class Moments:
    """Moments of all blocks on the driver: blocks x width x width, the label last."""

    m: np.ndarray
    rows: int

    @property
    def d(self) -> int:
        return self.m.shape[1] - 1

    @property
    def blocks(self) -> int:
        return len(self.m)

    def total(self) -> np.ndarray:
        return self.m.sum(axis=0)


def moments(mat: DataFrame, rotation: Rotation, blocks: int, d: int, n: int | None = None) -> Moments:
    """Rotate, cut in blocks, and bring the blocks' moments (checked against DRIVER_BYTES) to the driver."""
    n = n if n is not None else mat.count()
    width = d + 1
    if blocks * width * width * 8 > DRIVER_BYTES:
        raise ValueError(f"{blocks} blocks of {width} columns exceed the driver's {DRIVER_BYTES} bytes")
    tau = -(-rotation.height(n) // blocks)
    rotated = rotation.apply(stacked(mat), n, width)
    out = np.zeros((blocks, width, width))
    for r in block_moments(rotated, tau, width).collect():
        out[r.block_id] = np.array(r.m).reshape(width, width)
    return Moments(out, n)


def partial_gradients(rows: DataFrame, x: list, tau: int) -> DataFrame:
    """(block_id, j, g): each block's 2 A'(Ax - b) by coordinate; v holds features and then the label."""
    d = len(x)
    residual = sum((F.col("v")[j] * F.lit(c) for j, c in enumerate(x)), F.lit(0)) - F.col("v")[d]
    each = with_blocks(rows, tau).select("block_id", residual.alias("e"), "v")
    return each.groupBy("block_id").agg(*[(2 * F.sum(F.col("v")[j] * F.col("e"))).alias(f"g{j}") for j in range(d)])


def aggregate(partials: DataFrame, responders: DataFrame, d: int) -> DataFrame:
    """The responders' weighted sum (responders: block_id, weight)."""
    w = F.col("weight")
    return partials.join(responders, "block_id").agg(*[F.sum(F.col(f"g{j}") * w).alias(f"g{j}") for j in range(d)])


def overlapped(partials: DataFrame, d: int) -> DataFrame:
    """Each server's gradient when it also holds the next block (ablation only)."""
    nxt = partials.select((F.col("block_id") - 1).alias("block_id"), *[F.col(f"g{j}").alias(f"h{j}") for j in range(d)])
    return partials.join(nxt, "block_id", "left").select("block_id", *[(F.col(f"g{j}") + F.coalesce(f"h{j}", F.lit(0))).alias(f"g{j}") for j in range(d)])


def gram(rows: DataFrame, width: int) -> list[Column]:
    """Flat native moments of a narrow matrix: one sum per pair of columns (width up to 32)."""
    if width > 32:
        raise ValueError("use block_moments for wide matrices")
    return [F.sum(F.col("v")[i] * F.col("v")[j]).alias(f"m{i}_{j}") for i in range(width) for j in range(i, width)]
