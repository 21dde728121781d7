"""Orthonormal rotations of a matrix's rows, and the projections they are compared with.

A rotation takes (row_id, v ARRAY) and returns the same over its padded height.  Kronecker
powers (the Hadamard matrix is one) factor over groups of index digits: each stage brings
together the rows that differ only in its digits, one hash shuffle, and applies the power of
the base to the group with numpy.  Padding is never written: kernels fill absent rows with
zeros.  The dense kinds cost N^2; above ``DENSE_LIMIT`` rows their matrix is never held, but
made and applied in tiles that fit a processor's cache.
"""

from __future__ import annotations

import math
import os
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rotagrad.functions import prf

#: Rows of a dense matrix that is held as a whole, and rows and numbers in a tile of a taller one.
DENSE_LIMIT = 4096
ROWS = 64
PANEL = 1 << 16
#: Numbers of a group of reflections, its pieces (few, since threads wait for each other), and threads that work on them.
HELD = 1 << 23
PIECES = 8
AHEAD = max(1, min(8, os.cpu_count() or 1))
#: Rows of a stage's group at most (a stage's memory is this times the row width).
GROUP_ROWS = 1 << 13
HADAMARD = ((1, 1), (1, -1))


def kron_apply(x: np.ndarray, base: np.ndarray, digits: int) -> np.ndarray:
    """The ``digits``-fold Kronecker power of ``base`` times x (base^digits rows)."""
    k, d = len(base), x.shape[1]
    for i in range(digits):
        x = x.reshape(k**i, k, -1)
        x = np.stack([sum(base[a, c] * x[:, c] for c in range(k)) for a in range(k)], axis=1)
    return x.reshape(k**digits, d)


def as_rows(column) -> np.ndarray:
    """Vectors as rows of an array; null or ragged ones are refused."""
    flat = column.flatten()
    width = len(flat) // max(len(column), 1)
    if column.null_count or flat.null_count or len(set(column.value_lengths().unique().to_pylist())) > 1:
        raise ValueError("vectors must have one length and no nulls")
    return flat.to_numpy(zero_copy_only=False).reshape(len(column), width)


def as_lists(x: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(np.arange(0, x.size + 1, x.shape[1], dtype=np.int32), pa.array(np.ascontiguousarray(x).ravel()))


def stage(df: DataFrame, base, width: int, low: int, digits: int) -> DataFrame:
    """Apply the power over the index digits low .. low + digits - 1 of row_id in base k.

    Rows that repeat an id add up, as a transform is linear; a null id is an error.
    """
    k = len(base)
    step, size = k**low, k**digits
    group = F.expr(f"(row_id div {step * size}) * {step} + row_id % {step}")
    place = F.expr(f"(row_id div {step}) % {size}")
    known = F.when(F.col("row_id") >= 0, group.cast("bigint")).otherwise(F.raise_error(F.lit("row_id must be 0 or more")).cast("bigint"))
    rows = df.select(known.alias("g"), place.cast("int").alias("p"), "v")
    schema = df.schema["v"].dataType.simpleString()
    integer = "bigint" in schema
    matrix = np.array(base, np.int64 if integer else np.float64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, x = None, None

        def out() -> pa.RecordBatch:
            y = kron_apply(x, matrix, digits)
            ids = (now // step) * step * size + now % step + np.arange(size, dtype=np.int64) * step
            return pa.RecordBatch.from_arrays([pa.array(ids), as_lists(y)], ["row_id", "v"])

        for batch in batches:
            if not batch.num_rows:
                continue
            g, p, v = batch.column(0).to_numpy(), batch.column(1).to_numpy(), as_rows(batch.column(2))
            cuts = np.concatenate([[0], np.flatnonzero(np.diff(g)) + 1, [len(g)]])
            for a, b in zip(cuts[:-1], cuts[1:]):
                if now != g[a]:
                    if now is not None:
                        yield out()
                    now, x = int(g[a]), np.zeros((size, width), matrix.dtype)
                np.add.at(x, p[a:b], v[a:b])
        if now is not None:
            yield out()

    return rows.repartition("g").sortWithinPartitions("g").mapInArrow(run, f"row_id bigint, v {schema}")


class Rotation:
    """apply and inverse keep (row_id, v); height(n) is the padded number of rows."""

    name, orthonormal, structured = "rotation", True, False

    def height(self, n: int) -> int:
        return n

    def shuffles(self, n: int) -> int:
        return 0

    def key_bits(self, n: int) -> float:
        return 0.0

    def apply(self, df: DataFrame, n: int, width: int) -> DataFrame:
        raise NotImplementedError

    def inverse(self, df: DataFrame, n: int, width: int) -> DataFrame:
        raise NotImplementedError


class Identity(Rotation):
    name = "identity"

    def apply(self, df, n, width):
        return df.select("row_id", "v")

    inverse = apply


class Kronecker(Rotation):
    """A power of a small orthonormal base after keyed signs (none when key is None)."""

    name, structured = "kronecker", True

    def __init__(self, base, key: str | None = None, scale: float | None = 1.0, group_rows: int = GROUP_ROWS):
        self.base, self.key, self.scale, self.group_rows = tuple(map(tuple, base)), key, scale, group_rows

    def digits(self, n: int) -> int:
        k, out = len(self.base), 0
        while k**out < n:
            out += 1
        return max(out, 1)

    def height(self, n: int) -> int:
        return len(self.base) ** self.digits(n)

    def plan(self, n: int) -> list[tuple[int, int]]:
        """(lowest digit, digits) of each stage, high digits first; at least two stages for parallelism."""
        total = self.digits(n)
        most = max(1, int(math.log(self.group_rows) / math.log(len(self.base)) + 1e-9))
        count = max(-(-total // most), 2 if total > 3 else 1)
        cuts = [total * i // count for i in range(count + 1)]
        return [(a, b - a) for a, b in zip(cuts, cuts[1:])][::-1]

    def shuffles(self, n: int) -> int:
        return len(self.plan(n))

    def key_bits(self, n: int) -> float:
        return float(self.height(n)) if self.key else 0.0

    def signed(self, df: DataFrame) -> DataFrame:
        if self.key is None:
            return df.select("row_id", "v")
        kind = "bigint" if "bigint" in df.schema["v"].dataType.simpleString() else "double"
        s = prf.keyed_sign(self.key).cast(kind)
        return df.withColumn("s", s).select("row_id", F.transform("v", lambda x: x * F.col("s")).alias("v"))

    def scaled(self, df: DataFrame, n: int) -> DataFrame:
        if self.scale == 1.0:
            return df
        c = self.scale if self.scale is not None else 1 / math.sqrt(self.height(n))
        return df.select("row_id", F.transform("v", lambda x: x * F.lit(c)).alias("v"))

    def transform(self, df: DataFrame, n: int, width: int, base) -> DataFrame:
        for low, digits in self.plan(n):
            df = stage(df, base, width, low, digits)
        return df

    def apply(self, df, n, width):
        return self.scaled(self.transform(self.signed(df), n, width, self.base), n)

    def inverse(self, df, n, width):
        return self.signed(self.scaled(self.transform(df, n, width, tuple(zip(*self.base))), n))


class SignHadamard(Kronecker):
    """The normalised Hadamard matrix after keyed signs; raw +-1 entries with normalize=False (exact lane)."""

    name = "sign_hadamard"

    def __init__(self, key: str | None, normalize: bool = True, group_rows: int = GROUP_ROWS):
        super().__init__(HADAMARD, key, None if normalize else 1.0, group_rows)


class Scrambled(SignHadamard):
    """The former with its output rows permuted by a keyed bijection: a projection, no shuffle of its own.

    With ``perm="sort"`` the permutation is the explicit order of keyed hashes (one sort more).
    """

    name = "scrambled"

    def __init__(self, key: str, normalize: bool = True, group_rows: int = GROUP_ROWS, perm: str = "feistel"):
        super().__init__(key, normalize, group_rows)
        self.perm = perm

    def places(self, spark, n: int) -> DataFrame:
        """(old, row_id): where each row of the transform goes."""
        every = spark.range(self.height(n)).select(F.col("id").alias("old"))
        if self.perm == "feistel":
            return every.select("old", prf.feistel(self.key, self.digits(n), "old").alias("row_id"))
        from rotagrad.sources.matrices import dense_row_ids

        hashed = every.withColumn("h", F.expr(prf.SPARK.digits(f"{self.key}:sort", "old")))
        return dense_row_ids(hashed, ["h", "old"]).select("old", F.col("row_id").cast("bigint").alias("row_id"))

    def key_bits(self, n: int) -> float:
        return self.height(n) + prf.log2_factorial(self.height(n))

    def apply(self, df, n, width):
        out = super().apply(df, n, width)
        if self.perm != "feistel":
            return out.withColumnRenamed("row_id", "old").join(self.places(df.sparkSession, n), "old").select("row_id", "v")
        return out.select(prf.feistel(self.key, self.digits(n)).alias("row_id"), "v")

    def inverse(self, df, n, width):
        if self.perm == "feistel":
            return super().inverse(df.select(prf.unfeistel(self.key, self.digits(n)).alias("row_id"), "v"), n, width)
        pairs = self.places(df.sparkSession, n)
        return super().inverse(df.join(pairs, "row_id").select(F.col("old").alias("row_id"), "v"), n, width)


class SuperBlock(Rotation):
    """Keyed permutation, then the Hadamard matrix inside blocks of 2^bits rows only: one shuffle at any
    height.  Orthonormal, so unbiasedness and exact recovery hold; the secrecy of a full rotation does not."""

    name, structured = "super_block", True

    def __init__(self, key: str, bits: int = 12):
        self.key, self.bits = key, bits

    def height(self, n: int) -> int:
        return 1 << max(1, (n - 1).bit_length())

    def shuffles(self, n: int) -> int:
        return 1

    def key_bits(self, n: int) -> float:
        return self.height(n) + prf.log2_factorial(self.height(n))

    def apply(self, df, n, width):
        total = self.height(n).bit_length() - 1
        own = min(self.bits, total)
        mixed = Kronecker(HADAMARD, self.key, None).signed(df).select(prf.feistel(f"{self.key}:p", total).alias("row_id"), "v")
        out = stage(mixed, HADAMARD, width, 0, own)
        c = 1 / math.sqrt(1 << own)
        return out.select("row_id", F.transform("v", lambda x: x * F.lit(c)).alias("v"))


class Dense(Rotation):
    """A dense N x N matrix: uniform orthonormal, Gaussian or Rademacher (the last two are only projections).

    ``how`` makes the uniform one of up to DENSE_LIMIT rows: "qr_sign" (QR of a normal matrix, signs of the
    diagonal), "gram_schmidt" (its columns made orthonormal one by one, twice over) or "reflections", which is
    what taller ones always are.
    """

    def __init__(self, key: str, kind: str = "orthonormal", how: str = "qr_sign"):
        if how not in ("qr_sign", "gram_schmidt", "reflections"):
            raise ValueError(f"no construction {how}")
        self.key, self.kind, self.name, self.how = key, kind, kind, how
        self.orthonormal = kind == "orthonormal"

    def key_bits(self, n: int) -> float:
        return float(n) * n if self.kind == "rademacher" else float("inf")

    def matrix(self, n: int) -> np.ndarray:
        if n > DENSE_LIMIT:
            raise ValueError(f"a dense rotation of {n} rows; the limit is {DENSE_LIMIT}")
        r = prf.rng(f"{self.kind}:{self.key}")
        if self.kind == "rademacher":
            return (r.integers(0, 2, (n, n)) * 2 - 1) / math.sqrt(n)
        g = r.standard_normal((n, n))
        if self.kind == "gaussian":
            return g / math.sqrt(n)
        if self.how == "gram_schmidt":
            out = np.empty((n, n))  # a row holds a column, for contiguous products
            for i, column in enumerate(g.T):
                for _ in range(2):
                    column = column - out[:i].T @ (out[:i] @ column)
                out[i] = column / np.linalg.norm(column)
            return out.T
        q, t = np.linalg.qr(g)
        return q * np.sign(np.diag(t))

    def tiles(self, n: int, part: int = 0, parts: int = 1) -> Iterator[tuple[int, int, np.ndarray]]:
        """(row, column, tile) of a Gaussian or Rademacher matrix of any height, times sqrt(n); of every ``parts``
        panels of ROWS rows one, each from its own key.  A tile's memory is the next one's."""
        held, wide = np.empty(max(PANEL, ROWS)), max(1, PANEL // ROWS)
        for a in range(part * ROWS, n, ROWS * parts):
            r, rows = prf.rng(f"{self.kind}:{self.key}:{a}", np.random.SFC64), min(ROWS, n - a)
            for c in range(0, n, wide):
                shape = rows, min(wide, n - c)
                tile = held[: rows * shape[1]].reshape(shape)
                if self.kind == "rademacher":
                    tile[:] = np.unpackbits(np.frombuffer(r.bytes(-(-tile.size // 8)), np.uint8), count=tile.size).reshape(shape)
                    tile *= 2
                    tile -= 1
                else:
                    r.standard_normal(out=tile)
                yield a, c, tile

    def panels(self, x: np.ndarray, part: int = 0, parts: int = 1) -> Iterator[tuple[int, np.ndarray]]:
        """(first row, rows) of a tall projection's product with x, of every ``parts`` panels one."""
        now, y = None, None
        for a, c, tile in self.tiles(len(x), part, parts):
            if a != now:
                if now is not None:
                    yield now, y / math.sqrt(len(x))
                now, y = a, np.zeros((len(tile), x.shape[1]))
            y += tile @ x[c : c + tile.shape[1]]
        if now is not None:
            yield now, y / math.sqrt(len(x))

    def reflected(self, x: np.ndarray, transposed: bool) -> np.ndarray:
        """The product of reflections, or its transpose, times x.

        The k-th reflection sends a normal vector of n - k numbers to its first axis, so that the product of
        all, with keyed signs, is uniform over the orthonormal matrices.  A group of them, the k-th to the
        (k + own - 1)-th, is I - v t v' on the rows from k on.  Its pieces, each from its own key, are made and
        multiplied in threads and then, when all products are known, applied in threads.
        """
        n, many = len(x), min(64, max(1, HELD // len(x)))
        signs = (prf.rng(f"{self.kind}:{self.key}:signs").integers(0, 2, n) * 2.0 - 1)[:, None]
        out = x.astype(float) if transposed else x * signs
        held = np.empty(n * many)

        def made(k: int, v: np.ndarray, b: int, high: int) -> np.ndarray:
            tile = v[b : b + high]
            prf.rng(f"{self.kind}:{self.key}:{k}:{b}", np.random.SFC64).standard_normal(out=tile)
            return tile

        with ThreadPoolExecutor(AHEAD) as pool:
            for k in range(0, n, many) if transposed else range(0, n, many)[::-1]:
                own = min(many, n - k)
                v, y = held[: (n - k) * own].reshape(n - k, own), out[k:]
                high = max(many, ROWS, -(-(n - k) // PIECES))

                def multiplied(b: int) -> tuple[np.ndarray, np.ndarray]:
                    tile = made(k, v, b, high)
                    return tile.T @ tile, tile.T @ y[b : b + high]

                def applied(b: int) -> None:
                    y[b : b + high] -= v[b : b + high] @ h

                rest = pool.map(multiplied, range(high, n - k, high))
                first = made(k, v, 0, high)
                first[:own] = np.tril(first[:own])
                gram, cross = first[own:].T @ first[own:], np.zeros((own, x.shape[1]))
                for g, c in rest:  # in the order of the rows, so that threads change no digit
                    gram += g
                    cross += c
                at = np.arange(own)
                first[at, at] += np.copysign(np.sqrt(np.diag(gram) + (first[:own] ** 2).sum(axis=0)), first[at, at])
                gram += first[:own].T @ first[:own]
                cross += first.T @ y[:high]
                size = np.sqrt(np.diag(gram))
                t = np.linalg.inv(np.triu(gram / np.outer(size, size), 1) + np.eye(own) / 2)
                h = (t.T if transposed else t) @ (cross / size[:, None]) / size[:, None]
                list(pool.map(applied, range(0, n - k, high)))
        return out * signs if transposed else out

    def product(self, x: np.ndarray, transposed: bool) -> np.ndarray:
        """The matrix, or its transpose, times x."""
        n = len(x)
        if n <= DENSE_LIMIT and not (self.orthonormal and self.how == "reflections"):
            m = self.matrix(n)
            return (m.T if transposed else m) @ x
        if self.orthonormal:
            return self.reflected(x, transposed)
        out = np.zeros(x.shape)
        if transposed:
            for a, c, tile in self.tiles(n):
                out[c : c + tile.shape[1]] += tile.T @ x[a : a + len(tile)]
            return out / math.sqrt(n)
        for a, y in self.panels(x):
            out[a : a + len(y)] = y
        return out

    def spread(self, df: DataFrame, n: int, width: int) -> DataFrame:
        """A tall projection: every task holds all rows and makes its own panels."""
        parts = df.sparkSession.sparkContext.defaultParallelism

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held: dict[int, np.ndarray] = {}
            for batch in batches:
                if batch.num_rows:
                    part, at, v = batch.column(0).to_numpy(), batch.column(1).to_numpy(), as_rows(batch.column(2))
                    for p in np.unique(part).tolist():
                        np.add.at(held.setdefault(p, np.zeros((n, width))), at[part == p], v[part == p])
            for p, x in held.items():
                for a, y in self.panels(x, p, parts):
                    yield pa.RecordBatch.from_arrays([pa.array(np.arange(a, a + len(y))), as_lists(y)], ["row_id", "v"])

        every = df.select(F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"), "row_id", "v")
        # A task per part: sampled range bounds would give some tasks two of them and others none.
        return every.repartitionById(parts, "part").mapInArrow(run, "row_id bigint, v array<double>")

    def times(self, df: DataFrame, n: int, width: int, transposed: bool) -> DataFrame:
        if n > DENSE_LIMIT and not self.orthonormal and not transposed:
            return self.spread(df, n, width)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            x = np.zeros((n, width))
            for batch in batches:
                if batch.num_rows:
                    np.add.at(x, batch.column(0).to_numpy(), as_rows(batch.column(1)))
            y = self.product(x, transposed)
            for a in range(0, n, GROUP_ROWS):
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(a, min(a + GROUP_ROWS, n))), as_lists(y[a : a + GROUP_ROWS])], ["row_id", "v"])

        # One task holds all rows and some tiles of the matrix.
        return df.select("row_id", "v").repartition(1).mapInArrow(run, "row_id bigint, v array<double>")

    def apply(self, df, n, width):
        return self.times(df, n, width, False)

    def inverse(self, df, n, width):
        return self.times(df, n, width, True)


class SignedPermutation(Rotation):
    """Keyed signs, then a keyed bijection of the rows: projections only, at any height.

    Orthonormal, and a draw from the finite group that hides a matrix up to its rows' order and signs;
    it flattens nothing, as every entry of a row stays where its row goes.
    """

    name, structured = "signed_permutation", True

    def __init__(self, key: str):
        self.key = key

    def bits(self, n: int) -> int:
        return max(1, (n - 1).bit_length())

    def height(self, n: int) -> int:
        return 1 << self.bits(n)

    def key_bits(self, n: int) -> float:
        return self.height(n) + prf.log2_factorial(self.height(n))

    def signed(self, df: DataFrame) -> DataFrame:
        kind = "bigint" if "bigint" in df.schema["v"].dataType.simpleString() else "double"
        return df.withColumn("s", prf.keyed_sign(self.key).cast(kind)).select("row_id", F.transform("v", lambda x: x * F.col("s")).alias("v"))

    def apply(self, df, n, width):
        return self.signed(df).select(prf.feistel(self.key, self.bits(n)).alias("row_id"), "v")

    def inverse(self, df, n, width):
        return self.signed(df.select(prf.unfeistel(self.key, self.bits(n)).alias("row_id"), "v"))


def by_name(name: str, key: str = "k1") -> Rotation:
    """identity, sign_hadamard, scrambled, kronecker (a 3 x 3 base), super_block, signed_permutation, orthonormal, gaussian, rademacher."""
    if name == "identity":
        return Identity()
    if name in ("orthonormal", "gaussian", "rademacher"):
        return Dense(key, name)
    if name == "kronecker":
        return Kronecker(reflection(3), key)
    return {"sign_hadamard": SignHadamard, "scrambled": Scrambled, "super_block": SuperBlock, "signed_permutation": SignedPermutation}[name](key)


def reflection(k: int) -> list[list[float]]:
    """The orthonormal reflection I - 2/k J: no entry is zero for k > 2."""
    return [[float(i == j) - 2 / k for j in range(k)] for i in range(k)]


def givens(theta: float) -> list[list[float]]:
    return [[math.cos(theta), -math.sin(theta)], [math.sin(theta), math.cos(theta)]]
