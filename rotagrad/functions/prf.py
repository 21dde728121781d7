"""Keyed pseudo-random expressions, the same digits in Spark, DuckDB and Python.

Everything is a SQL expression over SHA-256, so it stays inside code generation.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

UNIT = 1 << 32


class Dialect:
    """How an engine writes the few functions that differ."""

    def __init__(self, duck: bool):
        self.duck = duck

    def digits(self, key: str, *parts: str) -> str:
        """The first 32 bits of the SHA-256 of key:part:part..."""
        text = " || ':' || ".join([f"'{key}'", *(f"cast({p} as varchar)" if self.duck else f"cast({p} as string)" for p in parts)])
        if self.duck:
            return f"('0x' || substr(sha256({text}), 1, 8))::BIGINT"
        return f"cast(conv(substr(sha2({text}, 256), 1, 8), 16, 10) as bigint)"

    def xor(self, a: str, b: str) -> str:
        return f"xor({a}, {b})" if self.duck else f"(({a}) ^ ({b}))"

    def uniform(self, key: str, *parts: str) -> str:
        return f"((cast({self.digits(key, *parts)} as double) + 0.5e0) / 4294967296.0e0)"

    def sign(self, key: str, part: str) -> str:
        return f"(case when {self.digits(key, part)} < 2147483648 then 1 else -1 end)"

    def div(self, a: str, b: int) -> str:
        return f"(({a}) // {b})" if self.duck else f"(({a}) div {b})"

    def feistel(self, key: str, x: str, bits: int, rounds: int = 4) -> str:
        """A keyed bijection of 0 .. 2^bits - 1, by alternately mixing one half into the other."""
        if bits == 0:
            return x
        low = bits - bits // 2
        high = bits - low
        a, b = self.div(x, 1 << low), f"(({x}) % {1 << low})"
        for r in range(rounds):
            if r % 2 == 0:
                a = self.xor(a, f"({self.digits(f'{key}:{r}', b)} % {1 << high})")
            else:
                b = self.xor(b, f"({self.digits(f'{key}:{r}', a)} % {1 << low})")
        return f"(({a}) * {1 << low} + ({b}))"

    def unfeistel(self, key: str, x: str, bits: int, rounds: int = 4) -> str:
        """The inverse of ``feistel``: the same rounds from the last to the first."""
        if bits == 0:
            return x
        low = bits - bits // 2
        a, b = self.div(x, 1 << low), f"(({x}) % {1 << low})"
        for r in reversed(range(rounds)):
            if r % 2 == 0:
                a = self.xor(a, f"({self.digits(f'{key}:{r}', b)} % {1 << (bits - low)})")
            else:
                b = self.xor(b, f"({self.digits(f'{key}:{r}', a)} % {1 << low})")
        return f"(({a}) * {1 << low} + ({b}))"


SPARK, DUCK = Dialect(False), Dialect(True)


def digits(key: str, *parts) -> int:
    """The Python twin of ``Dialect.digits``."""
    return int(hashlib.sha256(":".join([key, *map(str, parts)]).encode()).hexdigest()[:8], 16)


def uniform(key: str, *parts) -> float:
    return (digits(key, *parts) + 0.5) / UNIT


def keyed_sign(key: str, row_id: str = "row_id") -> Column:
    return F.expr(SPARK.sign(key, row_id))


def keyed_uniform(key: str, *parts: str) -> Column:
    return F.expr(SPARK.uniform(key, *parts))


def feistel(key: str, bits: int, row_id: str = "row_id") -> Column:
    return F.expr(SPARK.feistel(key, row_id, bits)).cast("bigint")


def unfeistel(key: str, bits: int, row_id: str = "row_id") -> Column:
    return F.expr(SPARK.unfeistel(key, row_id, bits)).cast("bigint")


def feistel_place(key: str, bits: int, x: int, rounds: int = 4) -> int:
    """The Python twin of ``feistel``."""
    low = bits - bits // 2
    a, b = x >> low, x & ((1 << low) - 1)
    for r in range(rounds):
        if r % 2 == 0:
            a ^= digits(f"{key}:{r}", b) % (1 << (bits - low))
        else:
            b ^= digits(f"{key}:{r}", a) % (1 << low)
    return a << low | b


def feistel_inverse(key: str, bits: int, y: int, rounds: int = 4) -> int:
    low = bits - bits // 2
    a, b = y >> low, y & ((1 << low) - 1)
    for r in reversed(range(rounds)):
        if r % 2 == 0:
            a ^= digits(f"{key}:{r}", b) % (1 << (bits - low))
        else:
            b ^= digits(f"{key}:{r}", a) % (1 << low)
    return a << low | b


def t_quantile(u: str, df: int) -> str:
    """Closed-form quantiles of the t distribution with 1, 2 or 4 degrees of freedom."""
    if df == 1:
        return f"tan(pi() * ({u} - 0.5e0))"
    if df == 2:
        return f"((2.0e0 * {u} - 1.0e0) / sqrt(2.0e0 * {u} * (1.0e0 - {u})))"
    a = f"(4.0e0 * {u} * (1.0e0 - {u}))"
    return f"(2.0e0 * sign({u} - 0.5e0) * sqrt(cos(acos(sqrt({a})) / 3.0e0) / sqrt({a}) - 1.0e0))"


def normal(u1: str, u2: str) -> str:
    """A standard normal from two uniforms (Box-Muller)."""
    return f"(sqrt(-2.0e0 * ln({u1})) * cos(2.0e0 * pi() * {u2}))"


def rng(key: str, bits=np.random.PCG64) -> np.random.Generator:
    """A seeded generator for driver-side dense draws."""
    return np.random.Generator(bits(int.from_bytes(hashlib.sha256(key.encode()).digest()[:8], "big")))


def log2_factorial(n: float) -> float:
    return math.lgamma(n + 1) / math.log(2)
