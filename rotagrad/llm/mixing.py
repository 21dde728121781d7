"""Mixing sources to target weights by Sainte-Lague apportionment.

Sources get a target number of words; the targets become whole blocks of equal size by
highest quotients (votes / odd numbers), first over sources, then over the shards of
each source.  Inside a shard the documents stand in a seeded order, and the shard's
quota of blocks is a number of whole passes plus a circular stretch of blocks from a
seeded start.  Every count is an integer and depends on ids, sizes and the seed only, so
reruns agree whatever the partitioning.

Sizes reach the driver per source only (at most MAX_SOURCES rows); a source's quota is
dealt over its shards in a group of at most ``max_shards`` rows, never of documents.  A
hot source has more shards, so its windows stay small.

Defined results: null text has size 0; null source is a source of its own, after all
others; documents of size 0 take 0; rows that repeat an id are separate documents;
an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import heapq
from fractions import Fraction

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from rotagrad.llm.common import checkpointed, word_count

#: Numbers of sources above this are refused: they would all stand on the driver.
MAX_SOURCES = 100_000


def capped_shares(sizes: list[int], weights: list[int], cap: int = 3) -> list[Fraction]:
    """Shares of sum(sizes) by weight, none above cap times its own size."""
    out = [Fraction(0)] * len(sizes)
    free, left = set(range(len(sizes))), Fraction(sum(sizes))
    while free:
        unit = left / sum(weights[i] for i in free)
        full = {i for i in free if unit * weights[i] > cap * sizes[i]}
        if not full:
            for i in free:
                out[i] = unit * weights[i]
            break
        for i in full:
            out[i] = Fraction(cap * sizes[i])
            left -= out[i]
        free -= full
    return out


def sainte_lague(votes: list, seats: int) -> list[int]:
    """Seats by highest quotients votes/(2k+1); equal quotients go to the first in order."""
    total = sum(votes)
    if seats <= 0 or total <= 0:
        return [0] * len(votes)
    # A divisor that hands out too few seats gives a lower bound for everyone.
    divisor = Fraction(total) / seats
    while True:
        got = [int(Fraction(v) / divisor + Fraction(1, 2)) if v else 0 for v in votes]
        if sum(got) <= seats:
            break
        divisor *= Fraction(1001, 1000)
    # Rounding up exactly at a tie may favour a later entry: give such seats back.
    got = [g - 1 if g and Fraction(v) / divisor + Fraction(1, 2) == g else g for v, g in zip(votes, got)]
    heap = [(-Fraction(v) / (2 * g + 1), i) for i, (v, g) in enumerate(zip(votes, got)) if v]
    heapq.heapify(heap)
    for _ in range(seats - sum(got)):
        _, i = heapq.heappop(heap)
        got[i] += 1
        heapq.heappush(heap, (-Fraction(votes[i]) / (2 * got[i] + 1), i))
    return got


def mix(
    df: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
    weights: tuple[int, ...] = (1, 2, 3),
    cap: int = 3,
    block_words: int = 8,
    seed: int = 17,
    rows_per_shard: int = 2048,
    max_shards: int = 4096,
) -> DataFrame:
    """One row per document: id, source, size, source_size, target, taken."""
    sized = checkpointed(df.select(F.col(id_col).alias("doc_id"), F.col(source_col).cast("string").alias("source"), word_count(F.col(text_col)).alias("size")))
    per = sized.groupBy("source").agg(F.sum("size").alias("words"), F.count(F.lit(1)).alias("n")).limit(MAX_SOURCES + 1).collect()
    if len(per) > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources")
    per.sort(key=lambda r: (r.source is None, r.source or ""))
    sizes = [r.words or 0 for r in per]
    targets = capped_shares(sizes, [weights[i % len(weights)] for i in range(len(per))], cap) if per else []
    blocks = sainte_lague(targets, round(sum(targets) / block_words))
    shards = [1 << max(0, min(max_shards.bit_length() - 1, (r.n // rows_per_shard).bit_length())) for r in per]

    spark = df.sparkSession
    schema = "source string, no int, shards int, source_size long, target double, blocks long, whole boolean"
    known = spark.createDataFrame([(r.source, i, shards[i], sizes[i], float(targets[i]), blocks[i], targets[i] == cap * sizes[i]) for i, r in enumerate(per)], schema)
    keyed = (
        sized.alias("d")
        .join(F.broadcast(known.alias("s")), F.col("d.source").eqNullSafe(F.col("s.source")))
        .select("d.doc_id", "d.source", "d.size", "no", "source_size", "target", F.pmod(F.xxhash64(F.col("d.doc_id"), F.lit(seed)), F.col("shards")).cast("int").alias("shard"))
    )

    def quotas(own: pd.DataFrame) -> pd.DataFrame:
        """A source's shards: whole passes over each, and the stretch of blocks beside them."""
        own = own.sort_values("shard")
        no, votes = int(own["no"].iloc[0]), own["words"].tolist()
        out = []
        for shard, w, seats in zip(own["shard"].tolist(), votes, sainte_lague(votes, int(own["blocks"].iloc[0]))):
            quota = cap * w if own["whole"].iloc[0] else min(seats * block_words, cap * w)
            passes, rest = divmod(quota, w) if w else (0, 0)
            start = (hash_mix(seed, no, shard) % max(1, -(-w // block_words))) * block_words
            out.append((no, shard, w, passes, rest, start))
        return pd.DataFrame(out, columns=["no", "shard", "w", "passes", "rest", "start"])

    words = keyed.groupBy("no", "shard").agg(F.sum("size").alias("words")).join(F.broadcast(known.select("no", "blocks", "whole")), "no")
    plan = words.groupBy("no").applyInPandas(quotas, "no int, shard int, w long, passes long, rest long, start long")
    order = W.Window.partitionBy("no", "shard").orderBy(F.xxhash64("doc_id", F.lit(seed + 1)), "doc_id", "size")
    before = F.sum("size").over(order.rowsBetween(W.Window.unboundedPreceding, 0)) - F.col("size")
    placed = keyed.withColumn("lo", before).join(plan, ["no", "shard"])

    def overlap(a, b):
        return F.greatest(F.lit(0), F.least(F.col("lo") + F.col("size"), b) - F.greatest(F.col("lo"), a))

    end = F.col("start") + F.col("rest")
    taken = F.col("passes") * F.col("size") + overlap(F.col("start"), F.least(end, F.col("w"))) + overlap(F.lit(0), end - F.col("w"))
    return placed.select("doc_id", "source", "size", "source_size", "target", taken.cast("long").alias("taken"))


def hash_mix(*parts: int) -> int:
    """A fixed 64-bit mixing of small integers (multiply and fold)."""
    x = 0x9E3779B97F4A7C15
    for p in parts:
        x = ((x ^ (p + 1)) * 0xD6E8FEB86659FD93) & 0xFFFFFFFFFFFFFFFF
        x ^= x >> 32
    return x
