"""SimHash near-duplicates by tiled exact comparison.

Fingerprints are compared in tiles with numpy exclusive-or and bit counts; rows stand by
population count, so tile pairs whose counts differ beyond the radius are skipped.  So
that no comparison is all against all, fingerprints are first dealt out into buckets, and the tiles
of a bucket meet in one task; equal fingerprints collapse before, so a bucket holds distinct ones.

``near_duplicates`` (64 bits, a small radius) deals by what any pair in reach must share: of
``radius + 2`` stretches of bits at least two are equal, hence one bucket per pair of
stretches, and nothing is lost.  A bucket above ``SPLIT`` rows is dealt out again by its other
bits, of which any pair in reach shares one of ``radius + 1`` runs; what is left of them bounds
a task's rows.

``similar`` (256 bits, a similarity of word shingles such as 0.8) would need a radius that leaves
no such stretch.  It deals by ``tables`` keyed choices of bits instead, as many as a pair of just that
similarity needs to meet with probability ``recall``; the choice widens with the logarithm of
the number of fingerprints, so buckets stay small.  The distance estimates the similarity (standard error
0.02 at 0.8).  A bucket above ``SPLIT`` rows is compared in salted parts, and the
least and greatest member of each part's groups meet once more.  What chance leaves out is found
exactly after that (``missed``): two sets of that similarity share one of the first shingles of
either, so documents of different groups that do are compared by their whole shingle sets.

A bucket gives only a spanning forest of its links, as trees of fan-out ``FAN``, so that no
vertex has many.  Components come from repeated hooking to the smallest neighbour and pointer
jumping on DataFrames, each round checkpointed and over the links that the last one left between
different trees; neither links nor fingerprints reach the driver.

Defined results: null and blank texts have fingerprint zero and are linked like any
other; repeated rows link with each other; a null id is never the smallest; an empty
table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rotagrad.llm.common import broadcast_if_small, checkpointed, drop_shuffles, freed

SEED = 42
TILE = 1024
SPLIT = 8192
PIECE = 1 << 15
#: Children of a vertex in the trees that a bucket gives.
FAN = 16
#: 64-bit words of a wide fingerprint.
WORDS = 4
LANES = np.uint64(0x0101010101010101)


def shingle_hashes(text: str | None, shingle: int) -> np.ndarray:
    """XXH64 of all word shingles, repeats included; the whole sequence if it has fewer words."""
    from xxhash import xxh64_intdigest

    words = text.encode().lower().split() if text else []
    n = len(words)
    if not n:
        return np.zeros(0, np.uint64)
    data = b" ".join(words)
    if n <= shingle:
        return np.array([xxh64_intdigest(data, SEED)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, n) + 1) - 1
    begins = np.concatenate([[0], ends[:-1] + 1])
    out = np.empty(n - shingle + 1, np.uint64)
    for i in range(0, len(out), PIECE):
        cut = slice(i, i + PIECE)
        out[cut] = [xxh64_intdigest(data[a:b], SEED) for a, b in zip(begins[: len(out)][cut].tolist(), ends[shingle - 1 :][cut].tolist())]
    return out


def bit_counts(h: np.ndarray) -> np.ndarray:
    """How many of the numbers have each of 64 bits, lowest first."""
    out = np.zeros((8, 8), np.int64)
    rows = np.arange(0, len(h), 255)  # so many ones fit a byte
    for shift in range(8):
        sums = np.add.reduceat((h >> np.uint64(shift)) & LANES, rows)
        out[:, shift] = sums.astype("<u8").view(np.uint8).reshape(-1, 8).sum(axis=0, dtype=np.int64)
    return out.ravel()


def majority(h: np.ndarray) -> np.ndarray:
    return np.packbits(2 * bit_counts(h) > len(h), bitorder="little")


def fingerprint(text: str | None, shingle: int = 3) -> int:
    """Majority bits of the XXH64 of all word shingles, repeats included; signed 64 bits."""
    h = shingle_hashes(text, shingle)
    return int(majority(h).view("<i8")[0]) if len(h) else 0


def wide_fingerprint(text: str | None, shingle: int = 5) -> bytes:
    """Majority bits of 256-bit expansions of the different shingles' hashes."""
    return wide_bits(np.unique(shingle_hashes(text, shingle)))


def wide_bits(h: np.ndarray) -> bytes:
    if not len(h):
        return bytes(8 * WORDS)
    parts = []
    for k in range(WORDS):
        z = h + np.uint64((0x9E3779B97F4A7C15 * (k + 1)) % (1 << 64))
        z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        parts.append(majority(z ^ (z >> np.uint64(31))))
    return np.concatenate(parts).tobytes()


def fingerprints(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3) -> DataFrame:
    """One row per input row: doc_id, fp (signed 64 bits)."""
    rows = df.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = [fingerprint(t.as_py(), shingle) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps, pa.int64())], ["doc_id", "fp"])

    return rows.mapInArrow(freed(run), f"doc_id {rows.schema['doc_id'].dataType.simpleString()}, fp long")


def stretches(count: int) -> list[int]:
    """Masks of ``count`` stretches that cover 64 bits."""
    cuts = [64 * k // count for k in range(count + 1)]
    return [((1 << b) - 1) ^ ((1 << a) - 1) for a, b in zip(cuts, cuts[1:])]


def distance(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Differing bits; wide fingerprints have their words along the last axis."""
    d = np.bitwise_count(a ^ b)
    return d if d.ndim < 3 else d.sum(axis=-1, dtype=np.int16)


def tiles(fps: np.ndarray, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs within the radius, tile by tile; fps uint64, distinct (of several words: a row each)."""
    ones = np.bitwise_count(fps)
    ones = ones if fps.ndim == 1 else ones.sum(axis=1, dtype=np.int64)
    order = np.argsort(ones, kind="stable")
    sorted_fps, ones = fps[order], ones[order].astype(np.int64)
    size = TILE if fps.ndim == 1 else TILE // 4
    for a in range(0, len(fps), size):
        last = ones[min(a + size, len(fps)) - 1]
        for b in range(a, len(fps), size):
            if ones[b] - last > radius:
                break  # rows stand by population count: no later tile is nearer
            near = distance(sorted_fps[a : a + size, None], sorted_fps[None, b : b + size]) <= radius
            i, j = np.nonzero(near)
            i, j = i + a, j + b
            keep = i < j
            yield order[i[keep]], order[j[keep]]


def pairs(fps: np.ndarray, radius: int, masks: list[int]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All index pairs within the radius; large sets are first cut by the bits in ``masks`` (one of which must be equal)."""
    if len(fps) <= SPLIT or not masks:
        yield from tiles(fps, radius)
        return
    for mask in masks:
        key = fps & np.uint64(mask)
        order = np.argsort(key, kind="stable")
        cuts = np.flatnonzero(np.diff(key[order])) + 1
        for run in np.split(order, cuts):
            if len(run) > 1:
                for i, j in tiles(fps[run], radius):
                    yield run[i], run[j]


def forest(fps: np.ndarray, radius: int, masks: list[int]) -> np.ndarray:
    """The smallest index of each index's component among these fingerprints."""
    root = np.arange(len(fps))
    for i, j in pairs(fps, radius, masks):
        while len(i):
            a, b = root[i], root[j]
            open_ = a != b
            i, j, a, b = i[open_], j[open_], a[open_], b[open_]
            np.minimum.at(root, np.maximum(a, b), np.minimum(a, b))
            while True:
                up = root[root]
                if (up == root).all():
                    break
                root = up
    return root


def tree_edges(root: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(child, parent) indices: a tree of fan-out FAN over each group of equal roots, the least index on top."""
    order = np.argsort(root, kind="stable")
    new = np.concatenate([[True], np.diff(root[order]) != 0])
    first = np.flatnonzero(new)[np.cumsum(new) - 1]  # where each row's group begins
    place = np.arange(len(order)) - first
    child = np.flatnonzero(place)
    return order[child], order[first[child] + (place[child] - 1) // FAN]


def grouped(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[list[np.ndarray]]:
    """Runs of whole groups (rows with equal last ``keys`` columns stand together) as arrays per column; rows are held in
    parts until their group ends and put together once."""
    held: list[list[np.ndarray]] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        now = [as_array(c) for c in batch.columns]
        same = np.ones(batch.num_rows, bool)
        for c in now[-keys:]:
            same &= c == c[-1]
        cut = int(np.flatnonzero(~same)[-1]) + 1 if not same.all() else 0
        ended = bool(held) and any(h[-1] != c[0] for h, c in zip(held[-1][-keys:], now[-keys:]))
        if cut or ended:
            done = [*held, [c[:cut] for c in now]]
            yield [np.concatenate(x) for x in zip(*done)]
            held = []
        held.append([c[cut:] for c in now])
    if held:
        yield [np.concatenate(x) for x in zip(*held)]


def as_array(column: pa.Array) -> np.ndarray:
    """Numbers, or the words of wide fingerprints as rows."""
    if pa.types.is_binary(column.type):
        return np.frombuffer(b"".join(column.to_pylist()), "<u8").reshape(len(column), -1)
    return np.asarray(column)


def links(distinct: DataFrame, radius: int = 2) -> DataFrame:
    """Rows (a, b), a > b as signed numbers: links that span every component of fingerprints in reach."""
    masks = stretches(radius + 2)
    chosen = list(combinations(range(len(masks)), 2))

    def signed(m: int) -> Column:
        return F.lit(m - (1 << 64) if m >> 63 else m)

    def rest(k: int) -> list[int]:
        return parts(sum(m for x, m in enumerate(masks) if x not in chosen[k]), radius + 1)

    keys = F.array(*[F.struct(F.lit(k).alias("k"), F.col("fp").bitwiseAND(signed(masks[a] | masks[b])).alias("bits")) for k, (a, b) in enumerate(chosen)])
    dealt = distinct.select("fp", F.explode(keys).alias("key")).select("fp", "key.k", "key.bits")
    hot = checkpointed(dealt.groupBy("k", "bits").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > SPLIT).drop("n"))
    no = F.lit(0).cast("long")
    if hot.isEmpty():
        dealt = dealt.select("fp", "k", "bits", F.lit(0).alias("part"), no.alias("sub"))
    else:
        # Any pair in reach shares one of the runs of a bucket's other bits.
        sub = F.array(F.struct(F.lit(0).alias("part"), no.alias("sub")))
        for k in range(len(chosen)):
            own = F.array(*[F.struct(F.lit(i).alias("part"), F.col("fp").bitwiseAND(signed(m)).alias("sub")) for i, m in enumerate(rest(k))])
            sub = F.when((F.col("k") == k) & F.col("hot"), own).otherwise(sub)
        dealt = dealt.join(hot.withColumn("hot", F.lit(True)), ["k", "bits"], "left").withColumn("hot", F.coalesce("hot", F.lit(False)))
        dealt = dealt.withColumn("x", F.explode(sub)).select("fp", "k", "bits", "x.part", "x.sub")
    dealt = dealt.repartition("k", "bits", "part", "sub").sortWithinPartitions("k", "bits", "part", "sub", "fp")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for fp, k, bits, part, sub in grouped(batches, 4):
            cuts = np.flatnonzero((np.diff(k) != 0) | (np.diff(bits) != 0) | (np.diff(part) != 0) | (np.diff(sub) != 0)) + 1
            starts = np.concatenate([[0], cuts])
            sizes = np.diff(np.concatenate([starts, [len(k)]]))
            two = starts[sizes == 2]  # a bucket of two is a tile of one comparison
            near = distance(fp[two].view(np.uint64), fp[two + 1].view(np.uint64)) <= radius
            out_a, out_b = [fp[two[near] + 1]], [fp[two[near]]]
            for s, n in zip(starts[sizes > 2].tolist(), sizes[sizes > 2].tolist()):
                own = fp[s : s + n]
                child, parent = tree_edges(forest(own.view(np.uint64), radius, rest(int(k[s]))))
                out_a.append(np.maximum(own[child], own[parent]))
                out_b.append(np.minimum(own[child], own[parent]))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(out_a)), pa.array(np.concatenate(out_b))], ["a", "b"])

    return dealt.mapInArrow(freed(run), "a long, b long").distinct()


def agreement(similarity: float) -> float:
    """The share of equal bits of two fingerprints whose shingle sets have that Jaccard similarity."""
    return 1 - math.acos(min(1.0, 2 * similarity / (1 + similarity))) / math.pi


def wide_links(distinct: DataFrame, radius: int, width: int, tables: int) -> DataFrame:
    """Rows (a, b) of wide fingerprints (column fp): links that span the groups of every bucket."""
    places = [np.random.default_rng([SEED, t]).permutation(64 * WORDS)[:width] for t in range(tables)]
    power = (1 << np.arange(width)).astype(np.int64)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.column(0).slice(at, 1024)
                bits = np.unpackbits(as_array(part).view(np.uint8), axis=1, bitorder="little")
                for t, own in enumerate(places):
                    yield pa.RecordBatch.from_arrays([part, pa.array(np.full(len(part), t, np.int32)), pa.array(bits[:, own] @ power)], ["fp", "k", "bits"])

    def compare(leaders: bool) -> Callable:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for fp, k, bits, salt in grouped(batches, 3):
                cuts = np.flatnonzero((np.diff(k) != 0) | (np.diff(bits) != 0) | (np.diff(salt) != 0)) + 1
                starts = np.concatenate([[0], cuts])
                sizes = np.diff(np.concatenate([starts, [len(k)]]))
                out: dict[str, list] = {"a": [], "b": [], "k": [], "bits": []}
                for s, n in zip(starts[sizes > 1].tolist(), sizes[sizes > 1].tolist()):
                    root = forest(fp[s : s + n], radius, [])
                    child, parent = tree_edges(root)
                    out["a"].append(s + child)
                    out["b"].append(s + parent)
                    out["k"].append(np.full(len(child), -1))
                if leaders:  # a group's first and last member, to meet the other parts'
                    for s, n in zip(starts.tolist(), sizes.tolist()):
                        root = forest(fp[s : s + n], radius, [])
                        last = np.zeros(n, np.int64)
                        last[root] = np.arange(n)
                        ends = np.unique(np.concatenate([np.unique(root), last[np.unique(root)]]))
                        out["a"].append(s + ends)
                        out["b"].append(s + ends)
                        out["k"].append(np.full(len(ends), int(k[s])))
                if out["a"]:
                    a, b, table = (np.concatenate(out[x]).astype(np.int64) for x in ("a", "b", "k"))
                    rows = [pa.array([x.tobytes() for x in fp[i]], pa.binary()) for i in (a, b)]
                    yield pa.RecordBatch.from_arrays([*rows, pa.array(table.astype(np.int32)), pa.array(bits[a])], ["a", "b", "k", "bits"])

        return run

    found = "a binary, b binary, k int, bits long"
    dealt = distinct.select("fp").mapInArrow(freed(deal), "fp binary, k int, bits long")
    count = dealt.groupBy("k", "bits").agg(F.count(F.lit(1)).alias("n"))
    hot = checkpointed(count.filter(F.col("n") > SPLIT))

    def together(rows: DataFrame) -> DataFrame:
        return rows.repartition("k", "bits", "salt").sortWithinPartitions("k", "bits", "salt", "fp")

    if hot.isEmpty():
        return together(dealt.withColumn("salt", F.lit(0))).mapInArrow(freed(compare(False)), found).select("a", "b").distinct()
    salted = dealt.join(hot, ["k", "bits"], "left")
    cold = salted.filter("n is null").select("fp", "k", "bits", F.lit(0).alias("salt"))
    warm = salted.filter("n is not null").select("fp", "k", "bits", F.pmod(F.xxhash64("fp"), F.ceil(F.col("n") / SPLIT)).cast("int").alias("salt"))
    first = checkpointed(together(warm).mapInArrow(freed(compare(True)), found))
    again = first.filter("k >= 0").select(F.col("a").alias("fp"), "k", "bits", F.lit(0).alias("salt"))
    rest = together(cold.union(again)).mapInArrow(freed(compare(False)), found)
    return rest.select("a", "b").union(first.filter("k < 0").select("a", "b")).distinct()


def similar(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 5, similarity: float = 0.8, recall: float = 0.97) -> DataFrame:
    """One row per input row: doc_id, component_id (smallest doc_id reachable over links of that similarity or more).

    Two fingerprints link up to the distance expected at ``similarity`` and one standard deviation more; two documents
    that this leaves apart link if their shingle sets reach ``similarity``.
    """
    rows = df.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))

    common, rank = common_shingles(rows, shingle)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                sets = [np.unique(shingle_hashes(t.as_py(), shingle)) for t in part.column(1)]
                columns = [[wide_bits(h) for h in sets], counted(sets), occupied(sets)]
                sizes = pa.array([len(h) for h in sets], pa.int32())
                yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(c, pa.binary()) for c in columns), sizes, first_shingles(sets, similarity, common, rank)], ["doc_id", "fp", "counts", "bits", "n", "first"])

    whole = checkpointed(rows.mapInArrow(freed(run), f"doc_id {rows.schema['doc_id'].dataType.simpleString()}, fp binary, counts binary, bits binary, n int, first array<long>"))
    whole = whole.withColumn("at", F.monotonically_increasing_id())
    docs = checkpointed(whole.select("doc_id", "fp", "at"))
    distinct = checkpointed(docs.groupBy("fp").agg(F.min("doc_id").alias("least"), F.min("at").alias("first")))
    p, bits = agreement(similarity), 64 * WORDS
    radius = int(bits * (1 - p) + math.sqrt(bits * p * (1 - p)))
    width = max(10, (distinct.count() >> 4).bit_length())
    tables = math.ceil(math.log(1 - recall) / math.log(1 - p**width))
    roots = components(wide_links(distinct, radius, width, tables))
    drop_shuffles(df.sparkSession)  # the buckets' go before the exact pairs' come
    more = missed(rows, whole, distinct, roots, similarity, shingle)
    if not more.isEmpty():
        roots = followed(roots, components(contracted(more, roots)))
    return labelled(docs, distinct, roots).select("doc_id", "component_id")


#: Numbers that a set's counts by beginning have, and bits of its occupied beginnings (powers of two).
COUNTS, PLACES = 32, 2048


def counted(sets: list[np.ndarray]) -> list[bytes]:
    """How many of each set's shingles have each of COUNTS beginnings; nothing where a byte does not hold a count."""
    owner = np.repeat(np.arange(len(sets)) * COUNTS, [len(h) for h in sets])
    begin = (np.concatenate(sets) >> np.uint64(65 - COUNTS.bit_length())).astype(np.int64)
    counts = np.bincount(owner + begin, minlength=len(sets) * COUNTS).reshape(-1, COUNTS)
    return [c.astype(np.uint8).tobytes() if c.max() < 256 else b"" for c in counts]


def occupied(sets: list[np.ndarray]) -> list[bytes]:
    """A bit for each of PLACES beginnings that any of a set's shingles has."""
    bits = np.zeros((len(sets), PLACES), bool)
    bits[np.repeat(np.arange(len(sets)), [len(h) for h in sets]), (np.concatenate(sets) >> np.uint64(65 - PLACES.bit_length())).astype(np.int64)] = True
    return [b.tobytes() for b in np.packbits(bits, axis=1)]


def most_by_counts(a: list[bytes], n_a: np.ndarray, b: list[bytes], n_b: np.ndarray) -> np.ndarray:
    """What two sets can have in common at most: the lesser count of each beginning."""
    out = np.minimum(n_a, n_b)
    known = np.array([i for i, (x, y) in enumerate(zip(a, b)) if x and y], np.int64)
    if len(known):
        x, y = (np.frombuffer(b"".join(side[i] for i in known), np.uint8).reshape(-1, COUNTS) for side in (a, b))
        out[known] = np.minimum(x, y).sum(axis=1, dtype=np.int64)
    return out


def most_by_bits(a: list[bytes], n_a: np.ndarray, b: list[bytes], n_b: np.ndarray) -> np.ndarray:
    """The same: a beginning that only one set has holds at least one shingle that the other lacks."""
    x, y = (np.frombuffer(b"".join(side), np.uint64).reshape(-1, PLACES // 64) for side in (a, b))
    alone = [np.bitwise_count(v & ~w).sum(axis=1, dtype=np.int64) for v, w in ((x, y), (y, x))]
    return np.minimum(n_a - alone[0], n_b - alone[1])


def first_shingles(sets: list[np.ndarray], t: float, common: np.ndarray, rank: np.ndarray) -> pa.Array:
    """Of each set the first n - ceil(t n) + 1 shingles in an order all sets share: by value, and those in ``common`` (ascending) last, by rank."""
    sizes = np.array([len(h) for h in sets], np.int64)
    every, owner = np.concatenate(sets), np.repeat(np.arange(len(sets)), sizes)
    last = np.zeros(len(every), np.int64)
    if len(common):
        where = np.minimum(np.searchsorted(common, every), len(common) - 1)
        last = np.where(common[where] == every, len(common) - rank[where], 0)
    order = np.lexsort((every, last, owner))
    take = np.where(sizes > 0, sizes - np.ceil(t * sizes - EPS).astype(np.int64) + 1, 0)
    place = np.arange(len(every)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    kept = every[order][place < np.repeat(take, sizes)]
    return pa.ListArray.from_arrays(np.concatenate([[0], np.cumsum(take)]).astype(np.int32), pa.array(kept.view(np.int64)))


EPS = 1e-9
#: One in so many documents is counted to find shingles that many share, and how many of those make one; only the order of shingles depends on it.
COUNTED, COMMON, LISTED = 16, 8, 1 << 16


def common_shingles(rows: DataFrame, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that many documents share, ascending, and the rank of each (0 the most common)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for t in batch.column(0):
                yield pa.RecordBatch.from_arrays([pa.array(np.unique(shingle_hashes(t.as_py(), shingle)).view(np.int64))], ["h"])

    each = rows.filter(F.pmod(F.xxhash64("text"), F.lit(COUNTED)) == 0).select("text").mapInArrow(freed(run), "h long")
    top = each.groupBy("h").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") >= COMMON).orderBy(F.desc("n"), "h").limit(LISTED).collect()
    h = np.array([r.h for r in top], np.int64).view(np.uint64)
    order = np.argsort(h)
    return h[order], order


def missed(rows: DataFrame, whole: DataFrame, distinct: DataFrame, roots: DataFrame, similarity: float, shingle: int) -> DataFrame:
    """Rows (a, b): fingerprints of documents in different groups whose shingle sets have the similarity; none is left out.

    The first shingles (``first_shingles``) of two sets in reach have one in common, and at the first in common sizes and
    places leave room for the overlap.  Pairs for which counts and occupied beginnings leave room too are compared by their
    whole sets, made anew from their texts.  rows: doc_id, text; whole: a row each, with its place ``at``; distinct: fp
    and its first at; roots: (v, root).
    """
    t, eps = similarity, EPS

    def pairs_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for at, root, n, place, h in grouped(batches, 1):
            starts = np.concatenate([[0], np.flatnonzero(np.diff(h)) + 1])
            sizes = np.diff(np.concatenate([starts, [len(h)]]))
            mixed = np.minimum.reduceat(root, starts) != np.maximum.reduceat(root, starts)
            keep = np.repeat(mixed, sizes)
            if not keep.any():
                continue
            at, root, n, place = (x[keep].astype(np.int64) for x in (at, root, n, place))
            sizes = sizes[mixed]
            run = np.repeat(np.arange(len(sizes)), sizes)

            def reach(i, j):
                small, large = np.minimum(n[i], n[j]), np.maximum(n[i], n[j])
                room = 1 + np.minimum(n[i] - place[i], n[j] - place[j]) - 1
                return (root[i] != root[j]) & (small >= t * large - eps) & (room >= t / (1 + t) * (small + large) - eps)

            def found(i, j):
                ok = reach(i, j)
                a, b = at[i[ok]], at[j[ok]]
                return pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], ["a", "b"])

            near = np.flatnonzero(np.repeat(sizes <= 64, sizes))
            for step in range(1, 64):  # rows of one run stand together
                near = near[near + step < len(run)]
                near = near[run[near] == run[near + step]]
                if not len(near):
                    break
                yield found(near, near + step)
            begin = np.cumsum(sizes) - sizes
            for s, m in zip(begin[sizes > 64].tolist(), sizes[sizes > 64].tolist()):
                by_size = s + np.argsort(n[s : s + m], kind="stable")
                limit = np.searchsorted(n[by_size], n[by_size] / t + eps, side="right")
                for i in range(0, m, TILE):
                    for j in range(i, int(limit[min(i + TILE, m) - 1]), TILE):
                        x, y = np.meshgrid(np.arange(i, min(i + TILE, m)), np.arange(j, min(j + TILE, m)), indexing="ij")
                        ahead = x < y
                        yield found(by_size[x[ahead]], by_size[y[ahead]])

    tops = distinct.join(roots, distinct.fp == roots.v).groupBy("root").agg(F.min("first").alias("top"))
    linked = broadcast_if_small(checkpointed(roots.join(tops, "root").select(F.col("v").alias("fp"), "top")))
    placed = whole.select("fp", "at", "n", "first").join(linked, "fp", "left").select("at", F.coalesce("top", "at").alias("root"), "n", F.posexplode("first").alias("place", "h"))
    met = placed.repartition("h").sortWithinPartitions("h").mapInArrow(freed(pairs_of), "a long, b long").distinct()

    def roomy(pairs: DataFrame, column: str, most: Callable) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if batch.num_rows:
                    n_a, n_b = (np.asarray(batch.column(k)).astype(np.int64) for k in (3, 5))
                    room = most(batch.column(2).to_pylist(), n_a, batch.column(4).to_pylist(), n_b)
                    yield batch.select([0, 1]).filter(pa.array(room >= t / (1 + t) * (n_a + n_b) - eps))

        a, b = (whole.select(F.col("at").alias(x), F.col(column).alias(f"x_{x}"), F.col("n").alias(f"n_{x}")) for x in "ab")
        both = pairs.join(a, "a").join(b, "b").select("a", "b", "x_a", "n_a", "x_b", "n_b")
        return checkpointed(both.mapInArrow(freed(run), "a long, b long"))

    met = roomy(roomy(met, "counts", most_by_counts), "bits", most_by_bits)
    sides = checkpointed(whole.join(broadcast_if_small(checkpointed(met.select(F.col("a").alias("at")).union(met.select("b")).distinct())), "at").select(F.col("doc_id").alias("id"), "at", "fp"))

    def again(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at, fp, text in zip(*(c.to_pylist() for c in batch.columns)):
                h = np.unique(shingle_hashes(text, shingle))
                if wide_bits(h) == fp:  # an id may stand on several texts
                    yield pa.RecordBatch.from_arrays([pa.array([at]), pa.array([fp], pa.binary()), pa.array([h.view(np.int64)], pa.list_(pa.int64()))], ["at", "fp", "shingles"])

    texts = rows.join(broadcast_if_small(sides), F.col("doc_id").eqNullSafe(F.col("id"))).select("at", "fp", "text")
    sets = checkpointed(texts.mapInArrow(freed(again), "at long, fp binary, shingles array<long>"))
    a, b = (sets.select(F.col("at").alias(x), F.col("fp").alias(f"fp_{x}"), F.col("shingles").alias(f"set_{x}")) for x in "ab")
    both = met.join(a, "a").join(b, "b").withColumn("shared", F.size(F.array_intersect("set_a", "set_b")))
    enough = F.col("shared") >= t * (F.size("set_a") + F.size("set_b") - F.col("shared")) - eps
    return checkpointed(both.filter(enough & (F.col("fp_a") != F.col("fp_b"))).select(F.col("fp_a").alias("a"), F.col("fp_b").alias("b")).distinct())


def parts(mask: int, count: int) -> list[int]:
    """A mask's bits cut into ``count`` runs: with fewer than ``count`` differing bits one run is equal."""
    bits = [x for x in range(64) if mask >> x & 1]
    return [sum(1 << x for x in bits[len(bits) * k // count : len(bits) * (k + 1) // count]) for k in range(count)]


def components(edges: DataFrame) -> DataFrame:
    """Rows (v, root) for every vertex of edges (a, b): root is the smallest vertex it reaches.

    Every vertex hooks to its smallest neighbour, trees are flattened, and only links between different trees go on, as one
    link between their tops: in two rounds at least half of the vertices go, so all rounds read little more than the first.
    """
    edges = settled(edges)
    ends = edges.select(F.col("a").alias("v"), F.col("b").alias("u")).union(edges.select("b", "a"))
    up = flattened(ends.filter("v != u").groupBy("v").agg(F.least(F.min("u"), F.col("v")).alias("root")))
    rest = settled(contracted(edges, up))
    return up if rest.isEmpty() else followed(up, components(rest))


def settled(df: DataFrame) -> DataFrame:
    """A checkpoint without the size that Spark foresees: a join's is the product of its sides', whose digits would double
    with every join of every round until planning takes longer than the joins."""
    done, spark = checkpointed(df)._jdf, df.sparkSession
    return DataFrame(spark._jsparkSession.createDataFrame(done.toJavaRDD(), done.schema()), spark)


def flattened(up: DataFrame) -> DataFrame:
    """Rows (v, root) of trees in which every root has a row too, with the tops of the trees as roots."""
    up = settled(up)
    while True:
        over = up.filter("v != root").select(F.col("v").alias("j"), F.col("root").alias("to"))
        new = settled(up.join(over, F.col("root") == F.col("j"), "left").select("v", F.coalesce("to", "root").alias("root"), F.col("to").isNotNull().alias("moved")))
        up = new.select("v", "root")
        if new.filter("moved").isEmpty():
            return up


def contracted(edges: DataFrame, roots: DataFrame) -> DataFrame:
    """The different links (a > b) that edges (a, b) make between roots; a vertex that ``roots`` lacks is its own."""
    a, b = (roots.select(F.col("v").alias(f"v_{x}"), F.col("root").alias(f"root_{x}")) for x in "ab")
    some = edges.join(a, F.col("a") == F.col("v_a"), "left").join(b, F.col("b") == F.col("v_b"), "left")
    some = some.select(F.coalesce("root_a", "a").alias("a"), F.coalesce("root_b", "b").alias("b")).filter("a != b")
    return some.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def followed(roots: DataFrame, more: DataFrame) -> DataFrame:
    """roots (v, root) whose roots have the roots that ``more`` (v, root) gives them; vertices that only ``more`` has are added."""
    over = more.select(F.col("v").alias("j"), F.col("root").alias("to"))
    moved = roots.join(over, F.col("root") == F.col("j"), "left").select("v", F.coalesce("to", "root").alias("root"))
    return settled(moved.union(more.join(roots.select("v"), "v", "left_anti")))


def labelled(docs: DataFrame, distinct: DataFrame, roots: DataFrame) -> DataFrame:
    """docs (doc_id, fp) with component_id; distinct: fp and its least id; roots: (v, root) of linked fingerprints."""
    named = distinct.join(roots, distinct.fp == roots.v, "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    least = named.groupBy("root").agg(F.min("least").alias("component_id"))
    by_fp = named.select("fp", "root").join(least, "root").select("fp", "component_id")
    return docs.join(by_fp, "fp").select("doc_id", "fp", "component_id")


def near_duplicates(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = 2, shingle: int = 3) -> DataFrame:
    """One row per input row: doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable)."""
    docs = checkpointed(fingerprints(df, id_col, text_col, shingle))
    distinct = docs.groupBy("fp").agg(F.min("doc_id").alias("least"))
    out = labelled(docs, distinct, components(links(distinct.select("fp"), radius)))
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
