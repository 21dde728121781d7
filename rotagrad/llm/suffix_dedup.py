"""Removal of repeated byte strings by a suffix array of many documents, built column-wise.

A byte goes if it lies in a string of ``length`` bytes that also starts anywhere else in
the corpus.  All windows of that length are dealt out by content first: a window belongs
to its minimiser, the k-mer of least hash in it (leftmost at ties), and neighbouring
windows with the same minimiser form one segment.  Equal windows have equal minimisers, so
only segments of one minimiser have to be compared, wherever they come from.
Equal segments collapse map-side to one with a count, so copies cost nothing further.

The different segments of a minimiser form a collection whose Burrows-Wheeler transform
and common prefixes are built column-wise: every round inserts one symbol of each document,
from the last to the first, and updates both arrays, which are read from and written to
sequential external files.  A symbol is a string of bytes (the longest divisor of ``length`` up to
``SYMBOL``), and each segment stands in the collection once per phase, so that every byte
position is the start of a suffix and a window is a whole number of symbols.  A window is repeated when the common
prefix with its upper or lower neighbour has that many symbols.

Minimisers with more than ``HOT`` different segments would make one collection too large
for a task; their windows are counted one by one with map-side combination instead, which
finds the same windows.

Defined results: null and empty texts have nothing to remove; texts shorter than ``length``
stay; repeated rows are copies of each other; any length of text is read whole (in
overlapping pieces); an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import os
import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from rotagrad.llm.common import checkpointed, text_or_empty

KMER = 32
SYMBOL = 40
PIECE = 1 << 20
PLACE = np.uint64((1 << 21) - 1)
BATCH = 60_000
HOT = 4096
BASE = 0x9E3779B97F4A7C15 | 1


def mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(29))


def rolling(data: np.ndarray, width: int) -> np.ndarray:
    """A 64-bit hash of every ``width`` bytes, by doubling and one overlap."""
    h, factor, k = data.astype(np.uint64) + np.uint64(1), BASE, 1
    while 2 * k <= width:
        h = h[: len(h) - k] * np.uint64(factor) + h[k:]
        factor = factor * factor & 0xFFFFFFFFFFFFFFFF
        k *= 2
    if k < width:
        h = mixed(h[: len(h) - (width - k)]) * np.uint64(BASE) + h[width - k :]
    return mixed(h)


def symbol_width(length: int) -> int:
    return max(w for w in range(1, SYMBOL + 1) if length % w == 0)


def segments(data: bytes, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first start, number of starts, minimiser hash) of each run of windows."""
    if len(data) < length:
        none = np.zeros(0, np.int64)
        return none, none, none
    h = rolling(np.frombuffer(data, np.uint8), KMER)
    key = (h & ~PLACE) | np.arange(len(h), dtype=np.uint64)
    span, k = length - KMER + 1, 1
    least = key
    while 2 * k <= span:
        least = np.minimum(least[: len(least) - k], least[k:])
        k *= 2
    windows = len(data) - length + 1
    place = (np.minimum(least[:windows], least[span - k : span - k + windows]) & PLACE).astype(np.int64)
    first = np.concatenate([[0], np.flatnonzero(np.diff(place)) + 1])
    return first, np.diff(np.concatenate([first, [windows]])), h[place[first]].view(np.int64)


class External:
    """An array in a file, read and written from end to end; two files take turns."""

    def __init__(self, folder: str, name: str, kind):
        self.files = [open(os.path.join(folder, f"{name}{i}"), "w+b", buffering=0) for i in (0, 1)]
        self.kind, self.turn, self.size = np.dtype(kind), 0, 0

    def read(self) -> np.ndarray:
        out = np.empty(self.size, self.kind)
        self.files[self.turn].seek(0)
        self.files[self.turn].readinto(out)
        return out

    def write(self, data: np.ndarray) -> None:
        self.turn ^= 1
        self.size = len(data)
        self.files[self.turn].seek(0)
        self.files[self.turn].write(np.ascontiguousarray(data, self.kind))

    def close(self) -> None:
        for f in self.files:
            f.close()


def range_minima(values: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """min(values[a+1 .. b]) for each pair a < b, over a table of doublings."""
    size = b - a
    level = np.frexp(size.astype(np.float64))[1] - 1
    out = np.empty(len(a), values.dtype)
    now = values
    for deep in range(int(level.max(initial=-1)) + 1):
        own = np.flatnonzero(level == deep)
        if len(own):
            out[own] = np.minimum(now[a[own] + 1], now[b[own] + 1 - (1 << deep)])
        if len(now) > 1 << deep:
            now = np.minimum(now[: len(now) - (1 << deep)], now[1 << deep :])
    return out


def repeated(parts: list[bytes], length: int, folder: str) -> list[np.ndarray]:
    """For each segment a mask of its starts whose window occurs at another start of the collection."""
    width = symbol_width(length)
    depth = length // width
    sizes = np.array([len(p) for p in parts])
    base = np.cumsum(sizes) - sizes
    data = np.frombuffer(b"".join(parts) + bytes(width), np.uint8)
    # Symbols as dense ranks from 1; 0 ends a document.
    _, symbol = np.unique(rolling(data, width), return_inverse=True)
    symbol = symbol.astype(np.int64) + 1
    narrow = np.uint16 if symbol.max() < 1 << 16 else np.uint32
    symbol = symbol.astype(narrow)

    # Documents: a phase of a segment.  Its symbols start at first, first + width, ...
    phase = np.arange(width)
    first = (base[:, None] + phase).ravel()
    count = np.maximum((sizes[:, None] - phase) // width, 0).ravel()
    docs = len(first)

    bwt, prefix, start = External(folder, "bwt", narrow), External(folder, "lcp", np.uint16), External(folder, "start", np.int32)
    place = first + count * width  # where each document's current suffix starts
    row = np.arange(docs)  # and its row
    open_ = count > 0
    bwt.write(np.where(open_, symbol[np.maximum(place - width, 0)], 0))
    prefix.write(np.zeros(docs, np.uint16))
    start.write(place)
    for _ in range(int(count.max(initial=0))):
        b, lcp, sa = bwt.read(), prefix.read(), start.read()
        live = np.flatnonzero(open_)
        fresh = np.zeros(len(b), bool)
        fresh[row[live]] = True
        order = np.argsort(b, kind="stable")  # rows by preceding symbol: the order of suffixes one symbol longer
        order = order[np.searchsorted(b[order], 1) :]
        new = fresh[order]
        at = np.flatnonzero(new)
        # Insert the new suffixes between the old ones.
        total = docs + len(order)
        taken = np.zeros(total, bool)
        taken[docs + at] = True
        begins = sa[order[at]].astype(np.int64) - width
        owner = np.empty(len(b), np.int64)
        owner[row[live]] = live
        who = owner[order[at]]
        more = begins > first[who]
        before = np.where(more, symbol[np.maximum(begins - width, 0)], 0)
        nb, nl, ns = np.empty(total, b.dtype), np.empty(total, np.uint16), np.empty(total, np.int32)
        nb[taken], nb[~taken] = before, b
        ns[taken], ns[~taken] = begins, sa
        nl[~taken] = lcp
        # Common prefixes of new suffixes and of those just after them.
        touched = np.unique(np.concatenate([at, at + 1]))
        touched = touched[touched < len(order)]
        here, above = order[touched], order[np.maximum(touched - 1, 0)]
        same = (touched > 0) & (b[here] == b[above])
        value = np.zeros(len(touched), np.uint16)
        value[same] = np.minimum(range_minima(lcp, above[same], here[same]), depth - 1) + 1
        nl[docs + touched] = value
        row[who] = docs + at
        # Rows of documents that have ended no longer matter.
        open_[who[~more]] = False
        bwt.write(nb)
        prefix.write(nl)
        start.write(ns)
    lcp, sa = prefix.read(), start.read()
    for file in (bwt, prefix, start):
        file.close()
    deep = lcp >= depth
    deep[:-1] |= deep[1:]
    hit = np.zeros(len(data), bool)
    hit[sa[deep]] = True
    return [hit[a : a + n - length + 1] for a, n in zip(base.tolist(), sizes.tolist())]


def runs(mask: np.ndarray) -> list[tuple[int, int]]:
    """Half-open runs of true."""
    edge = np.flatnonzero(np.diff(np.concatenate([[0], mask.astype(np.int8), [0]])))
    return list(zip(edge[::2].tolist(), edge[1::2].tolist()))


SEGMENT = "doc_id {kind}, x long, start long, n int, anchor long, hi long, lo long"


def _segments(rows: DataFrame, kind: str, length: int) -> DataFrame:
    names = ["doc_id", "x", "start", "n", "anchor", "hi", "lo"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh3_128_digest

        for batch in batches:
            owner, starts, sizes, anchors, digests, held = [], [], [], [], [], 0

            def out() -> pa.RecordBatch:
                who = pa.array(np.repeat(np.array([o[0] for o in owner], np.int64), [o[1] for o in owner]))
                halves = np.frombuffer(b"".join(digests), "<i8").reshape(-1, 2)
                columns = [batch.column(0).take(who), batch.column(1).take(who), pa.array(np.concatenate(starts)), pa.array(np.concatenate(sizes).astype(np.int32)), pa.array(np.concatenate(anchors)), pa.array(halves[:, 0].copy()), pa.array(halves[:, 1].copy())]
                return pa.RecordBatch.from_arrays(columns, names)

            for i, text in enumerate(batch.column(2)):
                data = text.as_buffer().to_pybytes() if text.is_valid else b""
                for offset in range(0, max(1, len(data) - length + 1), PIECE):
                    piece = data[offset : offset + PIECE + length - 1]
                    first, n, anchor = segments(piece, length)
                    if not len(first):
                        continue
                    owner.append((i, len(first)))
                    starts.append(first + offset)
                    sizes.append(n)
                    anchors.append(anchor)
                    digests += [xxh3_128_digest(piece[a:b]) for a, b in zip(first.tolist(), (first + n + length - 1).tolist())]
                    held += len(first)
                    if held > 50_000:
                        yield out()
                        owner, starts, sizes, anchors, digests, held = [], [], [], [], [], 0
            if held:
                yield out()

    return rows.mapInArrow(run, SEGMENT.format(kind=kind))


def _bytes_of(chosen: DataFrame, length: int) -> DataFrame:
    """chosen: rows (text, list of segments); one row per segment with its bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys, parts, held = [], [], 0
            for text, own in zip(batch.column(0), batch.column(1).to_pylist()):
                data = text.as_buffer().to_pybytes()
                for s in own:
                    keys.append((s["anchor"], s["hi"], s["lo"]))
                    parts.append(data[s["start"] : s["start"] + s["n"] + length - 1])
                    held += len(parts[-1])
                if held > 1 << 23:
                    yield pack(keys, parts)
                    keys, parts, held = [], [], 0
            if keys:
                yield pack(keys, parts)

    def pack(keys: list, parts: list) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([*(pa.array([k[i] for k in keys], pa.int64()) for i in range(3)), pa.array(parts, pa.binary())], ["anchor", "hi", "lo", "part"])

    return chosen.mapInArrow(run, "anchor long, hi long, lo long, part binary")


def _collections(parts: DataFrame, length: int) -> DataFrame:
    """(anchor, hi, lo, a, b): repeated runs of starts in segments, by the column-wise transform."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def flush(rows: list[tuple]) -> pa.RecordBatch:
            with tempfile.TemporaryDirectory() as folder:
                masks = repeated([r[3] for r in rows], length, folder)
            out = [(*r[:3], a, b) for r, m in zip(rows, masks) for a, b in runs(m)]
            return pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], pa.int64()) for i in range(5)], ["anchor", "hi", "lo", "a", "b"])

        done, now = [], []
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns)):
                if now and row[0] != now[-1][0]:
                    if len(now) > 1:
                        done += now
                    now = []
                    if sum(len(r[3]) for r in done) > BATCH:
                        yield flush(done)
                        done = []
                now.append(row)
        done += now if len(now) > 1 else []
        if done:
            yield flush(done)

    dealt = parts.repartition("anchor").sortWithinPartitions("anchor", "hi", "lo")
    return dealt.mapInArrow(run, "anchor long, hi long, lo long, a long, b long")


def _hot_windows(parts: DataFrame, length: int) -> DataFrame:
    """The same runs for minimisers with very many segments: windows are counted one by one."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh3_128_digest

        for batch in batches:
            for anchor, hi, lo, part in zip(*(c.to_pylist() for c in batch.columns)):
                n = len(part) - length + 1
                halves = np.frombuffer(b"".join(xxh3_128_digest(part[i : i + length]) for i in range(n)), "<i8").reshape(-1, 2)
                same = [pa.array(np.full(n, v, np.int64)) for v in (anchor, hi, lo)]
                yield pa.RecordBatch.from_arrays([*same, pa.array(np.arange(n)), pa.array(halves[:, 0].copy()), pa.array(halves[:, 1].copy())], ["anchor", "hi", "lo", "a", "w1", "w2"])

    windows = parts.mapInArrow(run, "anchor long, hi long, lo long, a long, w1 long, w2 long")
    often = windows.groupBy("w1", "w2").agg(F.count(F.lit(1)).alias("c")).filter("c > 1").select("w1", "w2")
    return windows.join(often, ["w1", "w2"], "left_semi").select("anchor", "hi", "lo", "a", (F.col("a") + 1).alias("b"))


def repeated_starts(docs: DataFrame, length: int) -> DataFrame:
    """(doc_id, x, spans): half-open runs of repeated starts; docs has doc_id, x (a hash of the text), text."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    segs = checkpointed(_segments(docs.filter(F.octet_length("text") >= length), kind, length))
    key = ["anchor", "hi", "lo"]
    same = segs.groupBy(*key).agg(F.count(F.lit(1)).alias("copies"), F.min(F.struct("doc_id", "x", "start", "n")).alias("at"))
    kinds = F.count(F.lit(1)).over(W.Window.partitionBy("anchor"))
    known = checkpointed(same.withColumn("kinds", kinds).filter("copies > 1 or kinds > 1"))

    mixed_ = known.filter("kinds > 1").select(F.col("at.doc_id").alias("of_id"), F.col("at.x").alias("of_x"), (F.col("kinds") > HOT).alias("hot"), F.struct(F.col("at.start").alias("start"), F.col("at.n").alias("n"), *key).alias("s"))
    per_doc = mixed_.groupBy("of_id", "of_x", "hot").agg(F.collect_list("s").alias("own"))
    joined = docs.join(per_doc, (F.col("x") == F.col("of_x")) & F.col("doc_id").eqNullSafe(F.col("of_id")))
    parts = _bytes_of(joined.filter("not hot").select("text", "own"), length)
    found = _collections(parts, length)
    if not known.filter(F.col("kinds") > HOT).isEmpty():
        found = found.union(_hot_windows(_bytes_of(joined.filter("hot").select("text", "own"), length), length))
    whole = known.filter("copies > 1").select(*key, F.lit(0).cast("long").alias("a"), F.col("at.n").cast("long").alias("b"))
    single = known.filter("copies = 1").select(*key)
    marked = whole.union(found.join(single, key, "left_semi"))
    spans = segs.select("doc_id", "x", "start", *key).join(marked, key)
    run = F.struct((F.col("start") + F.col("a")).alias("a"), (F.col("start") + F.col("b")).alias("b"))
    return spans.groupBy("doc_id", "x").agg(F.collect_list(run).alias("spans"))


def remove_repeats(df: DataFrame, length: int = 400, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: doc_id, n_bytes, n_removed, n_spans, removed (half-open byte runs), kept (bytes)."""
    if not KMER < length < 1 << 13:
        raise ValueError(f"length must be above {KMER} and below {1 << 13}")
    docs = df.select(F.col(id_col).alias("doc_id"), text_or_empty(F.col(text_col)).alias("text"))
    docs = docs.select("doc_id", F.xxhash64("text").alias("x"), "text")
    starts = repeated_starts(docs, length).select(F.col("doc_id").alias("of_id"), F.col("x").alias("of_x"), "spans")
    both = docs.join(starts, (F.col("x") == F.col("of_x")) & F.col("doc_id").eqNullSafe(F.col("of_id")), "left").select("doc_id", "text", "spans")
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = {"n_bytes": [], "n_removed": [], "n_spans": [], "removed": [], "kept": []}
            for text, spans in zip(batch.column(1), batch.column(2).to_pylist()):
                data, gone, kept, at = text.as_buffer().to_pybytes(), [], [], 0
                for a, b in sorted((s["a"], s["b"] + length - 1) for s in spans or ()):
                    if gone and a <= gone[-1][1]:
                        gone[-1][1] = max(gone[-1][1], b)
                    else:
                        gone.append([a, b])
                for a, b in gone:
                    kept.append(data[at:a])
                    at = b
                kept.append(data[at:])
                out["n_bytes"].append(len(data))
                out["n_removed"].append(sum(b - a for a, b in gone))
                out["n_spans"].append(len(gone))
                out["removed"].append([{"a": a, "b": b} for a, b in gone])
                out["kept"].append(b"".join(kept))
            types = [pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())])), pa.binary()]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(v, t) for v, t in zip(out.values(), types))], ["doc_id", *out])

    return both.mapInArrow(run, f"doc_id {kind}, n_bytes long, n_removed long, n_spans long, removed array<struct<a:long,b:long>>, kept binary")
