"""Byte-level BPE encoding and decoding with vectorised pre-tokenisation.

Texts become arrays of code-point classes.  A small deterministic automaton reads them
and says before which characters a pre-token starts.  Its transition functions form a
finite monoid, so runs of text are scanned by composing functions: each block of the
array is folded to one function (all blocks at once, a table lookup per character), the
block functions are scanned associatively by doubling, and a second lookup per character
replays each block from its now known entry state.  No regular expression is run.
The slices feed a bounded cache of merged pieces, and their offsets are kept.

Defined results: null text is empty and has no tokens; any length of text is encoded
whole; repeated rows are encoded each; an empty table gives an empty table; only the
named id and text columns are read.
"""

from __future__ import annotations

import base64
import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rotagrad.llm.common import freed, in_slices, one_per_worker

#: Code-point classes.  MID: white space before white space or the end; LAST_SP, LAST_WS:
#: a space, or other white space, before anything else; SHORT, LONG: an apostrophe that
#: may open a contraction of one or two letters; END: between two texts.
LETTER, NUMBER, OTHER, MID, LAST_SP, LAST_WS, SHORT, LONG, END = range(9)
#: States: what the last character left open.
FRESH, IN_L, IN_N, IN_O, IN_W, SPACE, ONE_MORE, TWO_MORE = range(8)
#: Fixed values of the public pattern: letters after the apostrophe.
CONTRACTED = ("s", "t", "m", "d", "re", "ve", "ll")


def automaton() -> tuple[np.ndarray, np.ndarray]:
    """(next state, cut before) by class and state."""
    step, cut = np.zeros((9, 8), np.uint8), np.ones((9, 8), bool)
    for c in range(9):
        for s in range(8):
            if c == END:
                continue
            if s in (ONE_MORE, TWO_MORE) and c == LETTER:
                step[c, s], cut[c, s] = (FRESH if s == ONE_MORE else ONE_MORE), False
                continue
            # After an apostrophe class only letters come; the rest is as in FRESH, which keeps the monoid small.
            if c in (LETTER, NUMBER, OTHER):
                run = {LETTER: IN_L, NUMBER: IN_N, OTHER: IN_O}[c]
                step[c, s], cut[c, s] = run, s not in (run, SPACE)
            elif c in (SHORT, LONG):
                joined = s in (IN_O, SPACE)
                step[c, s], cut[c, s] = (IN_O if joined else ONE_MORE if c == SHORT else TWO_MORE), not joined
            elif c == MID:
                step[c, s], cut[c, s] = IN_W, s != IN_W
            else:
                step[c, s] = SPACE if c == LAST_SP else FRESH
    return step, cut


def monoid(step: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The functions that classes generate: function x class, function x function, values by state."""
    funcs = [tuple(range(8))]
    index = {funcs[0]: 0}
    right = []
    for f in funcs:  # grows while it is read
        row = []
        for c in range(9):
            g = tuple(int(step[c, s]) for s in f)
            if g not in index:
                index[g] = len(funcs)
                funcs.append(g)
            row.append(index[g])
        right.append(row)
    compose = [[index[tuple(g[s] for s in f)] for g in funcs] for f in funcs]
    return np.array(right, np.uint16), np.array(compose, np.uint16), np.array(funcs, np.uint8)


def codepoint_classes() -> np.ndarray:
    """LETTER, NUMBER, MID (white space) or OTHER by code point, as the tiktoken library sees them."""
    import tiktoken

    every = "".join(map(chr, [*range(0xD800), *range(0xE000, 0x110000)]))
    table = np.full(0x110000, OTHER, np.uint8)
    for name, c in ((r"\p{L}", LETTER), (r"\p{N}", NUMBER), (r"\s", MID)):
        own = tiktoken.Encoding(name, pat_str=name, mergeable_ranks={bytes([i]): i for i in range(256)}, special_tokens={})
        found = bytes(own.encode_ordinary(every)).decode()
        table[np.frombuffer(found.encode("utf-32-le"), "<u4")] = c
    return table


class PreTokeniser:
    BLOCK = 64

    def __init__(self, table: np.ndarray):
        self.table = table
        step, self.cut = automaton()
        self.step = np.ascontiguousarray(step)
        self.right, self.compose, self.funcs = monoid(step)

    def classes(self, text: str, ends: np.ndarray) -> np.ndarray:
        """ends: positions of the characters that separate texts, the last one at the end."""
        cps = np.frombuffer(text.encode("utf-32-le"), "<u4")
        c = self.table[cps]
        space = c == MID
        c[ends] = END
        space[ends] = False
        open_next = np.ones(len(c), bool)  # followed by something that isn't white space
        open_next[:-1] = ~space[1:]
        open_next[ends - 1] = False  # at the end of its text (harmless at -1: the last separator)
        last = np.flatnonzero(space & open_next)
        c[last] = np.where(cps[last] == 32, LAST_SP, LAST_WS)
        quote = np.flatnonzero(cps == 39)
        quote = quote[c[quote] == OTHER]
        if len(quote):
            n = len(cps) - 1
            a, b = cps[np.minimum(quote + 1, n)], cps[np.minimum(quote + 2, n)]
            own = c[np.minimum(quote + 1, n)] == LETTER
            for word in CONTRACTED:
                fits = own & (a == ord(word[0]))
                if len(word) == 2:
                    fits &= b == ord(word[1])
                c[quote[fits]] = SHORT if len(word) == 1 else LONG
        return c

    def starts(self, c: np.ndarray) -> np.ndarray:
        """Positions before which a pre-token (or a separator) starts."""
        n, k = len(c), self.BLOCK
        rows = -(-n // k)
        grid = np.full(rows * k, END, np.uint8)
        grid[:n] = c
        grid = np.ascontiguousarray(grid.reshape(rows, k).T)
        right, step, cut = self.right.ravel(), self.step.ravel(), self.cut.ravel()
        f = np.zeros(rows, np.intp)
        for j in range(k):
            f = right[f * 9 + grid[j]].astype(np.intp)
        whole, m, d = f.astype(np.uint16), len(self.funcs), 1
        while d < rows:  # inclusive scan of function composition by doubling
            nxt = whole.copy()
            nxt[d:] = self.compose.ravel()[whole[:-d].astype(np.intp) * m + whole[d:]]
            whole, d = nxt, 2 * d
        state = np.zeros(rows, np.intp)
        state[1:] = self.funcs[whole[:-1], FRESH]
        cuts = np.empty((k, rows), bool)
        for j in range(k):
            at = grid[j].astype(np.intp) * 8 + state
            cuts[j] = cut[at]
            state = step[at].astype(np.intp)
        return np.flatnonzero(cuts.T.ravel()[:n])


class Merger(dict):
    """Piece (str) -> its ids as little-endian uint32 bytes; holds a bounded number of pieces."""

    LIMIT = 300_000

    def __init__(self, ranks: dict[bytes, int]):
        super().__init__()
        self.ranks = ranks

    def __missing__(self, piece: str) -> bytes:
        ids = np.array(self.merge(piece.encode()), "<u4").tobytes()
        if len(piece) <= 64:
            if len(self) >= self.LIMIT:
                self.clear()
            self[piece] = ids
        return ids

    def merge(self, data: bytes) -> list[int]:
        ranks = self.ranks
        if (whole := ranks.get(data)) is not None:
            return [whole]
        if len(data) > 40:
            return self.merge_long(data)
        parts = [data[i : i + 1] for i in range(len(data))]
        pairs = [ranks.get(a + b, 1 << 40) for a, b in zip(parts, parts[1:])]
        while pairs:
            best = min(pairs)
            if best == 1 << 40:
                break
            i = pairs.index(best)
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
            del pairs[i]
            if i < len(pairs):
                pairs[i] = ranks.get(parts[i] + parts[i + 1], 1 << 40)
            if i:
                pairs[i - 1] = ranks.get(parts[i - 1] + parts[i], 1 << 40)
        return [ranks[p] for p in parts]

    def merge_long(self, data: bytes) -> list[int]:
        """The same merges with a heap over a linked list, for pieces of any length."""
        ranks, n = self.ranks, len(data)
        end, prev = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(r, i, i + 2) for i in range(n - 1) if (r := ranks.get(data[i : i + 2])) is not None]
        heapq.heapify(heap)
        alive = [True] * n

        def offer(i: int) -> None:
            if end[i] < n:
                stop = end[end[i]]
                if stop - i <= 256 and (r := ranks.get(data[i:stop])) is not None:
                    heapq.heappush(heap, (r, i, stop))

        while heap:
            _, i, stop = heapq.heappop(heap)
            if not alive[i] or end[i] >= n or end[end[i]] != stop:
                continue
            j = end[i]
            alive[j], end[i] = False, stop
            if stop < n:
                prev[stop] = i
            offer(i)
            if prev[i] >= 0:
                offer(prev[i])
        out, i = [], 0
        while i < n:
            out.append(ranks[data[i : end[i]]])
            i = end[i]
        return out


class Codec:
    def __init__(self, ranks: dict[bytes, int], table: np.ndarray):
        self.pre, self.pieces = PreTokeniser(table), Merger(ranks)
        self.vocabulary = [b""] * (max(ranks.values()) + 1)
        for token, r in ranks.items():
            self.vocabulary[r] = token

    def encode(self, texts: list[str]) -> Iterator[tuple[bytes, list[str]]]:
        """(ids as little-endian uint32, pre-tokens) of each text."""
        text = "\0".join(texts) + "\0"
        ends = np.cumsum([len(t) + 1 for t in texts]) - 1
        starts = self.pre.starts(self.pre.classes(text, ends))
        cut = np.searchsorted(starts, ends)
        places, cut = starts.tolist(), cut.tolist()
        pieces = [text[a:b] for a, b in zip(places, places[1:])]
        k, get = 0, self.pieces.__getitem__
        for e in cut:
            own = pieces[k:e]
            yield b"".join(map(get, own)), own
            k = e + 1

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.vocabulary.__getitem__, np.frombuffer(ids, "<u4").tolist()))

    def offsets(self, ids: bytes) -> bytes:
        """Where each token starts in the text's UTF-8 bytes, as little-endian int64."""
        size = np.fromiter((len(self.vocabulary[i]) for i in np.frombuffer(ids, "<u4").tolist()), "<i8")
        return (np.cumsum(size) - size).astype("<i8").tobytes()


def read_ranks(data: bytes) -> dict[bytes, int]:
    return {base64.b64decode(a): int(b) for a, b in map(bytes.split, data.splitlines()) if a}


def codec(shared) -> Codec:
    """The worker's codec for a shared vocabulary."""

    def make() -> Codec:
        data, table = shared.value
        return Codec(read_ranks(data), np.frombuffer(table, np.uint8))

    return one_per_worker(shared.id, make)


class _Shared:
    """A broadcast with an id that workers can tell apart."""

    def __init__(self, spark, path: str):
        import hashlib

        with open(path, "rb") as f:
            data = f.read()
        self.id = hashlib.md5(data).hexdigest()
        self._value = spark.sparkContext.broadcast((data, codepoint_classes().tobytes()))

    @property
    def value(self):
        return self._value.value


#: Characters that are encoded together; a longer text stands alone.
CHUNK = 1 << 21


def chunks(texts: list[str]) -> Iterator[list[str]]:
    now, size = [], 0
    for t in texts:
        if now and size + len(t) > CHUNK:
            yield now
            now, size = [], 0
        now.append(t)
        size += len(t) + 1
    if now:
        yield now


def encode(df: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", decode_back: bool = False, offsets: bool = False) -> DataFrame:
    """One row per input row: id, n_tokens, ids (little-endian uint32); decoded bytes and byte offsets on request.

    The vocabulary file (under 1 MB) is read on the driver from ``path`` and broadcast.
    """
    shared = _Shared(df.sparkSession, path)
    rows = df.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    kind = rows.schema["doc_id"].dataType.simpleString()
    schema = f"doc_id {kind}, n_tokens long, ids binary" + ", decoded binary" * decode_back + ", offsets binary" * offsets

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(shared)
        for batch in (part for whole in batches for part in in_slices(whole)):
            done = 0
            for part in chunks(batch.column(1).to_pylist()):
                ids = [x for x, _ in own.encode(part)]
                columns = [batch.column(0).slice(done, len(part)), pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array(ids, pa.binary())]
                names = ["doc_id", "n_tokens", "ids"]
                if decode_back:
                    columns.append(pa.array(map(own.decode, ids), pa.binary()))
                    names.append("decoded")
                if offsets:
                    columns.append(pa.array(map(own.offsets, ids), pa.binary()))
                    names.append("offsets")
                yield pa.RecordBatch.from_arrays(columns, names)
                done += len(part)

    return rows.mapInArrow(freed(run, model=True), schema)


def decode(df: DataFrame, path: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """One row per input row: id, decoded (bytes); null ids decode to nothing."""
    shared = _Shared(df.sparkSession, path)
    rows = df.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(ids_col), F.lit(b"")).alias("ids"))
    kind = rows.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(shared)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(map(own.decode, batch.column(1).to_pylist()), pa.binary())], ["doc_id", "decoded"])

    return rows.mapInArrow(run, f"doc_id {kind}, decoded binary")
