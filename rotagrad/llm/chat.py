r"""Chat formatting with offset-aligned loss masks.

A whole conversation is rendered, encoded once with offsets, and the sorted spans of the
turns to learn from are intersected with the token spans by binary search.  Conversations
are streamed: rows are dealt out by conversation and sorted, and one task holds no more
than ``PART`` characters of a conversation at a time, so a conversation of any length
passes.  A part ends after a turn; the template's line end is a pre-token of its own
there, so tokens are the same as without the cut.

Template: ``### role: text</turn>`` and a line feed.  Reversible escapes: a backslash goes
before each backslash, before each ``###`` and before each ``</turn>`` of a text, and in
roles also before a colon.

Defined results: null text and null role are empty; null turns come first and equal turns
stand by role, then text; rows that repeat are turns of their own; a null conversation id
is a conversation; an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import os
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

PART = 1 << 17
CLOSE = "</turn>\n"
_TEXT = re.compile(r"\\|#(?=##)|<(?=/turn>)")
_ROLE = re.compile(r"\\|:|#(?=##)|<(?=/turn>)")
_TURN = re.compile(r"### ((?:[^\\:]|\\.)*+): ((?:[^\\<]+|\\.|<(?!/turn>))*+)</turn>\n", re.S)
_ESCAPED = re.compile(r"\\(.)", re.S)


def escape(text: str, pattern: re.Pattern = _TEXT) -> str:
    return pattern.sub(lambda m: "\\" + m[0], text)


def unescape(text: str) -> str:
    return _ESCAPED.sub(r"\1", text) if "\\" in text else text


def render(turns: list[tuple[str, str]]) -> str:
    return "".join(f"### {escape(role, _ROLE)}: {escape(text)}{CLOSE}" for role, text in turns)


def parse(formatted: str) -> list[tuple[str, str, int, int]]:
    """(role, text, start and end of the escaped text) of each turn."""
    out, at = [], 0
    for m in _TURN.finditer(formatted):
        if m.start() != at:
            break
        out.append((unescape(m[1]), unescape(m[2]), m.start(2), m.end(2)))
        at = m.end()
    if at != len(formatted):
        raise ValueError("not a rendered conversation")
    return out


def loss_mask(starts: np.ndarray, ends: np.ndarray, spans: list[tuple[int, int]]) -> np.ndarray:
    """Which tokens overlap one of the sorted spans."""
    mask = np.zeros(len(starts), bool)
    filled = [s for s in spans if s[0] < s[1]]
    if filled:
        a, b = np.array(filled).T
        for i, j in zip(np.searchsorted(ends, a, "right"), np.searchsorted(starts, b, "left")):
            mask[i:j] = True
    return mask


def encoder(data: str):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"  # Spark's tasks are the parallelism
    from tokenizers import Tokenizer
    from tokenizers.processors import ByteLevel

    t = Tokenizer.from_str(data)
    t.encode_special_tokens = True
    t.post_processor = ByteLevel(trim_offsets=False)
    return t


def format_conversations(df: DataFrame, path: str, learn: tuple[str, ...] = ("assistant",), id_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """Rows (conv_id, part, formatted, ids, starts, ends, mask), the parts of a conversation in order.

    ids, starts, ends: little-endian uint32 per token, offsets in code points of the part;
    mask: one byte per token.  The tokenizer file (under 2 MB) is read on the driver and broadcast.
    """
    with open(path, encoding="utf-8") as f:
        shared = df.sparkSession.sparkContext.broadcast(f.read())
    empty = F.lit("")
    rows = df.select(F.col(id_col).alias("conv_id"), F.col(turn_col).alias("turn"), F.coalesce(F.col(role_col).cast("string"), empty).alias("role"), F.coalesce(F.col(text_col).cast("string"), empty).alias("text"))
    kind = rows.schema["conv_id"].dataType.simpleString()
    rows = rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text").select("conv_id", "role", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = encoder(shared.value)

        def write(parts: list[tuple[object, int, list[tuple[str, str]]]]) -> pa.RecordBatch:
            texts = [render(p[2]) for p in parts]
            out = {"ids": [], "starts": [], "ends": [], "mask": []}
            for text, e in zip(texts, own.encode_batch(texts, add_special_tokens=False)):
                offsets = np.array(e.offsets, "<u4").reshape(-1, 2)
                spans = [(a, b) for role, _, a, b in parse(text) if role in learn]
                out["ids"].append(np.array(e.ids, "<u4").tobytes())
                out["starts"].append(np.ascontiguousarray(offsets[:, 0]).tobytes())
                out["ends"].append(np.ascontiguousarray(offsets[:, 1]).tobytes())
                out["mask"].append(loss_mask(offsets[:, 0], offsets[:, 1], spans).tobytes())
            columns = [pa.array([p[0] for p in parts], ids_type), pa.array([p[1] for p in parts], pa.int32()), pa.array(texts, pa.string())]
            return pa.RecordBatch.from_arrays([*columns, *(pa.array(v, pa.binary()) for v in out.values())], ["conv_id", "part", "formatted", *out])

        ids_type, done, size = None, [], 0
        now, number, turns, held = None, 0, [], 0
        for batch in batches:
            ids_type = batch.schema.field(0).type
            for conv, role, text in zip(*(batch.column(c).to_pylist() for c in range(3))):
                if turns and (conv != now or held > PART):
                    done.append((now, number, turns))
                    size += held
                    number, turns, held = number + 1, [], 0
                    if size > PART:
                        yield write(done)
                        done, size = [], 0
                if conv != now:
                    now, number = conv, 0
                turns.append((role, text))
                held += len(text) + len(role)
        if turns:
            done.append((now, number, turns))
        if done:
            yield write(done)

    return rows.mapInArrow(run, f"conv_id {kind}, part int, formatted string, ids binary, starts binary, ends binary, mask binary")


def learned_text(formatted: str, starts: np.ndarray, ends: np.ndarray, mask: np.ndarray, spans: list[tuple[int, int]]) -> list[str]:
    """The unescaped text under the mask inside each span."""
    out = []
    for a, b in spans:
        i, j = np.searchsorted(ends, a, "right"), np.searchsorted(starts, b, "left")
        inside = mask[i:j]
        pieces, at = [], a
        for s, e in zip(np.maximum(starts[i:j][inside], a).tolist(), np.minimum(ends[i:j][inside], b).tolist()):
            s = max(s, at)  # tokens of one character share its offsets
            if e > s:
                pieces.append(formatted[s:e])
                at = e
        out.append(unescape("".join(pieces)))
    return out


def read_back(formatted: DataFrame, learn: tuple[str, ...] = ("assistant",)) -> DataFrame:
    """Digests of what ``format_conversations`` wrote, from its output alone and in its order:
    conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars."""
    kind = formatted.schema["conv_id"].dataType.simpleString()
    names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, state, done, ids_type = None, None, [], pa.int64()

        def flush(rows: list) -> pa.RecordBatch:
            cols = list(zip(*rows))
            types = [ids_type, pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types)], names)

        def close() -> None:
            if state:
                done.append((now, state[0], state[1].hexdigest(), state[2], state[3].hexdigest(), state[4]))

        for batch in batches:
            ids_type = batch.schema.field(0).type
            for conv, part, text, starts, ends, mask in zip(*(batch.column(batch.schema.get_field_index(c)).to_pylist() for c in ("conv_id", "part", "formatted", "starts", "ends", "mask"))):
                if part == 0:
                    close()
                    now, state = conv, [0, hashlib.sha256(), 0, hashlib.sha256(), 0]
                starts, ends, mask = np.frombuffer(starts, "<u4"), np.frombuffer(ends, "<u4"), np.frombuffer(mask, bool)
                turns = parse(text)
                for role, own, _, _ in turns:
                    state[1].update(f"{role}\n{own}\n".encode())
                for own in learned_text(text, starts, ends, mask, [(a, b) for role, _, a, b in turns if role in learn]):
                    state[2] += len(own)
                    state[3].update(own.encode())
                state[0] += len(turns)
                state[4] += len(text)
            if len(done) >= 5000:
                yield flush(done)
                done.clear()
        close()
        if done:
            yield flush(done)

    return formatted.mapInArrow(run, f"conv_id {kind}, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")
