"""Language identification with segmentation-marginalised unigrams.

The pieces come from a fixed public vocabulary; each language has a probability per
piece.  A word's likelihood is the sum over all its segmentations into pieces, by the
forward algorithm over the whole word, whatever its length, and all pieces of the vocabulary; pieces
never cross word boundaries, so a text's log likelihood is the sum of its words', every word of the
whole text counted.  Texts are lower-cased first.  The probabilities are fitted by
expectation-maximisation over the same lattices.  Words up to ``LONG`` characters go through in
batches, with every piece's probability scaled by its length against underflow; longer ones one by
one in logarithms: two ways to the same sums.

Only the fit looks at a bounded sample: at most about ``docs_per_language`` labelled
documents of each language, chosen by a hash of the id (``bound`` below).  All documents
are predicted over their whole texts.  Word scores are cached per worker in a bounded
table; a miss is scored with the other misses of its batch at once.

Defined results: a text that is null, empty or without letters is ``und`` with score 0;
ties go to the language that sorts first; without any labelled document all is ``und``;
repeated rows are predicted each; other columns pass through untouched, but an input column of an
output's name is replaced.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rotagrad.llm.common import freed, in_slices, one_per_worker

WORDS = re.compile(r"[^\W\d_]+")
#: Characters of a word (with its mark) up to which words are scored in batches.
LONG = 32
#: Factor per character that keeps products of probabilities in range.
SCALE = 1e3
MARK = "▁"
UNKNOWN_SHARE = 1e-7


def vocabulary(model: bytes) -> list[str]:
    """All ordinary pieces of a sentencepiece model."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_proto=model)
    pieces = (sp.id_to_piece(i) for i in range(sp.get_piece_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i)))
    return sorted(set(pieces))


#: A string that begins some piece but is none, and one that no piece begins with.
PREFIX, NO_PIECE = -1, -2

def with_prefixes(pieces: list[str]) -> dict[str, int]:
    """Numbers of pieces; PREFIX for strings that only begin one."""
    return {p[:n]: PREFIX for p in pieces for n in range(1, len(p))} | {p: i for i, p in enumerate(pieces)}


def edges(word: str, index: dict[str, int], unknown: int, longest: int) -> Iterator[tuple[int, int, int]]:
    """(start, end, piece) of every piece in a word; a single character without a piece is an unknown one."""
    known, n = index.get, len(word)
    for i in range(n):
        for j in range(i + 1, min(n, i + longest) + 1):
            p = known(word[i:j], NO_PIECE)
            if p >= 0:
                yield i, j, p
            elif j == i + 1:
                yield i, j, unknown
            if p == NO_PIECE:
                break


class Trie:
    """The strings of ``with_prefixes`` as states, to walk from many places at once."""

    def __init__(self, index: dict[str, int]):
        state = {"": 0} | {s: i for i, s in enumerate(index, 1)}
        steps = np.array([state[s[:-1]] << 21 | ord(s[-1]) for s in index], np.int64)
        order = np.argsort(steps)
        #: Parent and code point of each step in order, a bar above all, and where each leads.
        self.steps, self.to = np.append(steps[order], np.iinfo(np.int64).max), np.append(order + 1, -1).astype(np.int32)
        self.piece = np.array([PREFIX, *index.values()], np.int32)
        self.inner = np.zeros(len(self.piece), bool)
        self.inner[steps >> 21] = True

    def step(self, state: np.ndarray, code: np.ndarray) -> np.ndarray:
        """The states after one more character; -1 where no piece begins so."""
        key = state.astype(np.int64) << 21 | code
        at = np.searchsorted(self.steps, key)
        return np.where(self.steps[at] == key, self.to[at], -1)

    def edges(self, words: list[str], unknown: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """What ``edges`` gives for each word, as arrays word, start, end, piece; of one word and end, starts rise."""
        lengths = np.fromiter(map(len, words), np.int64, len(words))
        code = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
        word = np.repeat(np.arange(len(words)), lengths)
        begin = np.cumsum(lengths) - lengths
        last, own = (begin + lengths)[word], np.arange(len(code))
        state, size, out = np.zeros(len(code), np.int32), 0, []
        while len(own):
            state, size = self.step(state, code[own + size]), size + 1
            piece = np.where(state >= 0, self.piece[state], NO_PIECE)
            use = piece >= 0 if size > 1 else np.ones(len(own), bool)
            out.append((own[use], size, np.where(piece[use] >= 0, piece[use], unknown)))
            on = (state >= 0) & self.inner[state] & (own + size < last[own])
            own, state = own[on], state[on]
        at = np.concatenate([np.zeros(0, np.int64), *(x for x, _, _ in out[::-1])])
        size = np.repeat(np.array([n for _, n, _ in out[::-1]], np.int64), [len(x) for x, _, _ in out[::-1]])
        w = word[at]
        start = at - begin[w]
        return w, start, start + size, np.concatenate([np.zeros(0, np.int64), *(x for _, _, x in out[::-1])])


class Lattices:
    """All segmentations of many words of at most ``LONG`` characters: edges from start to end, grouped by end."""

    def __init__(self, words: list[str], index: dict[str, int] | Trie, unknown: int):
        """index: as ``with_prefixes`` makes it, or its trie; unknown: the number for characters without a piece."""
        trie = index if isinstance(index, Trie) else Trie(index)
        self.n, self.lengths = len(words), np.fromiter(map(len, words), np.int64, len(words))
        self.w, self.start, self.end, self.piece = trie.edges(words, unknown)
        self.deep = int(self.lengths.max(initial=0))
        self.scale = (SCALE ** np.arange(self.deep + 1))[self.end - self.start]
        by_end = np.argsort(self.end.astype(np.int16), kind="stable")
        self.at_end = np.split(by_end, np.cumsum(np.bincount(self.end, minlength=self.deep + 1)[1:-1])) if self.deep else []

    @cached_property
    def at_start(self) -> list[np.ndarray]:
        by_start = np.argsort(self.start.astype(np.int16), kind="stable")
        return np.split(by_start, np.cumsum(np.bincount(self.start, minlength=self.deep)[:-1])) if self.deep else []

    def forward(self, p: np.ndarray) -> np.ndarray:
        """Sums over segmentations of each prefix, times SCALE per character: words x positions."""
        alpha = np.zeros((self.n, self.deep + 1))
        alpha[:, 0] = 1
        scaled = p[self.piece] * self.scale
        for j, e in enumerate(self.at_end, 1):
            w = self.w[e]
            alpha[:, j] = np.bincount(w, alpha[w, self.start[e]] * scaled[e], self.n)
        return alpha

    def logs(self, p: np.ndarray) -> np.ndarray:
        """The logarithm of each word's likelihood."""
        return np.log(self.forward(p)[np.arange(self.n), self.lengths]) - self.lengths * np.log(SCALE)

    def expected(self, p: np.ndarray, counts: np.ndarray) -> np.ndarray:
        """Expected uses of each piece over words that occur ``counts`` times."""
        alpha, beta = self.forward(p), np.zeros((self.n, self.deep + 1))
        beta[np.arange(self.n), self.lengths] = 1
        total = alpha[np.arange(self.n), self.lengths]
        scaled = p[self.piece] * self.scale
        for i in range(self.deep - 1, -1, -1):
            e = self.at_start[i]
            w = self.w[e]
            beta[:, i] += np.bincount(w, beta[w, self.end[e]] * scaled[e], self.n)
        use = alpha[self.w, self.start] * scaled * beta[self.w, self.end] * (counts / total)[self.w]
        return np.bincount(self.piece, use, len(p))


class LongLattice:
    """The same for one word of any length, in logarithms."""

    def __init__(self, word: str, index: dict[str, int], unknown: int):
        self.n = len(word)
        own = edges(word, index, unknown, max(map(len, index), default=1))
        self.start, self.end, self.piece = np.array(list(own), np.int64).reshape(-1, 3).T.copy()
        self.by_end = np.argsort(self.end, kind="stable")
        self.to = np.searchsorted(self.end[self.by_end], np.arange(self.n + 2))
        self.of = np.searchsorted(self.start, np.arange(self.n + 1))

    def forward(self, p: np.ndarray) -> np.ndarray:
        """Logarithms of the sums over segmentations of each prefix; p may have a row per language."""
        edge, alpha = np.log(p)[..., self.piece], np.zeros((*p.shape[:-1], self.n + 1))
        for j in range(1, self.n + 1):
            e = self.by_end[self.to[j] : self.to[j + 1]]
            alpha[..., j] = np.logaddexp.reduce(alpha[..., self.start[e]] + edge[..., e], axis=-1)
        return alpha

    def logs(self, p: np.ndarray) -> np.ndarray:
        return self.forward(p)[..., -1]

    def expected(self, p: np.ndarray, count: float) -> np.ndarray:
        edge, alpha, beta = np.log(p)[self.piece], self.forward(p), np.zeros(self.n + 1)
        for i in range(self.n - 1, -1, -1):
            e = slice(self.of[i], self.of[i + 1])
            beta[i] = np.logaddexp.reduce(edge[e] + beta[self.end[e]])
        return np.bincount(self.piece, count * np.exp(alpha[self.start] + edge + beta[self.end] - alpha[-1]), len(p))


class Model:
    """languages, and log-free piece probabilities: languages x (pieces and one for unknown characters)."""

    def __init__(self, languages: list[str], pieces: list[str], probabilities: np.ndarray):
        self.languages, self.pieces, self.probabilities = languages, pieces, probabilities

    @classmethod
    def fit(cls, counts: list[tuple[str, str, int]], pieces: list[str], rounds: int = 4, smooth: float = 0.05) -> Model:
        """counts: (language, word, occurrences)."""
        index = with_prefixes(pieces)
        trie = Trie(index)
        languages = sorted({c[0] for c in counts})
        out = np.zeros((len(languages), len(pieces) + 1))
        for k, lang in enumerate(languages):
            own = sorted((MARK + w, n) for c, w, n in counts if c == lang)
            short = [x for x in own if len(x[0]) <= LONG]
            lattices, n = Lattices([w for w, _ in short], trie, len(pieces)), np.array([c for _, c in short], float)
            far = [(LongLattice(w, index, len(pieces)), c) for w, c in own if len(w) > LONG]
            p = np.full(len(pieces) + 1, 1 / len(pieces))
            p[-1] = UNKNOWN_SHARE
            for _ in range(rounds):
                use = sum((x.expected(p, c) for x, c in far), lattices.expected(p, n)) + smooth
                unknown = max(UNKNOWN_SHARE, use[-1] / use.sum() * 0.1)
                p = use / use[:-1].sum() * (1 - unknown)
                p[-1] = unknown
            out[k] = p
        return cls(languages, pieces, out)


class Scorer:
    LIMIT = 400_000

    def __init__(self, model: Model):
        self.model, self.index = model, with_prefixes(model.pieces)
        self.trie = Trie(self.index)
        self.clear()

    def clear(self) -> None:
        self.rows: dict[str, int] = {}
        self.logs = np.zeros((1024, len(self.model.languages)))

    def learn(self, words: list[str]) -> None:
        """Score words that the cache lacks."""
        marked = [MARK + w for w in words]
        p, unknown = self.model.probabilities, len(self.model.pieces)
        new = np.empty((len(words), len(p)))
        short = [k for k, w in enumerate(marked) if len(w) <= LONG]
        lattices = Lattices([marked[k] for k in short], self.trie, unknown)
        for lang, row in enumerate(p):
            new[short, lang] = lattices.logs(row)
        for k, w in enumerate(marked):
            if len(w) > LONG:
                new[k] = LongLattice(w, self.index, unknown).logs(p)
        first = len(self.rows)
        while len(self.logs) < first + len(words):
            self.logs = np.concatenate([self.logs, np.zeros_like(self.logs)])
        self.logs[first : first + len(words)] = new
        self.rows.update(zip(words, range(first, first + len(words))))

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        names, scores, part, size = [], [], [], 0
        for t in texts:
            part.append(WORDS.findall(t.lower()) if t else [])
            size += len(part[-1])
            if size > 100_000:
                self._predict(part, names, scores)
                part, size = [], 0
        self._predict(part, names, scores)
        return names, scores

    def _predict(self, texts: list[list[str]], names: list[str], scores: list[float]) -> None:
        seen = set().union(*texts) if texts else set()
        if len(self.rows) + len(seen) > self.LIMIT:
            self.clear()
        if self.model.languages and (new := sorted(seen - self.rows.keys())):
            self.learn(new)
        languages, get = self.model.languages, self.rows.__getitem__
        for words in texts:
            if not languages or not words or not any(c.isalpha() for w in words for c in w):
                names.append("und")
                scores.append(0.0)
                continue
            total = self.logs[np.fromiter(map(get, words), np.int64, len(words))].sum(axis=0)
            best = int(total.argmax())
            names.append(languages[best])
            scores.append(float(1 / np.exp(total - total[best]).sum()))


def train(labelled: DataFrame, vocabulary_path: str, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", docs_per_language: int = 400) -> Model:
    """Fit on labelled rows.  bound: about ``docs_per_language`` documents of each language,
    those with the smallest hash of their id; languages are as many as the labels name."""
    with open(vocabulary_path, "rb") as f:
        pieces = vocabulary(f.read())
    rows = labelled.select(F.col(id_col).alias("i"), F.col(text_col).alias("t"), F.col(lang_col).alias("l")).filter("l is not null and t is not null")
    size = {r.l: r.n for r in rows.groupBy("l").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not size:
        return Model([], pieces, np.zeros((0, len(pieces) + 1)))
    share = F.create_map(*[F.lit(x) for k, n in size.items() for x in (k, min(1.0, docs_per_language / n))])
    chance = F.pmod(F.xxhash64("i", F.lit(11)), F.lit(1 << 30)) / float(1 << 30)
    words = rows.filter(chance < share[F.col("l")]).select("l", F.explode(F.split(F.lower("t"), r"[^\p{L}]+")).alias("w")).filter("w != ''")
    return Model.fit([tuple(r) for r in words.groupBy("l", "w").count().collect()], pieces)


def identify(df: DataFrame, model: Model, text_col: str = "text", lang_out: str = "lang_pred", score_out: str = "score") -> DataFrame:
    """All columns of ``df`` and the prediction; input columns named like an output are replaced."""
    import hashlib

    df = df.select(*[F.col(c) for c in df.columns if c == text_col or c not in (lang_out, score_out)])

    shared = df.sparkSession.sparkContext.broadcast(model)
    tag = hashlib.md5(model.probabilities.tobytes() + repr(model.languages).encode()).hexdigest()
    where, names = df.columns.index(text_col), [*df.columns, lang_out, score_out]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = one_per_worker(tag, lambda: Scorer(shared.value))
        for batch in batches:
            for part in in_slices(batch):
                lang, score = scorer.predict(part.column(where).to_pylist())
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(lang, pa.string()), pa.array(score, pa.float64())], names)

    from pyspark.sql import types as T

    schema = T.StructType([*df.schema.fields, T.StructField(lang_out, T.StringType()), T.StructField(score_out, T.DoubleType())])
    return df.mapInArrow(freed(run, model=True), schema)


def letters(text: Column) -> Column:
    return F.coalesce(text.rlike(r"\p{L}"), F.lit(False))
