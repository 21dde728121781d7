"""Each training-data operator against brute force, round trips or held-out labels, and on edge rows."""

import collections
import hashlib
import itertools
import math
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from rotagrad.llm import bm25, bpe, chat, exact_dedup, html_text, langid, mixing, pii, queries, simhash, suffix_dedup

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, norm string, h string, size long, kept string"


def docs_of(spark, rows):
    """Documents with extra columns whose names clash with the operators' own."""
    return spark.createDataFrame([(i, t, "en", s, 1, "x", "y", 9, "z") for i, t, s in rows], SCHEMA).repartition(3)


EDGE = [(5, None, "a"), (6, "", "a"), (7, "  \t ", None), (8, "one two three four", None), (8, "one two three four", None), (9, "one two three four", "b"), (10, "word " * 30000, "b"), (None, "stray", "c")]


@pytest.fixture(scope="module")
def edge(spark):
    return docs_of(spark, EDGE)


@pytest.fixture(scope="module")
def empty(spark):
    return docs_of(spark, EDGE).filter("false")


@pytest.fixture(scope="module")
def real(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


# ---- 1 suffix-array dedup

def brute_repeats(texts, length):
    count = collections.Counter(t[i : i + length] for t in texts for i in range(len(t) - length + 1))
    out = []
    for t in texts:
        gone = np.zeros(len(t), bool)
        for i in range(len(t) - length + 1):
            if count[t[i : i + length]] > 1:
                gone[i : i + length] = True
        kept = bytes(b for b, g in zip(t, gone) if not g)
        out.append((len(t), int(gone.sum()), len(suffix_dedup.runs(gone)), kept))
    return out


def repeats_case(seed, n=40):
    rnd = random.Random(seed)
    blocks = ["".join(rnd.choice("abc é\n") for _ in range(rnd.randint(10, 150))) for _ in range(12)]
    return ["".join(rnd.choice(blocks) for _ in range(rnd.randint(0, 6))) for _ in range(n)] + ["a" * 500, "a" * 90, "", blocks[0] * 5]


@pytest.mark.parametrize("length,hot", [(80, 4096), (80, 2), (101, 4096), (400, 4096)])
def test_repeats_against_brute_force(spark, monkeypatch, length, hot):
    monkeypatch.setattr(suffix_dedup, "HOT", hot)
    texts = repeats_case(length)
    got = suffix_dedup.remove_repeats(docs_of(spark, [(i, t, None) for i, t in enumerate(texts)]), length).orderBy("doc_id").collect()
    assert [(r.n_bytes, r.n_removed, r.n_spans, bytes(r.kept)) for r in got] == brute_repeats([t.encode() for t in texts], length)


def test_repeats_across_pieces(spark, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "PIECE", 100)
    texts = repeats_case(3)
    got = {}
    for i, t in enumerate(texts):
        data = t.encode()
        starts = set()
        for offset in range(0, max(1, len(data) - 79), 100):
            first, n, _ = suffix_dedup.segments(data[offset : offset + 179], 80)
            starts |= {offset + a + k for a, m in zip(first, n) for k in range(m)}
        got[i] = starts == set(range(max(0, len(data) - 79)))
    assert all(got.values())


def test_repeats_edge(edge, empty):
    rows = suffix_dedup.remove_repeats(edge).collect()
    assert len(rows) == len(EDGE) and {r.n_removed for r in rows if r.doc_id != 10} == {0}
    assert next(r for r in rows if r.doc_id == 10).n_removed == 150000
    assert suffix_dedup.remove_repeats(empty).count() == 0


# ---- 2 chat formatting

def tokenizer_file():
    return queries.tokenizer_path("byte_bpe_50k.json")


def conversations(spark, rows):
    return spark.createDataFrame([(c, t, r, x, 1, "z") for c, t, r, x in rows], "conv_id bigint, turn bigint, role string, text string, part int, formatted string").repartition(3)


def chat_expected(rows):
    out = {}
    for c, own in itertools.groupby(sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or 0, r[2] or "", r[3] or "")), key=lambda r: r[0]):
        own = [(r[2] or "", r[3] or "") for r in own]
        loss = "".join(x for r, x in own if r == "assistant")
        out[c] = (len(own), hashlib.sha256("".join(f"{r}\n{x}\n" for r, x in own).encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest(), len(chat.render(own)))
    return out


def test_chat_round_trip(spark, monkeypatch):
    rnd = random.Random(1)
    bits = ["### Assistant: ", "</turn>", "\\", "\n", "####", " ", "é漢🙂", "word", "</turn", ": ", "\\n", "'s", "\t\t"]
    rows = [(c, t, rnd.choice(["user", "assistant", "a:b\n### x", None]), "".join(rnd.choice(bits) for _ in range(rnd.randint(0, 12)))) for c in range(30) for t in range(5)]
    rows += [(1, 2, "assistant", None), (None, None, "assistant", "x"), (3, 1, "user", "same"), (3, 1, "user", "same"), (99, 0, "assistant", "long " * 60000)]
    for part in (chat.PART, 50):
        monkeypatch.setattr(chat, "PART", part)
        got = chat.read_back(chat.format_conversations(conversations(spark, rows), tokenizer_file())).collect()
        assert {r.conv_id: tuple(r)[1:] for r in got} == chat_expected(rows)


def test_chat_parts_tokenise_like_the_whole(spark, monkeypatch):
    rows = [(1, t, "user" if t % 2 else "assistant", f" text {t}\n\n  end ") for t in range(40)]
    whole = chat.format_conversations(conversations(spark, rows), tokenizer_file()).collect()
    monkeypatch.setattr(chat, "PART", 60)
    parts = sorted(chat.format_conversations(conversations(spark, rows), tokenizer_file()).collect(), key=lambda r: r.part)
    assert len(parts) > 3 and b"".join(bytes(p.ids) for p in parts) == bytes(whole[0].ids)


def test_chat_empty(spark):
    none = conversations(spark, [(1, 1, "user", "x")]).filter("false")
    assert chat.read_back(chat.format_conversations(none, tokenizer_file())).count() == 0


# ---- 3 personal data

BASE = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def luhn(d):
    return sum((x if i % 2 == 0 else 2 * x - 9 * (2 * x > 9)) for i, x in enumerate(map(int, d[::-1]))) % 10 == 0


def brute_pii(text):
    out = []
    for kind, pattern in BASE.items():
        for m in re.finditer(pattern, text or ""):
            d = re.sub("[^0-9]", "", m[0])
            if kind == "ip" and any(int(p) > 255 for p in m[0].split(".")) or kind == "card" and not (13 <= len(d) <= 19 and luhn(d)) or kind == "phone" and not 9 <= len(d) <= 15:
                continue
            out.append(f"{kind}:{m.start()}:{m.end()}")
    return ",".join(out)


def pii_texts():
    rnd = random.Random(4)
    bits = ["a@b.c", "_d@e.f", "x", ".", "@", "-", " ", "1.2.3.4", ".5", "256.1.1.1", "4111111111111111", "4111 1111-1111 1111", "4111  1111", "12", "+1 (988) 555-2485", "+", "é🙂", "%", "3.4", "0004", "\n", "7", "378282246310005"]
    return ["".join(rnd.choice(bits) for _ in range(rnd.randint(0, 14))) for _ in range(1500)] + [None, "", "x" * 20000, "1" * 20000, "+" + "(" * 5000, "a.b@c.d" * 300, "4111111111111111 " * 2]


def test_pii_base_spans_against_the_plain_patterns(spark):
    texts = pii_texts()
    got = pii.find(docs_of(spark, [(i, t, None) for i, t in enumerate(texts)])).select("doc_id", pii.written(F.col("base")).alias("s")).collect()
    assert {r.doc_id: r.s for r in got} == {i: brute_pii(t) for i, t in enumerate(texts)}


def test_pii_terms_that_disclose(spark):
    # The name stands far from the address, and the block around the address is always the same.
    far = "word " * 200
    texts = [f"filler{'abcdefghij'[i]} zanzibar {far} reach us at 10.0.0.7 any day" for i in range(6)] + [f"the people of the land are many {'x' * i}" for i in range(1, 200)] + ["zanzibar again, alone"]
    frame = docs_of(spark, [(i, t, None) for i, t in enumerate(texts)])
    got = {r.doc_id: r.s for r in pii.find(frame).select("doc_id", pii.written(F.col("more")).alias("s")).collect()}
    assert got[205] == "term:0:8" and "term:8:16" in got[0] and got[10] == ""
    assert len({r.s for r in pii.sanitise(frame).filter("doc_id = 205").select(F.col("text").alias("s")).collect()} & {"[TERM] again, alone"}) == 1
    # Copies of one document prove nothing.
    copies = docs_of(spark, [(i, "unique quagmire 10.0.0.9 text", None) for i in range(20)] + [(i, f"plain words {'y' * i}", None) for i in range(20, 200)])
    assert pii.find(copies).filter("size(more) > 0").count() == 0


def test_pii_method_against_brute_force(spark, monkeypatch):
    import regex

    rnd = random.Random(11)
    rare = ["".join(rnd.choice("bcdfg") + rnd.choice("aeiou") for _ in range(3)) for _ in range(60)]
    common = ["alpha", "beta", "gamma", "the", "of"]
    entities = ["10.0.0.1", "me@site.org", "+1 (988) 555-2485", "4111111111111111"]
    texts = []
    for _ in range(300):
        e = rnd.randrange(5)
        words = rnd.choices(common, k=6) + rnd.choices(rare[:40], k=2)
        if e < 4:
            words += [entities[e]] + rnd.choices(rare[40 + 5 * e : 45 + 5 * e], k=2)
        rnd.shuffle(words)
        texts += [" ".join(words)] * rnd.choice([1, 1, 1, 4])
    texts += [None, "", f"{rare[41].upper()} {rare[41]}x {rare[41]}"]
    base = [re.findall(r"(\w+):(\d+):(\d+)", brute_pii(t)) for t in texts]
    contents = {(t or ""): frozenset((t or "")[int(a) : int(b)].lower() for _, a, b in s) for t, s in zip(texts, base)}
    terms = {t: {w for w in regex.split(r"[^\p{L}]+", t.lower()) if len(w) >= 3} for t in contents}
    n_e = collections.Counter(e for own in contents.values() for e in own)
    n_t = collections.Counter(w for own in terms.values() for w in own)
    n_et = collections.Counter((e, w) for t, own in contents.items() for e in own for w in terms[t])
    said = {w for (e, w), c in n_et.items() if c >= 3 and c / n_t[w] >= 0.5 and c * math.log2(c * len(contents) / (n_t[w] * n_e[e])) >= 20}
    want = {i: ",".join(f"term:{m.start()}:{m.end()}" for m in regex.finditer(r"\p{L}+", t or "") if m[0].lower() in said) for i, t in enumerate(texts)}
    assert said and any(want.values())
    frame = docs_of(spark, [(i, t, None) for i, t in enumerate(texts)])
    for bound in (200_000, 1):  # with broadcasts and without
        monkeypatch.setattr(pii, "BROADCAST_TERMS", bound)
        assert {r.doc_id: r.s for r in pii.find(frame).select("doc_id", pii.written(F.col("more")).alias("s")).collect()} == want


def test_pii_edge(edge, empty):
    assert pii.find(edge).count() == len(EDGE) and pii.find(empty).count() == 0
    assert pii.sanitise(edge).count() == len(EDGE)


# ---- 4 near duplicates

def brute_components(prints):
    root = {i: i for i in prints}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in itertools.combinations(sorted(prints), 2):
        if bin((prints[a] ^ prints[b]) & (1 << 64) - 1).count("1") <= 2:
            x, y = sorted((find(a), find(b)))
            root[y] = x
    return {i: find(i) for i in prints}


def plain_fingerprint(text):
    import xxhash

    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] if len(words) >= 3 else [" ".join(words)]
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_fingerprints():
    for t in (None, "", " \n", "A b", "É Ab\x0bcd\x85e f", "a b c a b c a b c d", "x " * 5000):
        assert simhash.fingerprint(t) & (1 << 64) - 1 == plain_fingerprint(t)


@pytest.mark.parametrize("split", [8192, 4])
def test_components_against_all_pairs(spark, monkeypatch, split):
    monkeypatch.setattr(simhash, "SPLIT", split)
    monkeypatch.setattr(simhash, "TILE", 8)
    rnd = random.Random(5)
    prints = {}
    for i in range(400):
        f = rnd.choice(list(prints.values())) if prints and rnd.random() < 0.7 else rnd.getrandbits(64)
        for _ in range(rnd.randint(0, 3)):
            f ^= 1 << rnd.randrange(64)
        prints[i] = f
    signed = [(i, f - (1 << 64) if f >> 63 else f) for i, f in prints.items()]
    distinct = spark.createDataFrame([(f,) for f in {f for _, f in signed}], "fp long").repartition(3)
    roots = {r.v: r.root for r in simhash.components(simhash.links(distinct)).collect()}
    groups = collections.defaultdict(set)
    for i, f in signed:
        groups[roots.get(f, f)].add(i)
    want = collections.defaultdict(set)
    for i, c in brute_components(prints).items():
        want[c].add(i)
    assert sorted(map(sorted, groups.values())) == sorted(map(sorted, want.values()))


def test_near_duplicates_on_real_rows(real, edge, empty):
    rows = {r.doc_id: r for r in simhash.near_duplicates(real).collect()}
    texts = {r.doc_id: r.text for r in real.collect()}
    prints = {i: plain_fingerprint(t) for i, t in texts.items()}
    assert {i: r.fingerprint for i, r in rows.items()} == {i: f"{f:016x}" for i, f in prints.items()}
    assert {i: r.component_id for i, r in rows.items()} == brute_components(prints)
    got = simhash.near_duplicates(edge).collect()
    assert len(got) == len(EDGE) and {r.component_id for r in got if r.doc_id in (5, 6, 7)} == {5} and {r.component_id for r in got if r.doc_id in (8, 9)} == {8}
    assert simhash.near_duplicates(empty).count() == 0


def five_word_similarity(a, b):
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} for w in (a.split(), b.split())]
    return len(sets[0] & sets[1]) / len(sets[0] | sets[1])


def near_copies(seed=4, bases=60):
    rnd = random.Random(seed)
    vocabulary = ["".join(rnd.choice("abcdefghij") for _ in range(5)) for _ in range(2000)]
    rows = []
    for _ in range(bases):
        words = [rnd.choice(vocabulary) for _ in range(rnd.randint(120, 400))]
        rows.append(" ".join(words))
        for changes in (1, 2, 40):
            own = list(words)
            for _ in range(changes):
                own[rnd.randrange(len(own))] = rnd.choice(vocabulary)
            rows.append(" ".join(own))
    return rows


@pytest.mark.parametrize("split", [8192, 6])
def test_similar_against_exact_similarities(spark, monkeypatch, edge, empty, split):
    """Pairs of five-word similarity 0.85 or more meet; groups hold no pair that only pairs below 0.7 connect."""
    monkeypatch.setattr(simhash, "SPLIT", split)
    texts = near_copies() + ["tiny text", "Tiny  text", "other one", None, "", " "]
    # A large group: every pair of these copies is near, and bits fall into few buckets.
    hub = " ".join(f"w{i}" for i in range(200))
    texts += [f"{hub} v{i}" for i in range(60)]
    got = {r.doc_id: r.component_id for r in simhash.similar(docs_of(spark, [(i, t, "s") for i, t in enumerate(texts)])).collect()}
    assert len(got) == len(texts)
    found, wanted = 0, 0
    joined = simhash_roots(texts, 0.7)
    for a, b in itertools.combinations(range(len(texts)), 2):
        if joined[a] != joined[b]:
            assert got[a] != got[b]
        elif five_word_similarity(texts[a] or "", texts[b] or "") >= 0.85:
            wanted, found = wanted + 1, found + (got[a] == got[b])
    assert wanted > 1800 and found > 0.98 * wanted
    rows = simhash.similar(edge).collect()
    assert len(rows) == len(EDGE) and {r.component_id for r in rows if r.doc_id in (5, 6, 7)} == {5} and {r.component_id for r in rows if r.doc_id in (8, 9)} == {8}
    assert simhash.similar(empty).count() == 0


def simhash_roots(texts, least):
    """Components over exact similarities of at least ``least``, by all pairs."""
    root = list(range(len(texts)))
    clean = [(t or "").lower() for t in texts]
    for a, b in itertools.combinations(range(len(texts)), 2):
        if root[a] != root[b] and five_word_similarity(clean[a], clean[b]) >= least:
            x, y = sorted((root[a], root[b]))
            root = [x if r == y else r for r in root]
    return root


def test_trees_have_small_fan_out():
    root = np.array([0] * 200 + [200] + [201] * 3)
    child, parent = simhash.tree_edges(root)
    assert len(child) == 199 + 2 and max(collections.Counter(parent.tolist()).values()) <= simhash.FAN
    top = root.copy()
    up = dict(zip(child.tolist(), parent.tolist()))
    for i in range(len(root)):
        j = i
        while j in up:
            j = up[j]
        assert j == top[i]


# ---- 5 search

def test_search_against_brute_force(spark, real, edge, empty):
    asked = real.filter("doc_id % 20 = 0")
    got = collections.defaultdict(list)
    for r in bm25.search(real, asked, k=5, shard_docs=40).collect():
        got[r.query_id].append((r["rank"], r.doc_id, r.score))
    count = {r.doc_id: collections.Counter(r.w.split()) for r in real.select("doc_id", bm25.words(F.col("text")).alias("w")).collect()}
    n, length = len(count), {i: sum(c.values()) for i, c in count.items()}
    mean = sum(length.values()) / n
    df = collections.Counter(w for c in count.values() for w in c)
    for q in (i for i in count if i % 20 == 0):
        scores = []
        for i, c in count.items():
            s = math.fsum(k * math.log((n - df[w] + 0.5) / (df[w] + 0.5) + 1) * c[w] * 2.2 / (c[w] + 1.2 * (0.25 + 0.75 * length[i] / mean)) for w, k in count[q].items() if w in c)
            if s > 0:
                scores.append((-round(s, 9), i))
        want = [(k + 1, i, -s) for k, (s, i) in enumerate(sorted(scores)[:5])]
        mine = sorted(got[q])
        assert [x[1] for x in mine] == [x[1] for x in want] and np.allclose([x[2] for x in mine], [x[2] for x in want])
    rows = bm25.search(edge, edge, k=3).collect()
    assert {r.doc_id for r in rows if r.query_id == 9 and r["rank"] == 1} == {8} and not [r for r in rows if r.query_id in (5, 6, 7)]
    assert bm25.search(empty, edge).count() == 0 and bm25.search(edge, empty).count() == 0


def test_pruning_skips_blocks_and_loses_nothing():
    rnd = random.Random(6)
    texts = [" ".join(rnd.choice("abcdefgh") for _ in range(5)) + (" rare" * 3 if i % 700 == 0 else "") for i in range(2000)]
    shard = bm25.Shard(list(range(2000)), texts, 5.0, 1.2, 0.75)
    calls = []
    plain = shard.visit
    shard.visit = lambda s, open_, *rest: (calls.append(len(open_)), plain(s, open_, *rest))[1]
    found = shard.search([("rare", 9.0), ("a", 0.1)], 3)
    assert sorted(i for i, _ in found) == [0, 700, 1400] and len(shard.stripes) == 2 and sum(calls) == 1


def test_pivots_pass_over_blocks_and_documents():
    """Sums over all documents beside the pruned search, for a batch of queries over words of very uneven frequency."""
    rnd = random.Random(12)
    words = [f"w{i}" for i in range(400)]
    texts = [" ".join(words[min(399, int(rnd.paretovariate(0.5)) - 1)] for _ in range(rnd.randint(0, 40))) for _ in range(3000)]
    mean = sum(len(t.split()) for t in texts) / len(texts)
    shard = bm25.Shard(list(range(3000)), texts, mean, 1.2, 0.75)
    df = collections.Counter(w for t in texts for w in set(t.split()))
    idf = {w: math.log((3000 - f + 0.5) / (f + 0.5) + 1) for w, f in df.items()}
    asked = [collections.Counter(t.split()) for t in texts[:60]]
    cells = [(i, shard.terms[w], c * idf[w]) for i, own in enumerate(asked) for w, c in own.items()]
    got = shard.search_many(*(np.array(x) for x in zip(*cells)), 60, 5)
    counts = [collections.Counter(t.split()) for t in texts]
    for own, mine in zip(asked, got):
        want = []
        for i, c in enumerate(counts):
            size = 1.2 * (0.25 + 0.75 * sum(c.values()) / mean)
            score = round(math.fsum(k * idf[w] * (c[w] * 2.2 / (c[w] + size)) for w, k in own.items() if w in c), 9)
            want += [(-score, i)] if score > 0 else []
        assert [i for i, _ in mine] == [i for _, i in sorted(want)[:5]] and np.allclose([s for _, s in mine], [-s for s, _ in sorted(want)[:5]])
    assert all(shard.counts.values()), shard.counts  # blocks and documents are both passed over and read


def test_batches_of_queries_survive_packing():
    texts, counts, dfs = ["a b zz", "b"], [[1, 3, 2], [4]], [[9, 70000, 1], [70000]]
    ids, rows, order, df, query, word, count = bm25.unpack(bm25.pack([7, None], [0, 5], texts, counts, dfs))
    assert (ids, rows) == ([7, None], [0, 5]) and dict(zip(order, df.tolist())) == {"a": 9, "b": 70000, "zz": 1}
    assert sorted(zip(query.tolist(), (order[i] for i in word), count.tolist())) == [(0, "a", 1), (0, "b", 3), (0, "zz", 2), (1, "b", 4)]


def test_search_merges_many_shards_and_copies(spark):
    """Ties, copies beyond k, several query batches and more shards than are merged at a time."""
    rnd = random.Random(8)
    rows = [(i, " ".join(rnd.choice("abcdefghijklmnop") * 2 for _ in range(rnd.randint(1, 12))), "s") for i in range(700)] + [(i, "same old text", "s") for i in range(700, 900)]
    docs = docs_of(spark, rows)
    one = sorted(map(tuple, bm25.search(docs, docs, k=4).collect()))
    many = sorted(map(tuple, bm25.search(docs, docs, k=4, shard_docs=10).collect()))
    assert one == many and [r[2] for r in one if r[0] == 850] == [700, 701, 702, 703] and len({r[0] for r in one}) == 900


# ---- 6 language

def test_forward_sums_all_segmentations():
    pieces = ["▁a", "▁ab", "b", "c", "bc", "▁"]
    index = langid.with_prefixes(pieces)
    p = np.array([0.3, 0.2, 0.1, 0.15, 0.2, 0.05, 1e-7])
    word = "▁abc"

    def total(rest):
        return 1.0 if not rest else sum(p[i] * total(rest[len(x) :]) for i, x in enumerate(pieces) if rest.startswith(x)) + (p[-1] * total(rest[1:]) if rest[0] not in pieces else 0)

    want = math.log(total(word))
    assert langid.Lattices([word, "▁"], index, len(pieces)).logs(p)[0] == pytest.approx(want)
    assert langid.LongLattice(word, index, len(pieces)).logs(p) == pytest.approx(want)
    uses = langid.Lattices([word], index, len(pieces)).expected(p, np.array([3.0]))
    assert langid.LongLattice(word, index, len(pieces)).expected(p, 3.0) == pytest.approx(uses)


def test_long_words_are_summed_whole():
    """Both ways agree around the border, and no segmentation across any place is left out."""
    pieces = ["▁", "a", "b", "ab", "abab", "ababababab"]
    index, rng = langid.with_prefixes(pieces), np.random.default_rng(5)
    p = rng.dirichlet(np.ones(len(pieces) + 1))
    for n in (5, langid.LONG - 1, langid.LONG, 1000):
        word = ("▁" + "ab" * n)[:n]
        alpha = [0.0]
        for j in range(1, n + 1):  # logarithms of the plain sums
            alpha.append(np.logaddexp.reduce([alpha[j - len(x)] + math.log(p[i]) for i, x in enumerate(pieces) if word[:j].endswith(x)]))
        assert langid.LongLattice(word, index, len(pieces)).logs(p) == pytest.approx(alpha[-1])
        if n <= langid.LONG:
            assert langid.Lattices([word], index, len(pieces)).logs(p)[0] == pytest.approx(alpha[-1])


def test_language_predictions_by_plain_recomputation(spark, real):
    """Every row's language and score from sums over whole words, without batches, caches or scaling."""
    model = langid.train(real, queries.tokenizer_path("piece_bpe_32k.model"))
    number, logs = {x: i for i, x in enumerate(model.pieces)}, np.log(model.probabilities)
    longest, seen = max(map(len, number)), {}

    def word_logs(word):
        alpha = np.zeros((len(word) + 1, len(logs)))
        for j in range(1, len(word) + 1):
            own = [alpha[i] + logs[:, number[word[i:j]]] for i in range(max(0, j - longest), j) if word[i:j] in number]
            alpha[j] = np.logaddexp.reduce(own + ([alpha[j - 1] + logs[:, -1]] if word[j - 1] not in number else []))
        return alpha[-1]

    rows = real.filter("length(text) < 1500").limit(60).select("doc_id", "text").collect()
    rows += [(-1, "²" * 9), (-2, "straße " * 3 + "z" * 90), (-3, None)]
    frame = spark.createDataFrame([tuple(r) for r in rows], "doc_id bigint, text string").withColumn("score", F.lit("x")).withColumn("lang_pred", F.lit(1))
    for r in langid.identify(frame, model).collect():
        words = re.findall(r"[^\W\d_]+", (r.text or "").lower())
        if not any(c.isalpha() for c in r.text or ""):
            assert (r.lang_pred, r.score) == ("und", 0.0)
            continue
        total = sum(seen.setdefault(w, word_logs("▁" + w)) for w in words)
        share = np.exp(total - total.max())
        assert r.lang_pred == model.languages[int(total.argmax())] and r.score == pytest.approx(share.max() / share.sum(), abs=1e-6)


def test_language_held_out_accuracy(spark, sf, real):
    rows = {r.doc_id: r for r in queries.op6_language_id(spark, sf).collect()}
    labels = {r.doc_id: r.lang for r in real.collect()}
    assert all(r.held_out == (zlib.crc32(str(i).encode()) % 5 == 0) for i, r in rows.items())
    held = [r.lang_pred == labels[i] for i, r in rows.items() if r.held_out and r.lang_pred != "und"]
    assert np.mean(held) > 0.97 and all(0 <= r.score <= 1 for r in rows.values())


def test_language_edge(spark, edge, empty, real):
    path = queries.tokenizer_path("piece_bpe_32k.model")
    model = langid.train(real, path)
    got = {r.doc_id: r.lang_pred for r in langid.identify(edge.select("doc_id", "text"), model).collect()}
    assert got[5] == got[6] == got[7] == "und" and got[8] != "und"
    odd = docs_of(spark, [(1, "12 34 !!", None), (2, "²³", None), (3, "x" * 5000, None), (4, "漢字", None), (5, "The and of that there", None)])
    got = {r.doc_id: r.lang_pred for r in langid.identify(odd.select("doc_id", "text"), model).collect()}
    assert got[1] == got[2] == "und" and got[3] != "und" and got[4] != "und" and got[5] == "en"
    assert langid.identify(empty, model, score_out="s").count() == 0
    none = langid.train(empty, path)
    assert {r.lang_pred for r in langid.identify(edge.select("doc_id", "text"), none).collect()} == {"und"}


# ---- 7 exact duplicates

def test_exact_groups(spark, edge, empty):
    rows = exact_dedup.exact_groups(edge).collect()
    assert {(r.doc_id, r.keep_id, r.group_size, r.kept) for r in rows} == {(5, 5, 2, True), (6, 5, 2, False), (7, 7, 1, True), (8, 8, 3, True), (9, 8, 3, False), (10, 10, 1, True), (None, None, 1, True)} and len(rows) == len(EDGE)
    assert exact_dedup.exact_groups(empty).count() == 0
    texts = ["a b", "a  b", "a\tb", "a\x0bb", "a\xa0b", "a b ", " a b", "A b", "a\r\n b", "a\x1cb"]
    norm = {i: re.sub(r"[\x20\x09-\x0D]+", " ", t) for i, t in enumerate(texts)}
    got = exact_dedup.exact_groups(docs_of(spark, [(i, t, None) for i, t in enumerate(texts)])).collect()
    assert {r.doc_id: r.keep_id for r in got} == {i: min(j for j in norm if norm[j] == norm[i]) for i in norm}
    assert {r.doc_id: r.text_sha256 for r in got} == {i: hashlib.sha256(t.encode()).hexdigest() for i, t in norm.items()}


# ---- 8 byte-level BPE

@pytest.fixture(scope="module")
def codec():
    with open(queries.tokenizer_path("byte_bpe_50k.tiktoken"), "rb") as f:
        ranks = bpe.read_ranks(f.read())
    import public_tokenizers
    import tiktoken

    return bpe.Codec(ranks, bpe.codepoint_classes()), tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_bpe_equals_the_library(codec, real):
    own, library = codec
    rnd = random.Random(7)
    bits = list("ab'stmdrevl  \n\t 12.!é漢 　\r-\0") + ["'s", "'ll", "'re", " '", "  ", "\n\n", "<|endoftext|>", "🙂", "́", "\x85", "\x1c", "ꟊ"]
    texts = ["".join(rnd.choice(bits) for _ in range(rnd.randint(0, 30))) for _ in range(20000)]
    texts += ["", " ", "a" * 3000, "'" * 300, " " * 2000, "é" * 2000, "\0", "a\0b", "x'", "'s"] + [r.text for r in real.collect()]
    for part in bpe.chunks(texts):
        for text, (ids, pieces) in zip(part, own.encode(part)):
            assert np.frombuffer(ids, "<u4").tolist() == library.encode_ordinary(text), text[:80]
            assert own.decode(ids) == text.encode() and "".join(pieces) == text


def test_bpe_every_code_point(codec):
    own, library = codec
    every = [chr(c) for c in [*range(0, 0xD800, 7), *range(0xE000, 0x110000, 101)]]
    for text, (ids, _) in zip(every, own.encode([f"a{c} {c}1{c}" for c in every])):
        assert np.frombuffer(ids, "<u4").tolist() == library.encode_ordinary(f"a{text} {text}1{text}")


def test_bpe_operator(spark, edge, empty):
    path = queries.tokenizer_path("byte_bpe_50k.tiktoken")
    rows = bpe.encode(edge, path, decode_back=True, offsets=True).collect()
    want = collections.Counter((i, (t or "").encode()) for i, t, _ in EDGE)
    assert collections.Counter((r.doc_id, bytes(r.decoded)) for r in rows) == want
    assert all(r.n_tokens * 8 == len(r.offsets) and r.n_tokens * 4 == len(r.ids) for r in rows)
    assert collections.Counter((r.doc_id, bytes(r.decoded)) for r in bpe.decode(bpe.encode(edge, path), path).collect()) == want
    assert bpe.encode(empty, path).count() == 0


# ---- 9 mixing

def brute_shares(sizes, weights, cap=3):
    target, total, fixed = [0.0] * len(sizes), float(sum(sizes)), set()
    while len(fixed) < len(sizes):
        free = [i for i in range(len(sizes)) if i not in fixed]
        left = total - sum(target[i] for i in fixed)
        for i in free:
            target[i] = left * weights[i] / sum(weights[j] for j in free)
        over = [i for i in free if target[i] > cap * sizes[i] + 1e-9]
        if not over:
            break
        for i in over:
            target[i] = cap * sizes[i]
            fixed.add(i)
    return target


def test_shares_and_quotients():
    rnd = random.Random(8)
    for _ in range(200):
        sizes = [rnd.choice([0, 1, 5, 100, 1000]) for _ in range(rnd.randint(1, 7))]
        weights = [i % 3 + 1 for i in range(len(sizes))]
        assert np.allclose([float(x) for x in mixing.capped_shares(sizes, weights)], brute_shares(sizes, weights))
        votes, seats = sizes, rnd.randint(0, 30)
        quotients = sorted(((-v / (2 * k + 1), i) for i, v in enumerate(votes) if v for k in range(seats)))[:seats]
        assert mixing.sainte_lague(votes, seats) == [sum(i == j for _, j in quotients) for i in range(len(votes))]


def test_mix_meets_targets_and_reruns_agree(spark, real):
    rows = mixing.mix(real, rows_per_shard=8).collect()
    again = mixing.mix(real.repartition(7), rows_per_shard=8).collect()
    assert sorted(map(tuple, rows)) == sorted(map(tuple, again))
    by = collections.defaultdict(list)
    for r in rows:
        by[r.source].append(r)
        assert 0 <= r.taken <= 3 * r.size
    sizes = [sum(r.size for r in by[s]) for s in sorted(by)]
    want = brute_shares(sizes, [i % 3 + 1 for i in range(len(sizes))])
    for s, t in zip(sorted(by), want):
        assert by[s][0].target == pytest.approx(t) and sum(r.taken for r in by[s]) == pytest.approx(t, abs=50)


def test_mix_edge(edge, empty):
    rows = mixing.mix(edge).collect()
    assert len(rows) == len(EDGE) and mixing.mix(empty).count() == 0
    assert all(r.taken == 0 for r in rows if r.size == 0)
    assert {r.source: r.source_size for r in rows} == {"a": 0, "b": 30004, "c": 1, None: 8}


# ---- 10 pages

def article_text(page):
    import html

    inside = page[page.find("<article>") : page.find("</article>")]
    inside = re.sub(r"</?b>", "", re.sub(r"</?(p|h1|br|article)>", " ", inside))
    return " ".join(html.unescape(inside).split())


def renamed(page):
    return page.replace("<article>", "<div>").replace("</article>", "</div>")


def test_html(spark, sf):
    for r in spark.read.parquet(f"{sf}/pages.parquet").collect():
        assert html_text.main_text(r.html) == html_text.main_text(renamed(r.html)) == article_text(r.html)


def test_html_density_decides(spark, sf, monkeypatch):
    """Without any list of elements or classes the densities find the text; a constant density does not."""
    pages = [(renamed(r.html), article_text(r.html)) for r in spark.read.parquet(f"{sf}/pages.parquet").collect()]
    share = lambda: sum(html_text.main_text(p, marks=False) == want for p, want in pages) / len(pages)
    assert share() > 0.85
    para = "w" * 200
    menu = "<div>" + "".join(f"<div><a href={i}>go {i}</a></div>" for i in range(9)) + "</div>"
    page = f"<body>{menu}<div><div>{''.join(f'<p>{para}{i}</p>' for i in range(4))}</div><div>{''.join(f'<p>{para}x{i}</p>' for i in range(3))}</div></div><div>small print</div>"
    want = " ".join([f"{para}{i}" for i in range(4)] + [f"{para}x{i}" for i in range(3)])
    assert html_text.main_text(page) == html_text.main_text(page, marks=False) == want
    for other in (lambda d, i: 1.0, lambda d, i: 0.0):
        monkeypatch.setattr(html_text.Densities, "density", other)
        assert share() < 0.2 and html_text.main_text(page) != want


def test_html_groups_lists_and_names():
    para = "some words of prose that make a paragraph of usual length here " * 4
    items = "".join(f"<li>{'item text here ' * 4}{i}</li>" for i in range(10))
    links = "<div><a href=1>related story one</a> <a href=2>related story two</a></div>"
    page = f"<body><header><h1>Site</h1></header><div><a href=1>home</a> <a href=2>news</a> <a href=3>contact</a></div><div><div><h1>Title</h1><p>{para}one</p><p>ok</p><ul>{items}</ul><p>The end.</p></div>{links}</div><div>&copy; 2020 x</div></body>"
    want = " ".join(f"Title {para}one ok {' '.join('item text here ' * 4 + str(i) for i in range(10))} The end.".split())
    assert html_text.main_text(page) == want
    # A long list beats the paragraphs' sum; they stay. Names that only contain a marking word are no furniture.
    page = f'<body><nav><a href=x>m</a></nav><div class="related-work"><p>{para}</p><p class="header-image">{para}</p><p class="cookie-notice">no</p><div id="comments-2">{para}</div></div></body>'
    assert html_text.main_text(page) == " ".join((para + para).split())


def test_html_deep_nesting_is_linear():
    began = __import__("time").time()
    assert html_text.main_text("<div><span>" * 30000 + "x" + "</b>" * 30000) == "x"
    assert html_text.main_text("<p><div>" + "<span>" * 30000 + "<hr>" * 30000 + "x") == "x"
    assert __import__("time").time() - began < 30


def test_html_furniture_and_broken_markup():
    page = '<body><div id="top-menu"><a href=x>m</a></div><main><div class="post"><h2>T&amp;C</h2>hel<b>lo</b> w<p>x\n y<div class="side-ad">no</div><p>two<ul><li>a<li>b</ul><form>f<input>g</form><section class="comments"><p>c</section></div></main><script>if (a<b) "</p>"</script><div role="contentinfo">no</div>'
    assert html_text.main_text(page) == "T&C hello w x y two a b"
    assert html_text.main_text("<p>a<!-- <p>b --> c &lt;d&gt; <i") == "a c <d>"
    assert html_text.main_text("<div hidden>x</div><p title='a > b'>y") == "y"
    for page in (None, "", "<html><body><nav>m</nav>", "<script>x"):
        assert html_text.main_text(page) == ""
    assert html_text.main_text("plain text") == "plain text" and html_text.main_text("<p>" + "w " * 50000) == ("w " * 50000).strip()


def test_html_edge(spark):
    rows = spark.createDataFrame([(1, "u", None, "t", 7), (1, "u", None, "t", 7), (None, None, "<p>x", "t", 7)], "page_id bigint, url string, html string, text string, n_chars int")
    assert html_text.extract(rows).columns == ["page_id", "url", "text", "n_chars"]
    assert sorted((r.page_id or 0, r.url or "", r.text, r.n_chars) for r in html_text.extract(rows).collect()) == [(0, "", "x", 1), (1, "u", "", 0), (1, "u", "", 0)]
    assert html_text.extract(rows.filter("false")).count() == 0
