"""Every pair of different texts whose five-word sets reach the similarity is linked, whatever its fingerprints say."""

import random

import pytest

from rotagrad.llm import simhash
from test_operators import five_word_similarity


def texts_at_the_edge():
    rnd = random.Random(11)
    words = [f"w{i}" for i in range(3000)]
    out = []
    for k in range(120):  # pairs at 0.8 or just above, of many sizes
        base = [rnd.choice(words) for _ in range(rnd.randint(60, 300))]
        other = list(base)
        while True:
            trial = list(other)
            trial[rnd.randrange(len(trial))] = rnd.choice(words)
            if five_word_similarity(" ".join(base), " ".join(trial)) < 0.8:
                break
            other = trial
        out += [" ".join(base), " ".join(other)]
    line = " ".join(rnd.choice(words) for _ in range(24))
    for k in range(90):  # a line in all, beside words of their own: similarities on both sides of 0.8
        out.append(" ".join([line, *(rnd.choice(words) for _ in range(k % 9))]))
    return out


@pytest.mark.parametrize("counted", [16, 1])
def test_no_pair_at_the_similarity_is_left_out(spark, monkeypatch, counted):
    monkeypatch.setattr(simhash, "COUNTED", counted)
    texts = texts_at_the_edge()
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r.component_id for r in simhash.similar(rows).collect()}
    assert len(got) == len(texts)
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} for w in (t.split() for t in texts)]
    pairs = [(a, b) for a in range(len(texts)) for b in range(a) if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]) - 1e-9]
    assert len(pairs) > 400 and all(got[a] == got[b] for a, b in pairs)


def test_exact_pairs_alone_give_all_links(spark, monkeypatch):
    """Without a single link from fingerprints."""
    monkeypatch.setattr(simhash, "wide_links", lambda distinct, *_: distinct.limit(0).selectExpr("fp as a", "fp as b"))
    test_no_pair_at_the_similarity_is_left_out(spark, monkeypatch, 1)
