"""Texts without letters are und at any length."""

import numpy as np

from rotagrad.llm import langid


def test_signs_that_are_no_letters_are_und_at_any_length():
    model = langid.Model(["de", "en"], ["a", "b"], np.full((2, 3), 1 / 3))
    scorer = langid.Scorer(model)
    for many in (1, 7, 8, 500):
        assert scorer.predict(["½ ① Ⅷ " * many]) == (["und"], [0.0])
        assert scorer.predict(["½ " * many + "b"])[0] != ["und"]


def test_short_words_are_cut_into_pieces_without_a_step_in_python_for_each(monkeypatch):
    pieces = ["▁", "▁a", "▁ab", "a", "ab", "abc", "b", "bc", "é", "😀", "😀a"]
    index = langid.with_prefixes(pieces)
    words = ["▁abcab", "▁", "▁a😀a", "▁éxé", "x", "▁ab" * 10]
    want = [sorted((w, *e) for e in langid.edges(word, index, len(pieces), 3)) for w, word in enumerate(words)]
    got = sorted(zip(*(x.tolist() for x in langid.Trie(index).edges(words, len(pieces)))))
    assert got == sorted(sum(want, []))
    assert [len(x) for x in langid.Trie(index).edges([], 0)] == [0, 0, 0, 0]
    monkeypatch.setattr(langid, "edges", None)
    p = np.full((2, len(pieces) + 1), 0.05)
    p[1, 0] = 0.5
    assert langid.Scorer(langid.Model(["de", "en"], pieces, p)).predict(["x y abc", "", "é"])[0] == ["en", "und", "en"]
