"""Pipeline stages against brute force, stage by stage, and the registered queries against SQL."""

import collections

import duckdb
import numpy as np
import pytest

import corpus_pipeline as cp
from rotagrad.llm import queries
from rotagrad.llm.simhash import wide_fingerprint

ROWS = [(1, "The cat sat on the mat and was glad of it all day long", "en", "a", 1), (2, "The cat  sat on the mat and was glad of it all day long", "en", "a", 1), (3, None, "en", "b", 0), (4, "", None, None, 0), (5, "123 456", "en", "b", 7), (6, "Der Hund und die Katze sind nicht hier, aber das Haus ist schön", "de", "b", 1), (6, "Der Hund und die Katze sind nicht hier, aber das Haus ist schön", "de", "b", 1), (7, "word " * 40000, "en", None, 9)]


def frame(spark, rows):
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    return docs.selectExpr("*", "1 as taken", "'x' as __lang").repartition(2)


def test_stages_on_edge_rows(spark, sf):
    docs, stage = frame(spark, ROWS), dict(cp.STAGES)
    a = stage["language_id"](spark, docs, sf)
    assert a.columns == cp.COLUMNS and sorted(r.doc_id for r in a.collect()) == [1, 2, 6, 6, 7]
    b = stage["exact_duplicates"](spark, a, sf)
    assert b.columns == cp.COLUMNS and sorted(r.doc_id for r in b.collect()) == [1, 6, 7]
    c = stage["near_duplicates"](spark, b, sf)
    assert sorted(r.doc_id for r in c.collect()) == [1, 6, 7]
    d = stage["source_mix"](spark, c, sf)
    assert d.columns == cp.COLUMNS and set(r.doc_id for r in d.collect()) <= {1, 6, 7}
    e = stage["encode"](spark, d, sf)
    assert e.count() == d.count()
    none = docs.filter("false")
    for f in stage.values():
        none = f(spark, none, sf)
        assert none.count() == 0


def test_run_keeps_clean_documents(spark, sf):
    """Every class of near copies keeps one document; nothing else is lost before mixing."""
    docs = queries.table(spark, sf, "documents")
    at = docs
    for name, f in cp.STAGES[:3]:
        at = f(spark, at, sf)
    kept = {r.doc_id for r in at.collect()}
    prints = {r.doc_id: int.from_bytes(wide_fingerprint(r.text), "little") for r in docs.collect()}
    far = lambda a, b: (prints[a] ^ prints[b]).bit_count()
    letters = {r.doc_id for r in docs.collect() if any(c.isalpha() for c in r.text or "")}
    # What goes has a near document; no two of those kept are near (by the radius of 0.8 and one standard deviation).
    assert all(i in kept or any(far(i, j) <= 44 for j in prints if j != i) for i in letters)
    assert all(far(i, j) > 44 for i in kept for j in kept if i < j)
    out = cp.run(spark, sf).collect()
    assert {r.doc_id for r in out} <= kept and all(n <= 3 for n in collections.Counter(r.doc_id for r in out).values())
    texts = {r.doc_id: len((r.text or "").encode()) for r in docs.collect()}
    assert all(len(np.frombuffer(r.ids, "<u4")) == r.n_tokens <= texts[r.doc_id] for r in out)


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_queries_against_sql(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "conversations"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    got = queries.queries()[name](spark, sf)
    want = con.sql(queries.oracle_sql()[name])
    columns = sorted(want.columns)
    assert columns == sorted(got.columns)
    key = lambda rows: sorted(tuple(map(str, r)) for r in rows)
    assert key(tuple(r[c] for c in columns) for r in got.collect()) == key(tuple(r[want.columns.index(c)] for c in columns) for r in want.fetchall())


def test_null_ids_and_one_id_on_two_texts(spark, sf):
    """Different clean texts stay whatever their ids; copies go even when their id is also on a kept text."""
    rng = np.random.default_rng(3)
    prose = [" ".join(rng.choice(["river", "stone", "lamp", "window", "quiet", "seven", "garden", "road", "letter", "cloud", "paper", "summer"], 60)) for _ in range(5)]
    rows = [(None, prose[0], "en", "a", 1), (None, prose[1], "en", "a", 1), (None, prose[1], "en", "a", 1), (3, prose[2], "en", "a", 1), (3, prose[3], "en", "a", 1), (4, prose[4], "en", "a", 1), (3, prose[4], "en", "a", 1), (None, prose[4], "en", "a", 1)]
    docs, stage = frame(spark, rows), dict(cp.STAGES)
    want = collections.Counter([(None, prose[0]), (None, prose[1]), (3, prose[2]), (3, prose[3]), (3, prose[4])])
    for name in ("exact_duplicates", "near_duplicates"):
        out = stage[name](spark, docs, sf)
        assert out.columns == cp.COLUMNS and collections.Counter((r.doc_id, r.text) for r in out.collect()) == want, name
        assert collections.Counter((r.doc_id, r.text) for r in stage[name](spark, out, sf).collect()) == want
    # Repeated rows add up: the same words come out as from rows apart.
    again = docs.union(docs)
    assert {(r.doc_id, r.text) for r in stage["source_mix"](spark, again, sf).collect()} <= {(r[0], r[1]) for r in rows}
    mixed = stage["source_mix"](spark, out, sf).collect()
    assert {(r.doc_id, r.text) for r in mixed} == set(want) and max(collections.Counter((r.doc_id, r.text) for r in mixed).values()) <= 3
