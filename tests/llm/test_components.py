"""Components read each link about once, however many rounds a large group of copies needs."""

import random

import pytest

from rotagrad.llm import simhash


def smallest(edges):
    up = {}

    def top(v):
        while up.setdefault(v, v) != v:
            v = up[v]
        return v

    for a, b in edges:
        x, y = top(a), top(b)
        up[max(x, y)] = min(x, y)
    return {v: top(v) for v in list(up)}


def one_large_group(size=400, trees=12, fan=16):
    """A group of near copies as many buckets give it, and a path in an order of chance beside it."""
    rnd, out = random.Random(5), set()
    for _ in range(trees):
        own = sorted(rnd.sample(range(size), size // 2))
        out |= {(own[i], own[(i - 1) // fan]) for i in range(1, len(own))}
    path = rnd.sample(range(size, 2 * size), size)
    return sorted(out | {(max(p), min(p)) for p in zip(path, path[1:])})


def joined_rows(spark, since):
    """Rows that the joins of all queries after ``since`` made."""
    store, total = spark._jsparkSession.sharedState().statusStore(), 0
    for i in range(store.executionsCount()):
        run = store.executionsList().apply(i)
        if run.executionId() > since:
            values, nodes = store.executionMetrics(run.executionId()), store.planGraph(run.executionId()).allNodes()
            for n in (nodes.apply(j) for j in range(nodes.size())):
                for m in (n.metrics().apply(j) for j in range(n.metrics().size())):
                    if "Join" in n.name() and m.name() == "number of output rows" and values.contains(m.accumulatorId()):
                        total += int(values.apply(m.accumulatorId()).replace(",", ""))
    return total


def last_run(spark):
    store = spark._jsparkSession.sharedState().statusStore()
    return max((store.executionsList().apply(i).executionId() for i in range(store.executionsCount())), default=-1)


@pytest.mark.parametrize("kind", ["long", "binary"])
def test_rounds_together_join_few_rows(spark, kind):
    edges = one_large_group()
    as_is = (lambda v: v) if kind == "long" else (lambda v: v.to_bytes(4, "big"))
    given = spark.createDataFrame([(as_is(a), as_is(b)) for a, b in edges], f"a {kind}, b {kind}")
    since = last_run(spark)
    got = {r.v: r.root for r in simhash.components(given).collect()}
    rows = joined_rows(spark, since)
    assert {as_is(v): as_is(r) for v, r in smallest(edges).items()} == {k if kind == "long" else bytes(k): v if kind == "long" else bytes(v) for k, v in got.items()}
    assert 0 < rows < 5 * len(edges), (rows, len(edges))
