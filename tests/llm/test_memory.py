"""Stages leave no model and no freed memory in the workers they used."""

import pyarrow as pa

from rotagrad.llm import common


def test_a_task_returns_memory_and_only_stages_with_a_model_keep_one(monkeypatch):
    returned = []
    monkeypatch.setattr(common, "return_memory", lambda: returned.append(1))
    monkeypatch.setattr(common, "_kept", {})
    common.one_per_worker("model", object)
    same = lambda batches: (b for b in batches)
    assert list(common.freed(same, model=True)(iter([1, 2]))) == [1, 2]
    assert "model" in common._kept and len(returned) == 1
    left = common.freed(same)(iter([1, 2]))
    assert next(left) == 1 and not common._kept
    left.close()
    assert len(returned) == 2
    monkeypatch.undo()
    common.return_memory()


def test_slices_hold_every_row():
    for n in (0, 1, 512, 513, 2000):
        parts = list(common.in_slices(pa.RecordBatch.from_pydict({"x": list(range(n))}, pa.schema([("x", pa.int64())]))))
        assert [x for p in parts for x in p.column(0).to_pylist()] == list(range(n))
        assert max(p.num_rows for p in parts) <= common.ROWS
