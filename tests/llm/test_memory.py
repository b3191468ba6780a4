"""Python tasks give their freed memory back when they end."""

import numpy as np
import pyarrow as pa
import pytest

from blockmf.llm import common, near_dedup, packing


def test_tasks_give_back_at_their_end(monkeypatch):
    calls = []
    monkeypatch.setattr(common, "give_back", lambda: calls.append(1))
    idf = near_dedup.Idf(np.zeros(0, np.uint64), np.zeros(0, np.float32), 1.25, np.zeros(1 << 16, bool))
    batch = pa.RecordBatch.from_pydict({"doc_id": [1], "text": ["one two three four five six"]})
    texts = batch.select(["text"])
    tasks = [(near_dedup._count_df(5, 1 << 16), texts), (near_dedup._count_exactly(5, np.ones(16, bool)), texts), (near_dedup._signatures(5, 24, idf), batch)]
    for k, (task, rows) in enumerate(tasks, 1):
        assert sum(b.num_rows for b in task(iter([rows]))) > 0
        assert len(calls) == k
    for task in (near_dedup._verify(5, idf), near_dedup._cross(24, 3, 13, None), packing._pieces("unused", 0, 2048)):
        assert task.__qualname__.startswith("lean.")


def test_given_back_also_after_an_error(monkeypatch):
    calls = []
    monkeypatch.setattr(common, "give_back", lambda: calls.append(1))

    def broken(batches):
        yield 1
        raise ValueError("broken")

    with pytest.raises(ValueError):
        list(common.lean(broken)(iter([])))
    assert calls == [1]


def test_slices_are_small():
    ends = np.arange(1, 65) * (100 << 10)
    assert all(ends[j - 1] - (ends[i - 1] if i else 0) <= 1 << 20 for i, j in near_dedup._cut_batch(np.zeros(0, np.uint8), ends))
