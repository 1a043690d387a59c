import pyarrow as pa

from locpref.llm import common


def test_slices_hold_every_row_once_within_bounds(monkeypatch):
    monkeypatch.setattr(common, "SLICE_BYTES", 100)
    texts = ["a" * n for n in (0, 300, 10, 10, 90, 5, 100, 1)] + [None, "é" * 60] + ["x"] * 40
    batch = pa.RecordBatch.from_pydict({"i": list(range(len(texts))), "text": texts})
    parts = list(common.slices(batch, 16))
    assert [x for p in parts for x in p.column("i").to_pylist()] == list(range(len(texts)))
    for p in parts:
        size = sum(len((t or "").encode()) for t in p.column("text").to_pylist())
        assert p.num_rows == 1 or (p.num_rows <= 16 and size <= 100)
    assert list(common.slices(batch.slice(0, 0))) == []
