"""Batches that the operators hold at once in Python workers."""

from rankfeed.llm import packing
from rankfeed.llm.runtime import BATCH_ROWS, BATCH_SETTING, written


def test_written_hands_small_batches_to_workers_and_restores_the_setting(spark):
    def rows_of(batches):
        import pyarrow as pa

        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows])], names=["n"])

    before = spark.conf.get(BATCH_SETTING)
    sizes = [r.n for r in written(spark.range(0, 12_000, 1, 1).mapInArrow(rows_of, "n long"), "batches").collect()]
    assert sum(sizes) == 12_000 and max(sizes) <= BATCH_ROWS
    assert spark.conf.get(BATCH_SETTING) == before


def test_packing_tokenizes_bounded_pieces_of_text(spark, monkeypatch):
    import numpy as np
    import pyarrow as pa

    seen = []

    class Whole:
        def encode(self, texts):
            seen.append(sum(len(t) for t in texts.to_pylist()))
            return np.zeros(len(texts), "<u4"), np.arange(len(texts) + 1)

    monkeypatch.setattr(packing, "encoder", lambda path: Whole())
    batch = pa.RecordBatch.from_pydict({"doc_id": list(range(9)), "text": ["x" * (1 << 20)] * 9})
    held = {}

    class Docs:
        def select(self, *columns):
            return self

        def mapInArrow(self, run, schema):
            held["run"] = run

    packing.tokenized(Docs(), "path", 8, 0, "doc_id", "text")
    out = list(held["run"](iter([batch])))
    assert sum(b.num_rows for b in out) == 9 and max(seen) <= packing.PIECE_BYTES
