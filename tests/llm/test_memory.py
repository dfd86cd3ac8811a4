"""What workers keep between stages."""

import pyarrow as pa

from wavesum.llm import common, sentencepieces


def test_blocks_give_memory_back_after_the_last(monkeypatch):
    calls = []
    monkeypatch.setattr(common, "give_back", lambda: calls.append(1))
    batch = pa.RecordBatch.from_arrays([pa.array(["a b", None, "c" * 50])], names=["text"])
    assert [b.num_rows for b in common.blocks([batch, batch], limit=10)] == [2, 1, 2, 1] and calls == [1]


def test_two_workers_tables_leave_room_for_the_heap():
    # some 400 bytes a chunk as measured; a worker beside another and a heap of 1,800 MB
    assert sentencepieces.CAP * 400 <= 150e6


def test_emptied_tables_change_no_ids():
    from wavesum.llm.queries import vocabulary

    path = vocabulary("piece_bpe_32k.model")
    texts, table = pa.array(["one two three", "two  four", None, "five one"]), sentencepieces.table(path)
    want = [x.to_pylist() if hasattr(x, "to_pylist") else x.tolist() for x in sentencepieces.encoded(texts, path)]
    cap, table.cap = table.cap, 2
    try:
        for i in range(len(texts)):
            got = sentencepieces.encoded(texts[i : i + 1], path)
            assert [x[0].as_py() if hasattr(x[0], "as_py") else x[0] for x in got] == [w[i] for w in want]
    finally:
        table.cap = cap
