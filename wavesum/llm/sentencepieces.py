"""SentencePiece ids and decoded texts through a table of distinct marked chunks.

A model whose pieces hold the white-space mark only as a prefix cannot merge across the
place where a mark follows another character.  So every text, after the dummy mark in
front, falls into chunks there; each distinct chunk is segmented once by the library and
the ids go back by position.  A model with other pieces, or one that removes white space,
is refused: `check_model` reads its pieces and tries them out.
"""

from __future__ import annotations

import functools
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from wavesum.llm.chunks import CHUNK_BLOCK, ChunkTable, listed
from wavesum.llm.common import blocks, flat, fresh, strings, sums

#: Chunks that a worker keeps; with their texts and the library's buffers some 400 bytes each.
CAP = 300_000
#: Fixed: the white-space mark of the library.
MARK = "▁"


def check_model(path: str):
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    if any(MARK in model.id_to_piece(i).lstrip(MARK) for i in range(model.get_piece_size())):
        raise ValueError("pieces of this model cross white-space marks")
    if model.decode(model.encode("  a  b ")) != "  a  b ":
        raise ValueError("this model doesn't keep white space")
    return model


@functools.cache
def table(path: str) -> ChunkTable:
    """The table of this worker.  A chunk is stored without its first mark, which the library adds."""
    model = check_model(path)
    mark = [model.piece_to_id(MARK)]

    names = pa.array(map(str, range(model.get_piece_size())), pa.large_string())

    def decoded(_, length: np.ndarray, ids: np.ndarray) -> list[str]:
        flat_ids, ends = ids.tolist(), np.cumsum(length).tolist()
        return model.decode([flat_ids[e - n : e] for e, n in zip(ends, length.tolist(), strict=True)])

    def written_out(_, length: np.ndarray, ids: np.ndarray) -> pa.Array:
        return join_by_doc(names.take(pa.array(ids)), np.concatenate([[0], np.cumsum(length)]))

    encode = lambda texts: listed([x or mark for x in model.encode(texts, num_threads=1)])
    return ChunkTable(encode, {"ids": written_out, "text": decoded}, cap=CAP)


def marked_chunks(texts: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """The chunks of every text without their first mark, and the chunk offsets by text; an empty text has none."""
    data, docs = flat(pc.replace_substring(pc.fill_null(texts.cast(pa.large_string()), ""), MARK, " "))
    border = data == 0x20
    border[1:] &= data[:-1] != 0x20
    border[docs[:-1][docs[:-1] < len(data)]] = False  # a text's first chunk has the dummy mark
    cuts = np.flatnonzero(border)
    starts = docs[:-1][np.diff(docs) > 0]
    begin = np.sort(np.concatenate([starts, cuts]))
    skip = np.zeros(len(data) + 1, np.int64)
    skip[1:] = np.cumsum(border)
    # offsets in the buffer without its borders
    offsets = np.append(begin, len(data))
    return strings(data[~border], offsets - skip[offsets]), np.searchsorted(begin, docs)


def join_by_doc(parts: pa.Array, by_doc: np.ndarray) -> pa.Array:
    lists = pa.ListArray.from_arrays(pa.array(by_doc, pa.int32()), parts)
    return pc.binary_join(lists, pa.scalar(" ", pa.large_string()))


def encoded(texts: pa.Array, path: str) -> tuple[np.ndarray, pa.Array, pa.Array]:
    """For each text: the number of ids, the ids as text, the decoded text (an end id only counts in the first)."""
    t = table(path)
    chunks, by_doc = marked_chunks(texts)
    at = t.index(chunks)
    take = pa.array(at)
    return sums(t.length[at], by_doc), join_by_doc(t.more["ids"].take(take), by_doc), join_by_doc(t.more["text"].take(take), by_doc)


def sentencepiece_digest(docs: DataFrame, path: str, end_id: int = 2) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every text.

    A null or empty text has the end id only and decodes to nothing; repeated rows and null
    ids are passed through; an empty table gives an empty result.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in blocks(batches, limit=CHUNK_BLOCK):
            n, ids, text = encoded(block.column("text"), path)
            tail = str(end_id).encode()
            sha = [hashlib.sha256(x.as_buffer().to_pybytes() + (b" " if x.as_buffer().size else b"") + tail).hexdigest() for x in ids]
            dec = [hashlib.sha256(x.as_buffer()).hexdigest() for x in text]
            yield pa.RecordBatch.from_arrays([block.column("doc_id").cast(pa.int64()), pa.array(n + 1, pa.int64()), pa.array(sha), pa.array(dec)], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])
            pa.default_memory_pool().release_unused()

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string")


def sentencepiece_ids(docs: DataFrame, path: str, end_id: int = 2) -> DataFrame:
    """All columns of docs, and `piece_ids` (array of int, the end id last) and `decoded`."""
    ids_name, text_name = fresh(docs.columns, "piece_ids", "decoded")
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema), f"`{ids_name}` array<int>", f"`{text_name}` string"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from wavesum.llm.common import spread

        for block in blocks(batches, limit=CHUNK_BLOCK >> 1):
            t = table(path)
            chunks, by_doc = marked_chunks(block.column("text"))
            at = t.index(chunks)
            where, offs = spread(t.length, t.begin, at)
            ends = offs[by_doc]
            ids = np.insert(t.ids[where].astype(np.int32), ends[1:], end_id)
            lists = pa.ListArray.from_arrays(pa.array(ends + np.arange(len(ends)), pa.int32()), pa.array(ids))
            text = join_by_doc(t.more["text"].take(pa.array(at)), by_doc)
            yield pa.RecordBatch.from_arrays([*block.columns, lists, text.cast(pa.string())], names=[*block.schema.names, ids_name, text_name])

    return docs.mapInArrow(run, schema)
