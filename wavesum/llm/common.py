"""Shared pieces of the text operators: shared-folder tables, bounded Arrow blocks, word tables.

Every kernel works on *blocks*: slices of Arrow batches that hold a bounded number of text
bytes (one longer text makes a block of its own), so memory follows the block and the
longest text, not the partition.
"""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

BLOCK_BYTES = 8 << 20
BLOCK_ROWS = 1 << 14

#: Fixed: the ASCII white space that separates words, `[^\x20\x09-\x0D]+` being a word.
SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
#: Fixed: A-Z to a-z, every other byte as it is.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[ord("A") : ord("Z") + 1] += 32


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster names in spark.checkpoint.dir; a temporary one only on a local master."""
    conf = spark.sparkContext.getConf()
    if base := conf.get("spark.checkpoint.dir"):
        return base.rstrip("/")
    if not conf.get("spark.master", "local").startswith("local") or "cluster" in conf.get("spark.master", ""):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    global _own
    _own = globals().get("_own") or tempfile.mkdtemp(prefix="wavesum-")
    return _own


#: Tables that this process has written and not removed.
_tables: list[str] = []


def cleanup(spark: SparkSession) -> int:
    """Removes the tables that `written` has made; to be called when nothing that reads them is wanted any more."""
    gone = 0
    while _tables:
        path = spark._jvm.org.apache.hadoop.fs.Path(_tables.pop())
        gone += path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
    return gone


def written(df: DataFrame, name: str) -> DataFrame:
    """df as a table in the shared folder, read back: computed once, and safe if executors go."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    _tables.append(path)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def fresh(taken: Iterable[str], *names: str) -> list[str]:
    """Column names made from `names` that don't clash with `taken`, case aside."""
    low, out = {t.lower() for t in taken}, []
    for name in names:
        while name.lower() in low:
            name = f"_{name}"
        low.add(name.lower())
        out.append(name)
    return out


def remainder(doc_id: Column, n: int) -> Column:
    """crc32 of doc_id as text, modulo n; a null id counts as the empty text, so as held out."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % n


def give_back() -> None:
    """Unused memory of this worker back to the system: it stays alive, idle, while other stages run beside it."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc only
    if trim:
        trim(0)


def blocks(batches: Iterable[pa.RecordBatch], text: str = "text", limit: int = BLOCK_BYTES, rows: int = BLOCK_ROWS) -> Iterator[pa.RecordBatch]:
    """Slices of the batches with at most `limit` text bytes each (or one row); memory goes back after the last."""
    for batch in batches:
        if not batch.num_rows:
            continue
        size = np.cumsum(pc.fill_null(pc.binary_length(batch.column(text)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
        at, base = 0, 0
        while at < batch.num_rows:
            end = int(np.searchsorted(size, base + limit, side="right"))
            end = min(max(end, at + 1), at + rows, batch.num_rows)
            yield batch.slice(at, end - at)
            at, base = end, int(size[end - 1])
    give_back()


def flat(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of all texts after each other (null: none), and the n + 1 offsets."""
    texts = pc.fill_null(texts.cast(pa.large_string() if pa.types.is_string(texts.type) else pa.large_binary() if pa.types.is_binary(texts.type) else texts.type), "" if pa.types.is_string(texts.type) or pa.types.is_large_string(texts.type) else b"")
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    _, offs, data = texts.buffers()
    if not len(texts):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    off = np.frombuffer(offs, np.int64)[texts.offset : texts.offset + len(texts) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[off[0] : off[-1]], off - off[0]


def strings(data: np.ndarray, offsets: np.ndarray, kind: pa.DataType | None = None) -> pa.Array:
    """An Arrow string array over a byte buffer."""
    return pa.Array.from_buffers(kind or pa.large_string(), len(offsets) - 1, [None, pa.py_buffer(np.ascontiguousarray(offsets, np.int64)), pa.py_buffer(np.ascontiguousarray(data))])


def word_spans(data: np.ndarray, docs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """starts, lengths of the words; word offsets by document; mask of the bytes in words."""
    inside = ~SPACE[data]
    first, last = inside.copy(), inside.copy()
    first[1:] &= ~inside[:-1]
    last[:-1] &= ~inside[1:]
    # words of neighbouring documents may touch
    edge = docs[:-1][docs[:-1] < len(data)]
    first[edge] = inside[edge]
    edge = docs[1:][docs[1:] > 0] - 1
    last[edge] = inside[edge]
    starts = np.flatnonzero(first)
    lengths = np.flatnonzero(last) + 1 - starts
    return starts, lengths, np.searchsorted(starts, docs), inside


def words_of(texts: pa.Array, lower: bool = False) -> tuple[pa.Array, np.ndarray]:
    """All words of the texts as one Arrow array, and the word offsets by document."""
    data, docs = flat(texts)
    if lower:
        data = LOWER[data]
    _, lengths, by_doc, inside = word_spans(data, docs)
    return strings(data[inside], np.concatenate([[0], np.cumsum(lengths)])), by_doc


def spread(lengths: np.ndarray, begin: np.ndarray, index: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Gather of variable-length runs: positions of run index[0], index[1], ... and offsets of the runs in the result."""
    n = lengths[index]
    offs = np.concatenate([[0], np.cumsum(n, dtype=np.int64)])
    return np.arange(offs[-1], dtype=np.int64) + np.repeat(begin[index] - offs[:-1], n), offs


def sums(values: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Sums of values by consecutive groups, empty groups included."""
    total = np.concatenate([[0], np.cumsum(values, dtype=np.float64 if values.dtype.kind == "f" else np.int64)])
    return total[offsets[1:]] - total[offsets[:-1]]
