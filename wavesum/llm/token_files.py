"""Token ids in binary segments with Elias-Fano coded document borders.

A segment holds the ids of consecutive documents (ascending doc_id) one after the other,
16 bits each if the vocabulary allows it, and two Elias-Fano sequences: the n + 1 token
offsets of its documents and their ids less the smallest.  A sequence of n values up to u
keeps l = floor(log2(u / n)) low bits of each as a packed array and the rest in unary, so
it takes about 2 + log2(u / n) bits a value; every 64th one bit's place is sampled, and
`select` scans from there.  There is no table of 64-bit offsets.

Segments are written by Spark as rows of a Parquet table, a binary value each, so that any
store that Spark can write will do; the offset of a segment among all tokens is not in it,
but follows from the token counts of the segments before it, which are ordinary columns.
"""

from __future__ import annotations

import functools
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wavesum.llm.chunks import CHUNK_BLOCK, ChunkTable, apart
from wavesum.llm.common import LOWER, blocks, flat, shared_dir, spread, strings, word_spans, words_of

#: Fixed: the format's mark and version, and its header's layout.
MAGIC, HEAD = b"EFTK\x01", "<5sBQQQqQQ"
SAMPLE = 64
#: Place of one bit number j in each byte.
PLACE = np.array([([b for b in range(8) if x >> b & 1] + [0] * 8)[:8] for x in range(256)])


class EliasFano:
    """A non-decreasing sequence of unsigned integers."""

    def __init__(self, n: int, l: int, low: np.ndarray, high: np.ndarray, samples: np.ndarray):
        self.n, self.l, self.low, self.high, self.samples = n, l, low, high, samples

    @classmethod
    def of(cls, values: np.ndarray) -> EliasFano:
        v = values.astype(np.uint64)
        n, u = len(v), int(v[-1]) if len(v) else 0
        l = max(0, (u // max(n, 1)).bit_length() - 1)
        bits = (v[:, None] >> np.arange(l, dtype=np.uint64)) & np.uint64(1)
        ones = ((v >> np.uint64(l)) + np.arange(n, dtype=np.uint64)).astype(np.int64)
        high = np.zeros(int(ones[-1]) + 1 if n else 0, np.uint8)
        high[ones] = 1
        return cls(n, l, np.packbits(bits.astype(np.uint8).ravel(), bitorder="little"), np.packbits(high, bitorder="little"), ones[::SAMPLE].astype(np.uint32))

    def dump(self) -> bytes:
        return struct.pack("<QBQQQ", self.n, self.l, len(self.low), len(self.high), len(self.samples)) + self.low.tobytes() + self.high.tobytes() + self.samples.tobytes()

    @classmethod
    def load(cls, raw: bytes, at: int) -> tuple[EliasFano, int]:
        n, l, a, b, c = struct.unpack_from("<QBQQQ", raw, at)
        at += struct.calcsize("<QBQQQ")
        low, high = np.frombuffer(raw, np.uint8, a, at), np.frombuffer(raw, np.uint8, b, at + a)
        return cls(n, l, low, high, np.frombuffer(raw, np.uint32, c, at + a + b)), at + a + b + 4 * c

    def low_bits(self, i: int) -> int:
        first, last = i * self.l, (i + 1) * self.l
        chunk = int.from_bytes(self.low[first // 8 : -(-last // 8)].tobytes(), "little")
        return chunk >> (first % 8) & ((1 << self.l) - 1)

    def select(self, i: int) -> int:
        """Value number i."""
        if not 0 <= i < self.n:
            raise IndexError(i)
        at, left = int(self.samples[i // SAMPLE]), i % SAMPLE
        byte = at // 8
        word = int(self.high[byte]) & (0xFF << (at % 8))
        while left >= (k := word.bit_count()):
            left -= k
            byte += 1
            word = int(self.high[byte])
        for _ in range(left):
            word &= word - 1
        place = byte * 8 + ((word & -word).bit_length() - 1)
        return (place - i) << self.l | self.low_bits(i)

    def select_many(self, i: np.ndarray) -> np.ndarray:
        """Values number i, as `select` gives them: the sampled place before each, then whole bytes, then bits."""
        if not len(i):
            return np.zeros(0, np.uint64)
        if not 0 <= int(i.min()) <= int(i.max()) < self.n:
            raise IndexError(i)
        first = self.samples[int(i.min()) // SAMPLE] // 8
        last = int(self.samples[int(i.max()) // SAMPLE + 1]) // 8 + 1 if int(i.max()) // SAMPLE + 1 < len(self.samples) else len(self.high)
        part = self.high[first:last].copy()
        skip = int(self.samples[int(i.min()) // SAMPLE]) % 8
        part[0] &= np.uint8(0xFF << skip & 0xFF)
        upto = np.cumsum(np.bitwise_count(part), dtype=np.int64)
        rank = i - int(i.min()) // SAMPLE * SAMPLE
        byte = np.searchsorted(upto, rank, side="right")
        left = rank - (upto[byte] - np.bitwise_count(part[byte]))
        place = (int(first) + byte) * 8 + PLACE[part[byte], left]
        bits = i[:, None] * self.l + np.arange(self.l)
        low = (self.low[bits >> 3] >> (bits & 7).astype(np.uint8) & np.uint8(1)).astype(np.uint64) @ np.left_shift(np.uint64(1), np.arange(self.l, dtype=np.uint64)) if self.l else np.uint64(0)
        return ((place - i).astype(np.uint64) << np.uint64(self.l)) + low

    def all(self) -> np.ndarray:
        ones = np.flatnonzero(np.unpackbits(self.high, bitorder="little"))[: self.n].astype(np.uint64)
        low = np.unpackbits(self.low, bitorder="little", count=self.n * self.l).reshape(self.n, self.l)
        weights = np.left_shift(np.uint64(1), np.arange(self.l, dtype=np.uint64))
        return ((ones - np.arange(self.n, dtype=np.uint64)) << np.uint64(self.l)) + (low.astype(np.uint64) @ weights if self.l else np.uint64(0))


def pack(doc_ids: np.ndarray, nulls: int, lengths: np.ndarray, ids: np.ndarray, width: int) -> bytes:
    """A segment.  doc_ids: ascending, without the `nulls` null ones, which come first."""
    base = int(doc_ids[0]) if len(doc_ids) else 0
    names = EliasFano.of(doc_ids.astype(np.int64).view(np.uint64) - np.uint64(base % (1 << 64))).dump()
    borders = EliasFano.of(np.concatenate([[0], np.cumsum(lengths, dtype=np.int64)])).dump()
    head = struct.pack(HEAD, MAGIC, width, len(lengths), len(ids), nulls, base, len(names), len(borders))
    return head + names + borders + ids.astype(f"<u{width}").tobytes()


class Segment:
    """A segment read back: `offset(i)` by select, ids of document i without touching the others."""

    def __init__(self, raw: bytes):
        magic, self.width, self.n, self.tokens, self.nulls, self.base, names, borders = struct.unpack_from(HEAD, raw, 0)
        if magic != MAGIC:
            raise ValueError("not a token segment")
        at = struct.calcsize(HEAD)
        self.names, _ = EliasFano.load(raw, at)
        self.borders, _ = EliasFano.load(raw, at + names)
        self.ids = np.frombuffer(raw, f"<u{self.width}", self.tokens, at + names + borders)

    def offset(self, i: int) -> int:
        return self.borders.select(i)

    def document(self, i: int) -> np.ndarray:
        return self.ids[self.offset(i) : self.offset(i + 1)]

    def doc_ids(self) -> list[int | None]:
        names = self.names.select_many(np.arange(self.names.n))
        return [None] * self.nulls + (names + np.uint64(self.base % (1 << 64))).view(np.int64).tolist()

    def offsets(self) -> np.ndarray:
        """The offsets of all documents and the end."""
        return self.borders.select_many(np.arange(self.n + 1)).astype(np.int64)


#: Fixed: ASCII letters, and ASCII punctuation.
LETTER, PUNCTUATION = (np.array([c < 128 and f(chr(c)) for c in range(256)]) for f in (str.isalpha, lambda x: x.isprintable() and not x.isalnum() and x != " "))


@functools.cache
def tokens(path: str) -> tuple[ChunkTable, int, bool]:
    """The worker's table of chunks, the bytes an id takes, and whether a word falls into chunks after letters and has no case."""
    import json
    import os

    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(path)
    with open(path) as f:
        parts = json.load(f)
    flatten = lambda x, key: [z for y in x[key] for z in flatten(y, key)] if x and key in x else [x or {}]
    lower = any(x.get("type") == "Lowercase" for x in flatten(parts["normalizer"], "normalizers"))
    patterns = [x["pattern"].get("Regex", "").split("|") for x in flatten(parts["pre_tokenizer"], "pretokenizers") if x.get("type") == "Split" and x.get("behavior") == "Removed" and x.get("invert")]
    apart_ = any(r"[\p{L}]+" in x and r"[^\s\p{L}\p{N}]+" in x and all(y.startswith(("'", "[")) for y in x) for x in patterns)
    return ChunkTable(apart(t)), 2 if t.get_vocab_size() <= 1 << 16 else 4, lower and apart_


def chunks_of(texts: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """The texts' words in lower case (A-Z) and cut where punctuation follows a letter, and chunk offsets by text.

    Words with the start of an added token's spelling stay as they are.
    """
    data, docs = flat(texts)
    _, lengths, by_doc, inside = word_spans(data, docs)
    body = data[inside]
    ends = np.cumsum(lengths)
    border = np.zeros(len(body), bool)
    border[1:] = LETTER[body[:-1]] & PUNCTUATION[body[1:]]
    small = LOWER[body]
    marks = np.flatnonzero((body[:-1] == ord("<")) & (body[1:] == ord("|")))
    for w in np.unique(np.searchsorted(ends, marks, side="right")).tolist():
        lo, hi = int(ends[w] - lengths[w]), int(ends[w])
        border[lo:hi] = False
        small[lo:hi] = body[lo:hi]
    border[ends - lengths] = True
    begin = np.flatnonzero(border)
    upto = np.append(ends - lengths, len(body))[by_doc]
    return strings(small, np.append(begin, len(body))), np.searchsorted(begin, upto)


def word_ids(texts: pa.Array, path: str, end_id: int) -> tuple[np.ndarray, np.ndarray]:
    """ids of all texts, an end id after each, and the n + 1 offsets.

    The tokenizer drops white space and its pieces end where it stands, and if its rules say
    so after a run of letters too, so distinct chunks are encoded once by the library.
    """
    t, _, finer = tokens(path)
    chunks, by_doc = chunks_of(texts) if finer else words_of(texts)
    at = t.index(chunks)
    where, offs = spread(t.length, t.begin, at)
    ends = offs[by_doc]
    return np.insert(t.ids[where], ends[1:], end_id), ends + np.arange(len(ends))


def write_tokens(docs: DataFrame, path: str, tokenizer: str, end_id: int = 1, segment_bytes: int = CHUNK_BLOCK) -> None:
    """Segments of all documents in ascending doc_id order (null ids first, repeated ids by row).

    The one shuffle is by range of (doc_id, row), so a repeated id spreads over tasks.
    """
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.monotonically_increasing_id().alias("row"))
    ordered = keyed.repartitionByRange(F.col("doc_id").asc_nulls_first(), F.col("row")).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "row")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, width = TaskContext.get().partitionId(), tokens(tokenizer)[1]
        for seq, block in enumerate(blocks(batches, limit=segment_bytes)):
            ids, offs = word_ids(block.column("text"), tokenizer, end_id)
            names = block.column("doc_id")
            blob = pack(names.drop_null().to_numpy(), names.null_count, np.diff(offs), ids, width)
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([seq], pa.int32()), pa.array([block.num_rows], pa.int64()), pa.array([len(ids)], pa.int64()), pa.array([blob], pa.binary())], names=["part", "seq", "n_docs", "n_tokens", "segment"])

    ordered.mapInArrow(run, "part int, seq int, n_docs bigint, n_tokens bigint, segment binary").write.mode("overwrite").parquet(path)


def read_tokens(spark, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of each document, from the segments alone."""
    segments = spark.read.parquet(path)
    order = lambda w: w.rowsBetween(Window.unboundedPreceding, -1)
    before = lambda c, w: F.coalesce(F.sum(c).over(order(w)), F.lit(0))
    sizes = segments.select("part", "seq", "n_tokens")
    parts = sizes.groupBy("part").agg(F.sum("n_tokens").alias("n")).select("part", before("n", Window.orderBy("part")).alias("part_start"))
    begin = sizes.select("part", "seq", before("n_tokens", Window.partitionBy("part").orderBy("seq")).alias("own")).join(parts, "part").select("part", "seq", (F.col("part_start") + F.col("own")).alias("begin"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, seq, blob in zip(batch.column("part").to_pylist(), batch.column("seq").to_pylist(), batch.column("segment"), strict=True):
                s = Segment(blob.as_buffer())
                offs = s.offsets()
                wide = memoryview(np.ascontiguousarray(s.ids, "<u4")).cast("B") if s.tokens else memoryview(b"")
                crc = [zlib.crc32(wide[4 * a : 4 * b]) for a, b in zip(offs[:-1].tolist(), offs[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array([part] * s.n, pa.int32()), pa.array([seq] * s.n, pa.int32()), pa.array(s.doc_ids(), pa.int64()), pa.array(offs[:-1]), pa.array(np.diff(offs)), pa.array(crc, pa.int64())], names=["part", "seq", "doc_id", "local", "n_tokens", "ids_crc32"])

    rows = segments.select("part", "seq", "segment").mapInArrow(run, "part int, seq int, doc_id bigint, local bigint, n_tokens bigint, ids_crc32 bigint")
    return rows.join(begin, ["part", "seq"]).select("doc_id", (F.col("begin") + F.col("local")).alias("start"), "n_tokens", "ids_crc32")


def token_file_digest(docs: DataFrame, tokenizer: str, end_id: int = 1) -> DataFrame:
    """Writes the segments into the shared folder and reads them back.

    A null or empty text is the end id alone; an empty table gives no rows.
    """
    import uuid

    path = f"{shared_dir(docs.sparkSession)}/token-segments-{uuid.uuid4().hex}"
    write_tokens(docs, path, tokenizer, end_id)
    return read_tokens(docs.sparkSession, path)
