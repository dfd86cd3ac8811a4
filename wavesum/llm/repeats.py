"""Repeated passages, found exactly and by hash-partitioned steps.

Shared frame of the suffix-array and the seed-and-extend operators.  Documents get a *home*
(a hash of doc_id and text; a bounded amount of text each) and anchors a *bucket* (the high bits of
their hash).  An anchor is the least gram hash of a window, so equal windows have equal
anchors:

1. every scan block sends its distinct anchors, 4 bytes each in packed rows, to their buckets;
2. a bucket tells the homes which of their anchors occur twice or more;
3. a home sends what it has of the windows with such anchors, each different text once, and
   notes the repeats within itself;
4. a bucket compares the windows of all homes and returns the covered places;
5. the home cuts them out.

Steps 3 and 5 read the documents by home, from one shuffle that Spark reuses.  A group of
copies, however large, sends one copy from each home in steps 1, 3 and 4.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavesum.llm.common import blocks, flat, fresh, give_back, spread

ROWS = "bucket int, home int, kind int, numbers binary, bytes binary"
NAMES = ["bucket", "home", "kind", "numbers", "bytes"]
NONE = pa.schema([("bucket", pa.int32()), ("home", pa.int32()), ("kind", pa.int32()), ("numbers", pa.binary()), ("bytes", pa.binary())])


def packed(rows: list[tuple[int, int, int, bytes, bytes]]) -> pa.Table:
    cols = list(zip(*rows, strict=True)) or [()] * 5
    return pa.table([pa.array(c, t) for c, t in zip(cols, NONE.types, strict=True)], names=NAMES)


def binaries(raw: np.ndarray, offs: np.ndarray) -> pa.Array:
    """An Arrow binary array over a buffer of any numbers; offs: in numbers."""
    return pa.Array.from_buffers(pa.binary(), len(offs) - 1, [None, pa.py_buffer(np.ascontiguousarray(offs * raw.itemsize, np.int32)), pa.py_buffer(np.ascontiguousarray(raw))])


def many_rows(bucket: np.ndarray, home: np.ndarray, kind: int, numbers: pa.Array, more: pa.Array) -> pa.Table:
    """Rows made at once: with many homes and buckets there are more rows than a loop could make."""
    return pa.table([pa.array(bucket, pa.int32()), pa.array(home, pa.int32()), pa.array(np.full(len(numbers), kind, np.int32)), numbers, more], names=NAMES)


def woven(*pieces: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Pieces (uint32 numbers, how many of them each row has) laid after each other row by row: the numbers and the rows' offsets."""
    sizes = np.stack([n for _, n in pieces])
    offs = np.concatenate([[0], np.cumsum(sizes.sum(axis=0))]).astype(np.int64)
    out, at = np.empty(offs[-1], np.uint32), offs[:-1].copy()
    for values, n in pieces:
        out[spread(n, at, np.arange(len(n)))[0]] = values
        at += n
    return out, offs


def unwoven(column: pa.ChunkedArray, kind: type = np.uint32) -> tuple[np.ndarray, np.ndarray]:
    """The numbers of all rows of a binary column, and the offset of each row's."""
    data, offs = flat(column.cast(pa.large_binary()))
    return np.frombuffer(data, kind), offs // np.dtype(kind).itemsize


def packed_bits(flags: np.ndarray, offs: np.ndarray) -> pa.Array:
    """Each row's flags in bytes of their own."""
    size = np.diff(offs)
    ends = np.concatenate([[0], np.cumsum(-(-size // 8))]).astype(np.int64)
    bits = np.zeros(8 * ends[-1], bool)
    bits[spread(size, 8 * ends[:-1], np.arange(len(size)))[0]] = flags
    return binaries(np.packbits(bits), ends)


def unpacked_bits(column: pa.ChunkedArray, size: np.ndarray) -> np.ndarray:
    """The flags of `packed_bits`, `size` of them in each row."""
    raw, offs = unwoven(column, np.uint8)
    return np.unpackbits(raw)[spread(size, 8 * offs[:-1], np.arange(len(size)))[0]].astype(bool)


def mixed(h: np.ndarray) -> np.ndarray:
    """A bijective mix of 64-bit numbers (xor-shifts and odd multipliers)."""
    h = h ^ (h >> np.uint64(31))
    h *= np.uint64(0x7FB5D329728EA185)
    h ^= h >> np.uint64(27)
    h *= np.uint64(0x81DADEF4BC2DD44D)
    h ^= h >> np.uint64(33)
    return h


BASE = 0x9E3779B97F4A7C15 | 1
#: A number for each byte value.
BYTE64 = mixed(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
_powers: dict[str, np.ndarray] = {}
#: Symbols that are hashed at once, and the longest run of powers that is kept.
PIECE = 1 << 18


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of BASE and of its inverse modulo 2^64, up to n of them; n is bounded by the callers' pieces."""
    if len(_powers.get("up", ())) < n:
        size = max(1 << 16, 1 << (n - 1).bit_length())
        for name, base in (("up", BASE), ("down", pow(BASE, -1, 1 << 64))):
            p = np.ones(size, np.uint64)
            k = 1
            while k < size:  # p[k:2k] = p[:k] * base^k
                p[k : 2 * k] = p[:k] * np.uint64(pow(base, k, 1 << 64))
                k *= 2
            _powers[name] = p
    return _powers["up"], _powers["down"]


def gram_hashes(symbols: np.ndarray, k: int) -> np.ndarray:
    """Hash of each run of k symbols (uint64): differences of one running sum, made place-free by the inverse powers.

    Sums begin anew with each piece, so the powers kept don't grow with a text.
    """
    n = len(symbols) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.empty(n, np.uint64)
    up, down = powers(min(PIECE, n) + k)
    for lo in range(0, n, PIECE):
        part = symbols[lo : lo + PIECE + k - 1]
        total = np.zeros(len(part) + 1, np.uint64)
        np.cumsum(part * up[: len(part)], out=total[1:])
        out[lo : lo + PIECE] = mixed((total[k:] - total[:-k]) * down[: len(part) - k + 1])
    return out


def span_hashes(body: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Hash of each of the byte spans that make up body: powers begin anew with each span and, in a long one, each piece."""
    out = np.zeros(len(lengths), np.uint64)
    ends = np.cumsum(lengths)
    lo = 0
    while lo < len(lengths):
        begin = int(ends[lo] - lengths[lo])
        hi = max(lo + 1, int(np.searchsorted(ends, begin + PIECE, side="right")))
        if hi == lo + 1 and lengths[lo] > PIECE:
            h = np.zeros(1, np.uint64)
            up, _ = powers(PIECE)
            for a in range(begin, int(ends[lo]), PIECE):
                part = BYTE64[body[a : min(a + PIECE, int(ends[lo]))]]
                h = mixed(h + (part * up[: len(part)]).sum(dtype=np.uint64, keepdims=True))
            out[lo] = h[0]
        else:
            n, some = lengths[lo:hi], lengths[lo:hi] > 0
            up, _ = powers(max(1, int(n.max())))
            start = ends[lo:hi] - n - begin
            place = np.arange(int(n.sum())) - np.repeat(start, n)
            value = BYTE64[body[begin : begin + len(place)]] * up[place]
            if len(value):
                out[lo:hi][some] = np.add.reduceat(value, start[some])
        lo = hi
    return mixed(out + lengths.astype(np.uint64))


def running_min(h: np.ndarray, w: int) -> np.ndarray:
    """Least of each w neighbours."""
    out, have = h, 1
    while have * 2 <= w:
        out = np.minimum(out[: len(out) - have], out[have:])
        have *= 2
    return np.minimum(out[: len(h) - w + 1], out[w - have : w - have + len(h) - w + 1]) if have < w else out


def least_grams(symbols: np.ndarray, docs: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Gram hashes, the least of each window, and which windows lie in one document."""
    h = gram_hashes(symbols, gram)
    if len(symbols) < window:
        return h, np.zeros(0, np.uint64), np.zeros(0, bool)
    least = running_min(h, window - gram + 1)
    # the last window of a document starts `window` before its end
    edge = np.zeros(len(least) + 1, np.int64)
    long = np.flatnonzero(np.diff(docs) >= window)
    np.add.at(edge, docs[long], 1)
    np.add.at(edge, docs[long + 1] - window + 1, -1)
    return h, least, np.cumsum(edge[:-1]) > 0


def anchor_places(symbols: np.ndarray, docs: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, np.ndarray]:
    """Every place of a gram that is the least, or one of the least, of a window, and its hash."""
    h, least, valid = least_grams(symbols, docs, window, gram)
    if not valid.any():
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    w = window - gram + 1
    # the greatest of the least values of the windows around a place: ~ turns least to greatest
    around = ~np.concatenate([np.full(w - 1, ~np.uint64(0)), ~np.where(valid, least, np.uint64(0)), np.full(w - 1, ~np.uint64(0))])
    top = ~running_min(~around, w)
    places = np.flatnonzero((top[: len(h)] == h) & (h > 0))
    return places, anchor_hash(h[places])


def anchors(symbols: np.ndarray, docs: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Maximal runs of windows of one document with one anchor: first window, number of windows, anchor."""
    _, least, valid = least_grams(symbols, docs, window, gram)
    n = len(least)
    first = np.ones(n, bool)
    first[1:] = (least[1:] != least[:-1]) | ~valid[:-1]
    # windows of neighbouring documents can be neighbours only if a window is one symbol
    inner = docs[:-1][docs[:-1] < n]
    first[inner] = True
    first &= valid
    starts = np.flatnonzero(first)
    # a run ends before the next start or the next place that is no window
    stop = np.append(starts[1:], n)
    last = docs[np.searchsorted(docs, starts, side="right")] - window + 1
    return starts, np.minimum(stop, last) - starts, anchor_hash(least[starts])


def anchor_hash(least: np.ndarray) -> np.ndarray:
    """Least hashes crowd at the low end; mixed once more they spread over all buckets."""
    return mixed(least ^ np.uint64(0xA5A5A5A5A5A5A5A5))


def bucket_of(h: np.ndarray, buckets: int) -> np.ndarray:
    return ((h >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32)).astype(np.int64)


def low(h: np.ndarray) -> np.ndarray:
    return (h & np.uint64(0xFFFFFFFF)).astype(np.uint32)


def sorted_table(t: pa.Table) -> pa.Table:
    """Rows of a home in an order that doesn't depend on their arrival."""
    return t.sort_by([("doc_id", "ascending"), ("text", "ascending")])


def cuts(*keys: np.ndarray) -> np.ndarray:
    """Offsets of the runs of equal keys."""
    n = len(keys[0])
    change = np.zeros(max(n - 1, 0), bool)
    for k in keys:
        change |= k[1:] != k[:-1]
    return np.concatenate([[0], np.flatnonzero(change) + 1, [n]]) if n else np.zeros(1, np.int64)


def anchor_rows(symbols_of: Callable, window: int, gram: int, buckets: int, twice: bool, limit: int) -> Callable:
    """Step 1.  twice: an anchor that a document has twice is repeated (else it takes two documents)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in blocks(batches, limit=limit):
            symbols, docs = symbols_of(block.column("text"))
            places, anchor = anchor_places(symbols, docs, window, gram)
            doc = np.searchsorted(docs, places, side="right") - 1
            home = block.column("home").to_numpy().astype(np.int64)[doc]
            if not twice:
                keep = first_of(doc, anchor)
                home, anchor = home[keep], anchor[keep]
            b = bucket_of(anchor, buckets)
            order = np.lexsort((anchor, home, b))
            b, home, anchor = b[order], home[order], anchor[order]
            c = cuts(b, home, anchor)
            count = np.diff(c)
            b, home, anchor = b[c[:-1]], home[c[:-1]], anchor[c[:-1]]
            if not len(b):
                continue
            # a row for each bucket: the number of homes, these, how many anchors each has, the anchors
            edge, e = cuts(b), cuts(b, home)
            homes = np.diff(np.searchsorted(e, edge))
            one = np.ones(len(homes), np.int64)
            numbers = binaries(*woven((homes, one), (home[e[:-1]], homes), (np.diff(e), homes), (low(anchor), np.diff(edge))))
            yield from many_rows(b[edge[:-1]], np.zeros(len(homes)), 0, numbers, packed_bits(count > 1, edge)).to_batches()

    return run


def first_of(doc: np.ndarray, anchor: np.ndarray) -> np.ndarray:
    """Rows that are the first of their (doc, anchor)."""
    order = np.lexsort((anchor, doc))
    c = cuts(doc[order], anchor[order])
    return order[c[:-1]]


def live_rows(hot: int) -> Callable:
    """Step 2: for each home its anchors that occur again, the low bit of `kind` rows telling the hot ones."""

    def run(key: tuple, table: pa.Table) -> pa.Table:
        bucket = key[0].as_py()
        a, at = unwoven(table.column("numbers"))
        rows, n = np.arange(table.num_rows), a[at[:-1]].astype(np.int64)
        home, count = (a[spread(n, at[:-1] + skip, rows)[0]].astype(np.int64) for skip in (1, 1 + n))
        size = np.diff(at) - 1 - 2 * n
        home, value = np.repeat(home, count), a[spread(size, at[:-1] + 1 + 2 * n, rows)[0]]
        multi = unpacked_bits(table.column("bytes"), size)
        order = np.argsort(value, kind="stable")
        home, value, multi = home[order], value[order], multi[order]
        c = cuts(value)
        size = np.diff(c)
        total = size + np.add.reduceat(multi.astype(np.int64), c[:-1]) if len(size) else size
        live, many = np.repeat(total > 1, size), np.repeat(size > hot, size)
        home, value, many = home[live], value[live], many[live]
        order = np.lexsort((value, home))
        home, value, many = home[order], value[order], many[order]
        c = cuts(home, value)
        home, value, many = home[c[:-1]], value[c[:-1]], many[c[:-1]]
        e = cuts(home)
        return many_rows(np.full(len(e) - 1, bucket), home[e[:-1]], 0, binaries(value, e), packed_bits(many, e))

    return run


def live_set(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """The home's live anchors as (bucket << 32 | low bits), ascending, and which of them are hot."""
    value, at = unwoven(table.column("numbers"))
    size = np.diff(at)
    keys = np.repeat(table.column("bucket").to_numpy().astype(np.uint64) << np.uint64(32), size) | value.astype(np.uint64)
    hot = unpacked_bits(table.column("bytes"), size)
    order = np.argsort(keys)
    return keys[order], hot[order]


def lookup(anchor: np.ndarray, buckets: int, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which anchors are live, and their places in keys."""
    key = bucket_of(anchor, buckets).astype(np.uint64) << np.uint64(32) | low(anchor).astype(np.uint64)
    at = np.minimum(np.searchsorted(keys, key), max(len(keys) - 1, 0))
    return (keys[at] == key if len(keys) else np.zeros(len(key), bool)), at


def covered(table: pa.Table, n: int, window: int) -> np.ndarray:
    """Mask of the symbols in windows that start in the ranges (uint32 pairs) of the rows."""
    edge = np.zeros(n + 1, np.int64)
    a = unwoven(table.column("numbers"))[0].astype(np.int64)
    np.add.at(edge, a[0::2], 1)
    np.add.at(edge, np.minimum(a[1::2] - 1 + window, n), -1)
    return np.cumsum(edge[:-1]) > 0


def ranges(starts: np.ndarray) -> np.ndarray:
    """Ascending places as uint32 pairs of half-open ranges."""
    if not len(starts):
        return np.zeros(0, np.uint32)
    c = np.concatenate([[0], np.flatnonzero(np.diff(starts) != 1) + 1, [len(starts)]])
    return np.stack([starts[c[:-1]], starts[c[1:] - 1] + 1], axis=1).astype(np.uint32).ravel()


def plan(docs: DataFrame, text_bytes: int, home: str) -> tuple[DataFrame, int, int]:
    """docs with a home, and the number of homes and buckets: both follow the total size of the texts.

    A home is drawn by doc_id and text, so rows that share an id, or have none, spread.
    """
    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    homes, buckets = max(1, -(-total // text_bytes)), max(1, -(-total // (2 * text_bytes)))
    return docs.withColumn(home, F.pmod(F.xxhash64("doc_id", "text"), F.lit(homes)).cast("int")), homes, buckets


def pipeline(docs: DataFrame, text_bytes: int, symbols_of: Callable, window: int, gram: int, twice: bool, send: Callable, compare: Callable, cut: Callable, schema: str, hot: int = 4096) -> DataFrame:
    """The five steps as one lazy plan.  docs: any columns, doc_id and text among them.

    send(home, docs table, live keys, hot, buckets), compare(bucket, table) and cut(docs
    table, symbols, offsets, mask) are the steps 3, 4 and 5 of the operator.
    """
    (name,) = fresh(docs.columns, "home")
    homed, _, buckets = plan(docs, text_bytes, name)
    first = homed.select(F.col(name).alias("home"), "text").mapInArrow(anchor_rows(symbols_of, window, gram, buckets, twice, text_bytes), ROWS)
    live = first.groupBy("bucket").applyInArrow(live_rows(hot), ROWS)
    at_home = homed.groupBy(name)

    def third(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        give_back()
        keys, many = live_set(right)
        return send(key[0].as_py(), sorted_table(left), keys, many, buckets) if left.num_rows and len(keys) else NONE.empty_table()

    def fifth(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        give_back()
        left = sorted_table(left).drop_columns([name])
        symbols, offs = symbols_of(left.column("text").combine_chunks() if left.num_rows else pa.array([], pa.string()))
        return cut(left, symbols, offs, covered(right, len(symbols), window))

    sent = at_home.cogroup(live.groupBy("home")).applyInArrow(third, ROWS)
    back = sent.groupBy("bucket").applyInArrow(lambda key, t: compare(key[0].as_py(), t), ROWS)
    return at_home.cogroup(back.groupBy("home")).applyInArrow(fifth, schema)
