"""Exact substring dedup over bytes by blockwise suffix sorting.

A byte goes if a string of `length` bytes that covers it also starts in a document with a
smaller doc_id.  Windows that no other document can share are set aside by their anchors
(see `repeats`); the texts of the others meet by anchor bucket, where their suffixes are
sorted one prefix bucket at a time with the ranks of a difference-cover sample
(`suffixes`).  Neighbours in that order with `length` equal bytes are one string, and its
smallest doc_id keeps it.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from wavesum.llm.common import flat, spread, strings, sums
from wavesum.llm.repeats import BYTE64, NAMES, NONE, anchors, binaries, bucket_of, cuts, gram_hashes, lookup, many_rows, mixed, packed, pipeline, unwoven, woven
from wavesum.llm.suffixes import CoverSuffixes, same_prefix

LENGTH, GRAM, TEXT_BYTES = 50, 20, 2_000_000


def byte_symbols(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    data, docs = flat(texts)
    return BYTE64[data], docs


def send(length: int):
    def run(home: int, table: pa.Table, keys: np.ndarray, hot: np.ndarray, buckets: int) -> pa.Table:
        """Each different live segment once with its first document; repeats in later documents are settled here."""
        data, docs = flat(table.column("text").combine_chunks())
        names = table.column("doc_id").to_numpy(zero_copy_only=False)
        known = pc.is_valid(table.column("doc_id")).to_numpy(zero_copy_only=False)
        symbols = BYTE64[data]
        starts, count, anchor = anchors(symbols, docs, length, GRAM)
        live, at = lookup(anchor, buckets, keys)
        live &= known[np.searchsorted(docs, starts, side="right") - 1]
        starts, count, anchor, many = starts[live], count[live], anchor[live], hot[at[live]]
        target = bucket_of(anchor, buckets)
        if many.any():
            # the windows of hot anchors go by their own hash, one by one
            each, _ = spread(count, starts, np.flatnonzero(many))
            target = np.concatenate([target[~many], bucket_of(gram_hashes(symbols, length)[each], buckets)])
            starts, count = np.concatenate([starts[~many], each]), np.concatenate([count[~many], np.ones(len(each), np.int64)])
        if not len(starts):
            return NONE.empty_table()
        order = np.argsort(starts, kind="stable")
        starts, count, target = starts[order], count[order], target[order]
        size = count + length - 1
        where, offs = spread(size, starts, np.arange(len(starts)))
        coded = pc.dictionary_encode(strings(data[where], offs, pa.large_binary()))
        code = coded.indices.to_numpy().astype(np.int64)
        doc = names[np.searchsorted(docs, starts, side="right") - 1].astype(np.int64)
        order = np.argsort(code, kind="stable")
        owner = order[cuts(code[order])[:-1]]  # documents come in the order of doc_id
        later = doc > doc[owner][code]
        out = []
        if later.any():
            flags = np.stack([starts[later], starts[later] + count[later]], axis=1).astype(np.uint32)
            out.append(packed([(home % buckets, home, 1, flags.tobytes(), b"")]))
        mine = np.flatnonzero(~later)
        mine = mine[np.lexsort((starts[mine], code[mine], target[mine]))]
        # a row for each bucket: m segments, k places; m sizes, m counts of places, the places, m doc_ids
        c = cuts(target[mine], code[mine])
        one, n_occ = mine[c[:-1]], np.diff(c)
        edge = cuts(target[one])
        m, k = np.diff(edge), np.diff(c[edge])
        head = np.stack([m, k], axis=1).ravel()
        numbers = woven((head, np.full(len(m), 2)), (size[one], m), (n_occ, m), (starts[mine], k), (doc[one].view(np.uint32), 2 * m))
        where, offs = spread(size, starts, one)
        to = target[one[edge[:-1]]]
        out.append(many_rows(to, np.full(len(to), home), 0, binaries(*numbers), binaries(data[where], offs[edge])))
        return pa.concat_tables(out)

    return run


def compare(length: int):
    def run(bucket: int, table: pa.Table) -> pa.Table:
        """Suffix order of the bucket's segments; windows whose string an earlier document has go back to their homes."""
        settled = pc.equal(table.column("kind"), 1)
        out, table = [table.filter(settled)], table.filter(pc.invert(settled))
        if table.num_rows:
            a, at = unwoven(table.column("numbers"))
            at, each = at[:-1], np.arange(table.num_rows)
            m, k = a[at].astype(np.int64), a[at + 1].astype(np.int64)
            size, n_occ, place = (a[spread(n, at + skip, each)[0]].astype(np.int64) for n, skip in ((m, 2), (m, 2 + m), (k, 2 + 2 * m)))
            doc = np.ascontiguousarray(a[spread(2 * m, at + 2 + 2 * m + k, each)[0]]).view(np.int64)
            home = np.repeat(table.column("home").to_numpy().astype(np.int64), m)
            text, _ = unwoven(table.column("bytes"), np.uint8)
            base, first_occ = np.cumsum(size) - size, np.cumsum(n_occ) - n_occ
            count = size - length + 1
            # equal segments of several homes: the smallest doc_id's stands for them, later ones go as a whole
            code = pc.dictionary_encode(strings(text, np.append(base, len(text)), pa.large_binary())).indices.to_numpy().astype(np.int64)
            least = np.full(int(code.max()) + 1 if len(code) else 0, np.iinfo(np.int64).max)
            np.minimum.at(least, code, doc)
            whole = np.flatnonzero(doc > least[code])
            where, _ = spread(n_occ, first_occ, whole)
            span = np.repeat(count[whole], n_occ[whole])
            absolute, _ = spread(span, place[where], np.arange(len(where)))
            to = np.repeat(np.repeat(home[whole], n_occ[whole]), span)
            own = np.flatnonzero(doc == least[code])
            own = own[np.argsort(code[own], kind="stable")]
            edge = cuts(code[own])
            one = own[edge[:-1]]  # a segment of each kind; those of the same doc_id share its verdict
            sharers, first_sharer = np.diff(edge), edge[:-1]
            where, offs = spread(size, base, one)
            text = text[where]
            base_one, doc_one = offs[:-1], doc[one]
            positions, _ = spread(count[one], base_one, np.arange(len(one)))
            segment_at = np.zeros(len(text), np.int32)
            segment_at[positions] = np.repeat(np.arange(len(one)), count[one])
            flagged = [np.zeros(0, np.int64)]
            suffixes = CoverSuffixes(text, depth=length)
            for order in suffixes.buckets(positions):
                same = same_prefix(suffixes.first, order, length)
                group = np.cumsum(~same) - 1
                d = doc_one[segment_at[order]]
                first_doc = np.minimum.reduceat(d, np.flatnonzero(~same)) if len(d) else d
                flagged.append(order[d > first_doc[group]])
            flagged = np.concatenate(flagged)
            seg = segment_at[flagged]
            which, _ = spread(sharers, first_sharer, seg)
            which, at = own[which], np.repeat(flagged - base_one[seg], sharers[seg])
            where, _ = spread(n_occ, first_occ, which)
            absolute = np.concatenate([absolute, place[where] + np.repeat(at, n_occ[which])])
            to = np.concatenate([to, np.repeat(home[which], n_occ[which])])
            order = np.lexsort((absolute, to))
            absolute, to = absolute[order], to[order]
            e = cuts(to, absolute - np.arange(len(absolute)))
            spans = np.stack([absolute[e[:-1]], absolute[e[1:] - 1] + 1], axis=1).astype(np.uint32).ravel()
            to = to[e[:-1]]
            h = cuts(to)
            out.append(many_rows(np.full(len(h) - 1, bucket), to[h[:-1]], 1, binaries(spans, 2 * h), binaries(np.zeros(0, np.uint8), np.zeros(len(h), np.int64))))
        return pa.concat_tables([t.select(NAMES).cast(NONE) for t in out])

    return run


def digest(table: pa.Table, symbols: np.ndarray, docs: np.ndarray, gone: np.ndarray) -> pa.Table:
    data, _ = flat(table.column("text").combine_chunks())
    begins = gone.copy()
    begins[1:] &= ~gone[:-1]
    edge = docs[:-1][docs[:-1] < len(gone)]
    begins[edge] = gone[edge]
    removed = sums(gone, docs)
    kept, offs = data[~gone].tobytes(), np.concatenate([[0], np.cumsum(np.diff(docs) - removed)])
    view = memoryview(kept)
    sha = [hashlib.sha256(view[a:b]).hexdigest() for a, b in zip(offs[:-1].tolist(), offs[1:].tolist(), strict=True)]
    return pa.table([table.column("doc_id").cast(pa.int64()), pa.array(np.diff(docs)), pa.array(removed), pa.array(sums(begins, docs)), pa.array(sha)], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])


def suffix_dedup_digest(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of every document.

    Null texts are empty; a row without doc_id neither loses bytes nor takes any from
    others; rows with one doc_id don't count as earlier than each other; texts shorter than
    `length` stay whole; an empty table gives an empty result.
    """
    schema = "doc_id bigint, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string"
    return pipeline(docs.select("doc_id", "text"), TEXT_BYTES, byte_symbols, length, GRAM, False, send(length), compare(length), digest, schema)


def suffix_dedup(docs: DataFrame, length: int = LENGTH, text: str = "text") -> DataFrame:
    """The documents with their repeated bytes cut out, and all their columns.

    Cut places inside a character drop what is left of it.  A document that loses all its
    bytes is left out.
    """
    fields = [f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema]

    def cut(table: pa.Table, symbols: np.ndarray, offs: np.ndarray, gone: np.ndarray) -> pa.Table:
        data, _ = flat(table.column("text").combine_chunks())
        removed = sums(gone, offs)
        raw, ends = data[~gone].tobytes(), np.concatenate([[0], np.cumsum(np.diff(offs) - removed)]).tolist()
        texts = table.column("text").to_pylist()
        for i in np.flatnonzero(removed).tolist():
            texts[i] = raw[ends[i] : ends[i + 1]].decode("utf-8", "ignore")
        out = table.set_column(table.schema.get_field_index("text"), "text", pa.array(texts, pa.string()))
        if "n_chars" in table.schema.names:
            out = out.set_column(out.schema.get_field_index("n_chars"), "n_chars", pa.array([None if t is None else len(t) for t in texts], pa.int64()))
        return out.filter(pa.array((removed == 0) | (np.diff(ends) > 0)))

    return pipeline(docs, TEXT_BYTES, byte_symbols, length, GRAM, False, send(length), compare(length), cut, ", ".join(fields))
