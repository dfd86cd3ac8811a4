"""Substring dedup over words by seed and extend.

Seeds are winnowed anchors: the first least 8-word gram of each 20-word window, so equal
windows have their seed at the same place.  Documents are joined on their seeds in hash
buckets; a seed that occurs once is dropped.  The occurrences of a seed are extended word by
word to both sides, all at once: after each step, those are still together whose words are
the same so far.  A window of k words before its seed is a repeat of an earlier place if an
occurrence there is together with it after k steps to the left and the rest to the right.
Neighbouring and overlapping repeats merge into maximal ones, whose words go.

Hashes only choose buckets and candidates; words are compared by themselves.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from wavesum.llm.common import flat, spread, strings, sums, word_spans, words_of
from wavesum.llm.repeats import NONE, anchor_hash, bucket_of, cuts, gram_hashes, least_grams, lookup, packed, pipeline, ranges, span_hashes

WINDOW, GRAM, TEXT_BYTES = 20, 8, 6 << 20


def coded_words(texts: pa.Array) -> tuple[np.ndarray, pa.Array, np.ndarray]:
    """A number for each word, the different words by number, and the word offsets by document."""
    words, by_doc = words_of(texts)
    coded = pc.dictionary_encode(words)
    return coded.indices.to_numpy().astype(np.int64), coded.dictionary, by_doc


def hashes_of(words: pa.Array) -> np.ndarray:
    data, offs = flat(words)
    return span_hashes(data, np.diff(offs))


def word_symbols(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """A 64-bit hash of each word, and the word offsets by document."""
    codes, words, by_doc = coded_words(texts)
    return (hashes_of(words)[codes] if len(codes) else np.zeros(0, np.uint64)), by_doc


def first_least(h: np.ndarray, w: int) -> np.ndarray:
    """Place of the least of each w neighbours, the first of equal ones."""
    at, have = np.arange(len(h)), 1
    better = lambda a, b: np.where(h[a] <= h[b], a, b)
    while have * 2 <= w:
        at = better(at[: len(at) - have], at[have:])
        have *= 2
    n = len(h) - w + 1
    return better(at[:n], at[w - have : w - have + n]) if have < w else at[:n]


def seeds(symbols: np.ndarray, docs: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Runs of neighbouring windows with one seed: first window, number of windows, the seed's place, its anchor."""
    h, _, valid = least_grams(symbols, docs, window, gram)
    if not valid.any():
        return (*(np.zeros(0, np.int64) for _ in range(3)), np.zeros(0, np.uint64))
    place = first_least(h, window - gram + 1)
    first = valid.copy()
    first[1:] &= ~valid[:-1] | (place[1:] != place[:-1])
    starts = np.flatnonzero(first)
    upto = np.append(np.cumsum(valid) - valid, valid.sum())
    count = np.diff(upto[np.append(starts, len(valid))])
    return starts, count, place[starts], anchor_hash(h[place[starts]])


def together(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """A number for each pair (a, b) of small numbers, in order of first appearance."""
    return pd.factorize(a * (int(b.max(initial=0)) + 1) + b)[0].astype(np.int64)


def repeats(codes: np.ndarray, seed: np.ndarray, left: np.ndarray, mask: np.ndarray, doc: np.ndarray, begin: np.ndarray, gram: int) -> np.ndarray:
    """(occurrences, offsets): windows, as mask has them, that an earlier place has too.

    codes: words; seed: the occurrences' places in them; left: the words before the seed that
    are there; mask: the offsets whose windows are asked for; begin: the seed's place in its
    document.  Offset o has o words before the seed.
    """
    n, offsets = mask.shape
    out = np.zeros(mask.shape, bool)
    if not n:
        return out
    order = np.lexsort((begin, doc))
    seed, left, mask, doc, begin = seed[order], left[order], mask[order], doc[order], begin[order]
    right = offsets - 1 - np.where(mask.any(1), mask.argmax(1), offsets - 1)
    same = pd.factorize(codes[seed])[0].astype(np.int64)
    for j in range(1, gram):
        same = together(same, codes[seed + j])
    befores, afters = [same], [same]
    for steps, have, at in ((befores, left, lambda j: -j), (afters, right, lambda j: gram - 1 + j)):
        for j in range(1, offsets):
            longer, there = np.full(n, -1, np.int64), np.flatnonzero(have >= j)
            longer[there] = together(steps[-1][there], codes[seed[there] + at(j)])
            steps.append(longer)
    for o in range(offsets):
        rows = np.flatnonzero(mask[:, o])
        if not len(rows):
            continue
        group = together(befores[o][rows], afters[offsets - 1 - o][rows])
        new = np.ones(len(rows), bool)
        new[1:] = group[1:] > np.maximum.accumulate(group)[:-1]
        first = rows[new][group]  # rows come in order of place, groups by their first row
        out[order[rows], o] = (doc[rows] > doc[first]) | (begin[rows] > begin[first])
    return out


def send(window: int):
    def run(home: int, table: pa.Table, keys: np.ndarray, hot: np.ndarray, buckets: int) -> pa.Table:
        """Occurrences of live seeds with the windows that are first here; later ones are settled here."""
        codes, words, docs = coded_words(table.column("text").combine_chunks())
        names = table.column("doc_id").to_numpy(zero_copy_only=False)
        known = pc.is_valid(table.column("doc_id")).to_numpy(zero_copy_only=False)
        symbols = hashes_of(words)[codes] if len(codes) else np.zeros(0, np.uint64)
        starts, count, seed, anchor = seeds(symbols, docs, window, GRAM)
        live, at = lookup(anchor, buckets, keys)
        live &= known[np.searchsorted(docs, starts, side="right") - 1]
        starts, count, seed, anchor, at = starts[live], count[live], seed[live], anchor[live], at[live]
        if not len(starts):
            return NONE.empty_table()
        row = np.searchsorted(docs, starts, side="right") - 1
        doc, begin = names[row].astype(np.int64), seed - docs[row]
        offsets = np.arange(window - GRAM + 1)
        most, least = seed - starts, seed - starts - count + 1
        mask = (offsets >= least[:, None]) & (offsets <= most[:, None])
        later = repeats(codes, seed, most, mask, doc, begin, GRAM)
        rows = []
        if later.any():
            i, o = np.nonzero(later)
            rows.append((home % buckets, home, 1, ranges(np.sort(seed[i] - o)).tobytes(), b""))
        mask &= ~later
        target, keep = bucket_of(anchor, buckets), mask.any(1)
        many = hot[at]
        if (keep & many).any():
            # the windows of hot seeds go by their own hash, one by one
            i, o = np.nonzero(mask & many[:, None])
            alone = offsets == o[:, None]
            to = bucket_of(gram_hashes(symbols, window)[seed[i] - o], buckets)
            keep &= ~many
            seed, doc, begin = (np.concatenate([x[keep], x[i]]) for x in (seed, doc, begin))
            mask, target = np.concatenate([mask[keep], alone]), np.concatenate([target[keep], to])
        else:
            seed, doc, begin, mask, target = seed[keep], doc[keep], begin[keep], mask[keep], target[keep]
        left = len(offsets) - 1 - mask[:, ::-1].argmax(1)
        right = len(offsets) - 1 - mask.argmax(1)
        data, spans = flat(words)
        order = np.argsort(target, kind="stable")
        e = cuts(target[order])
        bits = mask @ (1 << offsets)
        for lo, hi in zip(e[:-1].tolist(), e[1:].tolist(), strict=True):
            part = order[lo:hi]
            where, _ = spread(left + GRAM + right, seed - left, part)
            used, local = np.unique(codes[where], return_inverse=True)
            size = np.diff(spans)[used]
            raw, _ = spread(np.diff(spans), spans[:-1], used)
            numbers = np.concatenate([[len(part), len(used), len(where)], seed[part], begin[part], left[part], right[part], bits[part], size, local]).astype(np.uint32)
            rows.append((int(target[part[0]]), home, 0, numbers.tobytes(), doc[part].tobytes() + data[raw].tobytes()))
        return packed(rows)

    return run


def compare(window: int):
    offsets = window - GRAM + 1

    def run(bucket: int, table: pa.Table) -> pa.Table:
        """Windows that an earlier place of another home has, back to their homes."""
        rows, got, texts, sizes = [], [], [], []
        words = seen = 0
        for home, kind, numbers, raw in zip(table.column("home").to_pylist(), table.column("kind").to_pylist(), table.column("numbers").to_pylist(), table.column("bytes").to_pylist(), strict=True):
            if kind == 1:
                rows.append((bucket, home, 1, numbers, b""))
                continue
            a = np.frombuffer(numbers, np.uint32).astype(np.int64)
            m, d, n = a[:3].tolist()
            place, begin, left, right, bits = a[3 : 3 + 5 * m].reshape(5, m)
            size, local = a[3 + 5 * m : 3 + 5 * m + d], a[3 + 5 * m + d :]
            length = left + GRAM + right
            got.append((np.full(m, home), place, begin, left, bits, np.frombuffer(raw, np.int64, m), seen + np.cumsum(length) - length + left, local + words))
            texts.append(np.frombuffer(raw, np.uint8, offset=8 * m))
            sizes.append(size)
            words, seen = words + d, seen + n
        if got:
            home, place, begin, left, bits, doc, seed, local = map(np.concatenate, zip(*got, strict=True))
            spans = np.concatenate([[0], np.cumsum(np.concatenate(sizes))])
            codes = pc.dictionary_encode(strings(np.concatenate(texts), spans, pa.large_binary())).indices.to_numpy().astype(np.int64)[local]
            later = repeats(codes, seed, left, (bits[:, None] >> np.arange(offsets) & 1).astype(bool), doc, begin, GRAM)
            i, o = np.nonzero(later)
            home, place = home[i], place[i] - o
            order = np.lexsort((place, home))
            place, home = place[order], home[order]
            e = cuts(home)
            rows += [(bucket, int(home[lo]), 1, ranges(place[lo:hi]).tobytes(), b"") for lo, hi in zip(e[:-1].tolist(), e[1:].tolist(), strict=True)]
        return packed(rows)

    return run


def kept_words(table: pa.Table, docs: np.ndarray, gone: np.ndarray) -> tuple[pa.Array, np.ndarray]:
    """The words left of each document, joined by blanks, and the numbers removed."""
    data, by_text = flat(table.column("text").combine_chunks())
    _, lengths, _, inside = word_spans(data, by_text)
    words = strings(data[inside], np.concatenate([[0], np.cumsum(lengths)]))
    removed = sums(gone, docs)
    offs = np.concatenate([[0], np.cumsum(np.diff(docs) - removed)])
    lists = pa.ListArray.from_arrays(pa.array(offs, pa.int32()), words.filter(pa.array(~gone)))
    return pc.binary_join(lists, pa.scalar(" ", pa.large_string())), removed


def digest(table: pa.Table, symbols: np.ndarray, docs: np.ndarray, gone: np.ndarray) -> pa.Table:
    texts, removed = kept_words(table, docs, gone)
    sha = [hashlib.sha256(t.as_buffer()).hexdigest() for t in texts]
    return pa.table([table.column("doc_id").cast(pa.int64()), pa.array(np.diff(docs), pa.int64()), pa.array(removed), pa.array(sha)], names=["doc_id", "n_words", "n_removed", "kept_sha256"])


def seed_dedup_digest(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 of every document.

    Null texts have no words; a row without doc_id neither loses words nor takes any from
    others; of rows with one doc_id only an earlier start counts as earlier; an empty table
    gives an empty result.
    """
    return pipeline(docs.select("doc_id", "text"), TEXT_BYTES, word_symbols, window, GRAM, True, send(window), compare(window), digest, "doc_id bigint, n_words bigint, n_removed bigint, kept_sha256 string")


def seed_dedup(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """The documents with their repeated words cut out, the rest joined by blanks where anything was cut; all columns kept.

    Rows and cases as in `seed_dedup_digest`; a document that loses all its words stays, with
    an empty text, and one that loses none keeps its text as it is, null included.
    """

    def cut(table: pa.Table, symbols: np.ndarray, offs: np.ndarray, gone: np.ndarray) -> pa.Table:
        texts, removed = kept_words(table, offs, gone)
        text = pc.if_else(pa.array(removed > 0), texts.cast(pa.string()), table.column("text").combine_chunks())
        return table.set_column(table.schema.get_field_index("text"), "text", text)

    return pipeline(docs, TEXT_BYTES, word_symbols, window, GRAM, True, send(window), compare(window), cut, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema))
