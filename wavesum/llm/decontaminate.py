"""Benchmark decontamination by the CGK embedding and bit-sampling LSH.

Texts and items are sequences of lower-cased words without their outer punctuation.  A
document is contaminated by an item of n words if some part of it is within word edit
distance floor(0.3 n).

1. Screen, without loss: a window within k edits of an n-word item with q different word
   pairs has at least q - 2k of them, so windows with fewer different ones among the pairs of
   the items of that length are left out.
2. CGK embedding: a random walk over a sequence repeats or advances at each step by a random
   bit of the current word, so sequences at a small edit distance get embeddings at a small
   Hamming distance.  There are WALKS walks, and from each a number of tables that sample a
   few of its 3n steps; equal samples make a candidate.  The number of tables is the least
   power of two that finds the target share of items with k random edits; for a length that
   no number up to the largest does it for (very short items), every item that shares a word
   pair with a window, or is its one word, is a candidate, which loses nothing.
3. Every candidate is verified by the exact edit distance of the item to the best part of
   the text around the window.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavesum.llm.common import LOWER, blocks, flat, spread, word_spans
from wavesum.llm.repeats import mixed, span_hashes

SHARE, RECALL, SAMPLED = 0.3, 0.99, 3
#: The pipeline's filter: an item of fewer words is found, but is no reason to drop a document.
TELLING_WORDS = 5
WALKS = 6
GATHER = 2_000_000
#: Items are broadcast in groups of at most so many bytes of text and so many items: an item's keys take 6 kB at most.
ITEM_BYTES, ITEMS = 8 << 20, 1 << 14
PAD = np.uint64(0x5851F42D4C957F2D)

#: ASCII punctuation counts as a blank at a word's edges and inside it alike.
PLAIN = LOWER.copy()
PLAIN[[b for b in range(33, 127) if not chr(b).isalnum()]] = 0x20


def plain_words(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """A hash of each word of the texts, and the word offsets by text."""
    data, docs = flat(texts)
    data = PLAIN[data]
    _, lengths, by_doc, inside = word_spans(data, docs)
    return span_hashes(data[inside], lengths), by_doc


def allowed(n: int) -> int:
    return int(SHARE * n)


def walk(symbols: np.ndarray, start: np.ndarray, length: np.ndarray, seed: int, steps: np.ndarray) -> np.ndarray:
    """The embedding at the ascending `steps` for each sequence symbols[start : start + length]."""
    rng = np.random.default_rng(seed)
    salts = rng.integers(1, 1 << 63, int(steps[-1]) + 1, dtype=np.uint64)
    at, out = np.zeros(len(start), np.int64), np.empty((len(start), len(steps)), np.uint64)
    for j, salt in enumerate(salts):
        word = np.where(at < length, symbols[np.minimum(start + at, len(symbols) - 1)], PAD)
        if (k := np.searchsorted(steps, j)) < len(steps) and steps[k] == j:
            out[:, k] = word
        at += (mixed(word ^ salt) >> np.uint64(63)).astype(np.int64)
    return out


class Items:
    """The items of one group, by length, with their word pairs and hash tables."""

    def __init__(self, ids: list, texts: list[str]):
        self.symbols, by = plain_words(pa.array(texts, pa.string()))
        self.ids, self.begin, self.length = ids, by[:-1].copy(), np.diff(by)
        self.classes = {}
        for n in np.unique(self.length[self.length > 0]).tolist():
            rows = np.flatnonzero(self.length == n)
            self.classes[n] = {"rows": rows, "pairs": np.unique(np.concatenate([np.zeros(0, np.uint64), *(pair_hash(self.symbols[b : b + n]) for b in self.begin[rows])]))}
            # repeated pairs of an item count once, as they do in a window
            self.classes[n]["need"] = max(1, min(len(np.unique(pair_hash(self.symbols[b : b + n]))) for b in self.begin[rows]) - 2 * allowed(n))
            self.classes[n]["tables"] = self.tables(rows, n) if n > 1 else None
            # each pair (or the one word) with the items that have it
            own = [np.unique(pair_hash(self.symbols[b : b + n]) if n > 1 else self.symbols[b : b + 1]) for b in self.begin[rows]]
            pair, item = np.concatenate(own), np.repeat(rows, [len(x) for x in own])
            order = np.argsort(pair, kind="stable")
            self.classes[n]["having"] = pair[order], item[order]
            if n == 1:
                self.classes[n]["need"] = 1
        self.pairs = np.unique(np.concatenate([c["pairs"] for c in self.classes.values()])) if self.classes else np.zeros(0, np.uint64)
        self.screen = np.zeros(1 << 20, bool)
        self.screen[(self.pairs >> np.uint64(44)).astype(np.int64)] = True

    def edited(self, rows: np.ndarray, n: int, trials: int) -> tuple[np.ndarray, np.ndarray]:
        """Items with the allowed number of random edits, cut to n words: words and offsets."""
        rng, words, offs = np.random.default_rng(n), [], [0]
        for t in range(trials):
            seq = self.symbols[self.begin[rows[t % len(rows)]] :][:n].tolist()
            for _ in range(allowed(n)):
                kind, at = rng.integers(3), int(rng.integers(len(seq)))
                if kind == 0:
                    seq[at] = int(rng.integers(1 << 62))
                elif kind == 1:
                    seq.insert(at, int(rng.integers(1 << 62)))
                elif len(seq) > 1:
                    del seq[at]
            words += seq[:n]
            offs.append(len(words))
        return np.array(words, np.uint64), np.array(offs)

    def tables(self, rows: np.ndarray, n: int, trials: int = 128) -> list[tuple[int, np.ndarray, np.ndarray, np.ndarray]] | None:
        """(seed, sampled steps of each table, sorted keys of all tables, their items) of each walk; None if they miss the target."""
        every = np.arange(3 * n)
        own = [walk(self.symbols, self.begin[rows], self.length[rows], seed, every) for seed in range(WALKS)]
        words, offs = self.edited(rows, n, trials)
        other = [walk(words, offs[:-1], np.diff(offs), seed, every) for seed in range(WALKS)]
        item = np.arange(trials) % len(rows)
        for size, count in ((SAMPLED, 8), (SAMPLED, 16), (SAMPLED, 32), (SAMPLED, 64), (2, 64), (1, 64)):
            steps = [np.random.default_rng([seed, n]).integers(0, 3 * n, (count, size)) for seed in range(WALKS)]
            met = np.zeros(trials, bool)
            for s, a, b in zip(steps, own, other, strict=True):
                met |= (keys_of(a, s)[item] == keys_of(b, s)).any(1)
            if met.mean() >= RECALL:
                break
        else:
            return None
        out = []
        for seed, (s, a) in enumerate(zip(steps, own, strict=True)):
            keys = keys_of(a, s).ravel()
            order = np.argsort(keys)
            out.append((seed, s, keys[order], np.repeat(rows, count)[order]))
        return out

    def candidates(self, symbols: np.ndarray, start: np.ndarray, length: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
        """(window, item) rows that fall together in some table, or without tables those that share a pair."""
        found = [np.zeros((0, 2), np.int64)]
        for seed, steps, keys, rows in self.classes[n]["tables"] or [(None, None, *self.classes[n]["having"])]:
            if steps is None:
                size = np.maximum(length - (n > 1), 0)
                at, _ = spread(size, start, np.arange(len(start)))
                window = np.repeat(np.arange(len(start)), size)
                mine = mixed(symbols[at] * np.uint64(0x9E3779B97F4A7C15) + symbols[at + 1]) if n > 1 else symbols[at]
            else:
                mine = keys_of(walk(symbols, start, length, seed, np.arange(int(steps.max()) + 1)), steps).ravel()
                window = np.repeat(np.arange(len(start)), steps.shape[0])
            lo, hi = np.searchsorted(keys, mine), np.searchsorted(keys, mine, side="right")
            hit = np.flatnonzero(hi > lo)
            lo, size = lo[hit], (hi - lo)[hit]
            offset = np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size, size)
            found.append(np.unique(np.stack([np.repeat(window[hit], size), rows[np.repeat(lo, size) + offset]], axis=1), axis=0))
        both = np.unique(np.concatenate(found), axis=0)
        return both[:, 0], both[:, 1]


def pair_hash(symbols: np.ndarray) -> np.ndarray:
    return mixed(symbols[:-1] * np.uint64(0x9E3779B97F4A7C15) + symbols[1:])


def keys_of(embedded: np.ndarray, steps: np.ndarray) -> np.ndarray:
    """A key for each sequence (rows of embedded) and each table (rows of steps); tables' keys don't mix."""
    key = np.broadcast_to(np.arange(1, len(steps) + 1, dtype=np.uint64), (len(embedded), len(steps))).copy()
    for c in range(steps.shape[1]):
        key = mixed(key * np.uint64(0xD6E8FEB86659FD93) + embedded[:, steps[:, c]])
    return key


def best_part(item: np.ndarray, text: np.ndarray) -> tuple[int, int, int]:
    """Least edit distance of item to a part text[lo:hi], with lo and hi."""
    m = len(text)
    cost, origin = np.zeros(m + 1, np.int64), np.arange(m + 1)
    for i, w in enumerate(item.tolist(), 1):
        diag = cost[:-1] + (text != w)
        up = cost[1:] + 1
        new, src = np.empty(m + 1, np.int64), np.empty(m + 1, np.int64)
        new[0], src[0] = i, 0
        take = diag <= up
        new[1:], src[1:] = np.where(take, diag, up), np.where(take, origin[:-1], origin[1:])
        # insertions run along the row: least of new[j'] + (j - j')
        run = np.minimum.accumulate(new - np.arange(m + 1))
        at = np.maximum.accumulate(np.where(new - np.arange(m + 1) == run, np.arange(m + 1), 0))
        cost, origin = run + np.arange(m + 1), src[at]
    hi = int(cost.argmin())
    return int(cost[hi]), int(origin[hi]), hi


def windows(items: Items, symbols: np.ndarray, docs: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """For each item length, the first words of the windows that pass the screen, ascending."""
    if 1 in items.classes:
        first = np.flatnonzero(np.isin(symbols, items.classes[1]["having"][0]))
        if len(first):
            yield 1, first
    if len(symbols) < 2 or not items.classes:
        return
    pair = pair_hash(symbols)
    hit = np.flatnonzero(items.screen[(pair >> np.uint64(44)).astype(np.int64)])
    edge = np.zeros(len(symbols) + 1, bool)
    edge[docs] = True
    hit = hit[~edge[hit + 1]]
    at = np.minimum(np.searchsorted(items.pairs, pair[hit]), len(items.pairs) - 1)
    hit = hit[items.pairs[at] == pair[hit]]
    value = pair[hit]
    for n, c in items.classes.items():
        if n == 1:
            continue
        mine = np.isin(value, c["pairs"])
        p, v, t = hit[mine], value[mine], c["need"]
        if len(p) < t:
            continue
        # t hits within one window of n words, so within n - 2 places of each other
        close = np.flatnonzero(p[t - 1 :] - p[: len(p) - t + 1] <= n - 2)
        if not len(close):
            continue
        first, offs = spread(p[close] + 1 - np.maximum(p[close + t - 1] - (n - 2), 0), np.maximum(p[close + t - 1] - (n - 2), 0), np.arange(len(close)))
        first = np.unique(first)
        # different pairs in the window: hits whose last equal hit is before it
        order = np.lexsort((p, v))
        last = np.full(len(p), -1)
        same = v[order][1:] == v[order][:-1]
        last[order[1:][same]] = p[order[:-1][same]]
        lo = np.searchsorted(p, first)
        keep = np.zeros(len(first), bool)
        for x in range(0, len(first), 4096):
            places = lo[x : x + 4096, None] + np.arange(n - 1)
            inside = np.minimum(places, len(p) - 1)
            fresh = (places < len(p)) & (p[inside] <= first[x : x + 4096, None] + n - 2) & (last[inside] < first[x : x + 4096, None])
            keep[x : x + 4096] = fresh.sum(1) >= t
        first = first[keep]
        if len(first):
            # a window of the document before may reach over its end: the document's own first window stands for it
            doc = np.searchsorted(docs, first + n - 2, side="right") - 1
            own = docs[doc[docs[doc] >= first]]
            yield n, np.unique(np.concatenate([first, own[own < len(symbols)]]))


def suspects(items: Items, symbols: np.ndarray, docs: np.ndarray) -> np.ndarray:
    """Whether each document has a window that passes the screen."""
    out = np.zeros(len(docs) - 1, bool)
    for n, first in windows(items, symbols, docs):
        out[np.searchsorted(docs, first, side="right") - 1] = True
        out[np.searchsorted(docs, np.minimum(first + n - 2, len(symbols) - 1), side="right") - 1] = True
    return out


def matches(items: Items, symbols: np.ndarray, docs: np.ndarray) -> list[tuple[int, int, int, int, int]]:
    """(document row, item row, first word, end, distance) of all verified parts, words counted in the document."""
    out = []
    for n, first in windows(items, symbols, docs):
        row = np.searchsorted(docs, first, side="right") - 1
        size = np.minimum(docs[row + 1] - first, n)
        w, item = items.candidates(symbols, first, size, n)
        k = allowed(n)
        order = np.lexsort((first[w], item, row[w]))
        d, i, s = row[w][order], item[order], first[w][order]
        # neighbouring candidates of one item are one stretch of text, verified once
        new = np.flatnonzero(np.concatenate([[True], (d[1:] != d[:-1]) | (i[1:] != i[:-1]) | (s[1:] - s[:-1] > n)])) if len(d) else np.zeros(0, np.int64)
        for a, b in zip(new.tolist(), [*new[1:].tolist(), len(d)], strict=True):
            begin, end = int(docs[d[a]]), int(docs[d[a] + 1])
            lo, hi = max(begin, int(s[a]) - k), min(end, int(s[b - 1]) + n + 2 * k + 1)
            words = items.symbols[items.begin[i[a]] : items.begin[i[a]] + n]
            # a part within k edits has n - k of the item's words; after a match both sides of it are searched
            unsearched = [(lo, hi)]
            while unsearched:
                lo, hi = unsearched.pop()
                if np.isin(words, symbols[lo:hi]).sum() < n - k:
                    continue
                cost, x, y = best_part(words, symbols[lo:hi])
                if cost <= k:
                    out.append((int(d[a]), int(i[a]), lo + x - begin, lo + y - begin, cost))
                    unsearched += [(lo + y, hi), (lo, lo + x)]
    return out


def verified(items: Items, batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[list[pa.RecordBatch], list[pa.RecordBatch], list]]:
    """(rows of suspected documents, rows of others, matches by place in the former), as enough of them come together.

    The tables' cost is by batch rather than by window, so suspected documents, a few in a
    hundred, are gathered over blocks, up to GATHER words of them.
    """
    rows, words, offs = [], [], [np.zeros(1, np.int64)]
    for block in blocks(batches, limit=4 << 20):
        symbols, by_doc = plain_words(block.column("text"))
        bad = suspects(items, symbols, by_doc)
        yield [], [block.filter(pa.array(~bad))], []
        if bad.any():
            where = np.flatnonzero(bad)
            at, o = spread(np.diff(by_doc), by_doc[:-1], where)
            rows.append(block.filter(pa.array(bad)))
            words.append(symbols[at])
            offs.append(o[1:] + offs[-1][-1])
        if offs[-1][-1] > GATHER:
            yield rows, [], matches(items, np.concatenate(words), np.concatenate(offs))
            rows, words, offs = [], [], [np.zeros(1, np.int64)]
    if rows:
        yield rows, [], matches(items, np.concatenate(words), np.concatenate(offs))


def benchmark_items(benchmark: DataFrame, least_words: int = 1) -> list[Items]:
    """The items on the driver, in groups of bounded size; null items, and those of fewer words, match nothing."""
    groups, size = [([], [])], 0
    for r in benchmark.select("item_id", "text").filter("text is not null").orderBy("item_id").toLocalIterator():
        if least_words > 1 and plain_words(pa.array([r.text]))[1][-1] < least_words:
            continue
        if size + len(r.text) > ITEM_BYTES or len(groups[-1][0]) >= ITEMS:
            groups.append(([], []))
            size = 0
        groups[-1][0].append(r.item_id)
        groups[-1][1].append(r.text)
        size += len(r.text)
    return [Items(a, b) for a, b in groups if a]


def contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, item_id, first_word, end_word, distance: one row for each verified part of a document.

    Words are counted after punctuation is blanked.  Items of any length are searched, those
    without a word match nothing; null texts match nothing; repeated rows are reported each;
    a text of any length is searched whole; empty tables give an empty result.
    """
    spark, schema = docs.sparkSession, "doc_id bigint, item_id bigint, first_word bigint, end_word bigint, distance bigint"
    out = spark.createDataFrame([], schema)
    for group in benchmark_items(benchmark):
        shared = spark.sparkContext.broadcast(group)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            items = shared.value
            for rows, _, found in verified(items, batches):
                if not found:
                    continue
                ids = pa.concat_arrays([r.column("doc_id").cast(pa.int64()) for r in rows])
                cols = [ids.take(pa.array([f[0] for f in found], pa.int64())), pa.array([items.ids[f[1]] for f in found], pa.int64()), *(pa.array([f[c] for f in found], pa.int64()) for c in (2, 3, 4))]
                yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "item_id", "first_word", "end_word", "distance"])

        out = out.unionByName(docs.select("doc_id", "text").mapInArrow(run, schema))
    return out


def decontaminate(docs: DataFrame, benchmark: DataFrame, least_words: int = TELLING_WORDS) -> DataFrame:
    """The documents that no item of at least `least_words` words contaminates, in one scan for each group of items.

    All columns are kept, whatever their names; null and empty texts stay; repeated rows stay
    or go together; without items or documents, documents come back as they are.
    """
    for group in benchmark_items(benchmark, least_words):
        shared = docs.sparkSession.sparkContext.broadcast(group)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            for rows, rest, found in verified(shared.value, batches):
                yield from rest
                if rows:
                    clean = np.ones(sum(r.num_rows for r in rows), bool)
                    clean[[f[0] for f in found]] = False
                    yield from pa.Table.from_batches(rows).filter(pa.array(clean)).to_batches()

        docs = docs.mapInArrow(run, docs.schema)
    return docs
