"""Seed and extend: words decide, not their hashes."""

import random

import numpy as np
import pyarrow as pa
import pytest


def brute(codes, docs, names, window):
    """Windows (start) whose words start earlier: smaller doc_id, or same document and earlier."""
    first, out = {}, []
    at = [(names[d], s - docs[d], s) for d in range(len(names)) for s in range(docs[d], docs[d + 1] - window + 1)]
    for name, begin, s in sorted(at):
        key = tuple(codes[s : s + window])
        if key in first and first[key] < (name, begin):
            out.append(s)
        first.setdefault(key, (name, begin))
    return sorted(out)


def texts(seed, n=30):
    rng = random.Random(seed)
    vocab = [f"w{i}" for i in range(6)] + ["é", "w" * 300]
    base = [rng.choice(vocab) for _ in range(60)]
    out = []
    for _ in range(n):
        lo = rng.randrange(30)
        part = base[lo : lo + rng.randrange(15, 40)]
        if rng.random() < 0.4:
            part[rng.randrange(len(part))] = rng.choice(vocab)
        out.append(" ".join([*(rng.choice(vocab) for _ in range(rng.randrange(5))), *part, *(["a", "b"] * rng.randrange(25))]))
    return out


@pytest.mark.parametrize("collide", [False, True])
def test_homes_and_buckets_compare_words(monkeypatch, collide):
    from wavesum.llm import repeats, seed_dedup

    if collide:  # every word gets one hash: every window has one seed hash
        monkeypatch.setattr(seed_dedup, "span_hashes", lambda body, lengths: np.full(len(lengths), 7, np.uint64))
    for seed in range(4):
        all_texts, names = texts(seed), list(range(100, 130))
        homes = [list(range(0, 30, 2)), list(range(1, 30, 2))]
        tables = [pa.table({"doc_id": [names[i] for i in h], "text": [all_texts[i] for i in h]}) for h in homes]
        found, sent = {0: [], 1: []}, []
        for home, table in enumerate(tables):
            symbols, docs = seed_dedup.word_symbols(table.column("text").combine_chunks())
            _, anchor = repeats.anchor_places(symbols, docs, 20, 8)
            keys = np.unique(repeats.low(anchor)).astype(np.uint64)
            hot = np.arange(len(keys)) % 3 == 0
            sent.append(seed_dedup.send(20)(home, table, keys, hot, 1))
        back = seed_dedup.compare(20)(0, pa.concat_tables(sent))
        for home, numbers in zip(back.column("home").to_pylist(), back.column("numbers").to_pylist(), strict=True):
            a = np.frombuffer(numbers, np.uint32).reshape(-1, 2)
            found[home] += [x for lo, hi in a.tolist() for x in range(lo, hi)]
        codes = [w for t in all_texts for w in t.split()]
        offs = np.concatenate([[0], np.cumsum([len(t.split()) for t in all_texts])]).tolist()
        want = {0: [], 1: []}
        for s in brute(codes, offs, names, 20):
            d = int(np.searchsorted(offs, s, side="right")) - 1
            own = homes[d % 2]
            want[d % 2].append(s - offs[d] + sum(len(all_texts[i].split()) for i in own[: own.index(d)]))
        assert {h: sorted(set(x)) for h, x in found.items()} == {h: sorted(x) for h, x in want.items()}


def test_hashes_of_long_words_and_texts():
    from wavesum.llm import repeats

    rng = np.random.default_rng(1)
    lengths = np.array([3, 0, repeats.PIECE * 2 + 5, 0, 4, repeats.PIECE, 7])
    body = rng.integers(97, 123, int(lengths.sum())).astype(np.uint8)
    ends = np.cumsum(lengths)
    one = [repeats.span_hashes(body[e - n : e], np.array([n]))[0] for e, n in zip(ends, lengths, strict=True)]
    assert repeats.span_hashes(body, lengths).tolist() == one and len(set(one)) == 6
    symbols = rng.integers(0, 4, repeats.PIECE + 5000).astype(np.uint64)
    h = repeats.gram_hashes(symbols, 20)
    at = [0, 17, repeats.PIECE - 30, repeats.PIECE - 1, repeats.PIECE, repeats.PIECE + 4000]
    assert [h[i] for i in at] == [repeats.gram_hashes(symbols[i : i + 20], 20)[0] for i in at]
    assert all(len(p) <= 4 * repeats.PIECE for p in repeats._powers.values())
